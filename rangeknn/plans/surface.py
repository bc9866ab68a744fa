"""Operators around the methods, as a user writes them: plain DataFrame or SQL plans over the tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangeknn.functions import vectors
from rangeknn.sources.catalog import objects, table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

_E = "o AS (SELECT vec_id AS id, embedding::DOUBLE[] AS vec, label, o_totalprice AS attr FROM embeddings JOIN orders ON vec_id = o_orderkey)"


def registered(sql: str | None):
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _labelled(spark: SparkSession, d: str) -> DataFrame:
    return objects(spark, d).join(table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), "label"), "id")


@registered(f"WITH {_E} SELECT id, attr FROM o WHERE attr BETWEEN 50000 AND 150000")
def filter_range(spark: SparkSession, d: str) -> DataFrame:
    return objects(spark, d).where(F.col("attr").between(50_000, 150_000)).select("id", "attr")


@registered(f"WITH {_E} SELECT id, label, attr FROM o WHERE attr >= 50000 AND attr < 150000 AND label IN (1, 3)")
def filter_label_range(spark: SparkSession, d: str) -> DataFrame:
    return _labelled(spark, d).where("attr >= 50000 and attr < 150000 and label in (1, 3)").select("id", "label", "attr")


@registered("SELECT vec_id AS id FROM embeddings JOIN orders ON vec_id = o_orderkey JOIN events ON vec_id = event_id WHERE o_totalprice BETWEEN 50000 AND 150000 AND value BETWEEN 10 AND 80")
def filter_box(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").select(F.col("event_id").alias("id"), "value")
    return objects(spark, d).join(e, "id").where("attr between 50000 and 150000 and value between 10 and 80").select("id")


@registered("SELECT vec_id, round(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS norm FROM embeddings")
def vec_norm(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select("vec_id", F.round(vectors.norm(F.col("embedding")), 6).alias("norm"))


@registered("SELECT label, i - 1 AS pos, round(avg(v), 6) AS mean FROM (SELECT label, unnest(embedding::DOUBLE[]) AS v, generate_subscripts(embedding, 1) AS i FROM embeddings) GROUP BY ALL")
def centroid_per_label(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("pos", "v"))
    return e.groupBy("label", F.col("pos").cast("bigint").alias("pos")).agg(F.round(F.avg(F.col("v").cast("double")), 6).alias("mean"))


@registered(f"WITH {_E} SELECT floor(attr / 25000)::BIGINT AS bucket, count(*) AS n FROM o GROUP BY ALL")
def attr_histogram(spark: SparkSession, d: str) -> DataFrame:
    return objects(spark, d).groupBy(F.floor(F.col("attr") / 25_000).alias("bucket")).agg(F.count("*").alias("n"))


@registered(f"WITH {_E} SELECT id, attr FROM o ORDER BY attr DESC, id LIMIT 15")
def topk_global(spark: SparkSession, d: str) -> DataFrame:
    return objects(spark, d).select("id", "attr").orderBy(F.desc("attr"), "id").limit(15)


@registered(f"WITH {_E} SELECT label, id, attr FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY attr, id) AS n FROM o) WHERE n <= 3")
def topk_per_group(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("label").orderBy("attr", "id")
    return _labelled(spark, d).withColumn("n", F.row_number().over(w)).where("n <= 3").select("label", "id", "attr")


@registered("SELECT vec_id FROM embeddings SEMI JOIN (SELECT * FROM orders WHERE o_totalprice > 100000) ON vec_id = o_orderkey")
def semi_in_range(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders").where("o_totalprice > 100000")
    return table(spark, d, "embeddings").join(o, F.col("vec_id") == F.col("o_orderkey"), "left_semi").select("vec_id")


@registered("SELECT vec_id FROM embeddings ANTI JOIN part ON vec_id = p_partkey")
def anti_no_attr(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").join(table(spark, d, "part"), F.col("vec_id") == F.col("p_partkey"), "left_anti").select("vec_id")


@registered("SELECT vec_id, p_size FROM embeddings LEFT JOIN part ON vec_id = p_partkey")
def outer_attr(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").join(table(spark, d, "part"), F.col("vec_id") == F.col("p_partkey"), "left").select("vec_id", "p_size")


@registered("SELECT label, o_orderpriority, count(*) AS n, round(avg(o_totalprice), 2) AS mean, (grouping(label) * 2 + grouping(o_orderpriority))::INT AS level FROM embeddings JOIN orders ON vec_id = o_orderkey GROUP BY CUBE (label, o_orderpriority)")
def price_cube(spark: SparkSession, d: str) -> DataFrame:
    j = table(spark, d, "embeddings").join(table(spark, d, "orders"), F.col("vec_id") == F.col("o_orderkey"))
    return j.cube("label", "o_orderpriority").agg(F.count("*").alias("n"), F.round(F.avg("o_totalprice"), 2).alias("mean"), F.grouping_id().cast("int").alias("level"))


@registered("SELECT label, o_orderpriority, count(*) AS n FROM embeddings JOIN orders ON vec_id = o_orderkey GROUP BY GROUPING SETS ((label), (o_orderpriority), ())")
def price_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    table(spark, d, "embeddings").createOrReplaceTempView("rk_embeddings")
    table(spark, d, "orders").createOrReplaceTempView("rk_orders")
    return spark.sql("SELECT label, o_orderpriority, count(*) AS n FROM rk_embeddings JOIN rk_orders ON vec_id = o_orderkey GROUP BY GROUPING SETS ((label), (o_orderpriority), ())")


@registered(f"WITH {_E}, r AS (SELECT id, row_number() OVER (ORDER BY attr, id) AS rank FROM o) SELECT id, level, ((rank - 1) >> level)::BIGINT AS segment FROM r, (SELECT unnest(range(0, 10))::INT AS level)")
def segment_ids(spark: SparkSession, d: str) -> DataFrame:
    """Segments of a binary tree over ranks, level by level."""
    from rangeknn.operators.index import with_rank

    r = with_rank(objects(spark, d)).select("id", "rank", F.explode(F.sequence(F.lit(0), F.lit(9))).alias("level"))
    return r.select("id", "level", F.expr("shiftright(rank - 1, level)").alias("segment"))


@registered("SELECT vec_id AS id, label, count(*) OVER (PARTITION BY label ORDER BY o_totalprice RANGE BETWEEN 10000 PRECEDING AND 10000 FOLLOWING) AS n FROM embeddings JOIN orders ON vec_id = o_orderkey")
def range_frame_counts(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("label").orderBy("attr").rangeBetween(-10_000, 10_000)
    return _labelled(spark, d).select("id", "label", F.count("*").over(w).alias("n"))


@registered("""WITH t AS (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents) SELECT w, count(*) AS n FROM t GROUP BY w""")
def text_tokens(spark: SparkSession, d: str) -> DataFrame:
    words = table(spark, d, "documents").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), 0)).alias("w"))
    return words.groupBy("w").agg(F.count("*").alias("n"))


@registered("SELECT event_id, epoch_us(ts) AS attr FROM events")
def time_to_attr(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").select("event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("attr"))


@registered(f"WITH {_E} SELECT a.id AS a, b.id AS b, round(list_distance(a.vec, b.vec), 6) AS dist FROM o a JOIN o b ON a.label = b.label AND a.id < b.id AND b.attr BETWEEN a.attr - 5000 AND a.attr + 5000 WHERE list_distance(a.vec, b.vec) < 1.3")
def pairs_within_eps(spark: SparkSession, d: str) -> DataFrame:
    """Vectors of one label with close attributes and a small distance: a banded range join.

    Bands as wide as the tolerance turn the range into an equality on label and band.
    """
    e = _labelled(spark, d)
    a = e.select("label", F.col("id").alias("a"), F.col("vec").alias("va"), F.col("attr").alias("ta"), F.floor(F.col("attr") / 5_000).alias("band"))
    own = F.floor(F.col("attr") / 5_000)
    b = e.select("label", F.col("id").alias("b"), F.col("vec").alias("vb"), F.col("attr").alias("tb"), F.explode(F.array(own - 1, own, own + 1)).alias("band"))
    near = a.join(b, ["label", "band"]).where("a < b and tb between ta - 5000 and ta + 5000").withColumn("dist", vectors.l2(F.col("va"), F.col("vb")))
    return near.where("dist < 1.3").select("a", "b", F.round("dist", 6).alias("dist"))


@registered("SELECT user_id, count(*) AS n, list_sort(list(DISTINCT event_type)) AS types FROM events GROUP BY user_id")
def user_types(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").groupBy("user_id").agg(F.count("*").alias("n"), F.sort_array(F.collect_set("event_type")).alias("types"))


@registered("SELECT lang, approx.n AS docs, round(q, 1) AS median FROM (SELECT lang, count(*) AS n, quantile_cont(n_chars, 0.5) AS q FROM documents GROUP BY lang) approx")
def length_by_language(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").groupBy("lang").agg(F.count("*").alias("docs"), F.round(F.percentile("n_chars", 0.5), 1).alias("median"))


# Functions of this package in the hands of a user.


@registered("SELECT a.vec_id, round(list_distance(a.embedding::DOUBLE[], z.embedding::DOUBLE[]), 6) AS l2 FROM embeddings a JOIN embeddings z ON z.vec_id = 0")
def udf_l2(spark: SparkSession, d: str) -> DataFrame:
    """Distances to vector 0 by the Arrow UDF."""
    e = table(spark, d, "embeddings")
    zero = F.broadcast(e.where("vec_id = 0").select(F.col("embedding").alias("q")))
    return e.join(zero, F.lit(True)).select("vec_id", F.round(vectors.arrow_l2()("embedding", "q"), 6).alias("l2"))


@registered("SELECT label, (i - 1)::BIGINT AS pos, round(avg(v), 6) AS mean FROM (SELECT label, unnest(embedding::DOUBLE[]) AS v, generate_subscripts(embedding, 1) AS i FROM embeddings) GROUP BY label, i")
def udaf_centroids(spark: SparkSession, d: str) -> DataFrame:
    """The mean vector of each label from partial sums of Arrow batches."""
    return vectors.centroids(table(spark, d, "embeddings"), "label", "embedding").select("label", "pos", F.round("mean", 6).alias("mean"))


@registered(r"SELECT page_id, len(t)::INT AS n_chars, md5(t) AS digest FROM (SELECT page_id, trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \t\r\n]+', ' ', 'g')) AS t FROM pages)")
def html_text(spark: SparkSession, d: str) -> DataFrame:
    """Pages without their tags, by regular expressions in the JVM."""
    text = F.trim(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), "[ \\t\\r\\n]+", " "))
    return table(spark, d, "pages").select("page_id", text.alias("t")).select("page_id", F.length("t").alias("n_chars"), F.md5("t").alias("digest"))
