"""Workloads over the given tables, each with its SQL where SQL can express it."""

from __future__ import annotations

import math
import posixpath
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangeknn.functions import vectors
from rangeknn.operators import baselines, exact, index, kernels, metrics
from rangeknn.operators.index import graph_kernel, materialise, scan_kernel
from rangeknn.plans import around, methods, surface  # noqa: F401  methods and around add their queries to those of surface
from rangeknn.plans.workload import E_SQL, LARGE_EF, SMALL, Setup, index_sql, intervals_sql, measured, scan_graph_sql, shown
from rangeknn.sources.catalog import TABLES, intervals, objects, table
from rangeknn.streaming import stream

def exact_knn(share: float | None = 0.1, name: str = "E", k: int = 10, rows: int = index.SHARD_ROWS):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = Setup(spark, sf_dir, name, share, k)
        return shown(index.search(s.packed(rows), s.queries))

    return run


def saturated(share: float | None = 0.1, name: str = "E", k: int = 10, rows: int = index.SHARD_ROWS, entry: str = "header"):
    """The index with a pool as large as the data visits the whole interval."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = Setup(spark, sf_dir, name, share, k)
        return shown(index.search(s.built(rows=rows), s.queries, graph_kernel(LARGE_EF, entry)))

    return run


def with_baseline(method: Callable[[Setup], DataFrame], share: float | None = 0.1):
    return lambda spark, sf_dir: shown(method(Setup(spark, sf_dir, "E", share)))


def worth(method: Callable[[Setup], DataFrame]):
    """Recall, distances and hops of an approximate method."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = Setup(spark, sf_dir)
        return measured(method(s), s.truth())

    return run


def open_ended(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Setup(spark, sf_dir)
    half = s.queries.withColumn("lo", F.when(F.col("qid") % 2 == 0, F.col("lo"))).withColumn("hi", F.when(F.col("qid") % 2 == 1, F.col("hi")))
    return shown(index.search(s.built(), half, graph_kernel(LARGE_EF)))


def empty_ranges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reversed intervals have no rows."""
    s = Setup(spark, sf_dir)
    turned = s.queries.select("qid", "qvec", (F.col("hi") + 1).alias("lo"), (F.col("lo") - 1).alias("hi"), "k")
    return index.search(s.packed(), turned).agg(F.count("*").alias("n"))


def approximate(how: kernels.Params = SMALL, ef: int = 20, entry: str = "header", name: str = "E", pool: str = "ef"):
    """(share, method) recall and distances per query of a search that is not saturated."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = None
        s = Setup(spark, sf_dir, name)
        built = s.built(how)
        for share in (0.05, 0.1, 0.5, None):
            asked = materialise(intervals(s.ranked, s.queries.select("qid", "qvec"), share), "queries")
            truth = materialise(index.search(built, asked), "truth")
            found = materialise(index.search(built, asked, graph_kernel(ef, entry, pool)), "found")
            cost = found.groupBy("qid").agg(F.max("n_dist").alias("n_dist"))
            r = metrics.recall_at_k(found, truth, 10, "min_k_truth").join(cost, "qid", "left").agg(F.round(F.avg("recall"), 4).alias("recall"), F.round(F.avg("n_dist"), 1).alias("n_dist"))
            r = r.select(F.lit("mixed" if share is None else f"{share:g}").alias("share"), "recall", "n_dist")
            out = r if out is None else out.union(r)
        return out

    return run


def edges_of(how: kernels.Params):
    return lambda spark, sf_dir: index.edges(Setup(spark, sf_dir).built(how)).select(F.col("src_rank").alias("src"), F.col("dst_rank").alias("dst"))


def rank_attr(spark: SparkSession, sf_dir: str) -> DataFrame:
    return index.with_rank(objects(spark, sf_dir, "PS"), buckets=4).select("id", "attr", "rank")


def rank_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Setup(spark, sf_dir, "PS")
    return index.to_ranks(s.queries, s.ranked).select("qid", "r_lo", "r_hi")


def window_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return index.window_pairs(Setup(spark, sf_dir).ranked, 8)


def heredity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For ten intervals, edges by which the exact graph within them differs from the graph rebuilt there: none, among so many."""
    s = Setup(spark, sf_dir)
    graph = materialise(exact.between_graph(s.ranked), "graph")
    return around.same_inside(s, graph, lambda lo, hi: exact.between_graph(s.ranked.where(F.col("rank").between(lo, hi))))


def violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ordered pairs of all ranks that break the monotone property of the exact graph: none."""
    s = Setup(spark, sf_dir)
    graph = materialise(exact.between_graph(s.ranked), "graph")
    return exact.monotone_violations(graph, s.ranked).agg(F.count("*").alias("n")).join(graph.agg(F.count("*").alias("edges")), F.lit(True))


class Probe:
    """One index against indexes rebuilt within ten intervals of a tenth of the ranks each, same parameters."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str = "E") -> None:
        self.s = Setup(spark, sf_dir, name)
        self.parts = F.broadcast(spark.createDataFrame(around.ten_intervals(self.s), "shard bigint, r_lo bigint, r_hi bigint"))
        self.inside = materialise(self.s.ranked.join(self.parts, F.col("rank").between(F.col("r_lo"), F.col("r_hi"))), "inside")
        centre = index.global_centroid(self.s.ranked)
        self.rebuilt = index.build_packed(materialise(index.packs(self.inside), "interval_shards"), SMALL, centre)
        self.whole = index.build(self.s.ranked, SMALL, centroid=centre)


def coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each interval, edges of the rebuilt graph, those the one index has too, and their share."""
    p = Probe(spark, sf_dir)
    own = index.edges(p.whole).select("src", "dst", F.lit(1).alias("hit"))
    each = index.edges(p.rebuilt).join(own, ["src", "dst"], "left").groupBy("shard").agg(F.count("hit").alias("shared"), F.count("*").alias("rebuilt"))
    return each.join(p.parts, "shard").select("r_lo", "r_hi", "shared", "rebuilt", F.round(F.col("shared") / F.col("rebuilt"), 6).alias("coverage"))


def experiment_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean, least and greatest coverage over the intervals, and what the one index and the rebuilt ones pay in distances a
    query where each first reaches recall 0.98, up to 50 held-out queries an interval."""
    p = Probe(spark, sf_dir, "D")
    own = index.edges(p.whole).select("src", "dst", F.lit(1).alias("hit"))
    each = index.edges(p.rebuilt).join(own, ["src", "dst"], "left").groupBy("shard").agg((F.count("hit") / F.count("*")).alias("c"))
    spread = each.agg(*(F.round(f("c"), 4).alias(n) for n, f in (("coverage", F.avg), ("least", F.min), ("greatest", F.max))))
    ends = p.inside.groupBy("shard").agg(F.min("attr").alias("lo"), F.max("attr").alias("hi"))
    held = p.s.queries.select("qid", "qvec").orderBy(F.xxhash64("qid"), "qid").limit(50)
    pools = F.explode(F.array(*(F.lit(v) for v in (10, 14, 20, 28, 40, 80, 160)))).alias("ef")
    asked = held.join(F.broadcast(ends), F.lit(True)).select((F.col("qid").bitwiseAND(F.lit((1 << 40) - 1)) * 10_000 + F.col("shard") * 1_000).alias("base"), "qvec", "lo", "hi", "shard", F.lit(10).alias("k"), pools)
    asked = materialise(asked.withColumn("qid", F.col("base") + F.col("ef")), "probe_queries")
    kernel = lambda sh, q, lo, hi, k, qid: graph_kernel(qid % 1_000)(sh, q, lo, hi, k, qid)
    truth = materialise(index.search(p.rebuilt, asked), "truth")
    out = None
    for name, built, queries in (("one index", p.whole, asked.drop("shard")), ("rebuilt", p.rebuilt, asked)):
        found = materialise(index.search(built, queries, kernel), "found")
        cost = found.groupBy("qid").agg(F.max("n_dist").alias("n_dist"))
        r = metrics.recall_at_k(found, truth, 10, "min_k_truth").join(cost, "qid", "left").groupBy((F.col("qid") % 1_000).alias("ef"))
        r = r.agg(F.avg("recall").alias("recall"), F.avg(F.coalesce("n_dist", F.lit(0))).alias("cost")).withColumn("method", F.lit(name))
        out = r if out is None else out.unionByName(r)
    at = metrics.at_recall(materialise(out, "curve"), 0.98)
    return at.join(spread, F.lit(True)).select("method", F.round("max_recall", 4).alias("max_recall"), F.round("cost", 1).alias("n_dist"), "coverage", "least", "greatest")


def header_entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The entry of every query: the object in range nearest to the global centroid, the best of the shards' entries."""
    s = Setup(spark, sf_dir)
    return index.search_entries(s.built(), s.queries, index.global_centroid(s.ranked)).select("qid", "id")


def cover_choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Setup(spark, sf_dir)
    return baselines.choose_cover(index.to_ranks(s.queries, s.ranked), s.ranked.count())


def recall_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hits by share of the interval and residue of the query, with totals (saturated: all)."""
    s = Setup(spark, sf_dir)
    truth, found = index.search(s.packed(), s.queries), index.search(s.built(), s.queries, graph_kernel(LARGE_EF))
    r = metrics.recall_at_k(found, truth, 10).withColumn("part", F.col("qid") % 4)
    return r.rollup("part").agg(F.count("*").alias("queries"), F.sum("hits").cast("bigint").alias("hits"), F.round(F.avg("recall"), 6).alias("recall"))


def asof_event_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each order the last event at or before its date: union, then the last seen value."""
    e = table(spark, sf_dir, "events").select(F.col("ts").alias("at"), "event_id", F.lit(None).cast("bigint").alias("o_orderkey"))
    o = table(spark, sf_dir, "orders").select(F.col("o_orderdate").alias("at"), F.lit(None).cast("bigint").alias("event_id"), "o_orderkey")
    # rows are dealt by ranges of time, the last event of each range is handed to the later ones, of which there are few
    order = ["at", "late", "event_id", "o_orderkey"]
    both = e.union(o).withColumn("late", F.col("o_orderkey").isNotNull())
    ranges = max(1, math.ceil(both.count() / 1_000_000))
    dealt = materialise(both.repartitionByRange(ranges, *order).withColumn("part", F.spark_partition_id()), "ranges")
    turn = Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    here = dealt.withColumn("last", F.last("event_id", ignorenulls=True).over(turn))
    ends = dealt.groupBy("part").agg(F.max_by("event_id", F.when(F.col("event_id").isNotNull(), F.struct("at", "event_id"))).alias("e"))
    before = ends.select("part", F.last("e", ignorenulls=True).over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)).alias("carry"))
    return here.where("late").join(before, "part").select("o_orderkey", F.coalesce("last", "carry").alias("event_id"))


def streamed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries written to files and replayed as a stream against a static index."""
    s = Setup(spark, sf_dir)
    packed = materialise(s.packed(), "shards")
    files = materialise(s.queries.repartition(4), "query_files")
    path = files.inputFiles()[0].rsplit("/", 1)[0]
    root = posixpath.join(path, "..", uuid.uuid4().hex)
    source = spark.readStream.schema(s.queries.schema).option("maxFilesPerTrigger", 2).parquet(path)
    stream.search_stream(source, packed, f"{root}/found", f"{root}/checkpoint").awaitTermination()
    return shown(spark.read.parquet(f"{root}/found"))


def counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for t in TABLES:
        one = table(spark, sf_dir, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.union(one)
    return out


def knn_label_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distance to vector 0 of the vectors of its label with a price in range, by column functions."""
    e, o = table(spark, sf_dir, "embeddings"), table(spark, sf_dir, "orders")
    zero = e.where("vec_id = 0").select(F.col("embedding").alias("q"), F.col("label").alias("l"))
    near = e.join(o, F.col("vec_id") == F.col("o_orderkey")).where(F.col("o_totalprice").between(50_000, 200_000)).join(F.broadcast(zero), F.col("label") == F.col("l"))
    return near.where("vec_id <> 0").select("vec_id", F.round(vectors.l2(F.col("embedding"), F.col("q")), 6).alias("l2"), F.round(vectors.cosine(F.col("embedding"), F.col("q")), 6).alias("cosine"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Range search on the index with the customary pool."""
    s = Setup(spark, sf_dir)
    return shown(index.search(s.built(), s.queries, graph_kernel(64)))


_PS = """o AS (SELECT vec_id AS id, embedding::DOUBLE[] AS vec, p_size::DOUBLE AS attr FROM embeddings JOIN part ON vec_id = p_partkey),
r AS (SELECT *, row_number() OVER (ORDER BY attr, id) AS rank FROM o WHERE id % 25 <> 7)"""


def _knn(base: str = E_SQL, share: str = "0.1", k: int = 10, cond: str = "attr BETWEEN lo AND hi") -> str:
    return f"""WITH {base}, {intervals_sql(share)},
d AS (SELECT qid, id, list_distance(vec, qvec) AS dist FROM q JOIN r ON {cond})
SELECT qid, rn, id, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rn FROM d) WHERE rn <= {k}"""


_COVERS = """lv AS (SELECT unnest(range(0, 30)) AS i), sz AS (SELECT i, ceil(n / pow(2, i))::BIGINT AS size, n FROM lv, n),
used AS (SELECT * FROM sz WHERE i <= (SELECT min(i) FROM sz WHERE size <= 32)),
st AS (SELECT i, size, n, greatest(1, size // 2) AS stride FROM used),
win AS (SELECT DISTINCT least(a, greatest(1, n - size + 1)) AS c_lo, least(n, a + size - 1) AS c_hi FROM (SELECT *, unnest(range(1, greatest(2, n - size + 1 + stride), stride)) AS a FROM st))"""

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "scan_all_counts": counts,
    "rank_attr": rank_attr,
    "rank_interval": rank_interval,
    "exact_knn_range": exact_knn(),
    "exact_knn_range_mixed": exact_knn(None),
    "exact_knn_range_time": exact_knn(0.5, "T"),
    "exact_knn_range_price": exact_knn(0.1, "P"),
    "exact_knn_range_k40": exact_knn(0.1, k=40),
    "range_search_saturated": saturated(),
    "range_search_ties": saturated(name="PS"),
    "range_search_open_ended": open_ended,
    "range_search_empty": empty_ranges,
    "range_search_k_exceeds": saturated(0.01, k=20),
    "range_search_entry_first": saturated(entry="first"),
    "range_search_entry_random": saturated(entry="random"),
    "range_search_entry_centre": saturated(entry="centre"),
    "sharded_search_saturated": saturated(0.5, rows=100),
    "unfiltered_knn_saturated": saturated(1.0),
    "prefilter_scan": with_baseline(lambda s: baselines.pre_filter(s.packed(), s.queries)),
    "postfilter_overfetch": with_baseline(lambda s: baselines.post_filter(s.packed(), s.queries)),
    "auto_placement": with_baseline(lambda s: baselines.auto(s.built(), s.queries, ef=LARGE_EF), None),
    "ivf_probe_all": with_baseline(lambda s: baselines.ivf_search(s.packed(), s.queries, nprobe=LARGE_EF, rerank=LARGE_EF)),
    "infilter_spatial_approx": worth(lambda s: baselines.in_filter(s.built(kernels.Params(16, 0, 32, prune="spatial")), s.queries)),
    "ivf_probe_approx": worth(lambda s: baselines.ivf_search(s.packed(), s.queries)),
    "segment_tree_approx": worth(lambda s: baselines.segment_tree_search(s.packed(), s.queries)),
    "dense_predicate_approx": worth(lambda s: baselines.dense_predicate_search(s.packed(), s.queries)),
    "layered_graph_approx": worth(lambda s: baselines.layered_search(s.packed(), s.queries)),
    "postfilter_graph_approx": worth(lambda s: baselines.post_filter(s.built(), s.queries, graph=True)),
    "window_candidates": window_candidates,
    "exact_between_graph": lambda spark, d: exact.between_graph(Setup(spark, d).ranked),
    "exact_mrng": lambda spark, d: exact.mrng(Setup(spark, d).ranked),
    "induced_subgraph": lambda spark, d: exact.induce(exact.between_graph(Setup(spark, d).ranked, sources=(101, 300)), 101, 300),
    "heredity_diff": heredity,
    "monotone_violations": violations,
    "pruned_index_edges": edges_of(SMALL),
    "index_degree_stats": lambda spark, d: metrics.degree_stats(Setup(spark, d).built()),
    "edge_coverage_probe": coverage,
    "experiment_coverage_approx": experiment_coverage,
    "entry_header_lookup": header_entry,
    "cover_choice": cover_choice,
    "recall_rollup": recall_rollup,
    "search_quality_approx": approximate(),
    "search_quality_nn_descent_approx": approximate(kernels.Params(16, 32, 32, knn="nn_descent")),
    "search_quality_pool_k_approx": approximate(pool="k"),
    "ablation_no_window_approx": approximate(kernels.Params(16, 0, 32)),
    "ablation_spatial_prune_approx": approximate(kernels.Params(16, 32, 32, prune="spatial")),
    "ablation_both_approx": approximate(kernels.Params(16, 0, 32, prune="spatial")),
    "knn_label_range": knn_label_range,
    "asof_event_order": asof_event_order,
    "tumbling_events": lambda spark, d: stream.tumbling_counts(table(spark, d, "events")),
    "stream_range_search": streamed,
}

ORACLES: dict[str, str] = {
    "scan_all_counts": " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES),
    "rank_attr": "SELECT vec_id AS id, p_size::DOUBLE AS attr, row_number() OVER (ORDER BY p_size, vec_id) AS rank FROM embeddings JOIN part ON vec_id = p_partkey",
    "rank_interval": f"WITH {_PS}, {intervals_sql()} SELECT qid, min(rank) AS r_lo, max(rank) AS r_hi FROM q JOIN r ON attr BETWEEN lo AND hi GROUP BY qid",
    "range_search_ties": _knn(_PS),
    "exact_knn_range_mixed": _knn(share="pow(2, -(id % 8))"),
    "auto_placement": _knn(share="pow(2, -(id % 8))"),
    "exact_knn_range_time": _knn(E_SQL.replace("o_totalprice::DOUBLE", "epoch_us(ts)::DOUBLE").replace("orders ON vec_id = o_orderkey", "events ON vec_id = event_id"), "0.5"),
    "exact_knn_range_price": _knn(E_SQL.replace("o_totalprice::DOUBLE", "p_retailprice::DOUBLE").replace("orders ON vec_id = o_orderkey", "part ON vec_id = p_partkey")),
    "exact_knn_range_k40": _knn(k=40),
    "range_search_open_ended": _knn(cond="CASE WHEN qid % 2 = 0 THEN attr >= lo ELSE attr <= hi END"),
    "range_search_empty": "SELECT 0::BIGINT AS n",
    "range_search_k_exceeds": _knn(share="0.01", k=20),
    "sharded_search_saturated": _knn(share="0.5"),
    "unfiltered_knn_saturated": _knn(share="1.0"),
    "window_candidates": f"WITH {E_SQL} SELECT a.rank AS src, b.rank AS dst FROM r a JOIN r b ON b.rank BETWEEN a.rank - 8 AND a.rank + 8 AND a.rank <> b.rank",
    "exact_between_graph": f"{scan_graph_sql()} SELECT src, dst FROM graph",
    "induced_subgraph": f"{scan_graph_sql()} SELECT src, dst FROM graph WHERE src BETWEEN 101 AND 300 AND dst BETWEEN 101 AND 300",
    "exact_mrng": f"""WITH RECURSIVE {E_SQL},
p AS MATERIALIZED (SELECT a.rank AS x, list(list_distance(a.vec, b.vec) ORDER BY b.rank) AS ds, list(b.rank ORDER BY list_distance(a.vec, b.vec), b.rank) FILTER (b.rank <> a.rank) AS ord FROM r a, r b GROUP BY a.rank),
scan(x, j, kept) AS (
  SELECT rank, 0, []::BIGINT[] FROM r
  UNION ALL
  SELECT s.x, j + 1, CASE WHEN len(list_filter(kept, lambda z: a.ds[z] < a.ds[a.ord[j + 1]] AND b.ds[z] < a.ds[a.ord[j + 1]])) > 0 THEN kept ELSE list_append(kept, a.ord[j + 1]) END
  FROM scan s JOIN p a ON a.x = s.x JOIN p b ON b.x = a.ord[j + 1])
SELECT x AS src, unnest(kept) AS dst FROM (SELECT x, max_by(kept, j) AS kept FROM scan GROUP BY x)""",
    "heredity_diff": f"{scan_graph_sql()}{around.INSIDE_SQL}",
    "monotone_violations": f"{scan_graph_sql()} SELECT 0::BIGINT AS n, count(*) AS edges FROM graph",
    "pruned_index_edges": f"{index_sql()} SELECT src, dst FROM graph",
    "index_degree_stats": f"{index_sql()} SELECT (SELECT n FROM n) AS nodes, count(*) AS edges, round(count(*) / (SELECT n FROM n), 6) AS mean_degree, 4 * count(*) + 4 * (SELECT n FROM n) AS bytes FROM graph",
    "entry_header_lookup": f"""WITH {E_SQL}, {intervals_sql()},
c AS (SELECT list(m ORDER BY i) AS centre FROM (SELECT i, avg(v) AS m FROM (SELECT unnest(vec) AS v, generate_subscripts(vec, 1) AS i FROM r) GROUP BY i))
SELECT qid, arg_min(id, list_distance(vec, centre)) AS id FROM q JOIN r ON attr BETWEEN lo AND hi, c GROUP BY qid""",
    "cover_choice": f"""WITH {E_SQL}, {intervals_sql()}, n AS (SELECT count(*) AS n FROM r), {_COVERS},
qr AS (SELECT qid, min(rank) AS r_lo, max(rank) AS r_hi FROM q JOIN r ON attr BETWEEN lo AND hi GROUP BY qid)
SELECT qid, b.c_lo AS c_lo, b.c_hi AS c_hi FROM (SELECT qid, min({{'w': c_hi - c_lo, 'c_lo': c_lo, 'c_hi': c_hi}}) AS b FROM qr JOIN win ON c_lo <= r_lo AND c_hi >= r_hi GROUP BY qid)""",
    "recall_rollup": f"""WITH {E_SQL}, {intervals_sql()}, h AS (SELECT qid, least(10, count(*)) AS hits FROM q JOIN r ON attr BETWEEN lo AND hi GROUP BY qid)
SELECT qid % 4 AS part, count(*) AS queries, sum(hits)::BIGINT AS hits, round(avg(hits / 10), 6) AS recall FROM h GROUP BY ROLLUP (qid % 4)""",
    "knn_label_range": """SELECT a.vec_id, round(list_distance(a.embedding::DOUBLE[], z.embedding::DOUBLE[]), 6) AS l2, round(list_cosine_similarity(a.embedding::DOUBLE[], z.embedding::DOUBLE[]), 6) AS cosine
FROM embeddings a JOIN orders ON a.vec_id = o_orderkey JOIN embeddings z ON z.vec_id = 0 AND z.label = a.label WHERE a.vec_id <> 0 AND o_totalprice BETWEEN 50000 AND 200000""",
    "asof_event_order": """WITH e AS (SELECT ts, max(event_id) AS event_id FROM events GROUP BY ts) SELECT o_orderkey, event_id FROM orders ASOF LEFT JOIN e ON o_orderdate >= ts""",
    "tumbling_events": "SELECT date_trunc('day', ts) AS window_start, event_type, count(*) AS n FROM events GROUP BY ALL",
}


def _coverage_sql() -> str:
    """The ten intervals, each with an index of its own next to the one of all ranks."""
    first = "(SELECT 1 + {i} * 7919 % (count(*) - greatest(1, count(*) // 10) + 1) FROM whole)"
    width = "(SELECT greatest(1, count(*) // 10) FROM whole)"
    parts = []
    for i in range(10):
        r1 = first.format(i=i)
        base = E_SQL.replace("r AS (", "whole AS (") + f", r AS (SELECT * REPLACE (rank - {r1} + 1 AS rank) FROM whole WHERE rank BETWEEN {r1} AND {r1} + {width} - 1)"
        parts.append(f"SELECT * FROM ({index_sql(base)} SELECT {r1} AS r_lo, {r1} + {width} - 1 AS r_hi, src + {r1} - 1 AS src, dst + {r1} - 1 AS dst FROM graph)")
    return f"""SELECT r_lo, r_hi, count(g.src) AS shared, count(*) AS rebuilt, round(count(g.src) / count(*), 6) AS coverage
FROM ({" UNION ALL ".join(parts)}) p LEFT JOIN ({index_sql()} SELECT src, dst FROM graph) g ON g.src = p.src AND g.dst = p.dst GROUP BY r_lo, r_hi"""


ORACLES["edge_coverage_probe"] = _coverage_sql()
for _name in ("exact_knn_range", "range_search_saturated", "range_search_entry_first", "range_search_entry_random", "range_search_entry_centre", "prefilter_scan", "postfilter_overfetch", "ivf_probe_all", "stream_range_search"):
    ORACLES[_name] = _knn()
QUERIES |= surface.QUERIES
ORACLES |= surface.ORACLES
