"""The registered queries of the operators, with production parameters on whole tables."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import byte_bpe, embed_dedup, jaccard, packing, pii, substring, token_counts, toxicity, url_filter, vptree
from .storage import table

#: Key of the pseudonyms of the registered query; deployments pass their own secret.
DEMO_KEY = b"rangeknn demonstration key"
HELD_OUT = "coalesce(crc32(cast(doc_id as string)) % 5 = 0, false)"


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts with a cold cache: a new one is filled by each call."""
    counts = token_counts.token_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
    return counts.withColumn("over_limit", F.col("n_tokens") > 1024)


def toxicity_weights(spark: SparkSession, docs: DataFrame, sf_dir: str) -> list[tuple[int, float]]:
    labels = table(spark, sf_dir, "labels").where(f"not ({HELD_OUT})")
    return toxicity.train(docs, labels)


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = toxicity.score(docs.select("doc_id", "text"), toxicity_weights(spark, docs, sf_dir))
    return scored.select("doc_id", F.expr(HELD_OUT).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.encode_decode(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def _number(text: F.Column) -> F.Column:
    return F.conv(F.substring(F.md5(text), 1, 6), 16, 10).cast("int")


def dated_feed(pages: DataFrame) -> DataFrame:
    """A list with a history, made by rule from the hosts and sections that pages has.

    Days are whole numbers from 0. A third of the hosts is blocked for a while and some of them
    again later; a quarter of the sections (host and first path step) is allowed from some day.
    """
    hosts = pages.select(url_filter.host_of(F.col("url")).alias("h"), F.regexp_extract("url", url_filter.PATH, 1).alias("p")).where("h <> ''")
    one = hosts.select("h").distinct().withColumn("m", _number(F.col("h"))).where("m % 3 = 0")
    block = lambda day, change: one.select(F.col("h").alias("key"), F.lit("block").alias("action"), day.cast("int").alias("at"), F.lit(change).alias("change"))
    m = F.col("m")
    section = hosts.select(F.concat("h", F.lit("/"), F.split("p", "/")[1]).alias("key")).where("key is not null and key not like '%/'").distinct().withColumn("m", _number(F.col("key"))).where("m % 4 = 0")
    allow = section.select("key", F.lit("allow").alias("action"), (m % 300).cast("int").alias("at"), F.lit("add").alias("change"))
    return block(m % 200, "add").union(block(m % 200 + 30 + m % 50, "remove")).union(block(m % 200 + 150, "add")).union(allow)


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url").withColumn("fetched", _number(F.col("page_id").cast("string")) % 360)
    return url_filter.as_of_filter(pages, url_filter.validity_intervals(dated_feed(pages)), "page_id")


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed_dedup.near_duplicates(table(spark, sf_dir, "embeddings"))


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return vptree.neighbours(vectors, vectors.where("vec_id % 20 = 0"))


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Kinds and number of values replaced, the new text and its digest."""
    done = pii.pseudonymise(table(spark, sf_dir, "documents").select("doc_id", "text"), DEMO_KEY)
    found = F.aggregate(F.map_values("pii_kinds"), F.lit(0).cast("bigint"), lambda s, x: s + x)
    kinds = F.array_join(F.array_sort(F.map_keys("pii_kinds")), ",")
    return done.select("doc_id", found.alias("n_replaced"), kinds.alias("kinds"), F.sha2("text", 256).alias("text_sha256"), "text")


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_reference(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The broadcast form: passages of the benchmark are cut out of the documents."""
    reference = substring.reference_texts(table(spark, sf_dir, "benchmark"))
    return substring.match_reference(table(spark, sf_dir, "documents"), reference).drop("spans")


def op10_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The join with all its columns, the number of links included."""
    return jaccard.jaccard_components(table(spark, sf_dir, "documents"))


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of its SQL, which has no number of links."""
    return op10_links(spark, sf_dir).drop("n_links")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_token_counts": op1,
    "op2_toxicity": op2,
    "op3_byte_bpe": op3,
    "op4_url_filter": op4,
    "op5_embedding_dedup": op5,
    "op6_packing": op6,
    "op7_vantage_point_knn": op7,
    "op8_pii_pseudonyms": op8,
    "op9_substring_dedup": op9,
    "op9_substring_reference": op9_reference,
    "op10_ngram_jaccard": op10,
    "op10_ngram_jaccard_links": op10_links,
    "pipeline": pipeline,
}

_HOST = r"rtrim(lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)', 1)), '.')"
_PATH = r"regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*(/[^?#]*)', 1)"
_NUM = "('0x' || substr(md5({0}), 1, 6))::BIGINT"

ORACLES: dict[str, str] = {
    "op4_url_filter": f"""
WITH p AS (SELECT page_id, url, {_HOST} AS h, {_PATH} AS path, ({_NUM.format("page_id::VARCHAR")} % 360)::INT AS fetched FROM pages),
hosts AS (SELECT DISTINCT h AS key, {_NUM.format("h")} AS m FROM p WHERE h <> ''),
sections AS (SELECT DISTINCT h || '/' || split_part(path, '/', 2) AS key FROM p WHERE h <> '' AND split_part(path, '/', 2) <> ''),
feed AS (
  SELECT key, 'block' AS action, m % 200 AS since, m % 200 + 30 + m % 50 AS until FROM hosts WHERE m % 3 = 0
  UNION ALL SELECT key, 'block', m % 200 + 150, NULL FROM hosts WHERE m % 3 = 0
  UNION ALL SELECT key, 'allow', {_NUM.format("key")} % 300, NULL FROM sections WHERE {_NUM.format("key")} % 4 = 0),
hit AS (
  SELECT page_id, key, action FROM p JOIN feed ON fetched >= since AND (until IS NULL OR fetched < until)
   AND CASE WHEN action = 'block' THEN h = key OR h LIKE '%.' || key ELSE h || path = key OR (h || path) LIKE key || '/%' END),
best AS (SELECT page_id, count(*) AS n_active, max({{'n': length(key), 'a': action = 'allow', 'key': key, 'action': action}}) AS b FROM hit GROUP BY page_id)
SELECT p.page_id, h AS host, fetched, coalesce(n_active, 0) AS n_active, b.key AS rule, b.action AS rule_action, coalesce(b.action = 'block', false) AS blocked
FROM p LEFT JOIN best USING (page_id)""",
    "op5_embedding_dedup": """
WITH RECURSIVE v AS (
  SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL
   AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
link AS (SELECT a.vec_id AS x, b.vec_id AS y FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id AND list_cosine_similarity(a.e, b.e) >= 0.98),
reach(x, y) AS (SELECT x, y FROM link UNION SELECT r.x, l.y FROM reach r JOIN link l ON r.y = l.x),
comp AS (SELECT x, min(y) AS low FROM reach GROUP BY x),
n AS (SELECT x, count(*) AS n_links FROM link GROUP BY x)
SELECT vec_id, coalesce(n_links, 0) AS n_links, least(vec_id, coalesce(low, vec_id)) AS component_id, vec_id = least(vec_id, coalesce(low, vec_id)) AS kept
FROM embeddings LEFT JOIN comp ON comp.x = vec_id LEFT JOIN n ON n.x = vec_id""",
    "op9_substring_dedup": r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
win AS (SELECT doc_id, s, array_to_string(ws[s:s + 19], ' ') AS t FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 18)) AS s FROM w)),
dup AS (SELECT doc_id, s FROM (SELECT doc_id, s, row_number() OVER (PARTITION BY t ORDER BY doc_id, s) AS n FROM win) WHERE n > 1),
gone AS (SELECT DISTINCT doc_id, unnest(range(s, s + 20)) AS i FROM dup),
words AS (SELECT doc_id, unnest(ws) AS word, unnest(range(1, len(ws) + 1)) AS i FROM w),
kept AS (SELECT doc_id, count(*) AS n, string_agg(word, ' ' ORDER BY i) AS t FROM words ANTI JOIN gone USING (doc_id, i) GROUP BY doc_id)
SELECT doc_id, len(ws)::BIGINT AS n_words, (len(ws) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM w LEFT JOIN kept USING (doc_id)""",
    "op10_ngram_jaccard": r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(ws[i:i + 4], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 4, 1) + 1)) AS i FROM w WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
pair AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS o FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
link AS (SELECT x, y FROM pair JOIN n na ON na.doc_id = x JOIN n nb ON nb.doc_id = y WHERE 100 * o >= 80 * (na.n + nb.n - o)),
reach(x, y) AS (SELECT x, y FROM link UNION SELECT r.x, l.y FROM reach r JOIN link l ON r.y = l.x),
comp AS (SELECT x, min(y) AS low FROM reach GROUP BY x),
sets AS (SELECT doc_id, list_sort(list(g)) AS g FROM s GROUP BY doc_id),
cls AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY g) AS class_id FROM sets)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, coalesce(class_id, d.doc_id) AS class_id, least(d.doc_id, coalesce(low, d.doc_id)) AS component_id
FROM documents d LEFT JOIN n USING (doc_id) LEFT JOIN comp ON comp.x = d.doc_id LEFT JOIN cls ON cls.doc_id = d.doc_id""",
}

_EARLIER = "SELECT doc_id, s FROM (SELECT doc_id, s, row_number() OVER (PARTITION BY t ORDER BY doc_id, s) AS n FROM win) WHERE n > 1"
_IN_REFERENCE = r"""SELECT doc_id, s FROM win WHERE t IN (SELECT array_to_string(ws[s:s + 19], ' ') FROM (SELECT ws, unnest(range(1, len(ws) - 18)) AS s FROM (SELECT regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS ws FROM benchmark)))"""
ORACLES["op9_substring_reference"] = ORACLES["op9_substring_dedup"].replace(_EARLIER, _IN_REFERENCE)

ORACLES["op10_ngram_jaccard_links"] = (
    ORACLES["op10_ngram_jaccard"]
    .replace("comp AS (", "degree AS (SELECT x, count(*) AS n_links FROM link GROUP BY x),\ncomp AS (")
    .replace(" AS component_id\n", " AS component_id, coalesce(n_links, 0) AS n_links\n")
    + " LEFT JOIN degree ON degree.x = d.doc_id"
)
