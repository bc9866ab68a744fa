"""Token counts through a digest cache.

A count depends on the content and on the tokenizer alone. Both have a digest; the cache is a
Parquet table (tokenizer, digest, n_tokens) in a folder that all nodes share. Texts whose
digest is stored are never encoded, of the others each distinct one is encoded once, and
the new counts are appended as files of their own, so a failed or repeated append only adds
rows with equal values, which reading collapses.

Content is normalised by reading null as the empty text and nothing else: these vocabularies
tell every other pair of texts apart.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .batch_bpe import BatchBpe
from .blocks import trimmed
from .segments import SegmentEncoder
from .storage import new_path

CACHE_SCHEMA = "tokenizer string, digest binary, n_tokens bigint"


def tokenizer_version(path: str) -> str:
    """Digest of the vocabulary file and of the library's version."""
    import tokenizers

    return hashlib.sha256(Path(path).read_bytes() + tokenizers.__version__.encode()).hexdigest()


@lru_cache(maxsize=4)
def _counter(path: str, spaced: bool, limit: int) -> SegmentEncoder:
    bpe = BatchBpe(path)
    return SegmentEncoder(lambda xs: [len(ids) // 4 for ids in bpe.encode_many(xs)], spaced, limit)


def count_batches(batches: Iterator[pa.RecordBatch], path: str, spaced: bool, version: str, limit: int) -> Iterator[pa.RecordBatch]:
    """(digest, text) -> (tokenizer, digest, n_tokens)."""
    counter = _counter(path, spaced, limit)
    for batch in batches:
        counts = [sum(x) for x in counter.values(batch.column("text").to_pylist())]
        yield pa.RecordBatch.from_arrays([pa.array([version] * len(counts), pa.string()), batch.column("digest"), pa.array(counts, pa.int64())], names=["tokenizer", "digest", "n_tokens"])


def read_cache(spark: SparkSession, cache_path: str, version: str) -> DataFrame:
    """Stored counts of one tokenizer, a row for each digest; none if the cache is new."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(cache_path)
    if not hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(hadoop):
        return spark.createDataFrame([], "digest binary, n_tokens bigint")
    stored = spark.read.schema(CACHE_SCHEMA).parquet(cache_path).where(F.col("tokenizer") == version)
    return stored.groupBy("digest").agg(F.max("n_tokens").alias("n_tokens"))


def token_counts(docs: DataFrame, tokenizer_path: str, cache_path: str | None = None, id_col: str = "doc_id", text_col: str = "text", spaced: bool = True, limit: int = 400_000) -> DataFrame:
    """One row per row of docs: id, n_bytes (UTF-8), n_tokens, cached.

    ``cached`` tells that the count was stored before this call. Null and empty texts have 0
    tokens; repeated rows and ids give a row each; an empty table gives none; other columns
    are ignored, whatever their names. ``spaced`` is False for vocabularies that drop white
    space. Without cache_path a new, empty cache is filled in the shared folder; a given one may hold
    counts of other tokenizers and be filled by several jobs at once.
    """
    spark = docs.sparkSession
    private = cache_path is None
    cache_path = cache_path or new_path(spark, "token_counts")
    version = tokenizer_version(tokenizer_path)
    text = F.coalesce(F.col(text_col), F.lit(""))
    keyed = docs.select(F.col(id_col).alias("id"), text.alias("text")).withColumn("digest", F.unhex(F.sha2(F.col("text"), 256)))
    before = read_cache(spark, cache_path, version)
    known = bool(before.head(1))
    misses = keyed.join(before, "digest", "left_anti") if known else keyed
    distinct = misses.select("digest", "text").dropDuplicates(["digest"])
    fresh = distinct.mapInArrow(lambda batches: trimmed(count_batches(batches, tokenizer_path, spaced, version, limit)), CACHE_SCHEMA)
    fresh.write.mode("append").parquet(cache_path)
    # nobody else writes to a folder made by this call, so its rows need no collapse
    counts = spark.read.schema(CACHE_SCHEMA).parquet(cache_path).select("digest", "n_tokens") if private else read_cache(spark, cache_path, version)
    rows = keyed.select("id", "digest", F.octet_length("text").cast("bigint").alias("n_bytes")).join(counts, "digest")
    if known:
        rows = rows.join(before.select("digest", F.lit(True).alias("was")), "digest", "left")
    was = F.coalesce(F.col("was"), F.lit(False)) if known else F.lit(False)
    return rows.select(F.col("id").alias(id_col), "n_bytes", "n_tokens", was.alias("cached"))
