"""Structured Streaming of range queries against a static index, and windows over events."""

from __future__ import annotations

import posixpath
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import LongType, StructField, StructType

from rangeknn.operators import kernels
from rangeknn.operators.index import GRAPH_TYPE, SHARD_ROWS, Kernel, build, checkpoint_root, materialise, scan_kernel, search, validate, with_rank


def search_stream(queries_stream: DataFrame, packed: DataFrame, sink_path: str, checkpoint: str, kernel: Kernel = scan_kernel):
    """Answers each micro-batch of queries and appends the results to Parquet; runs what is there and ends."""

    def one(batch: DataFrame, batch_id: int) -> None:
        done = search(packed, batch, kernel).withColumn("batch", F.lit(batch_id))
        done.write.mode("append").parquet(sink_path)

    return queries_stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def tumbling_counts(events: DataFrame, width: str = "1 day", watermark: str = "2 hours") -> DataFrame:
    """Events per window and type; works on a stream (late rows beyond the watermark go) and on a table."""
    timed = events.withColumn("at", F.col("ts").cast("timestamp"))
    if events.isStreaming:
        timed = timed.withWatermark("at", watermark)
    return timed.groupBy(F.window("at", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("window_start"), "event_type", "n")


def fresh(events: DataFrame, key: str = "event_id", watermark: str = "2 hours") -> DataFrame:
    """The first row of each key; repeats that come within the watermark go, state older than it is freed."""
    return events.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", watermark).dropDuplicatesWithinWatermark([key])


def followed_by(left: DataFrame, right: DataFrame, key: str, within: str = "10 minutes", watermark: str = "2 hours") -> DataFrame:
    """(key, left_id, right_id): events of two streams with the right one at most ``within`` after the left one."""
    side = lambda df, p: df.select(F.col(key).alias(f"{p}_key"), F.col("event_id").alias(f"{p}_id"), F.col("ts").cast("timestamp").alias(f"{p}_at")).withWatermark(f"{p}_at", watermark)
    near = F.expr(f"left_key = right_key and right_at > left_at and right_at <= left_at + interval {within}")
    return side(left, "left").join(side(right, "right"), near).select(F.col("left_key").alias(key), "left_id", "right_id")


def recent(events: DataFrame, keep: int = 5, ttl_ms: int = 86_400_000, watermark: str = "2 hours") -> DataFrame:
    """(user_id, ids, n_seen) after each batch: the ids of a user's last ``keep`` events, newest first.

    State is bounded by ``keep`` for each user and is freed when the watermark passes the user's last
    event by ``ttl_ms``. Users, times and ids that are null are left out.
    """

    def update(user: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        at, ids, seen = state.get if state.exists else ([], [], 0)
        held = list(zip(at, ids, strict=True))
        for part in parts:
            seen += len(part)
            held = sorted([*held, *zip(part["us"].tolist(), part["event_id"].tolist(), strict=True)], reverse=True)[:keep]
        state.update(([a for a, _ in held], [i for _, i in held], seen))
        state.setTimeoutTimestamp(max(held[0][0] // 1_000, state.getCurrentWatermarkMs()) + ttl_ms)
        yield pd.DataFrame({"user_id": [user[0]], "ids": [[i for _, i in held]], "n_seen": [seen]})

    timed = events.where("user_id is not null and ts is not null and event_id is not null").withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", watermark)
    rows = timed.select("user_id", "event_id", "at", F.unix_micros("at").alias("us"))
    return rows.groupBy("user_id").applyInPandasWithState(update, "user_id bigint, ids array<bigint>, n_seen bigint", "at array<bigint>, ids array<bigint>, seen bigint", "update", GroupStateTimeout.EventTimeTimeout)


def drained(streaming: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over what is there now; its rows, with the number of their batch."""
    spark = streaming.sparkSession
    root = posixpath.join(checkpoint_root(spark), "rangeknn", uuid.uuid4().hex)

    def keep(batch: DataFrame, n: int) -> None:
        batch.withColumn("batch", F.lit(n).cast("bigint")).write.mode("overwrite").parquet(f"{root}/rows/part={n}")

    streaming.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/state").foreachBatch(keep).trigger(availableNow=True).start().awaitTermination()
    schema = StructType([*streaming.schema.fields, StructField("batch", LongType())])
    return spark.read.schema(schema).parquet(f"{root}/rows").select(*schema.names)



def late_rows(events: DataFrame, delay_s: int, root: str):
    """Counts, batch by batch, the rows that come later than ``delay_s`` behind the newest time of the batches before.

    Written to root/rows as (batch, n_rows, late, high); rows without a time are counted, never late. A batch that is run
    again replaces its own row, and the newest time is read back from the rows, so a restart goes on where it was.
    """
    spark = events.sparkSession
    schema = "n_rows bigint, late bigint, high bigint, batch bigint"

    def one(batch: DataFrame, n: int) -> None:
        path = f"{root}/rows"
        seen = spark.read.schema(schema).parquet(path).where(F.col("batch") < n).agg(F.max("high")).first()[0] if n else None
        at = F.unix_micros(F.col("ts").cast("timestamp"))
        late = F.lit(False) if seen is None else F.coalesce(at < seen - delay_s * 1_000_000, F.lit(False))
        row = batch.agg(F.count("*").alias("n_rows"), F.count_if(late).alias("late"), F.max(at).alias("high"))
        row.write.mode("overwrite").parquet(f"{path}/batch={n}")

    return events.writeStream.foreachBatch(one).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()


def quality_windows(results: DataFrame, width: str = "1 day", watermark: str = "2 hours") -> DataFrame:
    """(window_start, queries, hits, recall) of results (at, hits, recall) by the time of their queries, as a stream or a table."""
    timed = results.withWatermark("at", watermark) if results.isStreaming else results
    sums = timed.groupBy(F.window("at", width).alias("w")).agg(F.count("*").alias("queries"), F.sum("hits").alias("hits"), F.round(F.avg("recall"), 6).alias("recall"))
    return sums.select(F.col("w.start").alias("window_start"), "queries", "hits", "recall")


def append_stream(objs: DataFrame, root: str, how: kernels.Params = kernels.Params(), shard_rows: int = SHARD_ROWS):
    """New objects (id, vec, attr) of a stream become an index of their own, a segment for each batch under root/segments.

    What is there is not rebuilt. A batch that is run again replaces its own segment; a batch without a valid object writes none.
    """

    def one(batch: DataFrame, n: int) -> None:
        ranked = materialise(with_rank(validate(batch)), "ranked")
        if ranked.head(1):
            build(ranked, how, shard_rows).write.mode("overwrite").parquet(f"{root}/segments/segment={n}")

    return objs.writeStream.foreachBatch(one).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()


def search_segments(spark: SparkSession, root: str, queries: DataFrame, kernel: Kernel = scan_kernel) -> DataFrame:
    """The k nearest over all segments of ``append_stream``: each is asked on its own, and the lists meet in one window.

    Cost grows with the number of segments; many small ones are best put together by a build of all objects anew.
    """
    stored = spark.read.schema(f"{GRAPH_TYPE}, segment bigint").parquet(f"{root}/segments")
    names = [r["segment"] for r in stored.select("segment").distinct().orderBy("segment").collect()]
    found = None
    for name in names:
        one = search(stored.where(F.col("segment") == name).drop("segment"), queries, kernel)
        found = one if found is None else found.unionByName(one)
    if found is None:
        return spark.createDataFrame([], "qid bigint, rn int, id bigint, d2 double, n_dist bigint, n_hops bigint")
    ks = queries.select(F.col("qid").cast("bigint").alias("qid"), "k")
    best = Window.partitionBy("qid").orderBy("d2", "id")
    return found.drop("rn").join(ks, "qid").withColumn("rn", F.row_number().over(best)).where("rn <= k").select("qid", "rn", "id", "d2", "n_dist", "n_hops")


__all__ = ["append_stream", "drained", "followed_by", "fresh", "late_rows", "materialise", "quality_windows", "recent", "search_segments", "search_stream", "tumbling_counts"]
