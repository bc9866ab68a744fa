"""Accuracy and cost measures."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def recall_at_k(found: DataFrame, truth: DataFrame, k: int, denominator: str = "k") -> DataFrame:
    """(qid, hits, recall). denominator 'k' is the usual one; 'min_k_truth' counts what is in range."""
    hits = truth.join(found.select("qid", "id", F.lit(1).alias("hit")), ["qid", "id"], "left").groupBy("qid").agg(F.count("hit").alias("hits"), F.count("*").alias("n"))
    base = F.lit(k) if denominator == "k" else F.least(F.lit(k).cast("bigint"), F.col("n"))
    return hits.select("qid", "hits", (F.col("hits") / base).alias("recall"))


def degree_stats(index: DataFrame) -> DataFrame:
    """Nodes, edges, mean degree and deployed bytes (four for an edge, four for a node's pointer)."""
    n = index.agg(F.sum(F.size("ids")).alias("nodes"), F.sum(F.size("nbrs")).alias("edges"))
    return n.select("nodes", "edges", F.round(F.col("edges") / F.col("nodes"), 6).alias("mean_degree"), (4 * F.col("edges") + 4 * F.col("nodes")).alias("bytes"))


def edge_coverage(whole: DataFrame, rebuilt: DataFrame) -> DataFrame:
    """Share of a rebuilt graph's edges that the one index has within the interval."""
    both = rebuilt.join(whole.select("src", "dst", F.lit(1).alias("hit")), ["src", "dst"], "left")
    return both.agg(F.count("hit").alias("shared"), F.count("*").alias("rebuilt")).withColumn("coverage", F.round(F.col("shared") / F.col("rebuilt"), 6))


def at_recall(curve: DataFrame, target: float) -> DataFrame:
    """curve(method, recall, cost) -> the least cost that reaches target, null if none does."""
    ok = F.when(F.col("recall") >= target, F.col("cost"))
    return curve.groupBy("method").agg(F.min(ok).alias("cost"), F.max("recall").alias("max_recall"))


def interpolated(curve: DataFrame, target: float) -> DataFrame:
    """curve(method, recall, cost) -> cost at exactly ``target``, on the line between the two points around
    it; the first point's own if that already reaches it, null if none does."""
    turn = Window.partitionBy("method").orderBy("recall", F.desc("cost"))
    r0, c0 = F.lag("recall").over(turn), F.lag("cost").over(turn)
    steps = curve.select("method", "recall", "cost", r0.alias("r0"), c0.alias("c0"))
    line = F.col("c0") + (F.lit(target) - F.col("r0")) * (F.col("cost") - F.col("c0")) / (F.col("recall") - F.col("r0"))
    at = F.when((F.col("recall") >= target) & F.col("r0").isNull(), F.col("cost")).when((F.col("recall") >= target) & (F.col("r0") < target), line)
    return steps.groupBy("method").agg(F.min(at).alias("cost"), F.max("recall").alias("max_recall"))


def tuned(tried: DataFrame, fresh: DataFrame, target: float) -> DataFrame:
    """Both (method, ef, recall, n_dist), on two halves of the queries. For each method the cheapest ef
    that reaches target on the first half, with what it gives on the second; null if none reaches it."""
    choice = tried.groupBy("method").agg(F.min_by("ef", F.when(F.col("recall") >= target, F.col("n_dist"))).alias("ef"))
    return choice.join(fresh, ["method", "ef"], "left").select("method", "ef", "recall", "n_dist")


def speed_ratio(at: DataFrame, base: str) -> DataFrame:
    """(method, ratio): how many times the cost of ``base`` each method needs at the same recall."""
    one = at.where(F.col("method") == base).select(F.col("cost").alias("base_cost"))
    return at.join(F.broadcast(one), F.lit(True)).select("method", (F.col("cost") / F.col("base_cost")).alias("ratio"))


def header_stats(index: DataFrame) -> DataFrame:
    """Entry headers: nodes, total and mean ids of the list of each right end, bytes of the pointer form,
    their share of the deployed bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            total, edges = [], []
            for closer, nbrs in zip(batch.column("closer"), batch.column("nbrs"), strict=True):
                depth: list[int] = []
                for c in closer.values.to_pylist():
                    depth.append(1 if c < 0 else depth[c] + 1)
                total.append((len(depth), sum(depth)))
                edges.append(len(nbrs.values))
            yield pa.RecordBatch.from_arrays([pa.array([n for n, _ in total], pa.int64()), pa.array([t for _, t in total], pa.int64()), pa.array(edges, pa.int64())], names=["n", "t", "e"])

    parts = index.select("closer", "nbrs").mapInArrow(run, "n bigint, t bigint, e bigint")
    s = parts.agg(F.sum("n").alias("nodes"), F.sum("t").alias("header_ids"), F.sum("e").alias("edges"))
    return s.select("nodes", "header_ids", F.round(F.col("header_ids") / F.col("nodes"), 6).alias("mean_ids"), (4 * F.col("nodes")).alias("header_bytes"), F.round(F.col("nodes") / (F.col("nodes") + F.col("edges")), 6).alias("share"))


def gap_breakdown(edges: DataFrame, exact: DataFrame, candidates: DataFrame) -> DataFrame:
    """One row: how a bounded index departs from the exact graph. All inputs (src, dst), distinct.

    endpoint_absent: exact edges whose end was no candidate. crowded_out: exact edges whose end was one (cap
    reached, or a witness that the exact graph has dropped). witness_absent: edges the exact graph lacks.
    """
    flag = lambda df, c: df.select("src", "dst", F.lit(1).alias(c))
    both = flag(edges, "i").join(flag(exact, "x"), ["src", "dst"], "full").join(flag(candidates, "c"), ["src", "dst"], "left")
    n = lambda cond: F.count(F.when(cond, 1))
    has = {c: F.col(c).isNotNull() for c in "ixc"}
    got = both.agg(n(has["i"] & has["x"]).alias("shared"), n(has["x"] & ~has["i"] & ~has["c"]).alias("endpoint_absent"), n(has["x"] & ~has["i"] & has["c"]).alias("crowded_out"), n(has["i"] & ~has["x"]).alias("witness_absent"))
    return got.withColumn("recall", F.round(F.try_divide("shared", F.col("shared") + F.col("endpoint_absent") + F.col("crowded_out")), 6)).withColumn("precision", F.round(F.try_divide("shared", F.col("shared") + F.col("witness_absent")), 6))
