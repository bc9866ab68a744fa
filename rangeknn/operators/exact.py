"""Exact graphs and their properties. Work grows at least with the square: for theory and tests; what is broadcast is checked."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import kernels, thinning

MAX_OBJECTS = 5_000
#: Vectors that may be broadcast for an exact graph.
MAX_BYTES = 256 << 20
#: Sources of one task.
SOURCES = 500
#: Sources whose edges are handed on at once.
RUN = 128


def _shared_vectors(ranked: DataFrame):
    """Ranks in ascending order, and the vectors in that order as a broadcast."""
    n, one = ranked.count(), ranked.select(F.size("vec").alias("dim")).head()
    if n * (one["dim"] if one else 0) * 8 > MAX_BYTES:
        raise ValueError(f"exact graphs broadcast at most {MAX_BYTES >> 20} MB of vectors; build the index instead")
    rows = ranked.select("rank", F.col("vec").cast("array<double>").alias("vec")).orderBy("rank").toArrow()
    x = rows["vec"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(n, -1) if n else np.zeros((0, 0))
    return rows["rank"].to_numpy().astype(np.int64), ranked.sparkSession.sparkContext.broadcast(x)


def _tasks(n: int) -> int:
    return max(8, math.ceil(n / SOURCES))


def _by_source(ranked: DataFrame, kept, sources: tuple[int, int] | None = None, schema: str = "src bigint, dst bigint") -> DataFrame:
    """edges (src, dst) as ranks: kept(first, last position, all vectors) has a list for each source of a run, vectors broadcast. sources: the
    first and last rank whose edges are wanted; the others remain candidates and witnesses."""
    ranks, shared = _shared_vectors(ranked)
    base = int(ranks[0]) if len(ranks) else 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mine, x = np.sort(np.concatenate([np.zeros(0, np.int64), *(b.column("rank").to_numpy() for b in batches)])) - base, None
        for part in np.split(mine, np.flatnonzero(np.diff(mine) != 1) + 1):
            for a in range(0, len(part), RUN):
                x = thinning.Rows(shared.value) if x is None else x
                at = part[a : a + RUN]
                found = kept(int(at[0]), int(at[-1]), x)
                src = np.repeat(at, [len(f) for f in found]) + base
                yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(np.concatenate(found).astype(np.int64) + base)], names=["src", "dst"])

    own = ranked.select("rank") if sources is None else ranked.select("rank").where(F.col("rank").between(*sources))
    return own.repartitionByRange(_tasks(len(ranks) if sources is None else min(len(ranks), sources[1] - sources[0] + 1)), "rank").mapInArrow(run, schema)


def by_definition(x: int, vecs: np.ndarray) -> np.ndarray:
    """The recursive rule itself: by distance to x, a kept witness in between drops the edge."""
    own = kernels.d2(vecs[x], vecs)
    kept: list[int] = []
    for y in sorted((p for p in range(len(vecs)) if p != x), key=lambda p: (own[p], p)):
        lo, hi = min(x, y), max(x, y)
        if not any(lo < z < hi and own[z] < own[y] and kernels.d2(vecs[y], vecs[z : z + 1])[0] < own[y] for z in kept):
            kept.append(y)
    return np.array(sorted(kept), np.int64)


def between_graph(ranked: DataFrame, method: str = "prune", sources: tuple[int, int] | None = None) -> DataFrame:
    """Directed edges (src, dst) by rank: dropped only by a kept witness nearer to both ends that
    lies strictly between them in attribute order. sources: only edges that leave these ranks, first and last."""
    if method == "definition":
        return _by_source(ranked, lambda a, b, x: [by_definition(p, x.vecs) for p in range(a, b + 1)], sources)
    return _by_source(ranked, lambda a, b, x: x.two_sided(a, b), sources)


def mrng(ranked: DataFrame) -> DataFrame:
    """The spatial rule: witnesses may have any attribute."""
    return _by_source(ranked, lambda a, b, x: x.nearest_first(np.arange(a, b + 1)))


def box_graph(objs: DataFrame, m: int | None = None) -> DataFrame:
    """Several attributes (column ranks): witnesses in the closed box of the two ends. Ids, not ranks."""
    rows = objs.select("id", "vec", "ranks").orderBy("id").collect()
    if len(rows) > MAX_OBJECTS:
        raise ValueError(f"limited to {MAX_OBJECTS} objects")
    ids, x, r = np.array([a["id"] for a in rows]), np.array([a["vec"] for a in rows], float), np.array([a["ranks"] for a in rows])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            src, dst = [], []
            for i in batch.column("id").to_pylist():
                p = int(np.searchsorted(ids, i))
                found = ids[kernels.in_box(p, np.delete(np.arange(len(ids)), p), x, r, m)]
                src += [i] * len(found)
                dst += found.tolist()
            yield pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64())], names=["src", "dst"])

    return objs.select("id").repartition(8).mapInArrow(run, "src bigint, dst bigint")


def induce(edges: DataFrame, r_lo: int, r_hi: int) -> DataFrame:
    return edges.where(F.col("src").between(r_lo, r_hi) & F.col("dst").between(r_lo, r_hi))


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Edges in one graph only."""
    return a.exceptAll(b).union(b.exceptAll(a))


def missing_links(edges: DataFrame, ranked: DataFrame) -> DataFrame:
    """(src, dst): consecutive ranks without an edge. If none is missing, in either direction, every
    interval of ranks is strongly connected."""
    r = ranked.select("rank")
    up = r.join(r.select((F.col("rank") - 1).alias("rank")), "rank").select(F.col("rank").alias("a"), (F.col("rank") + 1).alias("b"))
    return up.union(up.select("b", "a")).toDF("src", "dst").join(edges, ["src", "dst"], "left_anti")


def knn_join(objs: DataFrame, queries: DataFrame, k: int, max_queries: int = 10_000) -> DataFrame:
    """(qid, rn, id, d2) of the k nearest in range, by column expressions alone; null ends are open.

    The queries are broadcast, so their number is checked: beyond it use ``index.search``.
    """
    from rangeknn.functions.vectors import l2_sq

    if queries.count() > max_queries:
        raise ValueError(f"more than {max_queries} queries: search in shards instead")
    inside = (F.col("lo").isNull() | (F.col("attr") >= F.col("lo"))) & (F.col("hi").isNull() | (F.col("attr") <= F.col("hi")))
    met = objs.select("id", "vec", "attr").join(F.broadcast(queries.select("qid", "qvec", "lo", "hi")), inside)
    best = Window.partitionBy("qid").orderBy("d2", "id")
    return met.select("qid", "id", l2_sq(F.col("vec"), F.col("qvec")).alias("d2")).withColumn("rn", F.row_number().over(best)).where(F.col("rn") <= k).select("qid", "rn", "id", "d2")


def stuck(x: int, out: np.ndarray, vecs: np.ndarray) -> np.ndarray:
    """Targets that x can neither reach directly nor approach by one of its neighbours ``out``."""
    own = kernels.d2(vecs[x], vecs)
    left = np.setdiff1d(np.arange(len(vecs)), np.append(out, x))
    for z in out:
        if not len(left):
            break
        left = left[kernels.d2(vecs[z], vecs[left]) >= own[left]]
    return left


def monotone_violations(edges: DataFrame, ranked: DataFrame) -> DataFrame:
    """Ordered pairs (x, y) of which x has no neighbour nearer to y than x is.

    All pairs are looked at, source by source with the vectors broadcast; only violations are emitted.
    """
    ranks, shared = _shared_vectors(ranked)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = None
        for batch in batches:
            at = np.searchsorted(ranks, batch.column("rank").to_numpy())
            outs = [np.searchsorted(ranks, np.zeros(0, np.int64) if out is None else out) for out in batch.column("out").to_numpy(zero_copy_only=False)]
            for a in range(0, len(at), RUN):
                for mine in np.split(np.arange(a, min(len(at), a + RUN)), np.flatnonzero(np.diff(at[a : a + RUN]) != 1) + 1):
                    rows = thinning.Rows(shared.value) if rows is None else rows
                    asked = outs[mine[0] : mine[-1] + 1]
                    found = rows.stuck(int(at[mine[0]]), asked) if rows.clear else [stuck(int(x), out, rows.vecs) for x, out in zip(at[mine], asked, strict=True)]
                    xs = np.repeat(ranks[at[mine]], [len(f) for f in found])
                    yield pa.RecordBatch.from_arrays([pa.array(xs), pa.array(ranks[np.concatenate(found).astype(np.int64)])], names=["x", "y"])

    out = edges.groupBy(F.col("src").alias("rank")).agg(F.collect_list("dst").alias("out"))
    run_of = F.floor(F.col("rank") / RUN)  # dealt by a hash of it: ranges would be sampled, and all lists made twice
    mine = ranked.select("rank").join(out, "rank", "left").repartition(_tasks(len(ranks)), run_of).sortWithinPartitions("rank")
    return mine.mapInArrow(run, "x bigint, y bigint")


def reach(edges: list[tuple[int, int]], start: int, lo: int, hi: int) -> int:
    """Nodes of [lo, hi] that can be reached from start inside it."""
    out: dict[int, list[int]] = {}
    for a, b in edges:
        if lo <= a <= hi and lo <= b <= hi:
            out.setdefault(a, []).append(b)
    seen, todo = {start}, [start]
    while todo:
        for b in out.get(todo.pop(), []):
            if b not in seen:
                seen.add(b)
                todo.append(b)
    return len(seen)
