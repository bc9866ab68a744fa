"""Several attributes: objects (id, vec, attrs), queries (qid, qvec, box, k), box an array of (lo, hi).

Shards are runs of ranks of the first attribute, so a box is routed by its first interval; inside a
shard the graph's edges are dropped only by witnesses in the closed box of their two ends.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels
from .index import GRAPH_TYPE, SHARD_ROWS, SHARD_TYPE, Shard, global_centroid, materialise, search, with_rank

BOX_TYPE = SHARD_TYPE + ", box binary"


def rank_first(objs: DataFrame) -> DataFrame:
    """Objects ranked by their first attribute; rows with a null or NaN attribute cannot be found and go."""
    whole = objs.where("id is not null and vec is not null and attrs is not null").where(~F.exists("attrs", lambda a: a.isNull() | F.isnan(a.cast("double"))))
    return with_rank(whole.withColumn("attr", F.element_at("attrs", 1).cast("double")))


def build(ranked: DataFrame, how: kernels.Params = kernels.Params(), shard_rows: int = SHARD_ROWS) -> DataFrame:
    """The box index, a row for each shard."""
    rows = ranked.select(((F.col("rank") - 1) / shard_rows).cast("bigint").alias("shard"), "rank", F.col("id").cast("bigint").alias("id"), F.col("vec").cast("array<double>").alias("vec"), F.col("attrs").cast("array<double>").alias("attrs"))
    centre = np.array(global_centroid(ranked))

    def pack(t: pa.Table) -> pa.Table:
        t = t.sort_by("rank")
        n, flat = t.num_rows, lambda c: t[c].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64)
        x, attrs = flat("vec").reshape(n, -1), flat("attrs").reshape(n, -1)
        start, nbrs = kernels.box_graph(x, attrs, how)
        closer = kernels.previous_closer(kernels.d2(centre, x))
        first = attrs[:, 0]
        longs, doubles = pa.list_(pa.int64()), pa.list_(pa.float64())
        made = {
            "shard": pa.array([t["shard"][0].as_py()], pa.int64()),
            "first_rank": pa.array([t["rank"][0].as_py()], pa.int64()),
            "lo": pa.array([float(first[0])], pa.float64()),
            "hi": pa.array([float(first[-1])], pa.float64()),
            "ids": pa.array([t["id"].to_pylist()], longs),
            "attrs": pa.array([first], doubles),
            "dim": pa.array([x.shape[1]], pa.int32()),
            "vecs": pa.array([x.tobytes()], pa.binary()),
            "start": pa.array([start], longs),
            "nbrs": pa.array([nbrs], longs),
            "closer": pa.array([closer], longs),
            "box": pa.array([attrs.tobytes()], pa.binary()),
        }
        return pa.table(made)

    return materialise(rows.groupBy("shard").applyInArrow(pack, GRAPH_TYPE + ", box binary"), "box_index")


def inside(s: Shard, lo: int, hi: int, box) -> np.ndarray:
    """Mask of the shard's rows in [lo, hi] that lie in every interval of the box."""
    ok = np.zeros(len(s.ids), bool)
    ok[lo : hi + 1] = True
    for j, b in enumerate(box):
        if b["lo"] is not None:
            ok &= s.box[:, j] >= b["lo"]
        if b["hi"] is not None:
            ok &= s.box[:, j] <= b["hi"]
    return ok


def _entry(s: Shard, lo: int, hi: int, ok: np.ndarray) -> int:
    """The first entry pointer of the first attribute that lies in the box, else the first row in it."""
    at = hi
    while at >= lo:
        if ok[at]:
            return at
        at = int(s.closer[at])
    return int(np.flatnonzero(ok)[0])


def box_kernel(ef: int = 64, fallback: bool = True):
    """Beam search inside the box. No theorem makes a box's subgraph connected: with fallback,
    a shard in which fewer than k of the box's rows were reached is scanned."""

    def run(s: Shard, q: np.ndarray, lo: int, hi: int, k: int, qid: int, box):
        ok = inside(s, lo, hi, box)
        if not ok.any():
            return [], 0, 0
        got, n_dist, hops = kernels.beam(s.start, s.nbrs, s.vecs, q, lo, hi, k, ef, _entry(s, lo, hi, ok), passes=ok)
        if fallback and len(got) < min(k, int(ok.sum())):
            got, more, _ = box_scan(s, q, lo, hi, k, qid, box)
            n_dist += more
        return got, n_dist, hops

    return run


def box_scan(s: Shard, q: np.ndarray, lo: int, hi: int, k: int, qid: int, box):
    """Exact: every row of the box."""
    at = np.flatnonzero(inside(s, lo, hi, box))
    d = kernels.d2(q, s.vecs[at])
    best = np.lexsort((s.ids[at], d))[:k]
    return [(float(d[i]), int(at[i])) for i in best], len(at), 0


def box_search(index: DataFrame, queries: DataFrame, kernel=None) -> DataFrame:
    """k nearest in the box, routed by its first interval; null ends are open, an empty box has no rows."""
    first = F.element_at("box", 1)
    return search(index, queries.withColumn("lo", first["lo"]).withColumn("hi", first["hi"]), kernel or box_kernel())


def edges(index: DataFrame) -> DataFrame:
    """(src, dst) ids of the box graph."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                s = Shard(batch.slice(i, 1))
                src = np.repeat(np.arange(len(s.ids)), np.diff(s.start))
                yield pa.RecordBatch.from_arrays([pa.array(s.ids[src]), pa.array(s.ids[s.nbrs])], names=["src", "dst"])

    return index.mapInArrow(run, "src bigint, dst bigint")
