"""Approximate nearest neighbours by inner product: a vantage-point tree for each shard.

One more coordinate makes all indexed vectors equally long, which turns the largest inner
product into the smallest Euclidean distance, a metric. A subtree is left out when its
triangle-inequality bound times ``factor`` exceeds the k-th distance so far: factor 1 is exact,
larger factors trade recall for work. Queries of a block walk the tree together, so
every node costs one matrix product.

Trees are grown once and stored. Queries come to them as broadcast chunks of bounded size; a task keeps
each query's best over all its trees, so what it has found in one prunes the next, and it sends one list on.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .blocks import matrix, runs
from .embed_dedup import usable
from .storage import materialise

SHARD_ROWS = 16_384
QUERY_BLOCK = 2_048
#: Bytes of query vectors that are broadcast at once; more queries are searched chunk by chunk.
BROADCAST_BYTES = 64 << 20
LEAF = 256
#: One restores the exact search; two keeps recall over 0.95 from 8 to 64 dimensions (README).
FACTOR = 2.0
MARGIN = 1e-9


class Tree:
    """ids and vectors in leaf order; nodes: rows from and to, the vantage's row (-1 in a leaf), two children;
    bounds: nearest and farthest of the left half, then of the right half, from the vantage."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, norm2: float, leaf: int = LEAF, seed: int = 0) -> None:
        self.norm2, self.leaf = norm2, leaf
        lift = np.sqrt(np.maximum(norm2 - (x * x).sum(axis=1), 0.0))
        rng = np.random.default_rng(seed)
        order = np.arange(len(ids))
        nodes: list[list[int]] = []
        bounds: list[tuple[float, ...]] = []

        def grow(a: int, b: int) -> int:
            at = len(nodes)
            nodes.append([a, b, -1, -1, -1])
            bounds.append((0.0, 0.0, 0.0, 0.0))
            if b - a > leaf:
                rows = order[a:b]
                some = rows[rng.choice(b - a, min(8, b - a), replace=False)]
                near = x[rows] @ x[some].T + np.outer(lift[rows], lift[some])
                v = int(near.var(axis=0).argmax())
                d = np.sqrt(np.maximum(2 * norm2 - 2 * near[:, v], 0.0))
                mid = (b - a) // 2
                split = np.argpartition(d, mid)
                order[a:b] = rows[split]
                d = d[split]
                if d.max() > d.min():
                    bounds[at] = (float(d[:mid].min()), float(d[:mid].max()), float(d[mid:].min()), float(d[mid:].max()))
                    nodes[at][2:] = int(some[v]), grow(a, a + mid), grow(a + mid, b)
            return at

        if len(ids):
            grow(0, len(ids))
        self.ids, self.x = ids[order], x[order]
        self.nodes, self.bounds = np.array(nodes, np.int64).reshape(-1, 5), np.array(bounds).reshape(-1, 4)
        place = np.argsort(order)
        inner = self.nodes[:, 2] >= 0
        self.nodes[inner, 2] = place[self.nodes[inner, 2]]

    @classmethod
    def opened(cls, norm2: float, ids: bytes, x: bytes, nodes: bytes, bounds: bytes) -> Tree:
        """A tree as it was stored."""
        self = cls.__new__(cls)
        self.norm2, self.ids = norm2, np.frombuffer(ids, np.int64)
        self.x = np.frombuffer(x).reshape(len(self.ids), -1)
        self.nodes, self.bounds = np.frombuffer(nodes, np.int64).reshape(-1, 5), np.frombuffer(bounds).reshape(-1, 4)
        return self

    def search(self, q: np.ndarray, k: int, factor: float, own: np.ndarray | None = None, best: tuple | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
        """(query row, id, score) of up to k best for each row of q, by row and rank, and the number of products.

        own: the id that each query has itself and must not find (-1 is no id of a row here). best: what other
        trees gave, which competes.
        """
        n = len(q)
        kth = np.full(n, -np.inf)
        best = best or (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        full = np.flatnonzero(np.bincount(best[0], minlength=n) >= k)
        kth[full] = best[2][np.searchsorted(best[0], full, "right") - 1]
        length = (q * q).sum(axis=1)
        work = 0

        def far(active: np.ndarray) -> np.ndarray:
            with np.errstate(invalid="ignore"):
                return np.sqrt(np.maximum(length[active] + self.norm2 - 2 * kth[active], 0.0))

        def leaf(a: int, b: int, active: np.ndarray) -> None:
            nonlocal best, work
            scores = q[active] @ self.x[a:b].T
            work += scores.size
            i, j = np.nonzero(scores >= kth[active][:, None] - MARGIN)
            rows, at = active[i], a + j
            if own is not None:
                keep = self.ids[at] != own[rows]
                rows, at = rows[keep], at[keep]
            if not len(rows):
                return
            exact = (q[rows] * self.x[at]).sum(axis=1)
            touched = np.zeros(n, bool)
            touched[rows] = True
            old = touched[best[0]]
            r = np.concatenate([best[0][old], rows])
            ids = np.concatenate([best[1][old], self.ids[at]])
            s = np.concatenate([best[2][old], exact])
            order = np.lexsort((ids, -s, r))
            r, ids, s = r[order], ids[order], s[order]
            start = np.flatnonzero(np.r_[True, r[1:] != r[:-1]])
            place = np.arange(len(r)) - np.repeat(start, np.diff(np.r_[start, len(r)]))
            keep = place < k
            full = place == k - 1
            kth[r[full]] = s[full]
            merged = [np.concatenate([b0[~old], new[keep]]) for b0, new in zip(best, (r, ids, s), strict=True)]
            order = np.argsort(merged[0], kind="stable")
            best = tuple(m[order] for m in merged)

        def walk(node: int, active: np.ndarray) -> None:
            nonlocal work
            a, b, vantage, lo, hi = self.nodes[node].tolist()
            if vantage < 0:
                leaf(a, b, active)
                return
            left, right = self.bounds[node, :2], self.bounds[node, 2:]
            d = np.sqrt(np.maximum(length[active] + self.norm2 - 2 * (q[active] @ self.x[vantage]), 0.0))
            work += len(active)
            to_left = d - left[1] <= right[0] - d
            for group, first, second in ((to_left, (lo, left), (hi, right)), (~to_left, (hi, right), (lo, left))):
                if not group.any():
                    continue
                for child, (near, wide) in (first, second):
                    bound = np.maximum(np.maximum(d[group] - wide, near - d[group]), 0.0)
                    go = bound * factor <= far(active[group]) + MARGIN
                    if go.any():
                        walk(child, active[group][go])

        if len(self.ids) and n:
            walk(0, np.arange(n))
        return (*best, work)


def _packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (dim, part) -> one row a group: dim, part, ids, x."""
    for _, by_dim in runs(batches, "dim"):
        for part, t in runs(iter(by_dim.combine_chunks().to_batches()), "part"):
            values = (t["dim"][0].as_py(), part, t["id"].to_numpy().tobytes(), matrix(t["vec"]).tobytes())
            yield pa.RecordBatch.from_arrays([pa.array([v], ty) for v, ty in zip(values, (pa.int32(), pa.int64(), pa.binary(), pa.binary()), strict=True)], names=["dim", "part", "ids", "x"])


def _pack(rows: DataFrame, per: int, name: str) -> DataFrame:
    """Groups of about ``per`` rows of one length, dealt by a hash of the id."""
    parts = rows.groupBy("dim").agg(F.ceil(F.count("*") / per).cast("bigint").alias("parts"))
    dealt = rows.join(parts, "dim").withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")).cast("bigint")).drop("parts")
    n = max(1, parts.agg(F.sum("parts")).first()[0] or 1)
    return materialise(dealt.repartition(n, "dim", "part").sortWithinPartitions("dim", "part").mapInArrow(_packed, "dim int, part bigint, ids binary, x binary"), name)


def neighbours(vectors: DataFrame, queries: DataFrame, k: int = 20, factor: float = FACTOR, id_col: str = "vec_id", vec_col: str = "embedding", shard_rows: int = SHARD_ROWS, query_block: int = QUERY_BLOCK, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Each query's k nearest rows of vectors but itself: query_id, rank (from 1), id, score.

    score is the inner product in double precision; ties go to the smaller id. Vectors that
    are null, zero or hold null or non-finite components, and rows without an id, take no part, on either side.
    Vectors meet only those of their own length. Fewer candidates than k: all of them. Rows that share an id
    are candidates of their own, none of them for a query of that id, and queries of their own. Other columns
    are ignored; empty tables give no rows.
    """
    spark = vectors.sparkSession
    pick = lambda df: df.select(F.col(id_col).cast("bigint").alias("id"), F.col(vec_col).cast("array<double>").alias("vec")).where(F.col("id").isNotNull() & usable("vec")).withColumn("dim", F.size("vec"))
    rows, asked = pick(vectors), pick(queries)
    norm2 = rows.agg(F.max(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x * x))).first()[0]
    widest, n_queries = asked.agg(F.max("dim"), F.count("*")).first()
    if norm2 is None or not n_queries:
        return spark.createDataFrame([], f"query_id bigint, rank int, {id_col} bigint, score double")

    def planted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for dim, part, ids, x in zip(*(batch.column(c).to_pylist() for c in ("dim", "part", "ids", "x")), strict=True):
                own = np.frombuffer(ids, np.int64)
                t = Tree(own, np.frombuffer(x).reshape(len(own), -1), norm2, seed=part)
                blobs = [pa.array([v.tobytes()], pa.binary()) for v in (t.ids, t.x, t.nodes, t.bounds)]
                yield pa.RecordBatch.from_arrays([pa.array([dim], pa.int32()), *blobs], names=["dim", "ids", "x", "nodes", "bounds"])

    trees = materialise(_pack(rows, shard_rows, "shards").mapInArrow(planted, "dim int, ids binary, x binary, nodes binary, bounds binary"), "trees")
    blocks = _pack(asked, query_block, "query_blocks").withColumn("block", F.monotonically_increasing_id())
    # every chunk is a bounded number of rows, whatever the number of queries
    places = [r["block"] for r in blocks.select("block").orderBy("block").collect()]
    per = max(1, broadcast_bytes // (8 * widest * query_block))
    partial = []
    for a in range(0, len(places), per):
        chunk = blocks.where(F.col("block").between(places[a], places[min(len(places), a + per) - 1])).orderBy("block").collect()
        shared = spark.sparkContext.broadcast([(r["dim"], a + i, bytes(r["ids"]), bytes(r["x"])) for i, r in enumerate(chunk)])

        def search(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            asks = [(dim, at, own := np.frombuffer(ids, np.int64), np.frombuffer(x).reshape(len(own), -1)) for dim, at, ids, x in shared.value]
            best: list[tuple | None] = [None] * len(asks)
            for batch in batches:
                for i in range(batch.num_rows):
                    t = Tree.opened(norm2, *(batch.column(c)[i].as_py() for c in ("ids", "x", "nodes", "bounds")))
                    for place, (dim, _, own, q) in enumerate(asks):
                        if dim == batch.column("dim")[i].as_py():
                            best[place] = t.search(q, k, factor, own, best[place])[:3]
            for (_, at, own, _), found in zip(asks, best, strict=True):
                if found:
                    yield pa.RecordBatch.from_arrays([pa.array((at << 32) + found[0]), pa.array(own[found[0]]), *map(pa.array, found[1:])], names=["ask", "query_id", "id", "score"])

        found = trees.mapInArrow(search, "ask bigint, query_id bigint, id bigint, score double")
        best = Window.partitionBy("ask").orderBy(F.desc("score"), "id")
        ranked = found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", F.col("id").alias(id_col), "score")
        partial.append(materialise(ranked, "nearest") if len(places) > per else ranked)
    return reduce(DataFrame.union, partial)
