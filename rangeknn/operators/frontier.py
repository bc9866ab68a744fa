"""Searches and candidate graphs written with joins instead of a kernel per shard."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangeknn.functions.vectors import l2_sq

from . import index, kernels
from .index import materialise


def frontier_search(ranked: DataFrame, edges: DataFrame, queries: DataFrame, ef: int, max_hops: int = 64, shard_rows: int | None = None) -> DataFrame:
    """Range search in bulk-synchronous hops: (qid, rn, id, d2, n_dist, n_hops).

    ranked(rank, id, vec), edges(src, dst) by rank, queries(qid, qvec, r_lo, r_hi, k). Each hop expands every
    unexpanded row of all pools, keeps neighbours in range that were not seen, and cuts the pools to the ef
    nearest. Entry: the first rank of the interval; with shard_rows, whose graphs have no edges between shards, the first
    one in each shard. Each hop writes out what is new, and the pools if one has to be cut; the loop ends
    when no pool has an unexpanded row; more than max_hops hops are an error.
    """
    nodes = materialise(ranked.select("rank", "id", "vec"), "nodes")
    links = materialise(edges.select("src", "dst"), "links")
    asked = materialise(queries.where("r_lo <= r_hi").select("qid", "qvec", "r_lo", "r_hi", "k"), "asked")
    nearest = Window.partitionBy("qid").orderBy("d2", "id")
    room = F.greatest(F.lit(ef), F.col("k"))

    def measured(pairs: DataFrame) -> DataFrame:
        both = pairs.join(nodes, "rank").join(asked.select("qid", "qvec"), "qid")
        return both.select("qid", "rank", "id", l2_sq(F.col("vec"), F.col("qvec")).alias("d2"))

    first = asked.select("qid", F.col("r_lo").alias("rank"))
    if shard_rows is not None:
        at = F.explode(F.sequence(F.expr(f"(r_lo - 1) div {shard_rows}"), F.expr(f"(r_hi - 1) div {shard_rows}"))).alias("shard")
        first = asked.select("qid", "r_lo", at).select("qid", F.greatest("r_lo", F.col("shard") * shard_rows + 1).alias("rank"))
    pool = front = materialise(measured(first).withColumn("hop", F.lit(0)), "pool")
    seen = pool.select("qid", "rank")
    for hop in range(1, max_hops + 1):
        if not front.head(1):
            break
        step = front.select("qid", F.col("rank").alias("src")).join(links, "src").join(asked.select("qid", "r_lo", "r_hi"), "qid")
        new = step.where("dst between r_lo and r_hi").select("qid", F.col("dst").alias("rank")).distinct().join(seen, ["qid", "rank"], "left_anti")
        new = materialise(measured(new).withColumn("hop", F.lit(hop)), "new")
        seen = seen.unionByName(new.select("qid", "rank"))
        both = pool.unionByName(new)
        if both.groupBy("qid").agg(F.count("*").alias("n")).join(asked.select("qid", "k"), "qid").where(F.col("n") > room).head(1):
            best = both.join(asked.select("qid", "k"), "qid").withColumn("place", F.row_number().over(nearest))
            pool = materialise(best.where(F.col("place") <= room).drop("place", "k"), "pool")
            front = pool.where(F.col("hop") == hop)
        else:
            pool, front = both, new
    else:
        if front.head(1):
            raise RuntimeError(f"pools still grow after {max_hops} hops")
    cost = seen.groupBy("qid").agg(F.count("*").alias("n_dist"))
    hops = pool.groupBy("qid").agg(F.max("hop").cast("bigint").alias("n_hops"))
    found = pool.join(asked.select("qid", "k"), "qid").withColumn("rn", F.row_number().over(nearest)).where("rn <= k")
    return found.join(cost, "qid").join(hops, "qid").select("qid", "rn", "id", "d2", "n_dist", "n_hops")


def exact_knn(ranked: DataFrame, k: int, shard_rows: int = index.SHARD_ROWS) -> DataFrame:
    """Exact k-NN graph (src, dst, d2) by ids, ties to the smaller one: blocks of objects meet slices of all vectors, which are
    broadcast, shard_rows of them at a time."""
    asked = ranked.select("rank", F.col("id").cast("bigint").alias("id"), F.col("vec").cast("array<double>").alias("vec"))
    asked = asked.repartition(max(1, math.ceil(asked.count() / 1_024)))

    def answer(ids, shared):
        def run(batches):
            for batch in batches:
                for a in range(0, batch.num_rows, 256):
                    part = batch.slice(a, 256)
                    mine = part.column("id").to_numpy()
                    got = kernels.nearest_of(mine, ids.value, np.stack(part.column("vec").to_numpy(zero_copy_only=False)), shared.value, k, shard_rows)
                    src = np.repeat(mine, [len(g[0]) for g in got])
                    dst, d2 = (np.concatenate([g[i] for g in got]) for i in (0, 1))
                    yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst), pa.array(d2)], names=["src", "dst", "d2"])

        return run

    slices, met = index.vector_slices(ranked, "id"), None
    for ids, shared in slices:
        one = asked.select("id", "vec").mapInArrow(answer(ranked.sparkSession.sparkContext.broadcast(ids), shared), "src bigint, dst bigint, d2 double")
        met = one if met is None else met.union(one)
    if met is None:
        return ranked.sparkSession.createDataFrame([], "src bigint, dst bigint, d2 double")
    if len(slices) == 1:
        return met
    best = Window.partitionBy("src").orderBy("d2", "dst")
    return met.withColumn("rn", F.row_number().over(best)).where(F.col("rn") <= k).drop("rn")


def bucketed_knn(objs: DataFrame, k: int, cell_rows: int = 2_000, copies: int = 3) -> DataFrame:
    """Approximate k-NN graph (src, dst, d2) of objects (id, vec): each row joins its nearest cells.

    Centres are the rows with the smallest hashes, one for every cell_rows rows; a row is a candidate in its
    ``copies`` nearest cells, each cell answers for all its members, and the lists meet in one window. A cell
    that is much larger than planned is worked through in blocks. One cell for all makes it exact.
    """
    n_cells = max(1, math.ceil(objs.count() / cell_rows))
    if n_cells > 100_000:
        raise ValueError("over 100,000 cells: make cells larger or shard first")
    some = objs.select("vec", F.xxhash64("id").alias("h")).orderBy("h").limit(n_cells).collect()
    centres = objs.sparkSession.sparkContext.broadcast(np.array([r["vec"] for r in some], float))

    def place(batches):
        c = centres.value
        for batch in batches:
            flat = batch.column("vec").flatten().to_numpy(zero_copy_only=False).astype(float)
            x = flat.reshape(batch.num_rows, -1)
            d = (c * c).sum(1)[None, :] - 2 * x @ c.T
            near = np.argsort(d, axis=1, kind="stable")[:, :copies]
            take = np.repeat(np.arange(batch.num_rows), near.shape[1])
            yield pa.RecordBatch.from_arrays([*batch.take(pa.array(take)).columns, pa.array(near.ravel(), pa.int64())], names=["id", "vec", "cell"])

    def answer(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        ids = t["id"].to_numpy()
        x = t["vec"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(ids), -1)
        near = kernels.knn_exact(x, k)
        src = np.repeat(np.arange(len(ids)), near.shape[1])
        dst = near.ravel()
        return pa.table({"src": ids[src], "dst": ids[dst], "d2": ((x[src] - x[dst]) ** 2).sum(axis=1)})

    rows = objs.select(F.col("id").cast("bigint").alias("id"), F.col("vec").cast("array<double>").alias("vec"))
    lists = rows.mapInArrow(place, "id bigint, vec array<double>, cell bigint").groupBy("cell").applyInArrow(answer, "src bigint, dst bigint, d2 double").dropDuplicates(["src", "dst"])
    best = Window.partitionBy("src").orderBy("d2", "dst")
    return lists.withColumn("rn", F.row_number().over(best)).where(F.col("rn") <= k).drop("rn")


def range_lune(ranked: DataFrame, pairs: DataFrame, between: bool = True) -> DataFrame:
    """(x, y, z): witnesses of pairs(x, y) of ranks, nearer to both ends than these are apart; with
    ``between`` also strictly between them by rank."""
    v = ranked.select("rank", "vec")
    ends = pairs.join(v.select(F.col("rank").alias("x"), F.col("vec").alias("vx")), "x").join(v.select(F.col("rank").alias("y"), F.col("vec").alias("vy")), "y")
    ends = ends.withColumn("d", l2_sq(F.col("vx"), F.col("vy")))
    near = (F.col("rank") > F.least("x", "y")) & (F.col("rank") < F.greatest("x", "y")) if between else ~F.col("rank").isin(F.col("x"), F.col("y"))
    met = ends.join(v, near)
    return met.where((l2_sq(F.col("vx"), F.col("vec")) < F.col("d")) & (l2_sq(F.col("vy"), F.col("vec")) < F.col("d"))).select("x", "y", F.col("rank").alias("z"))


def lune_counts(ranked: DataFrame, pairs: DataFrame, between: bool = True, shard_rows: int = index.SHARD_ROWS, block: int = 512) -> DataFrame:
    """(x, y, n): the number of witnesses of each pair (x, y) of ranks, as ``range_lune`` lists them.

    Blocks of pairs whose x lie within ``block`` ranks meet slices of all vectors, which are broadcast, shard_rows of them at
    a time; a block holds a vector for each of its ends, not for each pair. It costs least if x is the end around which fewer
    lie within the distance of the two. An end that is no rank does not occur: such pairs are left out.
    """
    slices = index.vector_slices(ranked)
    mine = pairs.select(F.col("x").cast("bigint").alias("x"), F.col("y").cast("bigint").alias("y"), F.expr(f"x div {block}").alias("run")).distinct()
    most = mine.groupBy("run").count().agg(F.max("count")).head()[0] or 0
    deal = F.pmod(F.xxhash64("x", "y"), F.lit(max(1, math.ceil(most / (64 * block)))))  # no end is in too many pairs of a block
    mine = mine.withColumn("deal", deal)
    key = ["run", "deal"]
    packed = mine.groupBy(*key).agg(F.collect_list("x").alias("xs"), F.collect_list("y").alias("ys"))
    if len(slices) > 1:  # else all ends are in the one broadcast
        ends = mine.select(*key, F.explode(F.array("x", "y")).alias("rank")).distinct().join(ranked.select("rank", F.col("vec").cast("array<double>").alias("vec")), "rank")
        packed = packed.join(ends.groupBy(*key).agg(F.array_sort(F.collect_list(F.struct("rank", "vec"))).alias("ends")), key)
    packed = materialise(packed.drop(*key), "pair_blocks")
    packed = packed.repartition(max(1, packed.count()))

    def count(ranks, shared):
        def run(batches):
            for batch in batches:
                for i in range(batch.num_rows):
                    x, y = (batch.column(c)[i].values.to_numpy(zero_copy_only=False) for c in ("xs", "ys"))
                    if "ends" in batch.schema.names:
                        ends = batch.column("ends")[i].values
                        places = ends.field("rank").to_numpy(zero_copy_only=False)
                        vecs = ends.field("vec").flatten().to_numpy(zero_copy_only=False).reshape(len(places), -1)
                    else:
                        places = np.intersect1d(ranks.value, np.concatenate([x, y]))
                        vecs = shared.value[np.searchsorted(ranks.value, places)]
                    known = np.isin(x, places) & np.isin(y, places)
                    x, y = x[known], y[known]
                    n = kernels.lunes(np.searchsorted(places, x), np.searchsorted(places, y), places, vecs, ranks.value, shared.value, between, shard_rows)
                    yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()), pa.array(y, pa.int64()), pa.array(n)], names=["x", "y", "n"])

        return run

    parts = None
    for ranks, shared in slices:
        one = packed.mapInArrow(count(ranked.sparkSession.sparkContext.broadcast(ranks), shared), "x bigint, y bigint, n bigint")
        parts = one if parts is None else parts.union(one)
    if parts is None:
        return ranked.sparkSession.createDataFrame([], "x bigint, y bigint, n bigint")
    return parts if len(slices) == 1 else parts.groupBy("x", "y").agg(F.sum("n").alias("n"))


def greedy_paths(ranked: DataFrame, edges: DataFrame, pairs: DataFrame, max_hops: int = 200) -> DataFrame:
    """(x, y, hops, reached): greedy walks between stored objects, all of them at once, a hop at a time.

    Each step goes to the neighbour nearest to y, ties to the smaller rank, and ends at y or where none is nearer
    than the place itself. edges and pairs(x, y) by ranks; pairs whose ends are no ranks are left out. A walk carries the
    vector of y and meets the list of its place's neighbours, whose vectors are broadcast in slices.
    """
    slices = index.vector_slices(ranked)
    v = ranked.select("rank", F.col("vec").cast("array<double>").alias("vec"))
    lists = materialise(edges.groupBy(edges.columns[0]).agg(F.collect_list(edges.columns[1]).alias("out")).toDF("at", "out"), "lists")
    start = pairs.select("x", "y").distinct().join(v.toDF("x", "vx"), "x").join(v.toDF("y", "vy"), "y")
    wide = "x bigint, y bigint, at bigint, vy array<double>, d double, hops bigint"

    def set_out(batches):
        for batch in batches:
            vx, vy = (np.stack(batch.column(c).to_numpy(zero_copy_only=False)) if batch.num_rows else np.zeros((0, 1)) for c in ("vx", "vy"))
            d = [kernels.steady(a, b[None])[0] for a, b in zip(vy, vx, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("x"), batch.column("y"), batch.column("x"), batch.column("vy"), pa.array(d, pa.float64()), pa.array(np.zeros(len(d), np.int64))], names=["x", "y", "at", "vy", "d", "hops"])

    def nearest(ranks, shared):
        def run(batches):
            for batch in batches:
                best = []
                for y, out in zip(batch.column("vy").to_numpy(zero_copy_only=False), batch.column("out").to_numpy(zero_copy_only=False), strict=True):
                    out = out[(out >= ranks[0]) & (out <= ranks[-1])]
                    e = kernels.steady(y, shared.value[np.searchsorted(ranks, out)])
                    best.append((float(e.min()), int(out[e == e.min()].min())) if len(out) else (None, None))
                e, to = (pa.array([b[i] for b in best], t) for i, t in ((0, pa.float64()), (1, pa.int64())))
                yield pa.RecordBatch.from_arrays([batch.column("x"), batch.column("y"), e, to], names=["x", "y", "e", "to"])

        return run

    walk, done = materialise(start.mapInArrow(set_out, wide), "walk"), None
    for _ in range(max_hops):
        here = walk.where("at <> y")
        if not here.head(1):
            break
        near = here.select("x", "y", "at", "vy").join(lists, "at").select("x", "y", "vy", "out")
        near, found = materialise(near, "near") if len(slices) > 1 else near, None
        for ranks, shared in slices:
            one = near.mapInArrow(nearest(ranks, shared), "x bigint, y bigint, e double, to bigint")
            found = one if found is None else found.union(one)
        best = found.where("to is not null").groupBy("x", "y").agg(F.min(F.struct("e", "to")).alias("b"))
        moved = here.join(best, ["x", "y"], "left")
        moves = F.coalesce((F.col("b.e") < F.col("d")) | (F.col("b.to") == F.col("y")), F.lit(False))
        at, d = (F.when(moves, F.col(f"b.{new}")).otherwise(F.col(old)).alias(old) for new, old in (("to", "at"), ("e", "d")))
        moved = materialise(moved.select("x", "y", at, "vy", d, (F.col("hops") + moves.cast("bigint")).alias("hops"), moves.alias("moves")), "walk")
        over = walk.where("at = y").select("x", "y", "hops", F.lit(True).alias("reached")).union(moved.where(~F.col("moves")).select("x", "y", "hops", F.lit(False)))
        done = over if done is None else done.union(over)
        walk = moved.where("moves").drop("moves")
    else:
        raise RuntimeError(f"paths are longer than {max_hops} hops")
    last = walk.select("x", "y", "hops", F.lit(True).alias("reached"))
    return last if done is None else done.union(last)
