"""Exact near-duplicate join of embeddings by pivots and the triangle inequality.

Unit vectors of one label are divided among pivots; a vector also goes to every other cell
whose border is no farther than the join radius, so that each vector's home cell holds all it
can link with and cells join independently. Cells beyond a bound are divided into
pairs of blocks. Equal vectors travel once, with their number, as the numbers they came in.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .blocks import Forest, matrix, runs, trimmed
from .graph import components
from .storage import discard, materialise

CELL_ROWS = 8_192
#: Pivots of all labels together, which are broadcast: 16 MB at 64 dimensions.
MAX_PIVOTS = 32_768
BLOCK_ROWS = 16_384
#: Products that a task holds at once.
CELLS = 4_000_000
EPS = 1e-9


def usable(vec: str = "embedding") -> F.Column:
    """Neither null nor zero, all components finite numbers."""
    c = F.col(vec)
    bad = F.exists(c, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return c.isNotNull() & ~bad & F.exists(c, lambda x: x != 0)


def unit(rows: np.ndarray) -> np.ndarray:
    scaled = rows / np.abs(rows).max(axis=1, keepdims=True)
    return scaled / np.sqrt((scaled * scaled).sum(axis=1, keepdims=True))


def _assign(batches: Iterator[pa.RecordBatch], pivots: dict, radius: float) -> Iterator[pa.RecordBatch]:
    """(cls, n, part, vec) -> a row for each cell: (cls, n, cell, home, vec)."""
    for batch in batches:
        parts = np.array(batch.column("part").to_pylist(), dtype=object)
        for part in set(parts):
            first, p = pivots[part]
            mine = np.flatnonzero(parts == part)
            step = max(1, CELLS // len(p))
            for a in range(0, len(mine), step):
                at = mine[a : a + step]
                some = batch.take(pa.array(at))
                cos = unit(matrix(some.column("vec"))) @ p.T
                best = cos.argmax(axis=1)
                rows = np.arange(len(at))
                # distance to the plane half way between the home pivot and each other pivot
                apart = np.sqrt(np.maximum(2 - 2 * p[best] @ p.T, 0))
                near = cos[rows, best][:, None] - cos <= radius * apart + EPS
                near[rows, best] = True
                i, j = np.nonzero(near)
                out = some.take(pa.array(i))
                yield pa.RecordBatch.from_arrays([out.column("cls"), out.column("n"), pa.array((first + j).astype(np.int64)), pa.array(j == best[i]), out.column("vec")], names=["cls", "n", "cell", "home", "vec"])


def _join(batches: Iterator[pa.RecordBatch], threshold: float) -> Iterator[pa.RecordBatch]:
    """Runs of one task's rows (cls, n, left, right, vec) -> per row: links seen, a linked class."""
    for _, t in runs(batches, "task"):
        ids, n, vec = t["cls"].to_numpy(), t["n"].to_numpy(), unit(matrix(t["vec"]))
        left, right = np.flatnonzero(t["left"].to_numpy()), np.flatnonzero(t["right"].to_numpy())
        links, forest = np.zeros(len(ids), np.int64), Forest(len(ids))
        order = np.argsort(ids, kind="stable")
        rank = np.empty(len(ids), np.int64)
        rank[order] = np.arange(len(ids))
        step = max(1, CELLS // max(1, len(right)))
        for a in range(0, len(left), step):
            own = left[a : a + step]
            hit = vec[own] @ vec[right].T >= threshold
            hit &= ids[own][:, None] != ids[right][None, :]
            links[own] += hit @ n[right]
            # links to the smallest partner, then whatever is still apart: a spanning forest
            for i in np.flatnonzero(hit.any(axis=1)).tolist():
                me, found = int(rank[own[i]]), rank[right[hit[i]]]
                roots = {forest.root(int(f)) for f in found.tolist()}
                for r in roots:
                    forest.join(me, r)
        roots = ids[order][[forest.root(int(r)) for r in rank]]
        mine = np.zeros(len(ids), bool)
        mine[left] = True
        keep = np.flatnonzero((mine & (links > 0)) | (roots != ids))
        yield pa.RecordBatch.from_arrays([pa.array(ids[keep]), pa.array(np.where(mine, links, 0)[keep]), pa.array(roots[keep])], names=["cls", "links", "other"])


def near_duplicates(vectors: DataFrame, threshold: float = 0.98, id_col: str = "vec_id", vec_col: str = "embedding", label_col: str = "label", cell_rows: int = CELL_ROWS, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """One row per row of vectors: id, n_links, component_id, kept.

    Vectors link when their labels are equal and not null and their cosine, in double precision,
    reaches threshold. Null, zero and non-finite vectors, and rows with a null label or id, link with
    nothing and are kept; vectors of different length do not link. Rows that share an id are vectors of their
    own, equal ones included: n_links is the number of other rows. Other columns are ignored; an
    empty table gives none.
    """
    if not -1 < threshold <= 1:
        raise ValueError("threshold must lie in (-1, 1]")
    element = "float" if vectors.schema[vec_col].dataType.simpleString() == "array<float>" else "double"
    vec_type = f"array<{element}>"
    label = F.concat_ws("/", F.col(label_col).cast("string"), F.size(vec_col).cast("string"))
    rows = vectors.select(F.col(id_col).cast("bigint").alias("id"), F.col(vec_col).cast(vec_type).alias("vec"), F.when(F.col(label_col).isNotNull(), label).alias("part"))
    takes_part = F.col("id").isNotNull() & F.col("part").isNotNull() & usable("vec")
    # two hashes stand for a vector's numbers
    key = ["part", "d1", "d2"]
    good = rows.where(takes_part).withColumn("d1", F.xxhash64("vec")).withColumn("d2", F.xxhash64("vec", F.lit(1)))
    classes = good.groupBy(*key).agg(F.min("id").alias("least"), F.count("*").alias("n"), F.first("vec").alias("vec"))
    classes = materialise(classes.withColumn("cls", F.monotonically_increasing_id()), "classes")
    total = classes.count()
    target = max(cell_rows, math.ceil(total / MAX_PIVOTS))
    # parts with more rows than one cell: fewer than total / target of them; the others are a cell each
    sizes = classes.groupBy("part").agg(F.count("*").alias("rows"))
    large = sizes.where(F.col("rows") > target)
    turn = Window.partitionBy("part").orderBy(F.xxhash64("cls"), "cls")
    picked = classes.join(F.broadcast(large), "part").withColumn("turn", F.row_number().over(turn)).where(F.col("turn") <= 2 * MAX_PIVOTS).where(F.col("turn") <= F.ceil(F.col("rows") / target))
    pivots: dict[str, tuple[int, np.ndarray]] = {}
    first = 0
    for r in picked.groupBy("part").agg(F.sort_array(F.collect_list(F.struct("turn", "vec"))).alias("p")).orderBy("part").collect():
        pivots[r["part"]] = (first, unit(np.array([x["vec"] for x in r["p"]], dtype=float)))
        first += len(r["p"])
    radius = math.sqrt(max(0.0, 2 - 2 * threshold))
    shared = vectors.sparkSession.sparkContext.broadcast(pivots)
    is_large = F.col("part").isin(list(pivots)) if pivots else F.lit(False)
    schema = f"cls bigint, n bigint, cell bigint, home boolean, vec {vec_type}"
    dealt = classes.where(is_large).select("cls", "n", "part", "vec").mapInArrow(lambda b: trimmed(_assign(b, shared.value, radius)), schema).withColumn("cell", F.xxhash64("cell", F.lit("pivot")))
    small = classes.where(~is_large).select("cls", "n", F.xxhash64("part", F.lit("part")).alias("cell"), F.lit(True).alias("home"), "vec")
    cells = materialise(dealt.union(small), "cells")
    many = cells.groupBy("cell").agg(F.count("*").alias("rows")).withColumn("blocks", F.ceil(F.col("rows") / block_rows)).where("rows > 1").select("cell", "blocks")
    placed = cells.join(many, "cell").withColumn("block", F.pmod(F.xxhash64("cls", F.lit(7)), F.col("blocks")))
    spread = F.sequence(F.lit(0).cast("bigint"), F.col("blocks") - 1)
    # a home row meets every block of its cell; the task of (i, j) has homes of i and all of j
    pairs = F.array_union(F.when(F.col("home"), F.transform(spread, lambda j: F.struct(F.col("block").alias("i"), j.alias("j")))).otherwise(F.array().cast("array<struct<i:bigint,j:bigint>>")), F.transform(spread, lambda i: F.struct(i.alias("i"), F.col("block").alias("j"))))
    tasks = placed.select("cls", "n", "cell", "home", "block", "vec", F.explode(pairs).alias("p")).select("cls", "n", F.xxhash64("cell", "p.i", "p.j").alias("task"), (F.col("home") & (F.col("block") == F.col("p.i"))).alias("left"), (F.col("block") == F.col("p.j")).alias("right"), "vec")
    seen = tasks.repartition("task").sortWithinPartitions("task").mapInArrow(lambda b: trimmed(_join(b, threshold)), "cls bigint, links bigint, other bigint")
    seen = materialise(seen, "seen")
    discard(cells)
    found = components(seen.where("cls <> other").select(F.col("cls").alias("a"), F.col("other").alias("b")))
    lists = classes.select("cls", *key, "least", "n")
    found = materialise(found.join(lists.select(F.col("cls").alias("id"), "least"), "id"), "found")
    lowest = found.groupBy("component_id").agg(F.min("least").alias("lowest"))
    found = found.join(lowest, "component_id").select(F.col("id").alias("cls"), "lowest")
    per_class = lists.join(seen.groupBy("cls").agg(F.sum("links").alias("links")), "cls", "left").join(found, "cls", "left")
    per_class = per_class.select(*key, (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("lowest", "least").alias("component_id"))
    out = good.select("id", *key).join(per_class, key).select("id", "n_links", "component_id")
    rest = rows.where(~F.coalesce(takes_part, F.lit(False))).select("id", F.lit(0).cast("bigint").alias("n_links"), F.col("id").alias("component_id"))
    return out.union(rest).select(F.col("id").alias(id_col), "n_links", "component_id", F.coalesce(F.col("id") == F.col("component_id"), F.lit(True)).alias("kept"))
