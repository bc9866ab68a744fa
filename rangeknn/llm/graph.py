"""Connected components by repeated contraction, every round written to the shared folder."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import Forest
from .storage import materialise

MAX_ROUNDS = 200
#: Edges, 3 MB of them, that one task puts together at the end.
LAST_EDGES = 200_000


def _settled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    parts = [[b.column(c).to_numpy() for c in ("a", "b")] for b in batches if b.num_rows]
    if not parts:
        return
    ids, place = np.unique(np.concatenate([np.concatenate([p[side] for p in parts]) for side in (0, 1)]), return_inverse=True)
    forest = Forest(len(ids))
    for i, j in zip(*np.split(place, 2), strict=True):
        forest.join(int(i), int(j))
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[[forest.root(i) for i in range(len(ids))]])], names=["root", "to"])


def components(edges: DataFrame, last_edges: int = LAST_EDGES) -> DataFrame:
    """edges(a bigint, b bigint) -> (id, component_id): every end and the smallest id it reaches.

    In each round a node hands over to the neighbour (or itself) with the least pseudo-random
    turn, which leaves a constant share of the nodes on average, whatever the shape: long
    chains need a logarithmic number of rounds. Loops, repeated and reversed edges and nulls
    do no harm; no edges give no rows. Minima are combined before shuffling, so stars with very
    many rays do not meet in one task. The rounds end when at most ``last_edges`` edges between
    different nodes are left, counted; one task joins these, in an executor.
    """
    live = materialise(edges.select("a", "b").dropna().distinct(), "edges")
    both = lambda e: e.select("a", "b").union(e.select(F.col("b"), F.col("a")))
    label = materialise(live.select(F.explode(F.array("a", "b")).alias("id")).distinct().withColumn("root", F.col("id")), "labels")
    live = live.where("a <> b")
    for turn in range(MAX_ROUNDS):
        left = live.count()
        if left <= last_edges:
            if left:
                rest = materialise(live.repartition(1).mapInArrow(_settled, "root bigint, to bigint"), "settled")
                label = label.join(rest, "root", "left").select("id", F.coalesce("to", "root").alias("root"))
            return label.groupBy("root").agg(F.min("id").alias("component_id")).join(label, "root").select("id", "component_id")
        own = both(live)
        order = lambda c, t=turn: F.struct(F.xxhash64(F.col(c), F.lit(t)).alias("h"), F.col(c).alias("v"))
        chosen = own.groupBy("a").agg(F.min(order("b")).alias("m")).select("a", F.least(order("a"), F.col("m")).getField("v").alias("to"))
        chosen = materialise(chosen, "chosen")
        label = materialise(label.join(chosen.withColumnRenamed("a", "root"), "root", "left").select("id", F.coalesce("to", "root").alias("root")), "labels")
        one = live.join(chosen.withColumnRenamed("to", "x"), "a").select("b", "x")
        two = one.join(chosen.select(F.col("a").alias("b"), F.col("to").alias("y")), "b").where("x <> y")
        live = materialise(two.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "edges")
    raise RuntimeError(f"components did not settle in {MAX_ROUNDS} rounds")
