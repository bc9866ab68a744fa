"""Forms meant for scale against plain ones on small inputs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangeknn.functions import vectors
from rangeknn.operators import frontier, index, kernels


def objects(spark, n=300, dim=5, ties=True):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(n, dim))
    x[7] = x[3]
    attr = rng.integers(0, 40, n).astype(float) if ties else rng.random(n)
    rows = [(i, x[i].tolist(), float(attr[i])) for i in range(n)]
    return x, attr, spark.createDataFrame(rows, "id bigint, vec array<double>, attr double")


def plain_between(rows, own, cap):
    kept = []
    for c in range(len(rows)):
        if cap is not None and len(kept) >= cap:
            break
        if not any(own[k] < own[c] and kernels.d2(rows[c], rows[k : k + 1])[0] < own[c] for k in kept):
            kept.append(c)
    return kept


@pytest.mark.parametrize("cap", [None, 1, 4, 100])
def test_witness_scan_is_the_plain_one(cap):
    rng = np.random.default_rng(2)
    for n in (0, 1, 2, 60):
        rows = rng.integers(0, 4, (n, 3)).astype(float)
        own = kernels.d2(np.ones(3), rows)
        assert kernels.between(rows, own, cap).tolist() == plain_between(rows, own, cap)


def test_ranks_of_intervals_with_ties_and_open_ends(spark):
    _, attr, objs = objects(spark)
    ranked = index.materialise(index.with_rank(objs, 7), "ranked")
    order = sorted(range(len(attr)), key=lambda i: (attr[i], i))
    place = {i: r + 1 for r, i in enumerate(order)}
    assert {r["id"]: r["rank"] for r in ranked.collect()} == place
    ends = [(0, 3.0, 9.0), (1, None, 5.0), (2, 38.5, None), (3, None, None), (4, 9.0, 3.0), (5, 100.0, 200.0), (6, 12.0, 12.0), (7, -5.0, -1.0)]
    got = {r["qid"]: (r["r_lo"], r["r_hi"]) for r in index.to_ranks(spark.createDataFrame(ends, "qid bigint, lo double, hi double"), ranked, run=16).collect()}
    for q, lo, hi in ends:
        inside = [place[i] for i in range(len(attr)) if (lo is None or attr[i] >= lo) and (hi is None or attr[i] <= hi)]
        assert got[q] == ((min(inside), max(inside)) if inside else (1, 0))


def test_exact_knn_over_shards(spark):
    x, _, objs = objects(spark)
    got = {}
    for r in frontier.exact_knn(index.with_rank(objs), 6, shard_rows=64).collect():
        got.setdefault(r["src"], set()).add(r["dst"])
    for i in range(len(x)):
        d = kernels.d2(x[i], x)
        d[i] = np.inf
        assert got[i] == set(np.lexsort((np.arange(len(x)), d))[:6].tolist())


def test_search_with_queries_shuffled_or_broadcast_and_one_shard_asked(spark, monkeypatch):
    x, attr, objs = objects(spark)
    packed = index.materialise(index.shards(index.with_rank(objs), 64), "shards")
    qs = spark.createDataFrame([(i, x[i].tolist(), 5.0, 30.0, 4) for i in range(10)], "qid bigint, qvec array<double>, lo double, hi double, k int")
    want = sorted(map(tuple, index.search(packed, qs).collect()))
    monkeypatch.setattr(index, "BROADCAST_BYTES", 0)
    assert sorted(map(tuple, index.search(packed, qs, query_block=3).collect())) == want
    one = index.search(packed, qs.withColumn("shard", F.lit(1).cast("bigint")))
    ids = {i for r in packed.where("shard = 1").collect() for i in r["ids"]}
    assert {r["id"] for r in one.collect()} <= ids
    some = packed.where("shard <> 2")
    assert {r["id"] for r in index.search(some, qs).collect()} <= {i for r in some.collect() for i in r["ids"]}


def test_walking_through_outsiders_keeps_them_all():
    """A line of outsiders between the entry and the only object in range, beside many that are nearer to the query."""
    n = 200
    vecs = np.r_[np.zeros((n, 1)), [[50.0]], [[60.0]]]
    start = np.r_[0, n, np.full(n, n), n + 1, n + 1].astype(np.int64)
    lists = [[*range(1, n), n]] + [[] for _ in range(n - 1)] + [[n + 1], []]
    start = np.r_[0, np.cumsum([len(v) for v in lists])].astype(np.int64)
    nbrs = np.array([v for row in lists for v in row], np.int64)
    got, _, _ = kernels.beam(start, nbrs, vecs, np.zeros(1), n + 1, n + 1, 1, 2, 0, through=True)
    assert [p for _, p in got] == [n + 1]


def test_vector_functions(spark):
    rows = [(1, [1.0, 2.0], [4.0, 6.0]), (1, [3.0, 4.0], None), (2, None, [1.0, 1.0]), (None, [5.0, 5.0], [5.0])]
    df = spark.createDataFrame(rows, "k int, vec array<double>, other array<double>")
    assert [r[0] for r in df.select(vectors.arrow_l2()("vec", "other")).collect()] == [5.0, None, None, None]
    got = {(r["k"], r["pos"]): r["mean"] for r in vectors.centroids(df, "k").collect()}
    assert got == {(1, 0): 2.0, (1, 1): 3.0, (None, 0): 5.0, (None, 1): 5.0}
    assert vectors.centroids(df.limit(0), "k").count() == 0
