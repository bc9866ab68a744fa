"""Worked examples, the theory's properties and the numpy kernels."""

import numpy as np
import pytest

from rangeknn.operators import exact, kernels

F1 = {1: (0, 0), 2: (6, 3), 3: (0, 3), 4: (10, 0)}
F2 = {2: (2, 1), 3: (0, 0), 4: (4, 0), 5: (6, 1), 6: (8, 0)}
F3 = {2: (2, 0), 3: (3.5, 0), 4: (0, 0), 6: (-2, 0.5)}
F7 = {1: (0, 0), 2: (1, 0), 3: (1, 1), 4: (0, 1)}


def graph(points, rule):
    names = sorted(points)
    x = np.array([points[n] for n in names], float)
    out = {}
    for i, n in enumerate(names):
        cand = np.delete(np.arange(len(names)), i)
        found = kernels.two_sided(i, cand, x) if rule == "between" else kernels.nearest_first(i, cand, x)
        out[n] = {names[j] for j in found}
    return out


@pytest.mark.parametrize(
    ("points", "between", "spatial"),
    [
        (F1, {1: {2, 3}, 2: {1, 3, 4}, 3: {1, 2, 4}, 4: {2, 3}}, {1: {3, 4}, 2: {3, 4}, 3: {1, 2}, 4: {2}}),
        (F2, {2: {3, 4}, 3: {2, 4}, 4: {2, 3, 5}, 5: {4, 6}, 6: {5}}, {2: {3, 4}, 3: {2}, 4: {2, 5}, 5: {4, 6}, 6: {5}}),
        (F3, {2: {3, 4}, 3: {2, 4}, 4: {2, 3, 6}, 6: {4}}, {2: {3, 4}, 3: {2}, 4: {2, 6}, 6: {4}}),
        (F7, {1: {2, 4}, 2: {1, 3}, 3: {2, 4}, 4: {1, 3}}, {1: {2, 4}, 2: {1, 3}, 3: {2, 4}, 4: {1, 3}}),
    ],
)
def test_worked_examples(points, between, spatial):
    assert graph(points, "between") == between
    assert graph(points, "spatial") == spatial


def test_chain_and_identical_vectors():
    chain = graph({n: (-n, 0) for n in range(1, 7)}, "between")
    assert chain == {n: {m for m in (n - 1, n + 1) if 1 <= m <= 6} for n in range(1, 7)}
    assert graph({n: (1.0, 2.0) for n in range(3)}, "between") == {0: {1, 2}, 1: {0, 2}, 2: {0, 1}}


def points(n=60, dim=5, seed=0):
    return np.random.default_rng(seed).normal(size=(n, dim))


def all_edges(x, lo=0, hi=None, m=None):
    hi = len(x) if hi is None else hi
    sub = x[lo:hi]
    return {(lo + i, lo + int(j)) for i in range(len(sub)) for j in kernels.two_sided(i, np.delete(np.arange(len(sub)), i), sub, m)}


def test_prune_equals_definition_and_is_hereditary():
    x = points()
    edges = all_edges(x)
    assert edges == {(i, int(j)) for i in range(len(x)) for j in exact.by_definition(i, x)}
    for lo, hi in ((0, 1), (3, 5), (10, 40), (0, 60)):
        assert {(a, b) for a, b in edges if lo <= a < hi and lo <= b < hi} == all_edges(x, lo, hi)


def test_every_interval_is_strongly_connected_even_when_minimal():
    x = points(40)
    start, nbrs = kernels.build(x, kernels.Params(spatial=0, window=1, m=2))
    edges = [(i, int(j)) for i in range(len(x)) for j in nbrs[start[i] : start[i + 1]]]
    assert sorted(edges) == sorted((i, j) for i in range(40) for j in (i - 1, i + 1) if 0 <= j < 40)
    for lo, hi in ((0, 39), (5, 6), (7, 30)):
        assert exact.reach(edges, lo, lo, hi) == exact.reach(edges, hi, lo, hi) == hi - lo + 1


def test_fixed_candidates_restrict_with_the_cap():
    x = points(80)
    start, nbrs = kernels.build(x, kernels.Params(8, 6, 6))
    whole = {(i, int(j)) for i in range(80) for j in nbrs[start[i] : start[i + 1]]}
    near = kernels.knn_exact(x, 8)
    lo, hi = 20, 60
    inside = set()
    for i in range(lo, hi):
        cand = np.unique(np.r_[near[i], np.arange(max(0, i - 6), min(80, i + 7))])
        cand = cand[(cand != i) & (cand >= lo) & (cand < hi)]
        inside |= {(i, int(j)) for j in kernels.two_sided(i, cand, x, 6)}
    assert inside == {(a, b) for a, b in whole if lo <= a < hi and lo <= b < hi}


def test_header_pointers():
    closer = kernels.previous_closer(np.array([5.0, 3, 4, 1, 2]))
    assert closer.tolist() == [-1, -1, 1, -1, 3]
    assert [kernels.header_entry(closer, a, b) for a, b in ((2, 2), (1, 2), (0, 4), (4, 4))] == [2, 1, 3, 4]
    d = np.random.default_rng(1).random(50)
    c = kernels.previous_closer(d)
    assert all(kernels.header_entry(c, a, b) == a + int(d[a : b + 1].argmin()) for a in range(50) for b in range(a, 50))


def test_saturated_beam_is_exact_and_pools_differ():
    x = points(150)
    start, nbrs = kernels.build(x, kernels.Params(8, 4, 8))
    q = points(1, seed=9)[0]
    got, n_dist, _ = kernels.beam(start, nbrs, x, q, 30, 120, 5, 1000, 30)
    d = kernels.d2(q, x[30:121])
    assert [p for _, p in got] == (30 + np.argsort(d)[:5]).tolist() and n_dist == 91
    assert kernels.beam(start, nbrs, x, q, 9, 3, 5, 10, 0)[0] == []
    a = kernels.beam(start, nbrs, x, q, 0, 149, 5, 10, 0, pool="k")[1]
    assert a == kernels.beam(start, nbrs, x, q, 0, 149, 5, 90, 0, pool="k")[1]


def test_box_prune_follows_its_definition():
    rng = np.random.default_rng(3)
    x, r = rng.normal(size=(30, 3)), rng.integers(0, 6, size=(30, 2))
    for i in range(30):
        own = kernels.d2(x[i], x)
        kept = []
        for y in sorted((j for j in range(30) if j != i), key=lambda j: (own[j], j)):
            lo, hi = np.minimum(r[i], r[y]), np.maximum(r[i], r[y])
            if not any((r[z] >= lo).all() and (r[z] <= hi).all() and own[z] < own[y] and kernels.d2(x[y], x[z : z + 1])[0] < own[y] for z in kept):
                kept.append(y)
        assert sorted(kernels.in_box(i, np.delete(np.arange(30), i), x, r).tolist()) == sorted(kept)


def test_descent_recall():
    x = points(600, 8)
    exact_ids, approx = kernels.knn_exact(x, 10), kernels.knn_descent(x, 10)
    assert np.mean([len(set(a) & set(b)) / 10 for a, b in zip(exact_ids, approx, strict=True)]) > 0.9


def test_monotone_violations_are_those_of_brute_force(spark):
    x = points(120)
    ranked = spark.createDataFrame([(i + 1, x[i].tolist()) for i in range(120)], "rank bigint, vec array<double>")
    whole = exact.between_graph(ranked)
    assert exact.monotone_violations(whole, ranked).count() == 0
    edges = whole.where("pmod(xxhash64(src, dst), 3) <> 0 and src <> 7")
    out = {i: set() for i in range(120)}
    for r in edges.collect():
        out[r["src"] - 1].add(r["dst"] - 1)
    d = np.array([kernels.d2(v, x) for v in x])
    want = {(a + 1, b + 1) for a in range(120) for b in range(120) if a != b and b not in out[a] and not any(d[z, b] < d[a, b] for z in out[a])}
    got = [tuple(r) for r in exact.monotone_violations(edges, ranked).collect()]
    assert len(got) == len(want) and set(got) == want and {b for a, b in want if a == 7} == set(range(1, 121)) - {7}


def test_monotone_query_looks_at_every_rank(spark, monkeypatch):
    from rangeknn.plans import queries

    whole = exact.between_graph
    monkeypatch.setattr(queries.exact, "between_graph", lambda ranked: whole(ranked).where("src <> 130"))
    n = queries.Setup(spark, "/root/testdata/sf0.001").ranked.count()
    assert n > 130 and queries.violations(spark, "/root/testdata/sf0.001").head()["n"] == n - 1


def test_edges_of_some_sources_are_those_of_the_whole_graph(spark):
    x = points(90)
    ranked = spark.createDataFrame([(i + 1, x[i].tolist()) for i in range(90)], "rank bigint, vec array<double>")
    part = exact.between_graph(ranked, sources=(20, 45))
    want = exact.between_graph(ranked).where("src between 20 and 45")
    assert sorted(map(tuple, part.collect())) == sorted(map(tuple, want.collect()))
    assert part.select("src").distinct().count() == 26
