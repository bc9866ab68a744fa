"""Boxes, all-range graphs, join forms, measures and the table function."""

import numpy as np
import pytest

from rangeknn.operators import exact, frontier, index, kernels, metrics, multi, multi_range
from rangeknn.operators.index import graph_kernel
from rangeknn.streaming import table_function

N, DIM = 200, 5


@pytest.fixture(scope="module")
def x():
    return np.random.default_rng(5).normal(size=(N, DIM))


def truth_of(x, q, ok, k):
    d = kernels.d2(q, x[ok])
    return ok[np.lexsort((ok, d))[:k]].tolist()


@pytest.mark.parametrize(
    "make",
    [
        lambda v: multi_range.StoredRanges(v, step=1),
        multi_range.StoredRanges,
        lambda v: multi_range.StoredRanges(v, "covers"),
        multi_range.SegmentBitmap,
        multi_range.CompressedRanges,
        lambda v: multi_range.CompressedRanges(v, leap="min"),
        multi_range.RectangleRanges,
        lambda v: multi_range.RectangleRanges(v, order=np.random.default_rng(0).permutation(len(v))),
    ],
)
def test_all_range_graphs_stay_in_range_and_find_most(x, make):
    g, rng, lost, asked = make(x), np.random.default_rng(8), 0, 0
    for lo, hi in ((0, 199), (10, 60), (100, 180), (50, 54), (7, 7)):
        for _ in range(6):
            q = rng.normal(size=DIM)
            got = [p for _, p in g.search(q, lo, hi, 5, 60)[0]]
            want = truth_of(x, q, np.arange(lo, hi + 1), 5)
            assert all(lo <= p <= hi for p in got)
            lost, asked = lost + len(set(want) - set(got)), asked + len(want)
    assert lost <= 0.2 * asked, lost
    passes = np.arange(N) % 3 == 0
    assert all(p % 3 == 0 for _, p in g.search(x[3], 20, 150, 5, 60, passes)[0])
    assert g.search(x[3], 20, 150, 5, 60, np.zeros(N, bool))[0] == []
    for tiny in (1, 2):
        assert len(make(x[:tiny]).search(x[0], 0, tiny - 1, 5, 10)[0]) >= 1


def test_labels_hold_what_they_say(x):
    for g in (multi_range.CompressedRanges(x[:80]), multi_range.RectangleRanges(x[:80])):
        src = np.repeat(np.arange(80), np.diff(g.start))
        low, high = np.minimum(src, g.nbrs), np.maximum(src, g.nbrs)
        t = g.labels
        assert ((t[:, 0] <= t[:, 1]) & (t[:, 1] <= low) & (t[:, 2] >= high)).all()
    assert len(multi_range.CompressedRanges(x).nbrs) <= len(multi_range.CompressedRanges(x, leap="min").nbrs)


def test_bitmap_segments():
    g = multi_range.SegmentBitmap(np.random.default_rng(0).normal(size=(50, 3)), n_segments=8)
    assert np.bincount(g.segment).tolist() == [7, 7, 6, 6, 6, 6, 6, 6]
    assert g.mask(0, 49) == 255 and g.mask(7, 13) == 2
    assert (g.bits == 1 << g.segment[g.nbrs]).all()


def test_greedy_walks_on_the_exact_graph_arrive(x):
    sub = x[:60]
    start, nbrs = kernels.build(sub, kernels.Params(0, 60, None))
    for a, b in ((0, 59), (59, 0), (17, 40), (5, 5)):
        path = kernels.greedy_path(start, nbrs, sub, a, b)
        d = kernels.d2(sub[b], sub[path])
        assert path[-1] == b and (np.diff(d) < 0).all()
    assert kernels.greedy_path(np.zeros(61, np.int64), np.zeros(0, np.int64), sub, 0, 5) == [0]


@pytest.fixture(scope="module")
def boxes(spark, x):
    rng = np.random.default_rng(6)
    attrs = np.stack([rng.integers(0, 30, N), rng.normal(size=N).round(2), rng.integers(0, 3, N)], axis=1).astype(float)
    objs = spark.createDataFrame([(i, x[i].tolist(), attrs[i].tolist()) for i in range(N)], "id bigint, vec array<double>, attrs array<double>")
    odd = objs.union(spark.createDataFrame([(900, [0.0] * DIM, None), (901, [0.0] * DIM, [1.0, None, 1.0]), (902, None, [1.0, 1.0, 1.0])], objs.schema))
    asked = [[(5.0, 20.0), (-0.5, 0.8), (0.0, 1.0)], [(None, None), (None, 0.0), (2.0, 2.0)], [(8.0, 8.0), (None, None), (None, None)], [(9.0, 3.0), (None, None), (None, None)]]
    qs = [(i, rng.normal(size=DIM).tolist(), b, 6) for i, b in enumerate(asked)]
    queries = spark.createDataFrame(qs, "qid bigint, qvec array<double>, box array<struct<lo:double,hi:double>>, k int")
    truth = {}
    for qid, q, box, k in qs:
        ok = np.ones(N, bool)
        for j, (lo, hi) in enumerate(box):
            ok &= (attrs[:, j] >= (-np.inf if lo is None else lo)) & (attrs[:, j] <= (np.inf if hi is None else hi))
        if ok.any():
            truth[qid] = truth_of(x, np.array(q), np.flatnonzero(ok), k)
    return multi.rank_first(odd), queries, truth


def answers(found):
    out = {}
    for r in found.orderBy("qid", "rn").collect():
        out.setdefault(r["qid"], []).append(r["id"])
    return out


@pytest.mark.parametrize("rows", [1 << 14, 70])
def test_box_search(boxes, rows):
    ranked, queries, truth = boxes
    built = multi.build(ranked, kernels.Params(10, 8, 16), rows)
    assert answers(multi.box_search(built, queries, multi.box_scan)) == truth
    for ef in (6, 10_000):  # the fallback completes what the walk does not reach
        got = answers(multi.box_search(built, queries, multi.box_kernel(ef)))
        assert {q: len(v) for q, v in got.items()} == {q: len(v) for q, v in truth.items()}
    assert multi.edges(built).count() > N


@pytest.fixture(scope="module")
def plain(spark, x):
    attr = np.random.default_rng(7).integers(0, 50, N).astype(float)
    objs = spark.createDataFrame([(i, x[i].tolist(), float(attr[i])) for i in range(N)], "id bigint, vec array<double>, attr double")
    ends = [(4.0, 30.0), (None, 9.0), (41.0, None), (None, None), (60.0, 70.0), (9.0, 3.0), (12.5, 12.7)]
    qs = [(i, np.random.default_rng(i).normal(size=DIM).tolist(), lo, hi, 4) for i, (lo, hi) in enumerate(ends)]
    return index.with_rank(objs), spark.createDataFrame(qs, "qid bigint, qvec array<double>, lo double, hi double, k int")


def test_rank_intervals(plain):
    ranked, queries = plain
    rows = ranked.select("rank", "attr").collect()
    for run in (7, 4096):
        for r in index.to_ranks(queries, ranked, run).collect():
            inside = [a["rank"] for a in rows if (r["lo"] is None or a["attr"] >= r["lo"]) and (r["hi"] is None or a["attr"] <= r["hi"])]
            assert (r["r_lo"], r["r_hi"]) == ((min(inside), max(inside)) if inside else (1, 0))


def test_frontier_equals_the_scan(plain):
    ranked, queries = plain
    built = index.build(ranked, kernels.Params(6, 4, 8))
    links = index.edges(built).selectExpr("src_rank as src", "dst_rank as dst")
    found = frontier.frontier_search(ranked, links, index.to_ranks(queries, ranked), 10_000)
    assert answers(found) == answers(index.search(built, queries))
    narrow = answers(frontier.frontier_search(ranked, links, index.to_ranks(queries, ranked), 8))
    assert sum(len(v) for v in narrow.values()) == sum(len(v) for v in answers(found).values())
    with pytest.raises(RuntimeError, match="hops"):
        frontier.frontier_search(ranked, links, index.to_ranks(queries, ranked), 10_000, max_hops=1)


def test_bucketed_neighbours(plain, x):
    ranked, _ = plain
    whole = {(r["src"], r["dst"]) for r in frontier.bucketed_knn(ranked, 6).collect()}
    assert whole == {(i, int(j)) for i, row in enumerate(kernels.knn_exact(x, 6)) for j in row}
    some = {(r["src"], r["dst"]) for r in frontier.bucketed_knn(ranked, 6, cell_rows=40, copies=3).collect()}
    assert len(some & whole) > 0.8 * len(whole)


def test_measures(spark, plain):
    ranked, _ = plain
    built = index.build(ranked, kernels.Params(6, 4, 8))
    h = metrics.header_stats(built).first()
    assert h["nodes"] == N and 1 <= h["mean_ids"] < 20
    to_ranks = index.edges(built).selectExpr("src_rank as src", "dst_rank as dst")
    cand = index.window_pairs(ranked, 4)
    assert cand.count() == 2 * sum(N - i for i in range(1, 5))
    g = metrics.gap_breakdown(to_ranks, exact.between_graph(ranked), cand).first()
    assert g["shared"] + g["witness_absent"] == to_ranks.count()
    assert g["shared"] + g["endpoint_absent"] + g["crowded_out"] == exact.between_graph(ranked).count()
    curve = spark.createDataFrame([("a", 0.8, 100.0), ("a", 1.0, 200.0), ("b", 0.95, 300.0), ("c", 0.1, 1.0)], "method string, recall double, cost double")
    at = {r["method"]: r["cost"] for r in metrics.interpolated(curve, 0.9).collect()}
    assert at["a"] == pytest.approx(150) and at["b"] == 300 and at["c"] is None
    ratio = {r["method"]: r["ratio"] for r in metrics.speed_ratio(metrics.interpolated(curve, 0.9), "a").collect()}
    assert ratio["b"] == pytest.approx(2)


def test_table_function(spark, plain, tmp_path):
    ranked, queries = plain
    built = index.build(ranked, kernels.Params(6, 4, 8), 60)
    index.save(built, str(tmp_path / "saved"))
    table_function.register(spark, ef=10_000)
    queries.createOrReplaceTempView("asked")
    found = spark.sql(f"SELECT qid, t.* FROM asked, LATERAL range_knn('{tmp_path}/saved', qvec, lo, hi, k) t")
    assert answers(found) == answers(index.search(built, queries, graph_kernel(10_000)))


def test_lists_made_when_read_are_those_of_the_whole_graph():
    x = np.random.default_rng(19).normal(size=(500, 6))
    how = kernels.Params(12, 0, 8, prune="spatial")
    start, nbrs = kernels.build(x, how)
    lists = kernels.Lists(x, how)
    q, none = x[3] + 0.1, np.zeros(0, np.int64)
    assert kernels.beam(none, none, x, q, 100, 400, 10, 20, 250, through=True, expand=lists) == kernels.beam(start, nbrs, x, q, 100, 400, 10, 20, 250, through=True)
    assert 0 < len(lists.made) < 300  # what is not read is not made
    assert all(lists(i).tolist() == nbrs[start[i] : start[i + 1]].tolist() for i in range(500))
    with pytest.raises(ValueError):
        kernels.Lists(x, kernels.Params(12, 4, 8, prune="spatial"))


def test_closest_keeps_ties_and_names():
    x = np.random.default_rng(20).normal(size=(900, 5))
    x[100:400] = x[7]  # more copies than asked for
    for q, names in ((x[7], None), (x[7] + 1e-9, np.arange(900)[::-1]), (x[0], None)):
        d = kernels.d2(q, x)
        want = np.lexsort((np.arange(900) if names is None else names, d))[:12]
        at, dist = kernels.closest(q, x, 12, names)
        assert at.tolist() == want.tolist() and dist.tolist() == d[want].tolist()


def test_an_interval_that_holds_a_shard_is_walked_once(monkeypatch):
    from types import SimpleNamespace

    x = np.random.default_rng(21).normal(size=(300, 5))
    start, nbrs = kernels.build(x, kernels.Params(6, 4, 8))
    s = SimpleNamespace(ids=np.arange(300), vecs=x, start=start, nbrs=nbrs, closer=kernels.previous_closer(kernels.d2(x.mean(axis=0), x)))
    walks, plain = [], kernels.reached
    monkeypatch.setattr(kernels, "reached", lambda *a: (walks.append(a[2:]), plain(*a))[1])
    kernel, fresh = index.graph_kernel(10**6), lambda *a: index.graph_kernel(10**6)(*a)
    asks = [(q, *span) for q in x[:4] for span in ((0, 299), (20, 299), (0, 299))]
    got = [kernel(s, q, lo, hi, 10, 0) for q, lo, hi in asks]
    assert len(walks) == 5
    assert got == [fresh(s, q, lo, hi, 10, 0) for q, lo, hi in asks]


def test_long_searches_of_the_curve_are_dealt_to_tasks():
    from types import SimpleNamespace

    from rangeknn.plans import methods

    kinds = methods.contenders(SimpleNamespace(built=lambda *a: None, packed=lambda: None))
    dealt = {n for n, (_, make) in kinds.items() if not getattr(make(lambda qid: 10), "builds", False)}
    assert {"range covers", "layered graph, in-filter"} <= dealt and "rectangle labels" not in dealt
