"""Lunes and walks of all pairs, k-NN graphs that are reused, indexes without vectors, streams that append and count."""

import numpy as np
import pytest

from rangeknn.operators import frontier, index, kernels
from rangeknn.streaming import stream


def ranked_of(spark, x):
    rows = [(i, i + 1, float(i), v.tolist()) for i, v in enumerate(x)]
    return spark.createDataFrame(rows, "id bigint, rank bigint, attr double, vec array<double>")


@pytest.mark.parametrize("between", [True, False])
def test_lune_counts_are_those_of_the_listed_witnesses(spark, between):
    x = np.random.default_rng(5).normal(size=(40, 3))
    x[7] = x[30]  # a witness as far away as an end is none
    ranked = ranked_of(spark, x)
    pairs = spark.createDataFrame([(a, b) for a in range(1, 41) for b in range(1, 41, 3) if a != b] + [(1, 99)], "x bigint, y bigint")
    got = {(r.x, r.y): r.n for r in frontier.lune_counts(ranked, pairs, between, shard_rows=9, block=50).collect()}
    listed = frontier.range_lune(ranked, pairs, between).groupBy("x", "y").count().collect()
    assert {p: n for p, n in got.items() if n} == {(r.x, r.y): r["count"] for r in listed}
    assert len(got) == pairs.count() - 1


def test_greedy_paths_are_those_of_the_kernel(spark):
    x = np.random.default_rng(6).normal(size=(50, 2))
    ranked = ranked_of(spark, x)
    start, nbrs = kernels.build(x, kernels.Params(3, 0, 3, prune="spatial"))
    edges = [(a + 1, int(b) + 1) for a in range(50) for b in nbrs[start[a] : start[a + 1]]]
    pairs = [(a, (a * 7) % 50 + 1) for a in range(1, 51)]
    got = {(r.x, r.y): (r.hops, r.reached) for r in frontier.greedy_paths(ranked, spark.createDataFrame(edges, "src bigint, dst bigint"), spark.createDataFrame(pairs, "x bigint, y bigint")).collect()}
    want = {}
    for a, b in pairs:
        path = kernels.greedy_path(start, nbrs, x, a - 1, b - 1)
        want[a, b] = (len(path) - 1, path[-1] == b - 1)
    assert got == want
    assert not all(r for _, r in got.values())


def test_a_given_knn_graph_replaces_the_search_for_one(spark):
    x = np.random.default_rng(7).normal(size=(60, 4))
    ranked, how = ranked_of(spark, x), kernels.Params(5, 2, 6)
    near = kernels.nearest(x, how)
    graph = spark.createDataFrame([(a + 1, int(b) + 1) for a in range(60) for b in near[a]], "src bigint, dst bigint")
    pairs = lambda built: {(r.src, r.dst) for r in index.edges(built).collect()}
    assert pairs(index.build(ranked, how, knn_graph=graph)) == pairs(index.build(ranked, how))
    window_only = pairs(index.build(ranked, kernels.Params(0, 2, 6)))
    assert pairs(index.build(ranked, how, knn_graph=graph.limit(0))) == window_only
    # of a graph over all ranks a shard takes what lies inside it
    assert all(a // 20 == b // 20 for a, b in pairs(index.build(ranked, how, shard_rows=20, knn_graph=graph)))


def test_an_index_without_vectors_needs_the_objects(spark, tmp_path):
    ranked = ranked_of(spark, np.random.default_rng(8).normal(size=(50, 4)))
    built = index.build(ranked, kernels.Params(4, 4, 8), shard_rows=20)
    index.save(built, path := str(tmp_path / "index"), vectors=False)
    with pytest.raises(ValueError):
        index.load(spark, path)
    again = index.load(spark, path, ranked, 20)
    rows = lambda df: sorted(map(tuple, df.select("shard", "first_rank", "vecs", "nbrs", "closer").collect()))
    assert rows(again) == rows(built)


def _stream(spark, parts, schema, path):
    for part in parts:
        spark.createDataFrame(part, schema).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def test_segments_answer_as_one_index_and_bad_batches_write_none(spark, tmp_path):
    x = np.random.default_rng(9).normal(size=(60, 4))
    rows = [(i, v.tolist(), float(i % 7)) for i, v in enumerate(x)]
    schema = "id bigint, vec array<double>, attr double"
    source = _stream(spark, [rows[:25], [(99, None, 1.0)], rows[25:]], schema, str(tmp_path / "in"))
    root = str(tmp_path / "out")
    stream.append_stream(source, root, kernels.Params(4, 8, 8)).awaitTermination()
    asked = spark.createDataFrame([(q, x[q].tolist(), lo, 5.0, 6) for q, lo in ((0, 1.0), (1, None))], "qid bigint, qvec array<double>, lo double, hi double, k int")
    got = {(r.qid, r.rn): r.id for r in stream.search_segments(spark, root, asked).collect()}
    whole = index.search(index.shards(index.with_rank(spark.createDataFrame(rows, schema))), asked)
    assert got == {(r.qid, r.rn): r.id for r in whole.collect()}
    assert spark.read.parquet(f"{root}/segments").select("segment").distinct().count() == 2


def test_late_rows_are_counted_against_earlier_batches(spark, tmp_path):
    at = lambda h: f"2024-01-01 {h:02d}:00:00"
    parts = [[(1, at(3)), (2, at(10))], [(3, at(9)), (4, at(8)), (5, None)], [(6, at(20)), (7, at(1))], [(8, at(18))]]
    source = _stream(spark, parts, "event_id bigint, ts string", str(tmp_path / "in"))
    root = str(tmp_path / "out")
    stream.late_rows(source, 3_600, root).awaitTermination()
    rows = spark.read.parquet(f"{root}/rows").orderBy("batch").select("n_rows", "late").collect()
    assert [tuple(r) for r in rows] == [(2, 0), (3, 1), (2, 1), (1, 1)]
    # a restart finds the newest time in what it wrote
    spark.createDataFrame([(9, at(5)), (10, at(21))], "event_id bigint, ts string").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    again = spark.readStream.schema("event_id bigint, ts string").parquet(str(tmp_path / "in"))
    stream.late_rows(again, 3_600, root).awaitTermination()
    assert [r.late for r in spark.read.parquet(f"{root}/rows").orderBy("batch").collect()][4:] == [1]


def test_walks_over_several_slices_of_vectors_are_the_same(spark, monkeypatch):
    x = np.random.default_rng(16).normal(size=(40, 2))
    ranked = ranked_of(spark, x)
    start, nbrs = kernels.build(x, kernels.Params(3, 0, 3, prune="spatial"))
    edges = spark.createDataFrame([(a + 1, int(b) + 1) for a in range(40) for b in nbrs[start[a] : start[a + 1]]], "src bigint, dst bigint")
    pairs = spark.createDataFrame([(a, (a * 7) % 40 + 1) for a in range(1, 41)], "x bigint, y bigint")
    monkeypatch.setattr(index, "SLICE_BYTES", 16 * 15)
    assert [len(ranks) for ranks, _ in index.vector_slices(ranked)] == [15, 15, 10]
    got = {(r.x, r.y): (r.hops, r.reached) for r in frontier.greedy_paths(ranked, edges, pairs).collect()}
    paths = {(a, (a * 7) % 40 + 1): kernels.greedy_path(start, nbrs, x, a - 1, (a * 7) % 40) for a in range(1, 41)}
    assert got == {p: (len(w) - 1, w[-1] == p[1] - 1) for p, w in paths.items()}


@pytest.mark.parametrize("between", [True, False])
def test_lunes_of_wide_balls_copies_and_borders(between):
    rng = np.random.default_rng(17)
    x = rng.normal(size=(300, 4))
    x[200:260] = x[:60]  # copies: as far away as an end
    x[260:] = np.round(x[260:], 0)  # exact ties
    a, b = (v.ravel() for v in np.meshgrid(np.arange(0, 300, 7), np.arange(300)))
    a, b = a[a != b], b[a != b]
    want = []
    for i, j in zip(a, b, strict=True):
        d = kernels.d2(x[i], x)[j]
        hit = (kernels.d2(x[i], x) < d) & (kernels.d2(x[j], x) < d)
        z = np.arange(300)
        want.append((hit & (z > min(i, j)) & (z < max(i, j)) if between else hit & (z != i) & (z != j)).sum())
    for how in ({"few": 0}, {}, {"chunk": 37, "block": 11, "few": 3}):
        assert kernels.lunes(a, b, np.arange(300), x, np.arange(300), x, between, **how).tolist() == want
    assert kernels.lunes(a, b, np.arange(300), x * 2.0**80, np.arange(300), x * 2.0**80, between, few=0).tolist() == want


@pytest.mark.parametrize("size", [64 << 20, 3 * 8 * 11])
def test_lunes_and_neighbours_over_slices(spark, monkeypatch, size):
    x = np.random.default_rng(18).normal(size=(40, 3))
    x[5:17] = x[5]  # more copies than neighbours asked for
    ranked = ranked_of(spark, x)
    monkeypatch.setattr(index, "SLICE_BYTES", size)
    pairs = spark.createDataFrame([(a, b) for a in range(1, 41) for b in range(1, 41, 3) if a != b] + [(1, 99), (77, 2)], "x bigint, y bigint")
    got = {(r.x, r.y): r.n for r in frontier.lune_counts(ranked, pairs, False, shard_rows=9, block=8).collect()}
    listed = frontier.range_lune(ranked, pairs, False).groupBy("x", "y").count().collect()
    assert {p: n for p, n in got.items() if n} == {(r.x, r.y): r["count"] for r in listed}
    assert len(got) == pairs.count() - 2
    near = {(r.src, r.dst) for r in frontier.exact_knn(ranked, 4, shard_rows=7).collect()}
    d = np.array([kernels.d2(v, x) for v in x])
    assert near == {(i, int(j)) for i in range(40) for j in [j for j in np.lexsort((np.arange(40), d[i])) if j != i][:4]}
