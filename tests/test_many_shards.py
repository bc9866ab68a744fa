"""Queries whose interval meets several shards, and other inputs larger than the given tables."""

import numpy as np
import pytest
from pyspark import TaskContext

from rangeknn.operators import baselines, exact, frontier, index, kernels
from rangeknn.plans import queries  # noqa: F401  registers all queries
from rangeknn.plans import around, methods

N, ROWS = 120, 25


@pytest.fixture(scope="module")
def sharded(spark):
    rng = np.random.default_rng(11)
    x = rng.normal(size=(N, 4))
    objs = spark.createDataFrame([(i, i + 1, float(i), v.tolist()) for i, v in enumerate(x)], "id bigint, rank bigint, attr double, vec array<double>")
    ends = [(0, 3.0, 9.0), (1, 20.0, 60.0), (2, None, 80.0), (3, 24.0, None), (4, 50.0, 49.0), (5, None, None)]
    asked = [(q, rng.normal(size=4).tolist(), lo, hi, 7) for q, lo, hi in ends]
    inside = {q: np.flatnonzero((np.arange(N) >= (0 if lo is None else lo)) & (np.arange(N) <= (N if hi is None else hi))) for q, lo, hi in ends}
    ranked = index.materialise(objs, "ranked")
    built = index.build(ranked, kernels.Params(6, 4, 8), ROWS)
    return x, ranked, built, spark.createDataFrame(asked, "qid bigint, qvec array<double>, lo double, hi double, k int"), inside


def test_one_header_entry_a_query_over_all_its_shards(sharded):
    x, ranked, built, queries, inside = sharded
    centre = np.array(index.global_centroid(ranked))
    got = [(r["qid"], r["id"]) for r in index.search_entries(built, queries, centre.tolist()).collect()]
    assert sorted(got) == [(q, int(at[kernels.d2(centre, x[at]).argmin()])) for q, at in sorted(inside.items()) if len(at)]


@pytest.mark.parametrize("ef", [7, 10_000])
def test_frontier_enters_every_shard(sharded, ef):
    x, ranked, built, queries, inside = sharded
    vec = {r["qid"]: np.array(r["qvec"]) for r in queries.collect()}
    links = index.edges(built).selectExpr("src_rank as src", "dst_rank as dst")
    got = {}
    for r in frontier.frontier_search(ranked, links, index.to_ranks(queries, ranked), ef, shard_rows=ROWS).collect():
        got.setdefault(r["qid"], {})[r["rn"]] = r["id"]
    assert {q: len(v) for q, v in got.items()} == {q: min(7, len(at)) for q, at in inside.items() if len(at)}
    if ef > N:
        want = {q: at[np.argsort(kernels.d2(vec[q], x[at]))[:7]].tolist() for q, at in inside.items() if len(at)}
        assert {q: [v[n] for n in sorted(v)] for q, v in got.items()} == want


def test_a_pool_that_holds_the_interval_visits_what_the_walk_reaches():
    """Rounds of whole fronts give what the walk one by one gives, also where an interval falls into parts."""
    x = np.random.default_rng(3).normal(size=(200, 4))
    x[9] = x[60]
    for how in (kernels.Params(5, 4, 6), kernels.Params(3, 0, 3, prune="spatial")):
        start, nbrs = kernels.build(x, how)
        for lo, hi, k in ((0, 199, 10), (30, 90, 10), (30, 90, 100), (7, 7, 3), (40, 60, 5)):
            for entry in {lo, hi, (lo + hi) // 2}:
                one = kernels.beam(start, nbrs, x, x[9], lo, hi, k, 10_000, entry, expand=lambda p, s=start, n=nbrs: n[s[p] : s[p + 1]])
                assert kernels.beam(start, nbrs, x, x[9], lo, hi, k, 10_000, entry) == one


def test_witness_scan_looks_only_at_what_is_left(monkeypatch):
    rng = np.random.default_rng(4)
    rows = rng.normal(size=(3_000, 64))
    own, looked, plain = kernels.d2(np.zeros(64), rows), [], kernels.d2
    monkeypatch.setattr(kernels, "d2", lambda x, r: looked.append(len(r)) or plain(x, r))
    kept = kernels.between(rows, own, None)
    assert len(kept) > 3 and sum(looked) < len(rows) * len(kept) / 2


def test_broadcast_join_of_many_attributes(spark):
    vecs = spark.createDataFrame([(i, i % 3) for i in range(40)], "vec_id bigint, label int")
    attrs = spark.createDataFrame([(i % 60, float(i)) for i in range(90)], "vec_id bigint, price double")
    want = sorted(map(tuple, vecs.join(attrs, "vec_id").collect()))
    for most in (100, 50, 30):  # the attributes, the vectors, slices of the attributes
        assert sorted(map(tuple, around.broadcast_attach(vecs, attrs, "vec_id", most).collect())) == want


def test_exact_graphs_take_more_than_five_thousand_objects(spark):
    n = 5_100
    ranked = spark.range(1, n + 1).selectExpr("id as rank", "array(double(id), 0d) as vec")
    got = exact.between_graph(ranked)
    assert got.count() == 2 * (n - 1) and got.where("abs(src - dst) <> 1").count() == 0


def test_exact_graphs_check_what_they_broadcast(spark, monkeypatch):
    monkeypatch.setattr(exact, "MAX_BYTES", 100)
    with pytest.raises(ValueError, match="broadcast"):
        exact.mrng(spark.range(1, 9).selectExpr("id as rank", "array(double(id), 0d) as vec"))


def test_cost_at_recall_reads_the_given_documents(spark, tmp_path):
    docs = [(i, "en", 1_000 - i) for i in range(100)] + [(200, "fr", 10), (201, None, 10), (202, "de", 5)]
    spark.createDataFrame(docs, "doc_id bigint, lang string, n_chars bigint").write.parquet(f"{tmp_path}/documents.parquet")
    marks = [(i, int(i < 10)) for i in range(100)] + [(200, 1), (201, 1), (202, 0)]
    spark.createDataFrame(marks, "doc_id bigint, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    got = {r["method"]: (r["cost"], r["max_recall"]) for r in methods.cost_at_recall(spark, str(tmp_path)).collect()}
    # en: lengths 1000 and 901-999 in steps of 250: one document with one of ten hits, then all hundred
    assert got == {"en": (pytest.approx(1 + (0.95 - 0.1) * 99 / 0.9), 1.0), "fr": (1.0, 1.0)}


def test_lanes_and_shuffled_queries_answer_alike(sharded, monkeypatch):
    _, _, built, queries, _ = sharded
    rows = lambda **how: sorted(map(tuple, index.search(built, queries, **how).collect()))
    want = rows(kernel=index.builds(lambda *a: index.scan_kernel(*a)))
    assert want and rows() == want
    monkeypatch.setattr(index, "BROADCAST_BYTES", 0)
    assert rows() == want


def test_one_large_shard_is_dealt_to_several_tasks(spark):
    x = np.random.default_rng(1).normal(size=(200, 3))
    objs = spark.createDataFrame([(i, i + 1, float(i), v.tolist()) for i, v in enumerate(x)], "id bigint, rank bigint, attr double, vec array<double>")
    queries = spark.createDataFrame([(i, v.tolist(), None, None, 1) for i, v in enumerate(x)], "qid bigint, qvec array<double>, lo double, hi double, k int")
    task = lambda *a: ([(0.0, 0)], TaskContext.get().partitionId(), 0)
    places = index.search(index.materialise(index.shards(objs), "shards"), queries, task).select("n_dist").distinct().count()
    assert places > 1
    assert index.search(index.materialise(index.shards(objs), "shards"), queries, index.builds(task)).select("n_dist").distinct().count() == 1


def test_broadcast_counts_every_shard_that_a_query_meets(sharded, monkeypatch):
    _, _, built, queries, inside = sharded
    asks = sum(len({p // ROWS for p in at.tolist()}) for at in inside.values())
    plan = lambda: index.search(built, queries)._jdf.queryExecution().optimizedPlan().toString()
    monkeypatch.setattr(index, "BROADCAST_BYTES", asks * (4 * 8 + 96))
    assert "strategy=broadcast" in plan()
    monkeypatch.setattr(index, "BROADCAST_BYTES", asks * (4 * 8 + 96) - 1)
    assert "strategy=broadcast" not in plan()


def test_hashing_compares_what_shares_a_bucket(sharded):
    x, ranked, _, queries, inside = sharded
    vec = {r["qid"]: np.array(r["qvec"]) for r in queries.collect()}
    got = {}
    for r in baselines.hashed_search(ranked, queries, width=1e9).collect():
        got.setdefault(r["qid"], {})[r["rn"]] = r["id"]
    # buckets that are cut at zero only: everything on the query's side of any line
    assert set(got) <= {q for q, at in inside.items() if len(at)} and got
    narrow = {(r["qid"], r["id"]) for r in baselines.hashed_search(ranked, queries, width=0.5).collect()}
    assert all(i in inside[q] for q, i in narrow)
    assert all(kernels.d2(vec[r["qid"]], x[r["id"] : r["id"] + 1])[0] == pytest.approx(r["d2"]) for r in baselines.hashed_search(ranked, queries).collect())


def test_settings_that_differ_by_the_pool_share_their_truth(sharded):
    _, _, built, queries, _ = sharded
    settings = [("a", 10, 3), ("a", 20, 3), ("a", 10, 5), ("a", 20, 5)]
    asked = None
    for i, (_, _, k) in enumerate(settings):
        one = queries.selectExpr(f"qid * 1000 + {i} as qid", "qvec", "lo", "hi", f"{k} as k")
        asked = one if asked is None else asked.union(one)
    want = sorted(map(tuple, index.search(built, asked).select("qid", "id").collect()))
    assert sorted(map(tuple, methods.truth_of(built, asked, settings).select("qid", "id").collect())) == want
