"""Restriction, repair, segment-tree fan-out, tuning, formats and streams with state."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangeknn.operators import baselines, exact, index, kernels, metrics
from rangeknn.sources import files
from rangeknn.streaming import stream


def ranked_of(spark, x):
    rows = [(i, i + 1, float(i), v.tolist()) for i, v in enumerate(x)]
    return spark.createDataFrame(rows, "id bigint, rank bigint, attr double, vec array<double>")


@pytest.mark.parametrize("m", [None, 6])
def test_restricted_candidates_give_the_edges_inside(m):
    x = np.random.default_rng(3).normal(size=(80, 4))
    how = kernels.Params(8, 6, m)
    near = kernels.nearest(x, how)
    pairs = lambda g: {(a, int(b)) for a in range(80) for b in g[1][g[0][a] : g[0][a + 1]]}
    whole = pairs(kernels.pruned(x, near, how))
    assert pairs(kernels.pruned(x, near, how, (20, 50))) == {(a, b) for a, b in whole if 20 <= a <= 50 and 20 <= b <= 50}
    assert pairs(kernels.pruned(x, near, how, (90, 99))) == set()
    assert pairs(kernels.build(x, how)) == whole


def test_repair_reaches_every_node():
    rng = np.random.default_rng(4)
    x = np.concatenate([rng.normal(size=(30, 3)) + 50 * c for c in range(4)])
    plain = kernels.build(x, kernels.Params(4, 0, 8, prune="spatial"))
    start, nbrs = kernels.build(x, kernels.Params(4, 0, 8, prune="spatial", repair=True))
    root = int(np.argmin(kernels.d2(x.mean(axis=0), x)))
    edges = [(a, int(b)) for a in range(120) for b in nbrs[start[a] : start[a + 1]]]
    assert exact.reach(edges, root, 0, 119) == 120
    assert len(nbrs) > len(plain[1])
    for n in (0, 1):
        assert len(kernels.build(x[:n], kernels.Params(4, 0, 8, prune="spatial", repair=True))[1]) == 0


@pytest.mark.parametrize("fanout", [2, 3, 8])
def test_segment_tree_of_any_fanout_finds_all_when_saturated(fanout):
    x = np.random.default_rng(5).normal(size=(100, 4))
    tree = baselines.SegmentTree(x, fanout=fanout)
    assert len(tree.levels[-1]) == 100
    got = tree.search(x[7], 0, 99, 5, 1_000)[0]
    want = np.lexsort((np.arange(100), kernels.d2(x[7], x)))[:5]
    assert [p for _, p in got] == want.tolist()
    assert all(20 <= p <= 60 for _, p in tree.search(x[7], 20, 60, 5, 50)[0])


def test_links_joins_and_reports(spark):
    x = np.random.default_rng(6).normal(size=(60, 4))
    ranked = ranked_of(spark, x)
    chain = spark.createDataFrame([(a, a + 1) for a in range(1, 60)] + [(a + 1, a) for a in range(2, 60)], "src bigint, dst bigint")
    assert [tuple(r) for r in exact.missing_links(chain, ranked).collect()] == [(2, 1)]
    asked = spark.createDataFrame([(1, x[3].tolist(), 10.0, 40.0), (2, x[4].tolist(), None, 5.0), (3, x[5].tolist(), 9.0, 8.0)], "qid bigint, qvec array<double>, lo double, hi double")
    got = {(r["qid"], r["rn"]): r["id"] for r in exact.knn_join(ranked, asked, 3).collect()}
    for qid, q, lo, hi in ((1, 3, 10, 40), (2, 4, 0, 5)):
        want = lo + np.lexsort((np.arange(lo, hi + 1), kernels.d2(x[q], x[lo : hi + 1])))[:3]
        assert [got[qid, n] for n in (1, 2, 3)] == want.tolist()
    assert not any(q == 3 for q, _ in got)
    with pytest.raises(ValueError):
        exact.knn_join(ranked, asked, 3, max_queries=2)
    report = index.build_report(index.shards(ranked, 25), [kernels.Params(4, 4, 8), kernels.Params(4, 0, 8)]).collect()
    assert sum(r["nodes"] for r in report) == 120 and all(r["knn_s"] >= 0 and r["prune_s"] > 0 for r in report)


def test_tuning_takes_the_cheapest_setting_that_reaches_the_target(spark):
    kind = "method string, ef bigint, recall double, n_dist double"
    tried = spark.createDataFrame([("a", 10, 0.9, 5.0), ("a", 20, 0.96, 9.0), ("a", 40, 0.99, 20.0), ("b", 10, 0.5, 1.0)], kind)
    fresh = spark.createDataFrame([("a", 10, 0.8, 6.0), ("a", 20, 0.94, 8.0), ("a", 40, 0.98, 21.0), ("b", 10, 0.6, 1.0)], kind)
    got = {r["method"]: tuple(r)[1:] for r in metrics.tuned(tried, fresh, 0.95).collect()}
    assert got == {"a": (20, 0.94, 8.0), "b": (None, None, None)}


@pytest.mark.parametrize("fmt", files.FORMATS)
def test_formats_keep_arrays_and_nulls(spark, tmp_path, fmt):
    kind = "id bigint, attr double, vec array<double>, name string"
    rows = [(1, 0.1, [1.0, 2.5], "a,b"), (2, None, [], "line\\nbreak"), (3, -1e300, None, None)]
    files.write(spark.createDataFrame(rows, kind), str(tmp_path / fmt), fmt)
    back = files.read(spark, str(tmp_path / fmt), kind, fmt)
    assert sorted(map(tuple, back.collect()), key=lambda r: r[0]) == rows
    with pytest.raises(ValueError):
        files.write(back, str(tmp_path / "x"), "xml")


def test_recent_keeps_state_over_batches_and_drops_what_is_too_late(spark, tmp_path):
    kind = "event_id bigint, ts timestamp, user_id bigint"
    t0 = dt.datetime(2024, 1, 1)
    day = [(i, t0 + dt.timedelta(minutes=i), 1) for i in range(4)] + [(None, t0, 1), (9, t0, None)]
    later = [(10 + i, t0 + dt.timedelta(days=3, minutes=i), 2) for i in range(2)]
    more = [(12, t0 + dt.timedelta(days=3, minutes=5), 2)]
    late = [(20, t0, 1), (21, t0 + dt.timedelta(days=3), 2)]
    for rows in (day, later, more, late):
        spark.createDataFrame(rows, kind).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    files_in_order = spark.readStream.schema(kind).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = stream.drained(stream.recent(files_in_order, keep=3, ttl_ms=3_600_000), "update").orderBy("batch", "user_id").collect()
    last = {r["user_id"]: r for r in got}
    # id 20 comes days behind the watermark; a batch is held against the watermark of the batch before the last
    assert last[1]["ids"] == [3, 2, 1] and last[1]["n_seen"] == 4
    assert last[2]["ids"] == [12, 11, 21] and last[2]["n_seen"] == 4
    assert last[2]["batch"] > last[1]["batch"]


def test_repeats_within_the_watermark_go(spark, tmp_path):
    kind = "event_id bigint, ts timestamp, user_id bigint"
    t0 = dt.datetime(2024, 1, 1)
    for _ in range(2):
        spark.createDataFrame([(1, t0, 1), (1, t0, 1), (2, t0, 1)], kind).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    source = spark.readStream.schema(kind).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    assert sorted(r["event_id"] for r in stream.drained(stream.fresh(source), "append").select(F.col("event_id")).collect()) == [1, 2]
