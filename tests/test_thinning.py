"""The scans that strike out by products of matrices against those that measure every pair."""

import numpy as np
import pytest

from rangeknn.operators import exact, kernels, thinning


def shapes(n, d):
    rng = np.random.default_rng(n + d)
    x = rng.normal(size=(n, d))
    return {"spread": x, "far away": x + 1e6, "ties": np.round(x), "copies": x[rng.integers(0, max(1, n // 5), n)], "near copies": np.concatenate([x[: n // 2], x[: n - n // 2] * (1 + 1e-9)]), "tiny": x * 1e-160, "huge": x * 1e160}


@pytest.mark.parametrize(("n", "d"), [(1, 3), (2, 2), (9, 2), (200, 3), (300, 64)])
@pytest.mark.parametrize("kind", ["spread", "far away", "ties", "copies", "near copies", "tiny", "huge"])
def test_scans_of_all_rows_keep_what_measuring_every_pair_keeps(n, d, kind):
    x = shapes(n, d)[kind]
    rows, others = thinning.Rows(x), [np.delete(np.arange(n), i) for i in range(n)]
    # narrow windows and few pilots leave much to the later steps
    for got in (rows.two_sided(0, n - 1), rows.two_sided(0, n - 1, 3, 1)):
        assert [g.tolist() for g in got] == [kernels.two_sided(i, o, x).tolist() for i, o in enumerate(others)]
    for got in (rows.nearest_first(np.arange(n)), rows.nearest_first(np.arange(n), 5, 1)):
        assert [g.tolist() for g in got] == [kernels.nearest_first(i, o, x).tolist() for i, o in enumerate(others)]
    if rows.clear:
        outs = [o[:: 1 + i % 7] for i, o in enumerate(others)]
        assert [g.tolist() for g in rows.stuck(0, outs, 3, 2)] == [exact.stuck(i, o, x).tolist() for i, o in enumerate(outs)]


def test_few_pairs_are_measured_by_differences(monkeypatch):
    x = np.random.default_rng(5).normal(size=(8_000, 32))
    rows, others = thinning.Rows(x), [np.delete(np.arange(len(x)), i) for i in range(4_000, 4_008)]
    measured, d2 = [], kernels.d2
    monkeypatch.setattr(kernels, "d2", lambda q, some: measured.append(len(some)) or d2(q, some))

    def pairs(f):
        measured.clear()
        f()
        return sum(measured)

    graph = rows.two_sided(4_000, 4_007)
    for new, old in (
        (lambda: rows.two_sided(4_000, 4_007), lambda: [kernels.two_sided(4_000 + i, o, x) for i, o in enumerate(others)]),
        (lambda: rows.nearest_first(np.arange(4_000, 4_008)), lambda: [kernels.nearest_first(4_000 + i, o, x) for i, o in enumerate(others)]),
        (lambda: rows.stuck(4_000, graph), lambda: [exact.stuck(4_000 + i, out, x) for i, out in enumerate(graph)]),
    ):
        assert 5 * pairs(new) < pairs(old)
