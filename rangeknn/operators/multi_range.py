"""Graphs that keep many ranges in one structure: methods of comparison, each known from one sentence.

What is built here is our reading of that sentence. Every class holds one shard (rows by rank) and
has search(q, lo, hi, k, ef, passes); passes is a mask for further predicates, such as a second attribute.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame

from . import kernels
from .baselines import DensePredicateGraph, InvertedFile, Layered, SegmentTree, covers
from .index import Shard, builds, search
from .multi import inside

Found = tuple[list[tuple[float, int]], int, int]


def _csr(lists: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    start = np.r_[0, np.cumsum([len(v) for v in lists])].astype(np.int64)
    return start, np.concatenate(lists).astype(np.int64) if lists else np.zeros(0, np.int64)


def _entry(lo: int, hi: int, passes: np.ndarray | None) -> int:
    """The middle of the interval, or the passing row next to it; -1 if none passes."""
    mid = (lo + hi) // 2
    if passes is None:
        return mid
    ok = lo + np.flatnonzero(passes[lo : hi + 1])
    return int(ok[np.abs(ok - mid).argmin()]) if len(ok) else -1


def _spatial(vecs: np.ndarray, m: int, spatial: int) -> tuple[np.ndarray, np.ndarray]:
    return kernels.build(vecs, kernels.Params(spatial, 0, m, prune="spatial"))


def _labelled(g, q: np.ndarray, lo: int, hi: int, k: int, ef: int, passes: np.ndarray | None) -> Found:
    """Beam over the edges whose labels (left ends from, to, right ends from, to) hold for [lo, hi]."""
    entry = _entry(lo, hi, passes)
    if entry < 0:
        return [], 0, 0

    def expand(p: int) -> np.ndarray:
        own = slice(g.start[p], g.start[p + 1])
        t = g.labels[own]
        return g.nbrs[own][(t[:, 0] <= lo) & (lo <= t[:, 1]) & (t[:, 2] <= hi) & (hi <= t[:, 3])]

    return kernels.beam(g.start, g.nbrs, g.vecs, q, lo, hi, k, ef, entry, passes=passes, expand=expand)


class StoredRanges:
    """A spatial graph for each stored range; a query takes the shortest one that holds it and filters.

    choose 'thinned': ends at every step-th rank (step 1: one graph for each possible range).
    choose 'covers': windows of halved lengths at half-length stride. Graphs are made when first asked for,
    list by list as a search reads them.
    """

    def __init__(self, vecs: np.ndarray, choose: str = "thinned", step: int = 16, m: int = 16, spatial: int = 32, keep: int = 256) -> None:
        self.vecs, self.choose, self.step, self.m, self.spatial, self.keep = vecs, choose, step, m, spatial, keep
        self.windows = [(a - 1, b - 1) for _, a, b in covers(len(vecs), step)] if choose == "covers" else []
        self.graphs: dict[tuple[int, int], kernels.Lists] = {}

    def stored(self, lo: int, hi: int) -> tuple[int, int]:
        if self.choose == "covers":
            return min((w for w in self.windows if w[0] <= lo and w[1] >= hi), key=lambda w: (w[1] - w[0], w))
        return lo // self.step * self.step, min(len(self.vecs) - 1, -(-hi // self.step) * self.step)

    def search(self, q: np.ndarray, lo: int, hi: int, k: int, ef: int, passes: np.ndarray | None = None) -> Found:
        a, b = self.stored(lo, hi)
        if (a, b) not in self.graphs:
            if len(self.graphs) >= self.keep:
                self.graphs.pop(next(iter(self.graphs)))
            self.graphs[a, b] = kernels.Lists(self.vecs[a : b + 1], kernels.Params(self.spatial, 0, self.m, prune="spatial"))
        entry = _entry(lo, hi, passes)
        if entry < 0:
            return [], 0, 0
        mask = None if passes is None else passes[a : b + 1]
        none = np.zeros(0, np.int64)
        got, n_dist, hops = kernels.beam(none, none, self.vecs[a : b + 1], q, lo - a, hi - a, k, ef, entry - a, passes=mask, through=True, expand=self.graphs[a, b])
        return [(d, p + a) for d, p in got], n_dist, hops


class SegmentBitmap:
    """Equal-count segments with a graph each; every node also has an edge to its nearest node of each
    other segment, tagged with the bit of that segment. A query follows edges whose bits meet its mask;
    very narrow ranges are scanned."""

    def __init__(self, vecs: np.ndarray, n_segments: int = 8, m: int = 16, spatial: int = 24, narrow: int = 32) -> None:
        if not 1 <= n_segments <= 63:
            raise ValueError("segments are bits of a signed 64-bit mask: 1 to 63")
        self.vecs, self.narrow = vecs, narrow
        n = len(vecs)
        n_segments = max(1, min(n_segments, n))
        big, size = n % n_segments, n // n_segments  # the first ones are larger, as with ntile
        self.segment = np.repeat(np.arange(n_segments), [size + (s < big) for s in range(n_segments)])
        lists: list[list[int]] = [[] for _ in range(n)]
        bits: list[list[int]] = [[] for _ in range(n)]
        for s in range(n_segments):
            rows = np.flatnonzero(self.segment == s)
            start, nbrs = _spatial(vecs[rows], m, spatial)
            for i, x in enumerate(rows):
                own = rows[nbrs[start[i] : start[i + 1]]].tolist()
                lists[x] += own
                bits[x] += [1 << s] * len(own)
            for x in range(n):
                if self.segment[x] != s:
                    lists[x].append(int(rows[kernels.d2(vecs[x], vecs[rows]).argmin()]))
                    bits[x].append(1 << s)
        self.start, self.nbrs = _csr([np.array(v, np.int64) for v in lists])
        self.bits = np.array([b for row in bits for b in row], np.int64)

    def mask(self, lo: int, hi: int) -> int:
        a, b = int(self.segment[lo]), int(self.segment[hi])
        return ((1 << (b - a + 1)) - 1) << a

    def search(self, q: np.ndarray, lo: int, hi: int, k: int, ef: int, passes: np.ndarray | None = None) -> Found:
        if hi - lo + 1 <= self.narrow:
            at = np.arange(lo, hi + 1) if passes is None else lo + np.flatnonzero(passes[lo : hi + 1])
            d = kernels.d2(q, self.vecs[at])
            order = np.lexsort((at, d))[:k]
            return [(float(d[i]), int(at[i])) for i in order], len(at), 0
        entry, meets = _entry(lo, hi, passes), self.mask(lo, hi)
        if entry < 0:
            return [], 0, 0

        def expand(p: int) -> np.ndarray:
            own = slice(self.start[p], self.start[p + 1])
            return self.nbrs[own][(self.bits[own] & meets) != 0]

        return kernels.beam(self.start, self.nbrs, self.vecs, q, lo, hi, k, ef, entry, passes=passes, expand=expand)


class CompressedRanges:
    """All ranges in one graph: rows are inserted by rank, and an edge is labelled with the left ends
    and the right ends for which it was chosen.

    Row x gets a list for each left end; leap 'min' moves on when the list first loses a member, leap
    'max' only when it has lost all, so fewer edges are kept. Back edges live until a later row crowds them out.
    """

    def __init__(self, vecs: np.ndarray, m: int = 8, spatial: int = 24, leap: str = "max") -> None:
        if leap not in ("min", "max"):
            raise ValueError("leap is min or max")
        self.vecs = vecs
        n = len(vecs)
        out: list[dict[int, list[int]]] = [{} for _ in range(n)]  # dst -> lo_from, lo_to, hi_from, hi_to
        alive: list[list[int]] = [[] for _ in range(n)]
        for x in range(n):
            d = kernels.d2(vecs[x], vecs[:x])
            order = np.argsort(d, kind="stable")
            left = 0
            while left < x:
                near = order[order >= left][:spatial]
                kept = kernels.nearest_first(x, near, vecs, m)
                for y in kept.tolist():
                    if y not in out[x]:
                        out[x][y] = [left, y, x, n - 1]
                        out[y][x] = [left, y, x, n - 1]
                        alive[y].append(x)
                left = 1 + int(kept.max() if leap == "max" else kept.min())
            for y in out[x]:
                if y < x and len(alive[y]) > 2 * m:
                    stay = set(kernels.nearest_first(y, np.array(sorted(alive[y])), vecs, m).tolist()) | {x}
                    for z in alive[y]:
                        if z not in stay:
                            out[y][z][3] = x - 1
                    alive[y] = [z for z in alive[y] if z in stay]
        self.start, self.nbrs = _csr([np.array(sorted(e), np.int64) for e in out])
        self.labels = np.array([e[v] for e in out for v in sorted(e)], np.int64).reshape(-1, 4)

    def search(self, q: np.ndarray, lo: int, hi: int, k: int, ef: int, passes: np.ndarray | None = None) -> Found:
        return _labelled(self, q, lo, hi, k, ef, passes)


class RectangleRanges:
    """Edges valid in a rectangle of (left, right) ends; rows may come in any order.

    Around u, candidates are taken nearest first. A kept witness between both ends drops the edge; one
    further left limits the left ends to those beyond it, one further right the right ends.
    """

    def __init__(self, vecs: np.ndarray, m: int = 32, spatial: int = 24, window: int = 8, order: np.ndarray | None = None) -> None:
        self.vecs, self.m = vecs, m
        n = len(vecs)
        self.pool: list[set[int]] = [set() for _ in range(n)]
        present = np.zeros(0, np.int64)
        for x in (np.arange(n) if order is None else np.asarray(order)).tolist():
            at = int(np.searchsorted(present, x))
            beside = present[max(0, at - window) : at + window]
            near = present[np.argsort(kernels.d2(vecs[x], vecs[present]), kind="stable")[:spatial]]
            for y in np.union1d(beside, near).tolist():
                self.pool[x].add(y)
                self.pool[y].add(x)
            present = np.insert(present, at, x)
        made = [self._edges(u) for u in range(n)]
        self.start, self.nbrs = _csr([np.array([e[0] for e in row], np.int64) for row in made])
        self.labels = np.array([e[1:] for row in made for e in row], np.int64).reshape(-1, 4)

    def _edges(self, u: int) -> list[tuple[int, int, int, int, int]]:
        cand, n = np.array(sorted(self.pool[u]), np.int64), len(self.vecs)
        own = kernels.d2(self.vecs[u], self.vecs[cand])
        out: list[tuple[int, int, int, int, int]] = []
        for i in np.lexsort((np.abs(cand - u), own)).tolist():
            v = int(cand[i])
            a, b = min(u, v), max(u, v)
            left, right = -1, n
            if out:
                kept = np.array([e[0] for e in out], np.int64)
                w = kept[(kernels.d2(self.vecs[v], self.vecs[kept]) < own[i]) & (kernels.d2(self.vecs[u], self.vecs[kept]) < own[i])]
                if ((w > a) & (w < b)).any():
                    continue
                left, right = int(w[w < a].max(initial=-1)), int(w[w > b].min(initial=n))
            if len(out) < self.m or abs(u - v) == 1:
                out.append((v, left + 1, a, b, right - 1))
        return out

    def search(self, q: np.ndarray, lo: int, hi: int, k: int, ef: int, passes: np.ndarray | None = None) -> Found:
        return _labelled(self, q, lo, hi, k, ef, passes)


def per_shard(make: Callable[[np.ndarray], object], ef: int | Callable[[int], int] = 64, lazy: bool = False):
    """Search kernel of a structure that is built when a task meets a shard; a box is tested while searching.

    lazy: it is made as searches read it, so a shard's queries may be dealt to several tasks. ef may depend on the query's id, so that one structure serves a sweep.
    """
    made: dict[int, object] = {}

    def run(s: Shard, q: np.ndarray, lo: int, hi: int, k: int, qid: int, box=None):
        key = int(s.ids[0])
        if key not in made:
            made.clear()
            made[key] = make(s.vecs)
        pool = ef(qid) if callable(ef) else ef
        return made[key].search(q, lo, hi, k, pool, None if box is None else inside(s, lo, hi, box))

    return run if lazy else builds(run)


def stored_ranges_search(packed: DataFrame, queries: DataFrame, ef: int = 64, **how) -> DataFrame:
    return search(packed, queries, per_shard(lambda v: StoredRanges(v, **how), ef, lazy=True))


def segment_bitmap_search(packed: DataFrame, queries: DataFrame, ef: int = 64, **how) -> DataFrame:
    return search(packed, queries, per_shard(lambda v: SegmentBitmap(v, **how), ef))


def compressed_search(packed: DataFrame, queries: DataFrame, ef: int = 64, **how) -> DataFrame:
    return search(packed, queries, per_shard(lambda v: CompressedRanges(v, **how), ef))


def rectangle_search(packed: DataFrame, queries: DataFrame, ef: int = 64, **how) -> DataFrame:
    return search(packed, queries, per_shard(lambda v: RectangleRanges(v, **how), ef))


def footprint(g) -> tuple[int, int]:
    """(edges, bytes) of a structure: four bytes an edge, a number of a label or a node's pointer; codes and tables as they are."""
    if isinstance(g, InvertedFile):
        return 0, g.codes.size + 4 * (g.centres.size + sum(b.size for b in g.books) + len(g.cell))
    edges = g.n_edges() if isinstance(g, SegmentTree) else g.near.size if isinstance(g, DensePredicateGraph) else len(g.nbrs)
    levels = len(g.levels) if isinstance(g, SegmentTree) else 1
    labels = sum(np.asarray(getattr(g, c)).size for c in ("labels", "bits") if hasattr(g, c))
    upper = sum(len(v) for layer in g.layers[1:] for v in layer.values()) if isinstance(g, Layered) else 0
    return int(edges + upper), int(4 * (edges + upper + labels + levels * len(g.vecs)))
