"""Numpy kernels on one shard: rows are in attribute order, a position is a rank. No Spark here."""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np


def d2(x: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Squared distances of one vector to rows: differences squared and summed, in double."""
    diff = rows - x
    return np.einsum("ij,ij->i", diff, diff)


def steady(x: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """d2, whose last digit for a row may depend on whether it stands alone, as if it never did."""
    return d2(x, rows) if len(rows) != 1 else d2(x, np.concatenate([rows, rows]))[:1]


def between(rows: np.ndarray, own: np.ndarray, cap: int | None) -> np.ndarray:
    """Places of the candidates kept by the witness scan, in the given order, at most cap of them.

    A candidate goes if some kept one is nearer to both ends of the edge than they are apart. Each kept one
    strikes out all it is a witness against at once, so the steps are those kept, not the candidates, and each looks only
    at what is left.
    """
    left, kept = np.arange(len(rows)), []
    while len(left) and (cap is None or len(kept) < cap):
        kept.append(int(left[0]))
        near, row, left, rows, own = own[0], rows[0], left[1:], rows[1:], own[1:]
        stay = (near >= own) | (d2(row, rows) >= own)
        if not stay.all():
            left, rows, own = left[stay], rows[stay], own[stay]
    return np.array(kept, np.int64)


def two_sided(x: int, cand: np.ndarray, vecs: np.ndarray, m: int | None = None) -> np.ndarray:
    """Neighbours of position x among sorted positions: each side on its own, smallest gap first."""
    if m is not None and m < 2:
        raise ValueError("m must be at least 2")
    out = []
    for side in (cand[cand < x][::-1], cand[cand > x]):
        if len(side):
            rows = vecs[side]
            out.append(side[between(rows, d2(vecs[x], rows), None if m is None else m // 2)])
    return np.concatenate(out) if out else np.zeros(0, np.int64)


def nearest_first(x: int, cand: np.ndarray, vecs: np.ndarray, m: int | None = None) -> np.ndarray:
    """The purely spatial prune: witnesses anywhere, candidates by distance."""
    own = d2(vecs[x], vecs[cand])
    order = np.lexsort((cand, own))
    side, own = cand[order], own[order]
    return side[between(vecs[side], own, m)]


def in_box(x: int, cand: np.ndarray, vecs: np.ndarray, ranks: np.ndarray, m: int | None = None) -> np.ndarray:
    """Several attributes: a witness lies in the closed box of the two ends; small rank gaps first."""
    gap = np.abs(ranks[cand] - ranks[x]).sum(axis=1)
    own = d2(vecs[x], vecs[cand])
    order = np.lexsort((cand, own, gap))
    side, own, kept = cand[order], own[order], []
    n_attr = ranks.shape[1]
    orthant = ((ranks[side] > ranks[x]) << np.arange(n_attr)).sum(axis=1)
    quota = None if m is None else max(1, m >> n_attr)
    used = np.zeros(1 << n_attr, np.int64)
    spare = []
    for c in range(len(side)):
        low, high = np.minimum(ranks[x], ranks[side[c]]), np.maximum(ranks[x], ranks[side[c]])
        k = np.array(kept + spare, dtype=np.int64)
        if len(k):
            inside = ((ranks[side[k]] >= low) & (ranks[side[k]] <= high)).all(axis=1) & (own[k] < own[c])
            if inside.any() and (d2(vecs[side[c]], vecs[side[k[inside]]]) < own[c]).any():
                continue
        if quota is None or used[orthant[c]] < quota:
            used[orthant[c]] += 1
            kept.append(c)
        else:
            spare.append(c)
    if m is not None:
        kept = (kept + spare)[:m]
    return side[kept]


def knn_exact(vecs: np.ndarray, k: int, block: int = 512) -> np.ndarray:
    """Positions of each row's k nearest others, ties to the smaller position."""
    n = len(vecs)
    k = min(k, n - 1)
    out = np.zeros((n, max(k, 0)), np.int64)
    if k <= 0:
        return out
    sq = np.einsum("ij,ij->i", vecs, vecs)
    for a in range(0, n, block):
        d = sq[a : a + block, None] + sq[None, :] - 2 * vecs[a : a + block] @ vecs.T
        d[np.arange(len(d)), np.arange(a, a + len(d))] = np.inf
        wide = min(n - 1, k + 8)
        part = np.argpartition(d, wide - 1, axis=1)[:, :wide]
        for i in range(len(d)):
            p = part[i]
            e = d2(vecs[a + i], vecs[p])
            out[a + i] = p[np.lexsort((p, e))[:k]]
    return out


def knn_descent(vecs: np.ndarray, k: int, iters: int = 8, delta: float = 0.002, seed: int = 0) -> np.ndarray:
    """Approximate neighbours: random start, then neighbours of neighbours until few changes."""
    n = len(vecs)
    k = min(k, n - 1)
    if n <= 4 * k + 2:
        return knn_exact(vecs, k)
    rng = np.random.default_rng(seed)
    ids = (np.arange(n)[:, None] + 1 + np.argsort(rng.random((n, min(n - 1, 4 * k))), axis=1)[:, :k] * ((n - 1) // (4 * k))) % n
    dist = np.stack([d2(vecs[i], vecs[ids[i]]) for i in range(n)])
    for _ in range(iters):
        back: list[list[int]] = [[] for _ in range(n)]
        for i, row in enumerate(ids.tolist()):
            for j in row:
                if len(back[j]) < k:
                    back[j].append(i)
        changed, new_ids, new_dist = 0, ids.copy(), dist.copy()
        for i in range(n):
            around = np.array(ids[i].tolist() + back[i])
            cand = np.setdiff1d(np.append(ids[around].ravel(), around), np.append(ids[i], i))
            if not len(cand):
                continue
            allids, alld = np.append(ids[i], cand), np.append(dist[i], d2(vecs[i], vecs[cand]))
            best = np.lexsort((allids, alld))[:k]
            changed += int((best >= k).sum())
            new_ids[i], new_dist[i] = allids[best], alld[best]
        ids, dist = new_ids, new_dist
        if changed < delta * n * k:
            break
    return ids


def nearest_of(asked: np.ndarray, ids: np.ndarray, vecs: np.ndarray, others: np.ndarray, k: int, chunk: int = 16_384) -> list[tuple[np.ndarray, np.ndarray]]:
    """(ids, squared distances) of the k nearest others of each row of vecs but itself, ties to the smaller id. Products of
    matrices only choose whom to measure: all that may be among the k are, by differences."""
    none = (np.zeros(0, np.int64), np.zeros(0))
    out, bound = [none] * len(asked), np.full(len(asked), np.inf)
    own = np.einsum("ij,ij->i", vecs, vecs)
    for a in range(0, len(ids), chunk):
        names, rows = ids[a : a + chunk], others[a : a + chunk]
        sq = np.einsum("ij,ij->i", rows, rows)
        d = vecs @ rows.T
        d *= -2
        d += sq
        d += own[:, None]
        last = min(k, len(names) - 1)
        cut = bound.copy()
        if len(more := np.flatnonzero(np.isinf(bound))):
            cut[more] = np.partition(d[more], last, axis=1)[:, last]
        cut += 1e-15 * (1_000 + vecs.shape[1]) * (own.max(initial=0) + sq.max(initial=0))
        for i, (name, x) in enumerate(zip(asked.tolist(), vecs, strict=True)):
            at = np.flatnonzero(d[i] <= cut[i])
            at = at[names[at] != name]
            if len(at):
                both, e = np.append(out[i][0], names[at]), np.append(out[i][1], steady(x, rows[at]))
                best = np.lexsort((both, e))[:k]
                out[i] = both[best], e[best]
                if len(best) == k:
                    bound[i] = e[best[-1]]
    return out


def closest(q: np.ndarray, vecs: np.ndarray, k: int, names: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(positions, squared distances) of the k rows nearest to q, ties to the smaller name or position. Of many rows a product
    chooses whom to measure: all that may be among the k are, by differences."""
    at = np.arange(len(vecs))
    if len(vecs) > max(256, 4 * k):
        sq = np.einsum("ij,ij->i", vecs, vecs)
        rough = sq - 2 * (vecs @ q)
        cut = np.partition(rough, k - 1)[k - 1] + 1e-15 * (1_000 + len(q)) * (sq.max() + q @ q)
        if np.isfinite(cut):
            at = np.flatnonzero(rough <= cut)
    dist = steady(q, vecs[at])
    best = np.lexsort((at if names is None else names[at], dist))[:k]
    return at[best], dist[best]


def lunes(x: np.ndarray, y: np.ndarray, ranks: np.ndarray, vecs: np.ndarray, others: np.ndarray, rows: np.ndarray, among: bool, chunk: int = 16_384, few: int = 64, block: int = 512) -> np.ndarray:
    """For pairs (x, y) of positions in ranks, vecs: how many of the others (ranks in ascending order, rows) are nearer to both
    than these are apart; ``among``: and lie strictly between them by rank.

    A ball around x with few members is measured member by member. Else rows of distances to all others, one for each end
    whatever the number of its pairs, are compared. Rows come from products of matrices; what lies too near to the border for them is measured by differences.
    """
    n, diff = np.zeros(len(x), np.int64), vecs[x] - vecs[y]
    apart = np.einsum("ij,ij->i", diff, diff) if len(x) != 1 else steady(vecs[x[0]], vecs[y])
    own = np.einsum("ij,ij->i", vecs, vecs)
    low, high = np.minimum(ranks[x], ranks[y]), np.maximum(ranks[x], ranks[y])

    def measured(j: int, at: np.ndarray, part: np.ndarray) -> int:
        near = at[steady(vecs[x[j]], part[at]) < apart[j]]
        return int((steady(vecs[y[j]], part[near]) < apart[j]).sum()) if len(near) else 0

    for a in range(0, len(others), chunk):
        place, part = others[a : a + chunk], rows[a : a + chunk]
        sq = np.einsum("ij,ij->i", part, part)
        scale = float(own.max(initial=0) + sq.max(initial=0))
        kind = np.float32 if 1e-20 < scale < 1e37 else np.float64
        slack = 4e-7 * apart + 1e-11 * scale
        below, above = (apart - slack).astype(kind), (apart + slack).astype(kind)
        first = np.searchsorted(place, low, "right") if among else np.zeros(len(x), np.int64)
        last = np.searchsorted(place, high, "left") if among else np.full(len(x), len(place))

        def table(ends: np.ndarray) -> np.ndarray:
            d = vecs[ends] @ part.T
            d *= -2
            d += sq
            d += own[ends][:, None]
            d = d.astype(kind)
            at = np.searchsorted(place, ranks[ends])
            mine = np.flatnonzero((at < len(place)) & (place[np.minimum(at, len(place) - 1)] == ranks[ends]))
            d[mine, at[mine]] = np.inf  # no end is its own witness
            return d

        todo, space = np.flatnonzero(first < last), np.empty(len(place), kind)
        for b in range(0, len(ends := np.unique(x[todo])), block):
            mine = ends[b : b + block]
            near, left = table(mine), []
            row_of = {int(e): i for i, e in enumerate(mine.tolist())}
            for j in todo[np.isin(x[todo], mine)].tolist():
                row, bound = near[row_of[int(x[j])], first[j] : last[j]], above[j]
                if len(row) > 1_024 and np.count_nonzero(row[:1_024] < bound) > few:
                    left.append(j)
                    continue
                inside = row < bound
                if (size := np.count_nonzero(inside)) > few:
                    left.append(j)
                elif size:
                    at = first[j] + np.flatnonzero(inside)
                    n[j] += measured(j, at[place[at] != ranks[y[j]]], part)
            left = np.array(left, np.int64)
            known = np.isin(y[left], mine)
            groups = [(near, row_of, left[known])]
            for c in range(0, len(far := np.unique(y[left[~known]])), block):
                some = far[c : c + block]
                groups.append((None, {int(e): i for i, e in enumerate(some.tolist())}, left[~known][np.isin(y[left[~known]], some)]))
            for other, at_row, mine_pairs in groups:
                other = table(np.array(list(at_row), np.int64)) if other is None else other
                for j in mine_pairs.tolist():
                    s = slice(first[j], last[j])
                    both = np.maximum(near[row_of[int(x[j])], s], other[at_row[int(y[j])], s], out=space[: last[j] - first[j]])
                    sure, most = np.count_nonzero(both < below[j]), np.count_nonzero(both < above[j])
                    n[j] += sure
                    if most > sure:
                        n[j] += measured(j, first[j] + np.flatnonzero((both >= below[j]) & (both < above[j])), part)
    return n


@dataclass(frozen=True)
class Params:
    """spatial: neighbours from the k-NN graph; window: ranks on each side; m: degree cap.

    prune 'between' is the index, 'spatial' its ablation; window 0 the other one. repair adds edges
    until the node nearest to the shard's own centroid reaches every other.
    """

    spatial: int = 32
    window: int = 64
    m: int | None = 64
    knn: str = "exact"
    prune: str = "between"
    repair: bool = False


def nearest(vecs: np.ndarray, how: Params, seed: int = 0) -> np.ndarray:
    """The k-NN graph, which may serve several prunes."""
    k = min(how.spatial, max(len(vecs) - 1, 0))
    return {"exact": knn_exact, "nn_descent": lambda v, n: knn_descent(v, n, seed=seed)}[how.knn](vecs, k)


def pruned(vecs: np.ndarray, near: np.ndarray, how: Params, within: tuple[int, int] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(start, neighbours) from a k-NN graph. within: only these positions have edges and are candidates."""
    n = len(vecs)
    lo, hi = within or (0, n - 1)
    lists = [np.zeros(0, np.int64)] * n
    for x in range(max(lo, 0), min(hi, n - 1) + 1):
        window = np.arange(max(lo, x - how.window), min(hi, n - 1, x + how.window) + 1)
        cand = np.unique(np.concatenate([near[x], window]))
        cand = cand[(cand != x) & (cand >= lo) & (cand <= hi)]
        lists[x] = two_sided(x, cand, vecs, how.m) if how.prune == "between" else nearest_first(x, cand, vecs, how.m)
    start = np.r_[0, np.cumsum([len(x) for x in lists])].astype(np.int64)
    nbrs = np.concatenate(lists).astype(np.int64) if n else np.zeros(0, np.int64)
    if how.repair and n:
        return reachable(start, nbrs, vecs, int(np.argmin(d2(vecs.mean(axis=0), vecs))))
    return start, nbrs


def build(vecs: np.ndarray, how: Params, seed: int = 0, within: tuple[int, int] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Graph of a shard as (start, neighbours)."""
    return pruned(vecs, nearest(vecs, how, seed), how, within)


class Lists:
    """The lists that ``build`` makes by the spatial prune alone, without window and repair: each is made when it is first asked
    for, against all rows, as no list depends on another. A search sees the same graph."""

    def __init__(self, vecs: np.ndarray, how: Params) -> None:
        if how.window or how.repair or how.knn != "exact" or how.prune != "spatial":
            raise ValueError("only a spatial graph has lists that do not depend on others")
        self.vecs, self.how, self.made = vecs, how, {}
        self.sq = np.einsum("ij,ij->i", vecs, vecs)

    def __call__(self, x: int) -> np.ndarray:
        if x not in self.made:
            k = min(self.how.spatial, len(self.vecs) - 1)
            near = np.zeros(0, np.int64)
            if k > 0:
                d = self.sq - 2 * (self.vecs @ self.vecs[x])
                d[x] = np.inf
                cut = np.partition(d, k - 1)[k - 1] + 1e-15 * (1_000 + self.vecs.shape[1]) * (self.sq[x] + self.sq.max())
                near = np.flatnonzero(d <= cut)
                near = near[near != x]
                near = np.sort(near[np.lexsort((near, steady(self.vecs[x], self.vecs[near])))[:k]])
            self.made[x] = nearest_first(x, near, self.vecs, self.how.m)
        return self.made[x]


def reachable(start: np.ndarray, nbrs: np.ndarray, vecs: np.ndarray, root: int) -> tuple[np.ndarray, np.ndarray]:
    """The graph with one more edge for each part that root does not reach, from the reached node
    nearest to the part's first node."""
    n = len(vecs)
    seen = np.zeros(n, bool)
    extra: dict[int, list[int]] = {}

    def walk(x: int) -> None:
        seen[x], todo = True, [x]
        while todo:
            a = todo.pop()
            new = nbrs[start[a] : start[a + 1]]
            new = new[~seen[new]]
            seen[new] = True
            todo += new.tolist()

    walk(root)
    for x in range(n):
        if not seen[x]:
            have = np.flatnonzero(seen)
            extra.setdefault(int(have[np.argmin(d2(vecs[x], vecs[have]))]), []).append(x)
            walk(x)
    lists = [np.append(nbrs[start[a] : start[a + 1]], extra.get(a, [])) for a in range(n)]
    return np.r_[0, np.cumsum([len(v) for v in lists])].astype(np.int64), np.concatenate(lists).astype(np.int64)


def previous_closer(distance: np.ndarray) -> np.ndarray:
    """For each position the nearest earlier one with a smaller distance, -1 if none."""
    out, stack = np.full(len(distance), -1, np.int64), []
    for i, v in enumerate(distance.tolist()):
        while stack and distance[stack[-1]] >= v:
            stack.pop()
        out[i] = stack[-1] if stack else -1
        stack.append(i)
    return out


def header_entry(closer: np.ndarray, lo: int, hi: int) -> int:
    """The member of [lo, hi] nearest to the centroid: pointers from the right end while inside."""
    at = hi
    while closer[at] >= lo:
        at = int(closer[at])
    return at


def beam(start: np.ndarray, nbrs: np.ndarray, vecs: np.ndarray, q: np.ndarray, lo: int, hi: int, k: int, ef: int, entry: int, pool: str = "ef", passes: np.ndarray | None = None, through: bool = False, expand=None, reach=None) -> tuple[list[tuple[float, int]], int, int]:
    """((d2, position) ascending, distances, hops); neighbours outside [lo, hi] are skipped.

    pool 'ef' keeps max(ef, k) results while searching, 'k' only k. through: walk over
    outsiders without returning them. passes: a mask for further predicates. expand: the
    neighbours of a position for this query, if they are not simply those of the lists. reach: ``reached`` or what has its answers. Of a long list of positions
    to visit the far end is dropped, as it could not enter the pool; walking through outsiders keeps it all.
    """
    if lo > hi:
        return [], 0, 0
    size = max(ef, k) if pool == "ef" else k
    if size > hi - lo and expand is None and passes is None and lo <= entry <= hi and not through:
        at = (reach or reached)(start, nbrs, lo, hi, entry)
        best, dist = closest(q, vecs[lo : hi + 1] if len(at) > hi - lo else vecs[at], k)
        return list(zip(dist.tolist(), at[best].tolist(), strict=True)), len(at), len(at)
    ok = lambda p: lo <= p <= hi and (passes is None or passes[p])
    seen = {entry}
    first = float(d2(q, vecs[entry : entry + 1])[0])
    todo, found = [(first, entry)], [(-first, -entry)] if ok(entry) else []
    n_dist, hops = 1, 0
    while todo:
        d, p = heapq.heappop(todo)
        if len(found) >= size and (d, p) > (-found[0][0], -found[0][1]):
            break
        hops += 1
        ends = nbrs[start[p] : start[p + 1]] if expand is None else expand(p)
        new = [v for v in ends.tolist() if v not in seen and (through or ok(v))]
        if not new:
            continue
        seen.update(new)
        dist = d2(q, vecs[new])
        n_dist += len(new)
        for e, v in zip(dist.tolist(), new, strict=True):
            if len(found) < size or (e, v) < (-found[0][0], -found[0][1]):
                heapq.heappush(todo, (e, v))
                if ok(v):
                    heapq.heappush(found, (-e, -v))
                    if len(found) > size:
                        heapq.heappop(found)
        if pool == "ef" and not through and len(todo) > 4 * size:
            todo = heapq.nsmallest(2 * size, todo)
    return sorted((-a, -b) for a, b in found)[:k], n_dist, hops


def reached(start: np.ndarray, nbrs: np.ndarray, lo: int, hi: int, entry: int) -> np.ndarray:
    """Positions of [lo, hi], ascending, that a walk from entry inside it reaches: what a pool that is never cut expands, whole
    rounds of positions at once."""
    seen, front = np.zeros(hi - lo + 1, bool), np.array([entry])
    seen[entry - lo] = True
    while len(front):
        size = start[front + 1] - start[front]
        at = np.repeat(start[front] - np.cumsum(size) + size, size) + np.arange(size.sum())
        ends = nbrs[at]
        ends = ends[(ends >= lo) & (ends <= hi)]
        new = np.zeros(hi - lo + 1, bool)
        new[ends - lo] = True
        new &= ~seen
        seen |= new
        front = lo + np.flatnonzero(new)
    return lo + np.flatnonzero(seen)


def greedy_path(start: np.ndarray, nbrs: np.ndarray, vecs: np.ndarray, x: int, y: int) -> list[int]:
    """Walk from x to the stored target y, each step to the neighbour nearest to y; ends where none is nearer."""
    path = [x]
    here = float(d2(vecs[y], vecs[x : x + 1])[0])
    while path[-1] != y:
        near = nbrs[start[path[-1]] : start[path[-1] + 1]]
        if (near == y).any():
            path.append(y)
            break
        if not len(near):
            break
        d = d2(vecs[y], vecs[near])
        best = int(np.lexsort((near, d))[0])
        if d[best] >= here:
            break
        here = float(d[best])
        path.append(int(near[best]))
    return path


def box_graph(vecs: np.ndarray, attrs: np.ndarray, how: Params) -> tuple[np.ndarray, np.ndarray]:
    """Graph over several attributes: spatial neighbours and a window in each attribute's order, pruned by boxes."""
    n, n_attr = attrs.shape
    ranks = np.stack([np.unique(attrs[:, j], return_inverse=True)[1] for j in range(n_attr)], axis=1)
    orders = [np.lexsort((np.arange(n), attrs[:, j])) for j in range(n_attr)]
    places = [np.argsort(o) for o in orders]
    near = knn_exact(vecs, min(how.spatial, max(n - 1, 0)))
    lists = []
    for x in range(n):
        windows = [o[max(0, p[x] - how.window) : p[x] + how.window + 1] for o, p in zip(orders, places, strict=True)]
        cand = np.unique(np.concatenate([near[x], *windows]))
        lists.append(in_box(x, cand[cand != x], vecs, ranks, how.m))
    start = np.r_[0, np.cumsum([len(v) for v in lists])].astype(np.int64)
    return start, np.concatenate(lists).astype(np.int64) if n else np.zeros(0, np.int64)
