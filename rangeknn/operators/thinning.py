"""Numpy kernels of the exact graphs: witness scans without a cap, many sources against all rows. No Spark here.

Products of matrices in single precision only strike out what is clear; whatever lies too near to a border is measured by
differences, so the edges are those of ``kernels.two_sided`` and ``kernels.nearest_first``.
"""

from __future__ import annotations

import numpy as np

from . import kernels

#: Columns of a table of distances that is worked through at once, so that it stays in a processor's cache; sources of one table.
COLUMNS, SOURCES = 8_192, 64


class Rows:
    """All vectors, with what the products need."""

    def __init__(self, vecs: np.ndarray) -> None:
        self.vecs = vecs
        shifted = vecs - vecs.mean(axis=0) if len(vecs) else vecs
        sq, dim = np.einsum("ij,ij->i", shifted, shifted), vecs.shape[1]
        top, whole = float(sq.max(initial=0)), float(np.einsum("ij,ij->i", vecs, vecs).max(initial=0))
        kind = np.float32 if 1e-20 < top < 1e30 else np.float64
        self.clear = 1e-280 < top and whole < 1e290  # else products are lost below or above
        #: More than a product can differ from the squared distance measured by differences.
        self.slack = 2 * (dim + 16) * (float(np.finfo(kind).eps) * top + 1e-15 * (top * whole) ** 0.5 + 1e-30 * whole) if self.clear else np.inf
        self.rough, self.sq = shifted.astype(kind), sq.astype(kind)
        self.wide = np.concatenate([self.rough, self.sq[:, None], np.ones((len(vecs), 1), kind)], axis=1)

    def table(self, at: np.ndarray, to: np.ndarray | slice = slice(None)) -> np.ndarray:
        """About the squared distances of the rows at these positions to all, or to those at ``to``."""
        return np.concatenate([-2 * self.rough[at], np.ones((len(at), 1), self.sq.dtype), self.sq[at][:, None]], axis=1) @ self.wide[to].T

    def scan(self, x: int, side: np.ndarray, own: np.ndarray, block: int = 64) -> np.ndarray:
        """The positions of ``side`` that the witness scan of x keeps, in the given order; own: their squared distances to x."""
        if len(side) < 8:
            return side[kernels.between(self.vecs[side], own, None)]
        half = ((own - self.slack).astype(self.sq.dtype) - self.sq[side]) / 2
        rows, out = np.concatenate([self.rough[side], half[:, None]], axis=1), []
        while len(side):
            # z strikes y if it is nearer to x and product + half of y is over half of z's square: clear above, to be measured just below
            strikers, goes = rows[:block].copy(), self.sq[side[:block], None] / 2
            strikers[:, -1] = 1
            goes[(own[:block] == 0) & (self.vecs[side[:block]] == self.vecs[x]).all(axis=1)] = np.inf  # a copy of x is nearer to nothing than x is
            product = strikers @ rows[:block].T
            near = np.triu((product >= goes - self.slack) & (own[:block] > own[:block, None]), 1)
            sure = near & (product > goes)
            near &= ~sure
            alive, kept = np.ones(len(strikers), bool), []
            for i in range(len(strikers)):
                if alive[i]:
                    kept.append(i)
                    alive &= ~sure[i]
                    if near[i].any():
                        self._measure(side[i], side[:block], own[:block], near[i], alive)
            out.append(side[kept])
            strikers, goes, closer = strikers[kept], goes[kept], own[kept]
            side, own, rows = side[block:], own[block:], rows[block:]
            product = strikers @ rows.T
            near = (product >= goes - self.slack) & (own > closer[:, None])
            sure = near & (product > goes)
            alive = ~sure.any(axis=0)
            near &= ~sure & alive
            for i in np.flatnonzero(near.any(axis=1)).tolist():
                self._measure(out[-1][i], side, own, near[i], alive)
            side, own, rows = side[alive], own[alive], rows[alive]
        return np.concatenate(out)

    def _measure(self, z: int, side: np.ndarray, own: np.ndarray, asked: np.ndarray, alive: np.ndarray) -> None:
        """Takes those asked out of ``alive`` that z, by differences, is nearer to than the source is."""
        at = np.flatnonzero(asked & alive)
        if len(at):
            alive[at] = kernels.steady(self.vecs[z], self.vecs[side[at]]) >= own[at]

    def _strike(self, zs: np.ndarray, near: np.ndarray, left: np.ndarray, own: np.ndarray) -> np.ndarray:
        """Which of ``left`` stay: no z that is nearer to the source is nearer to them than the source is. near, own: distances of both to the source."""
        d, closer = self.table(zs, left), near[:, None] < own
        sure = (closer & (d < (own - self.slack).astype(d.dtype))).any(axis=0)
        some, alive = closer & (d <= (own + self.slack).astype(d.dtype)) & ~sure, ~sure
        for i in np.flatnonzero(some.any(axis=1)).tolist():
            self._measure(zs[i], left, own, some[i], alive)
        return alive

    def two_sided(self, first: int, last: int, width: int = 64, pilots: int = 10) -> list[np.ndarray]:
        """Neighbours of each position from first to last as ``kernels.two_sided`` has them for all the others.

        What is kept among the next ``width`` ranks strikes out most of a side: their distances to all come from one table.
        """
        n, out = len(self.vecs), []
        if not self.clear:
            return [kernels.two_sided(x, np.delete(np.arange(n), x), self.vecs, None) for x in range(first, last + 1)]
        for a in range(first, last + 1, SOURCES):
            b = min(last + 1, a + SOURCES)
            base, top, stays, sides = max(0, a - width), min(n, b + width), np.ones((b - a, n), bool), []
            for x in range(a, b):
                low, high = max(0, x - width), min(n, x + width + 1)
                for win, far in ((np.arange(low, x)[::-1], slice(0, low)), (np.arange(x + 1, high), slice(high, n))):
                    own = kernels.steady(self.vecs[x], self.vecs[win]) if len(win) else np.zeros(0)
                    kept = self.scan(x, win, own)
                    sides.append((x, far, kept, own[np.isin(win, kept)]))
            for c in range(0, n, COLUMNS):
                t = self.table(np.arange(base, top), slice(c, c + COLUMNS))
                for x, far, kept, own in sides:
                    low, high = max(c, far.start), min(c + COLUMNS, far.stop)
                    if low < high:
                        some = slice(low - c, high - c)
                        clear, stay = t[x - base, some] - 2 * self.slack, stays[x - a, low:high]
                        for z, near in zip(kept[:pilots].tolist(), own[:pilots].tolist(), strict=True):
                            stay &= np.maximum(t[z - base, some], t.dtype.type(near)) >= clear
            halves = []
            for i, (x, far, kept, own) in enumerate(sides):
                left = np.flatnonzero(stays[x - a, far]) + far.start
                left = left if i % 2 else left[::-1]
                if len(left):
                    more = kernels.steady(self.vecs[x], self.vecs[left])
                    other = [bool(e) or bool((self.vecs[z] != self.vecs[x]).any()) for z, e in zip(kept, own, strict=True)]  # a copy of x strikes nothing
                    stay = self._strike(kept[other], own[other], left, more)
                    kept = np.concatenate([kept, self.scan(x, left[stay], more[stay])])
                halves.append(kept)
            out += [np.concatenate(halves[i : i + 2]) for i in range(0, len(halves), 2)]
        return out

    def nearest_first(self, at: np.ndarray, head: int = 512, pilots: int = 8) -> list[np.ndarray]:
        """Neighbours of each of these positions as ``kernels.nearest_first`` has them for all the others: what is kept among about
        ``head`` nearest strikes out most of the rest."""
        n, out = len(self.vecs), []
        if not self.clear:
            return [kernels.nearest_first(x, np.delete(np.arange(n), x), self.vecs, None) for x in at.tolist()]
        head = min(head, n - 1)
        for a in range(0, len(at), SOURCES // 2):
            block, begun = at[a : a + SOURCES // 2], []
            t = self.table(block)
            for x, row in zip(block.tolist(), t, strict=True):
                row[x] = np.inf
                cut = float(np.partition(row, head - 1)[head - 1])
                some = np.flatnonzero(row <= cut + 2 * self.slack)
                own = kernels.steady(self.vecs[x], self.vecs[some])
                order = np.lexsort((some, own))
                order = order[own[order] <= cut + self.slack]  # all others are farther
                some, own = some[order], own[order]
                kept = self.scan(x, some, own)
                begun.append((some, kept, own[np.isin(some, kept)]))
            strikers = [kept[own > 0][:pilots] for _, kept, own in begun]
            ends, zs = np.cumsum([0, *(len(z) for z in strikers)]), np.concatenate(strikers)
            t -= 2 * self.slack
            stays = np.ones(t.shape, bool)
            for c in range(0, n, COLUMNS):
                some = slice(c, c + COLUMNS)
                far = self.table(zs, some)
                for i, stay in enumerate(stays):
                    for other in far[ends[i] : ends[i + 1]]:
                        stay[some] &= other >= t[i, some]
            for x, stay, (some, kept, own) in zip(block.tolist(), stays, begun, strict=True):
                stay[x] = stay[some] = False
                left = np.flatnonzero(stay)
                if len(left):
                    more = kernels.steady(self.vecs[x], self.vecs[left])
                    order = np.lexsort((left, more))
                    kept = self.scan(x, np.concatenate([kept, left[order]]), np.concatenate([own, more[order]]))
                out.append(kept)
        return out

    def stuck(self, first: int, outs: list[np.ndarray], width: int = 64, pilots: int = 16) -> list[np.ndarray]:
        """For each position from first on, with its neighbours: the others that it can neither reach directly nor approach by a neighbour."""
        n, found = len(self.vecs), []
        for a in range(first, first + len(outs), SOURCES):
            asked = dict(zip(range(a, a + SOURCES), outs[a - first : a - first + SOURCES], strict=False))
            base, top, stays = max(0, a - width), min(n, a + len(asked) + width), np.ones((len(asked), n), bool)
            near = {x: out[(out >= base) & (out < top)] for x, out in asked.items()}
            near = {x: out[np.argsort(np.abs(out - x))[:pilots]].tolist() for x, out in near.items()}
            for c in range(0, n, COLUMNS):
                some = slice(c, c + COLUMNS)
                t = self.table(np.arange(base, top), some)
                for x, stay in zip(asked, stays, strict=True):
                    clear = t[x - base] - 2 * self.slack
                    for z in near[x]:
                        stay[some] &= t[z - base] >= clear
            for (x, out), stay in zip(asked.items(), stays, strict=True):
                stay[x] = stay[out] = False
                left = np.flatnonzero(stay)
                own = kernels.steady(self.vecs[x], self.vecs[left]) if len(left) else np.zeros(0)
                for c in range(0, len(out), SOURCES):
                    if len(left):
                        zs = out[c : c + SOURCES]
                        alive = self._strike(zs, np.full(len(zs), -1.0), left, own)
                        left, own = left[alive], own[alive]
                found.append(left)
        return found
