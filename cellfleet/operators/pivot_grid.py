"""A grid of pivots for kernels: nearest pivots and pivots within a distance, for blocks of points, without comparing all pairs.

Pivots are sorted by the squares of a grid with about two in each; the pivots of neighbouring squares of a grid row are then
one slice. A block of squares around a point is read, and doubled while something outside of it may still matter, so that
the expected work a point doesn't grow with the pivots. Squared distances of integers are exact longs; coordinates that would
overflow them raise an error. Points may also be doubles (the vertices of cells)."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np

#: Differences of coordinates stay below it, so that the sum of two squares fits a long.
MOST_SPREAD = 2**31 - 1
#: Pairs of points and pivots that are compared at once.
PAIRS = 1 << 21
#: So few pivots are compared one after the other, without a grid.
FEW = 32


class PivotGrid:
    def __init__(self, ids: Sequence[int], x: Sequence[int], y: Sequence[int], per_square: float = 2.0):
        self.ids, self.x, self.y = (np.asarray(v, dtype=np.int64) for v in (ids, x, y))
        n = len(self.ids)
        self.side = max(1, int(np.sqrt(n / per_square)))
        self.x0, self.y0 = (int(v.min()) if n else 0 for v in (self.x, self.y))
        span = lambda v: max(1.0, float(v.max() - v.min() + 1)) if n else 1.0
        self.w, self.h = span(self.x) / self.side, span(self.y) / self.side
        code = self._row(self.y) * self.side + self._column(self.x)
        self.order = np.lexsort((self.ids, code))
        self.start = np.searchsorted(code[self.order], np.arange(self.side * self.side + 1))
        self.sx, self.sy, self.sids = self.x[self.order], self.y[self.order], self.ids[self.order]

    def _column(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.x0) / self.w, 0, self.side - 1).astype(np.int64)

    def _row(self, y: np.ndarray) -> np.ndarray:
        return np.clip((y - self.y0) / self.h, 0, self.side - 1).astype(np.int64)

    def check(self, x: np.ndarray, y: np.ndarray) -> None:
        if len(x) and len(self.x) and np.issubdtype(x.dtype, np.integer):
            far = max(int(v.max()) - int(p.min()) for v, p in ((x, self.x), (y, self.y)))
            near = max(int(p.max()) - int(v.min()) for v, p in ((x, self.x), (y, self.y)))
            if max(far, near) > MOST_SPREAD:
                raise OverflowError("coordinates differ by 2 ** 31 or more: squared distances don't fit a long")

    def _pairs(self, c0: np.ndarray, c1: np.ndarray, r0: np.ndarray, r1: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(point, sorted pivot) index pairs of the squares in columns c0 to c1 and rows r0 to r1, some points at a time, in their order."""
        rows = r1 - r0 + 1
        at = np.repeat(np.arange(len(c0)), rows)
        row = np.arange(len(at)) - np.repeat(rows.cumsum() - rows, rows) + r0[at]
        lo, hi = self.start[row * self.side + c0[at]], self.start[row * self.side + c1[at] + 1]
        size = hi - lo
        ends = size.cumsum()
        by_point = ends[rows.cumsum() - 1] if len(rows) else ends
        s = 0
        while s < len(c0):
            done = by_point[s - 1] if s else 0
            e = max(s + 1, int(np.searchsorted(by_point, done + PAIRS, side="right")))
            a, b = int(rows[:s].sum()), int(rows[:e].sum())
            n = size[a:b]
            j = np.arange(int(n.sum())) - np.repeat(n.cumsum() - n, n) + np.repeat(lo[a:b], n)
            yield np.repeat(at[a:b], n), j
            s = e

    def nearest(self, x: np.ndarray, y: np.ndarray, but: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(pid, d2) of the nearest pivot of each point, ties to the least pid; ``but``: a pid for each point that doesn't count.
        Without any other pivot: -1 and the largest long."""
        self.check(x, y)
        most = np.iinfo(np.int64).max
        pid, d2 = np.full(len(x), -1, dtype=np.int64), np.full(len(x), most)
        if len(self.ids) <= FEW and np.issubdtype(x.dtype, np.integer):
            for j in np.argsort(self.ids, kind="stable"):
                dx, dy = x - self.x[j], y - self.y[j]
                d = dx * dx + dy * dy
                nearer = d < d2 if but is None else (d < d2) & (but != self.ids[j])
                pid[nearer], d2[nearer] = self.ids[j], d[nearer]
            return pid, d2
        todo, reach = np.arange(len(x)), 1
        while len(todo) and len(self.ids):
            px, py = x[todo], y[todo]
            c, r = self._column(px), self._row(py)
            c0, c1, r0, r1 = np.maximum(c - reach, 0), np.minimum(c + reach, self.side - 1), np.maximum(r - reach, 0), np.minimum(r + reach, self.side - 1)
            best, who = np.full(len(todo), most), np.full(len(todo), -1, dtype=np.int64)
            for i, j in self._pairs(c0, c1, r0, r1):
                ids = self.sids[j]
                d = (px[i] - self.sx[j]) ** 2 + (py[i] - self.sy[j]) ** 2
                if but is not None:
                    d = np.where(ids == but[todo[i]], most, d)
                if not len(i):
                    continue
                first = np.flatnonzero(np.concatenate([[True], i[1:] != i[:-1]]))
                least = np.minimum.reduceat(d, first)
                runs = np.diff(np.append(first, len(i)))
                best[i[first]] = least
                who[i[first]] = np.minimum.reduceat(np.where(d == np.repeat(least, runs), ids, most), first)
            # what isn't read is beyond a side of the block that isn't a side of the grid
            inf = np.inf
            beyond = np.minimum.reduce([
                np.where(c0 > 0, px - (self.x0 + c0 * self.w), inf), np.where(c1 < self.side - 1, self.x0 + (c1 + 1) * self.w - px, inf),
                np.where(r0 > 0, py - (self.y0 + r0 * self.h), inf), np.where(r1 < self.side - 1, self.y0 + (r1 + 1) * self.h - py, inf),
            ])
            sure = (best < most) & (np.sqrt(best.astype(np.float64)) * (1 + 1e-9) + 1 < beyond) | np.isinf(beyond)
            found = sure & (best < most)
            pid[todo[found]], d2[todo[found]] = who[found], best[found]
            todo, reach = todo[~sure], reach * 2
        return pid, d2

    def within(self, x: np.ndarray, y: np.ndarray, radius: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(point, place of the pivot among the given ones, d2) of all pivots within ``radius`` of a point, and maybe some more,
        some points at a time."""
        self.check(x, y)
        if not len(x) or not len(self.ids):
            return
        r = radius * (1 + 1e-9) + 1
        c0, c1, r0, r1 = self._column(x - r), self._column(x + r), self._row(y - r), self._row(y + r)
        for i, j in self._pairs(c0, c1, r0, r1):
            d2 = (x[i] - self.sx[j]) ** 2 + (y[i] - self.sy[j]) ** 2
            near = d2 <= r[i] * r[i]
            yield i[near], self.order[j[near]], d2[near]
