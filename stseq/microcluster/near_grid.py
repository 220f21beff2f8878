"""The sequential clustering of :mod:`stseq.microcluster.kernel` for groups of any size: the nearest centre from a grid.

Same rules, same clusters. Centres lie in the cells of three grids, each four times as coarse as the one before; a search goes
over the eight cells nearest to the event, then over rings of cells around it, from the finest grid on, and ends when no centre
outside can be nearer than the best (or equal to it after rounding). So the work of an event does not grow with the number of
clusters. While events come in order of time no centre lies later than the event, and later cells are left out. Sums of a
cluster are taken from its first member, so that their precision does not depend on where in the space it lies.
"""

from __future__ import annotations

import gc
from array import array
from math import floor

import numpy as np

from stseq.microcluster.kernel import SLACK, Clusters, split

LEVELS, SCALE = 3, 1e9
#: Bits of a cell number; a group whose cells do not fit is left to the scan.
BITS = 20
#: Share of a cell above which a centre may round into the next one in time.
ROUNDS = 1e-6


def _around(last: int) -> list[tuple[list[int], list[int], list[int]]]:
    """For each nearest corner of the event's cell the offsets of the 8 cells there, of the rest of ring 1 and of ring 2, up to the
    cell ``last`` in time (0: the corner is an earlier one).
    """
    out = []
    for corner in range(8):
        near = [(0, 1) if corner >> s & 1 else (-1, 0) for s in (2, 1, 0)]
        if not last:
            near[2] = (-1, 0)
        steps: tuple[list[int], list[int], list[int]] = ([], [], [])
        for i in range(-2, 3):
            for j in range(-2, 3):
                for k in range(-2, last + 1):
                    ring = 2 if max(abs(i), abs(j), abs(k)) > 1 else 0 if i in near[0] and j in near[1] and k in near[2] else 1
                    steps[ring].append((i << 2 * BITS) + (j << BITS) + k)
        out.append(steps)
    return out


_EVERY, _EARLIER = _around(2), _around(0)
_LIMIT = (1 + SLACK) ** 2


def side_of(p: np.ndarray, K: int | None) -> float:
    """Side of a fine cell, for one or two centres in each: no result depends on it."""
    gap = float((np.prod(np.maximum(np.ptp(p, axis=0), 1.0)) / len(p)) ** (1 / 3))
    return 1.3 * max(gap, 0.8 if K is None else min(0.8, gap * (0.7 * K) ** (1 / 3)), 1e-3)


class GridClusters:
    def __init__(self, points: np.ndarray, d: float, K: int | None = None, assign: str = "seed", recheck: str = "paper", zero_split: str = "halve"):
        p = np.zeros((len(points), 3))
        p[:, : points.shape[1]] = points / d
        self.np, self.K, self.assign, self.zero_split, self.until_fit = p, K, assign, zero_split, recheck == "until_fit"
        self.side = side_of(p, K) if len(p) else 1.0
        low = p.min(axis=0) if len(p) else np.zeros(3)
        margin = 4 ** LEVELS  # cells before the first one; a multiple of the coarsest side
        self.x, self.y, self.t = (array("d", (p[:, a] - low[a]).tobytes()) for a in range(3))
        self.margin = margin
        self.fits = len(p) == 0 or float(np.ptp(p, axis=0).max()) / self.side + 2 * margin < (1 << BITS) - 2
        self.cx, self.cy, self.ct = array("d"), array("d"), array("d")
        self.ox, self.oy, self.ot = array("d"), array("d"), array("d")
        self.sx, self.sy, self.st, self.sq = array("d"), array("d"), array("d"), array("d")
        self.at = array("q")
        self.members: list[list[int]] = []
        self.cells: list[dict[int, list[int]]] = [{} for _ in range(LEVELS)]
        self.latest = 0.0

    def run(self) -> list[list[int]]:
        on = gc.isenabled()
        gc.disable()  # millions of lists without cycles
        try:
            for i in range(len(self.x)):
                self._insert(i)
        finally:
            if on:
                gc.enable()
        return self.members

    def _insert(self, i: int) -> None:
        if not self.members:
            self.latest = self.t[i]
            self._add([i])
            return
        x, y, t = self.x[i], self.y[i], self.t[i]
        c = self._nearest(x, y, t)
        if t > self.latest:
            self.latest = t
        own = self.members[c]
        x, y, t = x - self.ox[c], y - self.oy[c], t - self.ot[c]
        if len(own) == 1 and self.K != 1 and x * x + y * y + t * t > _LIMIT:  # the split gives back the old one and the new one
            self._add([i])
            return
        own.append(i)
        self.sx[c] += x
        self.sy[c] += y
        self.st[c] += t
        self.sq[c] += x * x + y * y + t * t
        full = self.K is not None and len(own) > self.K
        if not full and not self._wide(c):
            self._place(c)
            return
        for piece in self._split(c):
            if (full or self.until_fit) and self._wide(piece):
                self._fit(piece)

    def _fit(self, c: int) -> None:
        for piece in self._split(c):
            if self.until_fit and self._wide(piece):
                self._fit(piece)

    def _nearest(self, x: float, y: float, t: float) -> int:
        cx, cy, ct = self.cx, self.cy, self.ct
        best, found = float("inf"), -1
        side, ordered = self.side, t >= self.latest
        for level in range(LEVELS):
            held_in = self.cells[level].get
            u, v, w = x / side, y / side, t / side
            i, j, k = int(u), int(v), int(w)  # none is negative
            pad = self.margin >> 2 * level
            base = (i + pad << 2 * BITS) + (j + pad << BITS) + k + pad
            u, v, w = u - i, v - j, w - k
            high = (4 if u >= 0.5 else 0) + (2 if v >= 0.5 else 0) + (1 if w >= 0.5 else 0)
            if ordered and w < 1 - ROUNDS:
                steps, before, after = _EARLIER[high], w, 2.0
            else:
                steps, before, after = _EVERY[high], w, 1 - w
            edge = min(u, 1 - u, v, 1 - v, before, after)
            corner = min(max(u, 1 - u), max(v, 1 - v), 1 + before if after == 2.0 else max(before, after))
            for deltas, reach in zip(steps, (corner, 1 + edge, 2 + edge)):
                for delta in deltas:
                    held = held_in(base + delta)
                    if held is None:
                        continue
                    for c in held:
                        a, b, e = cx[c] - x, cy[c] - y, ct[c] - t
                        d2 = a * a + b * b + e * e
                        if d2 < best - 2e-9:
                            best, found = d2, c
                        elif d2 <= best + 2e-9 and c != found:
                            n, o = floor(d2 * SCALE + 0.5), floor(best * SCALE + 0.5)
                            if n < o or (n == o and c < found):
                                best, found = d2, c
                reach *= side
                if best < reach * reach - 1e-6:
                    return found
            side *= 4
        gaps = (np.frombuffer(cx) - x) ** 2 + (np.frombuffer(cy) - y) ** 2 + (np.frombuffer(ct) - t) ** 2
        return int(np.argmin(np.floor(gaps * SCALE + 0.5)))

    def _wide(self, c: int) -> bool:
        n = len(self.members[c])
        if n < 2:
            return False
        sse = self.sq[c] - (self.sx[c] * self.sx[c] + self.sy[c] * self.sy[c] + self.st[c] * self.st[c]) / n
        return 2 * sse / (n - 1) > _LIMIT

    def _key(self, c: int) -> int:
        side, pad = self.side, self.margin
        return (floor(self.cx[c] / side) + pad << 2 * BITS) + (floor(self.cy[c] / side) + pad << BITS) + floor(self.ct[c] / side) + pad

    def _place(self, c: int) -> None:
        n = len(self.members[c])
        self.cx[c], self.cy[c], self.ct[c] = self.ox[c] + self.sx[c] / n, self.oy[c] + self.sy[c] / n, self.ot[c] + self.st[c] / n
        key = self._key(c)
        if key != self.at[c]:
            old, self.at[c] = self.at[c], key
            for level in range(LEVELS):
                a, b = _coarse(old, level), _coarse(key, level)
                if a == b:
                    break
                if old >= 0:
                    held = self.cells[level][a]
                    held.remove(c)
                    if not held:
                        del self.cells[level][a]
                self.cells[level].setdefault(b, []).append(c)

    def _set(self, c: int, own: list[int]) -> None:
        X, Y, T = self.x, self.y, self.t
        ox, oy, ot = X[own[0]], Y[own[0]], T[own[0]]
        sx = sy = st = sq = 0.0
        for i in own:
            a, b, e = X[i] - ox, Y[i] - oy, T[i] - ot
            sx, sy, st, sq = sx + a, sy + b, st + e, sq + a * a + b * b + e * e
        self.members[c] = own
        self.ox[c], self.oy[c], self.ot[c], self.sx[c], self.sy[c], self.st[c], self.sq[c] = ox, oy, ot, sx, sy, st, sq
        self._place(c)

    def _add(self, own: list[int]) -> int:
        c = len(self.members)
        self.members.append(own)
        if len(own) == 1:
            i = own[0]
            x, y, t = self.x[i], self.y[i], self.t[i]
            for column, value in ((self.cx, x), (self.cy, y), (self.ct, t), (self.ox, x), (self.oy, y), (self.ot, t)):
                column.append(value)
            for column in (self.sx, self.sy, self.st, self.sq):
                column.append(0.0)
            key = self._key(c)
            self.at.append(key)
            for level in range(LEVELS):
                self.cells[level].setdefault(_coarse(key, level), []).append(c)
            return c
        for column in (self.cx, self.cy, self.ct, self.ox, self.oy, self.ot, self.sx, self.sy, self.st, self.sq):
            column.append(0.0)
        self.at.append(-1)
        self._set(c, own)
        return c

    def _split(self, c: int) -> list[int]:
        own = self.members[c]
        if len(own) < 2:
            return [c]
        if len(own) > 16 or self.assign != "seed":
            left, right = split(self.np[own], self.assign, self.zero_split)
            left, right = [own[k] for k in left], [own[k] for k in right]
        else:
            left, right = self._halves(own)
        self._set(c, left)
        return [c, self._add(right)]

    def _halves(self, own: list[int]) -> tuple[list[int], list[int]]:
        """``split`` by the seeds, for few members."""
        rows = [(self.x[i], self.y[i], self.t[i]) for i in own]
        far, p, q = -1, 0, 1
        for i, (x, y, t) in enumerate(rows):
            for j in range(i + 1, len(rows)):
                a, b, e = rows[j]
                d2 = floor(((a - x) ** 2 + (b - y) ** 2 + (e - t) ** 2) * SCALE + 0.5)
                if d2 > far:
                    far, p, q = d2, i, j
        if far <= 0 and self.zero_split == "halve":
            half = (len(own) + 1) // 2
            return own[:half], own[half:]
        (x, y, t), (u, v, w) = rows[p], rows[q]
        left, right = [], []
        for k, (a, b, e) in enumerate(rows):
            lag = ((a - x) ** 2 + (b - y) ** 2 + (e - t) ** 2) - ((a - u) ** 2 + (b - v) ** 2 + (e - w) ** 2)
            (left if k == p or (k != q and lag * SCALE <= 0.5) else right).append(own[k])
        return left, right


def _coarse(key: int, level: int) -> int:
    """The cell of a grid that holds a cell of the finest one."""
    if key < 0 or not level:
        return key
    mask, shift = (1 << BITS) - 1, 2 * level
    return (key >> 2 * BITS >> shift << 2 * BITS) + ((key >> BITS & mask) >> shift << BITS) + ((key & mask) >> shift)


def clustered(points: np.ndarray, d: float, nearest: str = "grid", **options) -> list[list[int]]:
    """Member positions of each cluster of points in insertion order, by the search ``nearest``."""
    if nearest == "grid" and points.shape[1] <= 3:
        grid = GridClusters(points, d, **options)
        if grid.fits:
            return grid.run()
    return Clusters(points, d, nearest="scan" if nearest == "grid" else nearest, **options).run()
