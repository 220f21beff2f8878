"""The sequential clustering of one group of events (a type, or a type in one tile) in NumPy.

Events are inserted one after another into the nearest cluster, by its mean. A cluster that grows above K members or
the diameter bound is split at its farthest pair. Diameters follow from additive features; member
distances are taken only in a split.

Squared distances, in units of the diameter bound, are compared after rounding to ``DIGITS`` decimals, and ties go to the cluster made first (or the
member inserted first), so that events on a lattice give one result whatever the order of floating-point sums.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right, insort

import numpy as np

DIGITS, SLACK = 9, 1e-9


class Clusters:
    def __init__(self, points: np.ndarray, d: float, K: int | None = None, assign: str = "seed", recheck: str = "paper", zero_split: str = "halve", nearest: str = "scan"):
        self.p, self.d, self.K = points / d, 1.0, K
        self.assign, self.recheck, self.zero_split, self.pivoted = assign, recheck, zero_split, nearest == "pivot"
        size = 16
        self.centre = np.empty((size, points.shape[1]))
        self.order: list[tuple[float, int]] = []  # (distance to the first point, cluster), sorted; only for the pivot search
        self.pivot: list[float] = []
        self.total: list[np.ndarray] = []
        self.square: list[float] = []
        self.members: list[list[int]] = []
        self.distances = 0

    def run(self) -> list[list[int]]:
        for i in range(len(self.p)):
            self.insert(i)
        return self.members

    def insert(self, i: int) -> None:
        if not self.members:
            self._add([i])
            return
        c = self._nearest(self.p[i])
        x = self.p[i]
        self.members[c].append(i)
        self.total[c] = self.total[c] + x
        self.square[c] += float(x @ x)
        self._place(c)
        if self.K is not None and len(self.members[c]) > self.K:
            for piece in self._split(c):
                if self._wide(piece):
                    self._fit(piece)
        elif self._wide(c):
            for piece in self._split(c):
                if self.recheck == "until_fit" and self._wide(piece):
                    self._fit(piece)

    def _fit(self, c: int) -> None:
        for piece in self._split(c):
            if self.recheck == "until_fit" and self._wide(piece):
                self._fit(piece)

    def _gaps(self, c, x: np.ndarray) -> np.ndarray:
        diff = self.centre[c] - x
        self.distances += len(diff)
        return np.round(np.einsum("ij,ij->i", diff, diff), DIGITS)

    def _nearest(self, x: np.ndarray) -> int:
        if not self.pivoted:
            return int(np.argmin(self._gaps(slice(0, len(self.members)), x)))
        # a centre is farther from x than their distances to the pivot differ, so only a run of the sorted centres can hold it
        own = float(np.sqrt(((x - self.p[0]) ** 2).sum()))
        at = min(bisect_left(self.order, (own, -1)), len(self.order) - 1)
        first = [c for _, c in self.order[max(0, at - 1) : at + 1]]
        reach = float(np.sqrt(self._gaps(first, x).min() + SLACK)) + SLACK
        run = sorted(c for _, c in self.order[bisect_left(self.order, (own - reach, -1)) : bisect_right(self.order, (own + reach, len(self.members)))])
        return run[int(np.argmin(self._gaps(run, x)))]

    def _wide(self, c: int) -> bool:
        return self._diameter(c) > self.d + SLACK

    def _diameter(self, c: int) -> float:
        n = len(self.members[c])
        if n < 2:
            return 0.0
        sse = self.square[c] - float(self.total[c] @ self.total[c]) / n
        return float(np.sqrt(max(0.0, 2 * sse / (n - 1))))

    def _place(self, c: int) -> None:
        self.centre[c] = self.total[c] / len(self.members[c])
        if self.pivoted:
            far = float(np.sqrt(((self.centre[c] - self.p[0]) ** 2).sum()))
            if c < len(self.pivot):
                del self.order[bisect_left(self.order, (self.pivot[c], c))]
                self.pivot[c] = far
            else:
                self.pivot.append(far)
            insort(self.order, (far, c))

    def _set(self, c: int, own: list[int]) -> None:
        x = self.p[own]
        self.members[c], self.total[c], self.square[c] = own, x.sum(axis=0), float((x * x).sum())
        self._place(c)

    def _add(self, own: list[int]) -> int:
        c = len(self.members)
        if c == len(self.centre):
            self.centre = np.concatenate([self.centre, np.empty_like(self.centre)])
        self.members.append(own)
        self.total.append(None)
        self.square.append(0.0)
        self._set(c, own)
        return c

    def _split(self, c: int) -> list[int]:
        own = self.members[c]
        if len(own) < 2:
            return [c]
        left, right = split(self.p[own], self.assign, self.zero_split)
        self._set(c, [own[k] for k in left])
        return [c, self._add([own[k] for k in right])]


def farthest_pair(x: np.ndarray) -> tuple[int, int, float]:
    """Positions of the farthest two rows (the first such pair) and their squared distance."""
    best = (0, 1, -1.0)
    for a in range(0, len(x), 512):
        diff = x[a : a + 512, None, :] - x[None, :, :]
        d2 = np.round(np.einsum("ijk,ijk->ij", diff, diff), DIGITS)
        at = int(np.argmax(d2))
        i, j = divmod(at, len(x))
        if d2[i, j] > best[2]:
            best = (min(a + i, j), max(a + i, j), float(d2[i, j]))
    return best


def split(x: np.ndarray, assign: str = "seed", zero_split: str = "halve") -> tuple[list[int], list[int]]:
    """Two sides around the farthest pair; ties go to the earlier seed. Members that coincide are halved by order."""
    i, j, d2 = farthest_pair(x)
    if d2 <= 0 and zero_split == "halve":
        half = (len(x) + 1) // 2
        return list(range(half)), list(range(half, len(x)))
    if i == j:
        i, j = 0, 1
    left, right = [i], [j]
    if assign == "seed":
        near = np.round(((x - x[i]) ** 2).sum(axis=1) - ((x - x[j]) ** 2).sum(axis=1), DIGITS) <= 0
        for k in range(len(x)):
            if k not in (i, j):
                (left if near[k] else right).append(k)
    else:
        a, b = x[i].copy(), x[j].copy()
        for k in range(len(x)):
            if k in (i, j):
                continue
            if round(float(((x[k] - a) ** 2).sum() - ((x[k] - b) ** 2).sum()), DIGITS) <= 0:
                left.append(k)
                a += (x[k] - a) / len(left)
            else:
                right.append(k)
                b += (x[k] - b) / len(right)
    return sorted(left), sorted(right)


def cluster_points(points: np.ndarray, d: float, **options) -> list[list[int]]:
    """Member positions of each cluster of points in insertion order."""
    shifted = points - points.mean(axis=0) if len(points) else points
    return Clusters(shifted, d, **options).run()
