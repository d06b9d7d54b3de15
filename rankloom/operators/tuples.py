"""Deterministic tuple summary: values with bounds on their ranks.

Each kept value has the least and the largest rank it can have. Neighbours are
kept close enough that any rank is known to within eps n. A batch is a summary
without slack; inserting is merging the two, then dropping what is not needed.
"""

from __future__ import annotations

from typing import Any

import numpy as np


class TupleSummary:
    def __init__(self, eps: float, dtype: Any = np.float64):
        self.eps, self.n = eps, 0
        self.values = np.zeros(0, dtype)
        self.low = np.zeros(0, np.int64)
        self.high = np.zeros(0, np.int64)

    @property
    def size(self) -> int:
        return len(self.values)

    def insert(self, values: np.ndarray) -> None:
        """A batch of values of weight 1."""
        values = np.sort(values)
        rank = np.arange(1, len(values) + 1)
        self.merge(values, rank, rank, len(values))

    def insert_weighted(self, values: np.ndarray, weights: np.ndarray) -> None:
        order = np.argsort(values, kind="stable")
        rank = np.cumsum(weights[order])
        self.merge(values[order], rank - weights[order] + 1, rank, int(rank[-1]) if len(rank) else 0)

    def absorb(self, other: TupleSummary, times: int = 1) -> None:
        """One-way merge: this summary takes in another, whose items weigh times as much as its own."""
        self.merge(other.values, (other.low - 1) * times + 1, other.high * times, other.n * times)

    def merge(self, values: np.ndarray, low: np.ndarray, high: np.ndarray, n: int) -> None:
        if not n:
            return
        if not self.n:
            self.values, self.low, self.high, self.n = values, low.astype(np.int64), high.astype(np.int64), n
            self.compress()
            return

        def widened(v, lo, hi, w, other_lo, other_hi, other_n, side):
            """Bounds of v among both: at least the known ranks of smaller ones, at most those of the next larger one."""
            at = np.searchsorted(w, v, side)
            below = np.concatenate([[0], other_lo])[at]
            above = np.concatenate([other_hi - 1, [other_n]])[at]
            return lo + below, hi + np.maximum(above, below)

        a_lo, a_hi = widened(self.values, self.low, self.high, values, low, high, n, "left")
        b_lo, b_hi = widened(values, low, high, self.values, self.low, self.high, self.n, "right")
        v = np.concatenate([self.values, values])
        order = np.argsort(v, kind="stable")
        self.values = v[order]
        self.low, self.high = np.concatenate([a_lo, b_lo])[order], np.concatenate([a_hi, b_hi])[order]
        self.n += n
        self.low = np.maximum.accumulate(self.low)
        self.high = np.minimum.accumulate(self.high[::-1])[::-1]
        self.compress()

    def compress(self) -> None:
        """Keeps, from the largest down, the farthest value that leaves the gap within 2 eps n."""
        most = int(2 * self.eps * self.n)
        if len(self.values) <= 2 or most < 2:
            return
        keep = [len(self.values) - 1]
        while keep[-1] > 0:
            i = keep[-1]
            # The smallest j whose least rank is within reach of this one's largest.
            j = int(np.searchsorted(self.low, self.high[i] - most, "left"))
            keep.append(max(0, min(j, i - 1)))
        keep = np.array(keep[::-1])
        self.values, self.low, self.high = self.values[keep], self.low[keep], self.high[keep]

    def estimates(self) -> tuple[np.ndarray, np.ndarray]:
        """(values, estimated rank from each value up to the next one)."""
        if not self.n:
            return self.values, self.low
        ahead = np.append(self.high[1:] - 1, self.n)
        ahead = np.maximum(ahead, self.low)
        cumulative = (self.low + ahead) // 2
        cumulative[-1] = self.n
        return self.values, np.maximum.accumulate(cumulative)

    def spread(self) -> float:
        """Largest width of the interval in which a rank is known to lie."""
        if not self.n:
            return 0.0
        ahead = np.append(self.high[1:] - 1, self.n)
        first = float(self.low[0] - 1)
        return float(max((ahead - self.low).max(), first, (self.high - self.low).max()))
