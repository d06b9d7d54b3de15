"""Compactor hierarchy over numpy arrays: insert, compact, sample, merge, answer.

A Sketch holds levels of items of equal weight, at the bottom maybe a sampler of
one weighted item, on top maybe tuple summaries. Every change keeps count of what
it can have done to ranks: err_abs is the sum of possible displacements, err_sq the
sum of their squares, which bound the error of any later answer.
"""

from __future__ import annotations

import math
from typing import Any

import numpy as np

from rankloom.functions.coins import Coins, ManyCoins
from rankloom.operators.tuples import TupleSummary
from rankloom.plans.params import Plan
from rankloom.plans.schedule import capacities, level_weight, sampled_levels


def compact(items: np.ndarray, odd: bool | np.ndarray, holdback: str = "max") -> tuple[np.ndarray, np.ndarray]:
    """(survivors, held back): every second item in order; an odd one out stays at its weight.

    With an array of parities, items have a column for each of them, or one for all.
    """
    items = np.sort(items, axis=0)
    if len(items) % 2:
        keep = items[-1:] if holdback == "max" else items[:1]
        items = items[:-1] if holdback == "max" else items[1:]
    else:
        keep = items[:0]
    if isinstance(odd, np.ndarray):
        return np.where(odd, items[::2], items[1::2]), keep
    return items[0 if odd else 1 :: 2], keep


class WeightedSampler:
    """One stored item whose weight grows to 2**height and then leaves as a sample."""

    def __init__(self, height: int, random: np.random.Generator):
        self.height, self.random = height, random
        self.item: Any = None
        self.weight = 0
        self.operations = 0

    def update(self, item: Any, weight: int) -> list:
        """Items emitted (none or one) on receiving an item of at most 2**height."""
        full, together = 1 << self.height, self.weight + weight
        if weight >= full:
            return [item]
        self.operations += 1
        if together <= full:
            if self.random.random() * together < weight:
                self.item = item
            self.weight = together
            if together < full:
                return []
            self.weight = 0
            return [self.item]
        # Too heavy together: the lighter one stays, the heavier leaves with probability weight / full.
        heavy, heavy_weight = (self.item, self.weight) if self.weight >= weight else (item, weight)
        if self.weight >= weight:
            self.item, self.weight = item, weight
        return [heavy] if self.random.random() * full < heavy_weight else []

    def update_many(self, values: np.ndarray) -> np.ndarray:
        """update(value, 1) for all values in their order, in one go: a random one of every block."""
        full = 1 << self.height
        out = []
        if self.weight and len(values):
            head = values[: full - self.weight]
            values = values[len(head) :]
            together = self.weight + len(head)
            if self.random.random() * together >= self.weight:
                self.item = head[self.random.integers(len(head))]
            self.weight = together
            if together == full:
                out.append(np.array([self.item], dtype=head.dtype))
                self.weight = 0
                self.operations += 1
        blocks = len(values) // full
        if blocks:
            rows = values[: blocks * full].reshape(blocks, full)
            out.append(rows[np.arange(blocks), self.random.integers(full, size=blocks)])
            self.operations += blocks
        rest = values[blocks * full :]
        if len(rest):
            self.item, self.weight = rest[self.random.integers(len(rest))], len(rest)
        return np.concatenate(out) if out else values[:0]


class Sketch:
    """A rank summary of one stream."""

    def __init__(self, plan: Plan, seed: int = 42, scope: int = 0, start: int = 0, dtype: Any = np.float64, holdback: str = "max", lazy: bool = False):
        self.plan, self.seed, self.scope, self.dtype, self.holdback, self.lazy = plan, seed, scope, dtype, holdback, lazy
        self.coins = Coins(plan.policy, seed, scope, 1)
        self.sampler = WeightedSampler(start, Coins("fair", seed, scope, 2).random)
        self.levels: dict[int, np.ndarray] = {start + 1: np.zeros(0, dtype)}
        self.compactions: dict[int, int] = {}
        self.tops: dict[int, TupleSummary] = {}
        self.n = self.nulls = 0
        self.least = self.most = None
        self.err_sq = self.err_abs = 0.0
        self.flips = self.samples = 0
        if plan.tuples:
            self.tops = {h: TupleSummary(plan.eps / 2 if plan.kind != "none" or plan.rule != "none" else plan.eps, dtype) for h in ((0,) if plan.kind == "none" else (0, plan.band))}

    # -- shape -------------------------------------------------------------------

    @property
    def height(self) -> int:
        return max(self.levels)

    @property
    def bottom(self) -> int:
        return self.sampler.height + 1

    def capacity(self, level: int) -> int:
        p = self.plan
        return capacities(p.kind, p.k, p.c, self.height, p.band, p.anchor)[level - 1]

    def stored(self) -> int:
        if self.tops:
            return sum(t.size for t in self.tops.values()) + sum(len(x) for x in self.levels.values())
        return sum(len(x) for x in self.levels.values()) + (self.sampler.weight > 0)

    # -- input -------------------------------------------------------------------

    def insert(self, values: np.ndarray, nulls: int = 0) -> None:
        """A batch of values of weight 1, none of them null."""
        self.nulls += nulls
        if not len(values):
            return
        self.n += len(values)
        self._range(values.min(), values.max())
        if self.plan.kind == "none":
            self._top_only(values)
            return
        if 0 in self.tops:
            self.tops[0].insert(values)
        if self.sampler.height:
            before = self.sampler.operations
            values = self.sampler.update_many(values)
            self._sampled(self.sampler.operations - before)
        self._give(self.bottom, values)
        self.settle()

    def insert_picked(self, values: np.ndarray, nulls: int = 0) -> None:
        """Values that a block sampler of this sketch's sampler height picked before; n is what they stand for."""
        self.nulls += nulls << self.sampler.height
        if len(values):
            self.n += len(values) << self.sampler.height
            self._range(values.min(), values.max())
            self._sampled(len(values))
            self._give(self.bottom, values)
            self.settle()

    def insert_weighted(self, values: np.ndarray, weights: np.ndarray) -> None:
        """Values with whole weights: each goes to the levels of its weight's binary digits."""
        keep = weights > 0
        values, weights = values[keep], weights[keep]
        if not len(values):
            return
        self.n += int(weights.sum())
        self._range(values.min(), values.max())
        if self.plan.kind == "none" and not self.sampler.height:
            self.tops[0].insert_weighted(values, weights)
            return
        low = (1 << self.sampler.height) - 1
        if low:
            for v, w in zip(values, weights & low, strict=True):
                if w:
                    self.sample(v, int(w))
        for bit in range(self.sampler.height, int(weights.max()).bit_length()):
            part = values[(weights >> bit) & 1 == 1]
            if len(part):
                self._give(bit + 1, part)
        self.settle()

    def _range(self, lo: Any, hi: Any) -> None:
        self.least = lo if self.least is None else min(self.least, lo)
        self.most = hi if self.most is None else max(self.most, hi)

    def _top_only(self, values: np.ndarray) -> None:
        """Tuple summary on the (sampled) stream."""
        if self.sampler.height:
            values = self.sampler.update_many(values)
            self._sampled(len(values))
        if len(values):
            self.tops[0].insert(values)

    def _sampled(self, operations: int) -> None:
        self.samples += operations
        self.err_sq += float(operations) * 4.0**self.sampler.height
        self.err_abs += float(operations) * 2.0**self.sampler.height

    def sample(self, item: Any, weight: int) -> None:
        """An item of at most the sampler's weight."""
        out = self.sampler.update(item, weight)
        self._sampled(1)
        if out and self.plan.kind == "none":
            self.tops[0].insert(np.array(out, dtype=self.dtype))
        elif out:
            self._give(self.bottom, np.array(out, dtype=self.dtype))

    def _give(self, level: int, values: np.ndarray) -> None:
        if not len(values):
            return
        for h in range(self.height + 1, level + 1):
            self.levels[h] = np.zeros(0, self.dtype)
        held = self.levels[level]
        self.levels[level] = np.concatenate([held, values]) if len(held) else np.asarray(values, self.dtype)

    # -- compaction --------------------------------------------------------------

    def settle(self) -> None:
        """Compacts full levels, lowest first, and lets the sampler follow the height."""
        while True:
            p = self.plan
            room = capacities(p.kind, p.k, p.c, self.height, p.band, p.anchor)
            if self.lazy and sum(len(x) for x in self.levels.values()) <= sum(room[self.bottom - 1 :]):
                break
            full = [h for h in sorted(self.levels) if len(self.levels[h]) >= max(2, room[h - 1])]
            if not full:
                break
            h = full[0]
            survivors, kept = compact(self.levels[h], self.coins.odd(), self.holdback)
            self.flips += 1
            self.levels[h] = kept
            weight = float(level_weight(h))
            self.err_abs += weight
            self.err_sq += weight * weight
            self.compactions[h] = self.compactions.get(h, 0) + 1
            taller = h == self.height
            self._give(h + 1, survivors)
            if h + 1 in self.tops:
                self.tops[h + 1].insert(survivors)
            if taller:
                self._taller()

    def _taller(self) -> None:
        p = self.plan
        if p.tuples and p.band and self.height % p.band == 0 and self.height + p.band not in self.tops:
            self.tops[self.height + p.band] = TupleSummary(p.eps / 2, self.dtype)
            while len(self.tops) > 3 or (len(self.tops) == 3 and sorted(self.tops)[1] <= self.height - p.band):
                del self.tops[min(self.tops)]
        if p.variant in ("geo-sampled", "equal-fair-sampled", "sampled-tuple"):
            return
        wanted = sampled_levels(p.rule, self.height, p.k, p.c, p.band)
        if self.tops:
            wanted = min(wanted, max(0, min(self.tops) - 1))
        if wanted > self.sampler.height:
            self.raise_sampler(wanted)

    def raise_sampler(self, height: int) -> None:
        """A higher sampler takes in its old item and the levels at or below its height."""
        old_item, old_weight = self.sampler.item, self.sampler.weight
        swallowed = [(level_weight(h), self.levels.pop(h)) for h in sorted(self.levels) if h <= height]
        self.sampler.height, self.sampler.item, self.sampler.weight = height, None, 0
        self.levels.setdefault(height + 1, np.zeros(0, self.dtype))
        if old_weight:
            self.sample(old_item, old_weight)
        for weight, items in swallowed:
            for item in items:
                self.sample(item, weight)

    # -- merging -----------------------------------------------------------------

    def apart(self) -> list[Sketch]:
        """The sketches that this kernel stands for."""
        return [self]

    def count(self, s: Sketch) -> None:
        """Takes over what s has counted, not its items."""
        self.n += s.n
        self.nulls += s.nulls
        if s.least is not None:
            self._range(s.least, s.most)
        self.err_sq += s.err_sq
        self.err_abs += s.err_abs
        self.flips += s.flips
        self.samples += s.samples
        for h, m in s.compactions.items():
            self.compactions[h] = self.compactions.get(h, 0) + m

    def absorb(self, others: list[Sketch]) -> Sketch:
        """This sketch with others of the same kind merged in; levels are pooled, then settled once."""
        everyone = [self, *others]
        target = max(s.sampler.height for s in everyone)
        if target > self.sampler.height:
            self.raise_sampler(target)
        for s in others:
            self.count(s)
        for s in others:
            for h in sorted(s.levels):
                if h <= target:
                    for item in s.levels[h]:
                        self.sample(item, level_weight(h))
                else:
                    self._give(h, s.levels[h])
            if s.sampler.weight:
                self.sample(s.sampler.item, s.sampler.weight)
        p = self.plan
        wanted = sampled_levels(p.rule, self.height, p.k, p.c, p.band)
        if p.variant in ("geo-wsampled", "banded") and wanted > self.sampler.height:
            self.raise_sampler(wanted)
        self.settle()
        return self

    # -- answers -----------------------------------------------------------------

    def points(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(values, weights, levels) whose cumulative weights estimate ranks."""
        values, weights, levels = [], [], []

        def add(v: np.ndarray, w: Any, h: int) -> None:
            values.append(v)
            weights.append(np.broadcast_to(np.asarray(w, np.int64), len(v)))
            levels.append(np.full(len(v), h, np.int64))

        above = math.inf
        if self.tops:
            used = min(self.tops)
            top = self.tops[used]
            scale = 1 << (used - 1 if used else self.sampler.height if self.plan.kind == "none" else 0)
            v, cumulative = top.estimates()
            add(v, np.diff(cumulative, prepend=0) * scale, max(used, 1))
            above = used
        for h in sorted(self.levels):
            if h < above and len(self.levels[h]):
                add(self.levels[h], level_weight(h), h)
        if self.sampler.weight and above > 0 or (self.sampler.weight and self.plan.kind == "none"):
            add(np.array([self.sampler.item], dtype=self.dtype), self.sampler.weight, self.sampler.height)
        if not values:
            return np.zeros(0, self.dtype), np.zeros(0, np.int64), np.zeros(0, np.int64)
        v, w, h = np.concatenate(values), np.concatenate(weights), np.concatenate(levels)
        order = np.argsort(v, kind="stable")
        return v[order], w[order], h[order]

    def rank(self, x: Any, inclusive: bool = True) -> int:
        v, w, _ = self.points()
        return int(w[: np.searchsorted(v, x, "right" if inclusive else "left")].sum())

    def value_at_rank(self, rank: float) -> Any:
        v, w, _ = self.points()
        total = np.cumsum(w)
        return v[min(int(np.searchsorted(total, rank)), len(v) - 1)] if len(v) else None

    def certified(self, delta: float) -> float:
        """Error that an answer exceeds with probability delta at most, from what really happened."""
        below = self.sampler.height if self.plan.kind == "none" else 0
        tops = max((t.spread() / 2 * (1 << (h - 1 if h else below)) for h, t in self.tops.items() if h == min(self.tops)), default=0.0)
        random = math.sqrt(2 * self.err_sq * math.log(2 / delta)) if self.plan.policy == "fair" or self.samples else math.inf
        return min(self.err_abs, random) + tops


class Trials(Sketch):
    """Sketches of one stream, each with coins of its own; for unweighted rows and plans without sampler or tuple summary.

    Their levels are equally long, so one array holds a level of all, with a column for each sketch. The lowest has
    one column, since no coin was flipped for raw items.
    """

    def __init__(self, plan: Plan, seed: int, scopes: list[int], dtype: Any = np.float64, lazy: bool = False):
        if not self.fits(plan):
            raise ValueError(f"levels of {plan.variant} depend on more than coins")
        super().__init__(plan, seed, dtype=dtype, lazy=lazy)
        self.scopes = scopes
        self.coins = ManyCoins([Coins(plan.policy, seed, s, 1) for s in scopes])

    @staticmethod
    def fits(plan: Plan) -> bool:
        return plan.rule == "none" and not plan.tuples

    def insert(self, values: np.ndarray, nulls: int = 0) -> None:
        super().insert(values[:, None], nulls)

    def apart(self) -> list[Sketch]:
        out = []
        for i, scope in enumerate(self.scopes):
            s = Sketch(self.plan, self.seed, scope, dtype=self.dtype, lazy=self.lazy)
            s.count(self)
            s.levels = {h: x[:, min(i, x.shape[1] - 1)] if len(x) else np.zeros(0, self.dtype) for h, x in self.levels.items()}
            out.append(s)
        return out
