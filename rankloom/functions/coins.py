"""Coins of compactions: parity policies for kernels, and replayable coins in SQL."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

def scope_of(*parts: object) -> int:
    """A 63-bit name for whose coins are flipped; different parts have coins of their own."""
    return int.from_bytes(hashlib.blake2b(repr(parts).encode(), digest_size=8).digest(), "big") >> 1


POLICIES = ("fixed_odd", "fixed_even", "alternate", "fair")

#: A 'biased' coin, for controls, keeps even places once in so many flips.
BIAS = 8
#: Flips that coins of several kernels draw at once.
AHEAD = 256


class Coins:
    """Parities of one kernel; equal keys give equal sequences, so a retried task repeats itself."""

    def __init__(self, policy: str, *key: int):
        self.policy, self.flips = policy, 0
        self.random = np.random.Generator(np.random.Philox(np.random.SeedSequence([abs(int(k)) & 0xFFFFFFFFFFFFFFFF for k in key])))

    def odd(self) -> bool:
        """Shall the items at odd places (first, third, ...) be kept?"""
        self.flips += 1
        if self.policy == "fair":
            return bool(self.random.integers(2))
        if self.policy == "biased":
            return bool(self.random.integers(BIAS))
        if self.policy == "alternate":
            return self.flips % 2 == 1
        return self.policy == "fixed_odd"

    def odds(self, count: int) -> np.ndarray:
        """odd() so many times, in one go."""
        if self.policy in ("fair", "biased"):
            self.flips += count
            return self.random.integers(2 if self.policy == "fair" else BIAS, size=count) > 0
        return np.array([self.odd() for _ in range(count)], bool)


class ManyCoins:
    """Coins of kernels that flip together: a parity for each, of its own sequence."""

    def __init__(self, each: list[Coins]):
        self.each, self.flips = each, 0
        self.drawn = np.zeros((0, len(each)), bool)

    def odd(self) -> np.ndarray:
        at = self.flips % AHEAD
        if not at:
            self.drawn = np.stack([c.odds(AHEAD) for c in self.each], axis=1)
        self.flips += 1
        return self.drawn[at]


def digest_coin(seed: int | Column, *parts: Column | int | str) -> Column:
    """A fair coin from the first hex digit of an md5 digest; DuckDB gives the same."""
    text = [p if isinstance(p, Column) else F.lit(str(p)) for p in (seed, *parts)]
    return F.instr(F.lit("13579bdf"), F.substring(F.md5(F.concat_ws("|", *[t.cast("string") for t in text])), 1, 1)) > 0


def policy_coin(policy: str, seed: int, level: Column | int, block: Column) -> Column:
    """Keep odd places? For compactions in the relational form."""
    if policy == "fair":
        return digest_coin(seed, level, block)
    if policy == "alternate":
        return F.pmod(block, F.lit(2)) == 0
    return F.lit(policy == "fixed_odd")
