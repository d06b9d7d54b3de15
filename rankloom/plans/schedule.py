"""Capacities and weights of the levels of a compactor hierarchy.

Levels are numbered from 1 at the bottom; height is the number of levels.
"""

from __future__ import annotations

import math


def level_weight(level: int) -> int:
    """Weight of the items that level holds."""
    return 1 << (level - 1)


def equal(k: int, height: int) -> list[int]:
    return [k] * height


def geometric(k: int, c: float, height: int) -> list[int]:
    """Capacity k at the top, smaller by the factor c on each level below, 2 at least."""
    return [max(2, math.ceil(k * c ** (height - h)) + 1) for h in range(1, height + 1)]


def banded(k: int, c: float, height: int, band: int, anchor: str = "band") -> list[int]:
    """k on the top band levels, geometric below.

    anchor 'top' counts the decay from the very top, 'band' from the lowest level of the band.
    """
    out = []
    for h in range(1, height + 1):
        if h > height - band:
            out.append(k)
        else:
            drop = height - h if anchor == "top" else height - band - h
            out.append(max(2, math.ceil(k * c**drop) + 1))
    return out


def capacities(kind: str, k: int, c: float, height: int, band: int = 0, anchor: str = "band") -> list[int]:
    if kind == "equal":
        return equal(k, height)
    return banded(k, c, height, band, anchor) if kind == "banded" else geometric(k, c, height)


def sampled_levels(rule: str, height: int, k: int, c: float, band: int = 0) -> int:
    """How many of the lowest levels a sampler stands for.

    none     no sampler
    cap2     all levels whose capacity would be 2 or so
    log_eps  all but log2(k) levels
    two_s    all but log2(k) and twice the band
    """
    if rule == "none":
        return 0
    keep = {"cap2": math.ceil(math.log(k) / math.log(1 / c)), "log_eps": math.ceil(math.log2(k)), "two_s": 2 * band + math.ceil(math.log2(k))}[rule]
    return max(0, height - max(keep, 1))


def structure(variant: str, made: tuple, height: int, k: int, c: float, band: int) -> tuple[int, int, int, int]:
    """Levels of a construction (as made in params.VARIANTS) by their part: (sampled, shrinking, flat, of the tuple summary), from the bottom up."""
    kind, _, rule, top = made
    sampled = sampled_levels(rule, height, k, c, band)
    above = height - max(sampled, height - band) if kind == "banded" or top else 0
    flat, tupled = (0, above) if top else (above, 0)
    return sampled, height - sampled - above, flat, tupled
