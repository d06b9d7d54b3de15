"""Cost and accuracy measures of sketches and coresets."""

from __future__ import annotations

import itertools
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankloom.functions import answer
from rankloom.operators import exact
from rankloom.operators.ordered import running_sums


def errors(points: DataFrame, data: DataFrame, value: str, probes: list) -> DataFrame:
    """probe, exact_rank, est_rank, signed_error for literal probes."""
    truth = exact.ranks(data, value, probes)
    flat = [F.coalesce(F.sum(F.when(F.col("value") <= F.lit(p), F.col("weight"))), F.lit(0).cast("long")).alias(f"e{i}") for i, p in enumerate(probes)]
    one = points.agg(*flat)
    est = one.select(F.explode(F.array(*[F.struct(F.lit(p).alias("probe"), F.col(f"e{i}").alias("est_rank")) for i, p in enumerate(probes)])).alias("x")).select("x.*")
    return truth.join(est, "probe").select("probe", "exact_rank", "est_rank", (F.col("est_rank") - F.col("exact_rank")).alias("signed_error"))


def verdicts(points: DataFrame, data: DataFrame, value: str, probes: list, eps: float, variant: str) -> DataFrame:
    """variant, probe, exact_rank, within_bound: is each estimate within eps n?"""
    n = data.agg(F.count(value).alias("n"))
    rows = errors(points, data, value, probes).crossJoin(n)
    return rows.select(F.lit(variant).alias("variant"), "probe", "exact_rank", (F.abs("signed_error") <= eps * F.col("n")).alias("within_bound"))


def sup_error(points: DataFrame, data: DataFrame, value: str) -> DataFrame:
    """sup_error over all values of the data and just below each: one running sum over both."""
    mine = data.groupBy(F.col(value).alias("value")).agg(F.count("*").alias("n")).filter("value is not null")
    both = mine.select("value", "n", F.lit(0).cast("long").alias("w")).unionByName(points.select("value", F.lit(0).cast("long").alias("n"), F.col("weight").alias("w")))
    both = both.groupBy("value").agg(F.sum("n").alias("n"), F.sum("w").alias("w"))
    gaps = running_sums(both, "value", {"gap": F.col("w") - F.col("n")})
    return gaps.select(F.abs("gap").alias("e")).agg(F.max("e").alias("sup_error"))


def inverse_errors(points: DataFrame, data: DataFrame, value: str, targets: list[int]) -> DataFrame:
    """target, value, rank_error: distance of each target rank from the ranks that the answered value has."""
    lines = answer.cdf(points)
    wanted = F.explode(F.array(*[F.lit(t).cast("long") for t in targets])).alias("target")
    got = lines.select("value", "cum_weight", wanted).filter("cum_weight >= target").groupBy("target").agg(F.min("value").alias("value"))
    truth = exact.counts_by_value(data, value).select("value", (F.col("exact_rank") - F.col("n") + 1).alias("first"), "exact_rank")
    miss = F.greatest(F.lit(0).cast("long"), F.col("first") - F.col("target"), F.col("target") - F.col("exact_rank"))
    return got.join(truth, "value").select("target", "value", miss.alias("rank_error"))


def space(sketches: DataFrame, by: list[str] | None = None) -> DataFrame:
    """by..., height, items, compactions: stored items by level."""
    levels = sketches.select(*(by or []), F.explode("sketch.levels").alias("l"))
    return levels.select(*(by or []), F.col("l.height").alias("height"), F.size("l.items").cast("long").alias("items"), F.col("l.compactions").alias("compactions"))


def stored_items(sketches: DataFrame, by: list[str] | None = None) -> DataFrame:
    """by..., stored: items held over all levels, sampler and tuples."""
    levels = F.aggregate("sketch.levels", F.lit(0), lambda a, x: a + F.size(x["items"]))
    tops = F.aggregate("sketch.tops", F.lit(0), lambda a, x: a + F.size(x["tuples"]))
    return sketches.select(*(by or []), (levels + tops + (F.col("sketch.sampler.weight") > 0).cast("int")).cast("long").alias("stored"))


def mass(points: DataFrame, by: list[str] | None = None) -> DataFrame:
    return points.groupBy(*(by or [])).agg(F.sum("weight").alias("mass"))


def failure_rate(trial: Callable[[int], float], trials: int, bound: float) -> float:
    """Share of seeded trials whose error exceeds the bound."""
    return sum(trial(t) > bound for t in range(trials)) / trials


def bias(signed: list[float]) -> tuple[float, float]:
    """(mean signed error, its distance from 0 in standard errors)."""
    x = np.asarray(signed, float)
    spread = x.std(ddof=1) / np.sqrt(len(x)) if len(x) > 1 else 0.0
    return float(x.mean()), float(abs(x.mean()) / spread) if spread else 0.0


def cap2_equivalence(height: int) -> dict[int, int]:
    """How often each of 2**height items survives all coin outcomes of a chain of two-item compactors."""
    size = 1 << height
    seen = dict.fromkeys(range(size), 0)
    for coins in itertools.product((0, 1), repeat=height):
        items = list(range(size))
        for coin in coins:
            items = items[coin::2]
        seen[items[0]] += 1
    return seen


def uniformity(counts: list[int]) -> float:
    """Chi-square of counts against equal shares."""
    x = np.asarray(counts, float)
    return float(((x - x.mean()) ** 2 / x.mean()).sum())


def runtime(df: DataFrame) -> float:
    """Seconds to compute all rows of df."""
    begin = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - begin
