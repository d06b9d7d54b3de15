"""Exact ranks and quantiles. They sort or count all rows, by ranges: references for the sketches."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rankloom.operators.ordered import ROWS_EACH, range_column, running_sums


def rank_column(df: DataFrame, value: str, by: list[str] | None = None, rows_each: int = ROWS_EACH) -> DataFrame:
    """df with exact_rank: rows at or below each row's value."""
    if by:
        upto = Window.partitionBy(*by).orderBy(value).rangeBetween(Window.unboundedPreceding, Window.currentRow)
        return df.withColumn("exact_rank", F.count("*").over(upto))
    return running_sums(df, value, {"exact_rank": F.lit(1).cast("long")}, rows_each)


def ranks(df: DataFrame, value: str, probes: list) -> DataFrame:
    """probe, exact_rank, exact_below for a few literal probes, in one pass with partial sums."""
    v = F.col(value)
    flat = [x for i, p in enumerate(probes) for x in (F.count_if(v <= F.lit(p)).alias(f"r{i}"), F.count_if(v < F.lit(p)).alias(f"b{i}"))]
    one = df.agg(*flat)
    rows = F.array(*[F.struct(F.lit(p).alias("probe"), F.col(f"r{i}").alias("exact_rank"), F.col(f"b{i}").alias("exact_below")) for i, p in enumerate(probes)])
    return one.select(F.explode(rows).alias("x")).select("x.*")


def counts_by_value(df: DataFrame, value: str, rows_each: int = ROWS_EACH) -> DataFrame:
    """value, n, exact_rank: the exact cdf over different values."""
    counts = df.groupBy(F.col(value).alias("value")).agg(F.count("*").alias("n"))
    return running_sums(counts, "value", {"exact_rank": F.col("n")}, rows_each)


def nth(df: DataFrame, value: str, n: int) -> DataFrame:
    """The n-th smallest value, of any orderable type."""
    return counts_by_value(df, value).filter((F.col("exact_rank") >= n) & (F.col("exact_rank") - F.col("n") < n)).select("value")


def percentiles(df: DataFrame, value: str, fractions: list[float], by: list[str] | None = None) -> DataFrame:
    """by..., fraction, value (interpolated)."""
    at = F.array(*[F.lit(f) for f in fractions])
    rows = df.groupBy(*(by or [])).agg(F.percentile(value, at).alias("p"))
    places = F.sequence(F.lit(0), F.lit(len(fractions) - 1))
    return rows.select(*(by or []), "p", F.explode(places).alias("i")).select(*(by or []), at[F.col("i")].alias("fraction"), F.col("p")[F.col("i")].alias("value"))


def bracketed(df: DataFrame, value: str, fraction: float, accuracy: int = 10_000) -> DataFrame:
    """value: the interpolated quantile of a numeric column, without counting all of its different values.

    A summary gives two values around the quantile's rank, with room for twice its error; rows below them are counted,
    and only the values between them by value. Should a rank lie outside, all values are counted.
    """
    v, room = F.col(value), 2.0 / accuracy
    cuts = [max(0.0, fraction - room), min(1.0, fraction + room)]
    ends = df.agg(F.percentile_approx(value, cuts, accuracy).alias("e"), F.count(value).alias("n")).collect()[0]
    if not ends["n"]:
        return df.select(v.cast("double").alias("value")).limit(0).agg(F.max("value").alias("value"))
    place = (ends["n"] - 1) * fraction
    first, part = math.floor(place), place - math.floor(place)
    low, high = (F.lit(x).cast(df.schema[value].dataType) for x in ends["e"])
    below, upto = df.agg(F.count_if(v < low), F.count_if(v <= high)).collect()[0]
    if below <= first and first + (part > 0) < upto:
        df = df.filter((v >= low) & (v <= high))
    else:
        df, below = df.filter(v.isNotNull()), 0
    lines = counts_by_value(df, value).withColumn("upto", F.col("exact_rank") + below)
    at = lambda rank: F.min(F.when(F.col("upto") > rank, F.col("value").cast("double")))
    one = lines.agg(at(first).alias("a"), at(first + (part > 0)).alias("b"))
    return one.select(F.when(F.col("a") == F.col("b"), F.col("a")).otherwise((1 - F.lit(part)) * F.col("a") + F.lit(part) * F.col("b")).alias("value"))


def offline_grid(df: DataFrame, value: str, step: int) -> DataFrame:
    """Every step-th value in order, with its rank: the smallest summary of error step / 2."""
    lines = counts_by_value(df, value).withColumn("first", F.col("exact_rank") - F.col("n") + 1)
    ranks_here = F.sequence(F.expr(f"(first + {step - 1}) div {step} * {step}"), F.col("exact_rank"), F.lit(step).cast("long"))
    held = lines.filter(F.expr(f"exact_rank div {step} > (first - 1) div {step}"))
    return held.select("value", F.explode(ranks_here).alias("rank"))


def moving_median(df: DataFrame, value: str, order: str, rows: int, rows_each: int = ROWS_EACH) -> DataFrame:
    """df with the exact median of the last rows rows.

    Every range of the order is a partition of its own and gets the last rows of the range before, so a
    frame must be well below rows_each.
    """
    if 2 * rows > rows_each:
        raise ValueError("a frame of so many rows needs larger ranges")
    placed = df.withColumn("_range", range_column(df, order, rows_each))
    behind = F.row_number().over(Window.partitionBy("_range").orderBy(F.desc(order)))
    lent = placed.withColumn("_behind", behind).filter(F.col("_behind") < rows).drop("_behind").withColumn("_range", F.col("_range") + 1)
    both = placed.withColumn("_lent", F.lit(False)).unionByName(lent.withColumn("_lent", F.lit(True)))
    frame = Window.partitionBy("_range").orderBy(order).rowsBetween(-(rows - 1), 0)
    return both.withColumn("moving_median", F.percentile(value, F.lit(0.5)).over(frame)).filter("not _lent").drop("_lent", "_range")
