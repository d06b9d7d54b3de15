"""Baselines: Spark's own quantile aggregates beside the sketches of this package."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def builtin_percentile(df: DataFrame, value: str, fractions: list[float], accuracy: int = 10_000) -> DataFrame:
    """fraction, value by the deterministic built-in."""
    places = F.sequence(F.lit(0), F.lit(len(fractions) - 1))
    at = F.array(*[F.lit(f) for f in fractions])
    return df.agg(F.percentile_approx(value, at, accuracy).alias("p")).select("p", F.explode(places).alias("i")).select(at[F.col("i")].alias("fraction"), F.col("p")[F.col("i")].alias("value"))


def builtin_sketch_functions() -> tuple[Callable, Callable]:
    """Spark's randomised quantile sketch over doubles: (aggregate, rank of a value as a fraction)."""

    def by_suffix(end: str) -> Callable:
        (name,) = (x for x in dir(F) if x.endswith(end))
        return getattr(F, name)

    return by_suffix("_sketch_agg_double"), by_suffix("_sketch_get_rank_double")


def builtin_sketch_ranks(df: DataFrame, value: str, probes: list[float]) -> DataFrame:
    """probe, est_rank by the built-in sketch."""
    build, rank = builtin_sketch_functions()
    one = df.agg(build(F.col(value).cast("double")).alias("s"), F.count(value).alias("n"))
    rows = F.array(*[F.struct(F.lit(float(p)).alias("probe"), F.round(rank(F.col("s"), F.lit(float(p))) * F.col("n")).cast("long").alias("est_rank")) for p in probes])
    return one.select(F.explode(rows).alias("x")).select("x.*")


def heuristic_histogram(df: DataFrame, value: str, bins: int) -> DataFrame:
    """center, height of the built-in histogram, which guarantees nothing."""
    return df.agg(F.histogram_numeric(value, F.lit(bins)).alias("h")).select(F.explode("h").alias("b")).select(F.col("b.x").cast("double").alias("center"), F.col("b.y").cast("double").alias("height"))


