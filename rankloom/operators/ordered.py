"""Running sums over a total order without sorting everything in one task."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Rows that one task sorts, about, and the most ranges that a column is cut into.
ROWS_EACH, MOST_RANGES = 1 << 20, 2000
CUTTABLE = (T.NumericType, T.DateType, T.TimestampType, T.TimestampNTZType)


def range_column(df: DataFrame, order: str, rows_each: int = ROWS_EACH) -> Column:
    """Number of the range of order's values that a row falls into; equal values share one.

    Cut points are approximate quantiles, MOST_RANGES at most on the driver. A column
    without quantiles, or a small table, is one range.
    """
    ranges = min(MOST_RANGES, df.count() // rows_each)
    if ranges < 2 or not isinstance(df.schema[order].dataType, CUTTABLE):
        return F.lit(0)
    cuts = df.agg(F.percentile_approx(order, [i / ranges for i in range(1, ranges)], max(10_000, 10 * ranges))).collect()[0][0]
    kind = df.schema[order].dataType
    cuts = [F.lit(c).cast(kind) for c in sorted(set(cuts or []))]
    # Two levels of some dozen comparisons each instead of one of thousands.
    step = max(1, math.isqrt(len(cuts)))
    groups = [F.array(*cuts[i : i + step]) for i in range(0, len(cuts), step)]
    if not groups:
        return F.lit(0)
    below = lambda a: F.size(F.filter(a, lambda c: c < F.col(order)))
    group = F.greatest(below(F.array(*[c for c in cuts[::step]])) - 1, F.lit(0))
    return group * step + below(F.element_at(F.array(*groups), group + 1))


def running_sums(df: DataFrame, order: str, sums: dict[str, Column], rows_each: int = ROWS_EACH) -> DataFrame:
    """df with a column for each of sums: its total over all rows at or below the row's order value.

    Ranges are summed first; a row adds what lies before its range to a window within it.
    """
    names = list(sums)
    rows = df.withColumns({"_range": range_column(df, order, rows_each), **{f"_x_{n}": sums[n] for n in names}})
    before = Window.partitionBy(F.lit(0)).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    totals = rows.groupBy("_range").agg(*[F.sum(f"_x_{n}").alias(f"_t_{n}") for n in names])
    ahead = totals.select(F.col("_range").alias("_at"), *[F.coalesce(F.sum(f"_t_{n}").over(before), F.lit(0)).alias(f"_o_{n}") for n in names])
    inside = Window.partitionBy("_range").orderBy(order).rangeBetween(Window.unboundedPreceding, Window.currentRow)
    placed = rows.withColumns({n: F.sum(f"_x_{n}").over(inside) for n in names}).join(ahead, F.col("_range") == F.col("_at"))
    return placed.select(*df.columns, *[(F.col(n) + F.col(f"_o_{n}")).alias(n) for n in names])
