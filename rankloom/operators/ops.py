"""Operators around sketches: filters, buckets, roll-ups and pivots by rank."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rankloom.functions.answer import quantiles
from rankloom.operators.merge import tree


def value_column(df: DataFrame, expression: str | Column, dtype: str, name: str = "value") -> DataFrame:
    column = F.expr(expression) if isinstance(expression, str) else expression
    return df.select(column.cast(dtype).alias(name))


def where_above(df: DataFrame, value: str, cut: DataFrame) -> DataFrame:
    """Rows whose value lies above the single value of cut (one row, so it is broadcast)."""
    return df.crossJoin(F.broadcast(cut.select(F.col("value").alias("_cut")))).filter(F.col(value) > F.col("_cut")).drop("_cut")


def where_rank(df: DataFrame, value: str, low: float, high: float, sketches: DataFrame) -> DataFrame:
    """Rows between two quantiles of a sketch."""
    ends = quantiles(sketches, [low, high]).groupBy().pivot("fraction", [low, high]).agg(F.first("value")).toDF("_lo", "_hi")
    return df.crossJoin(F.broadcast(ends)).filter(F.col(value).between(F.col("_lo"), F.col("_hi"))).drop("_lo", "_hi")


def bucketize(df: DataFrame, value: str, splits: list, name: str = "bucket") -> DataFrame:
    """df with the number of splits below each value."""
    return df.withColumn(name, F.size(F.filter(F.array(*[F.lit(s) for s in splits]), lambda s: s < F.col(value))))


def rollup_sketch(sketches: DataFrame, keys: list[str]) -> DataFrame:
    """Sketches of the finest groups -> one for every prefix of keys, by merging upward; nothing is read again."""
    out = sketches.select(*keys, "sketch")
    types = {f.name: f.dataType for f in sketches.schema.fields}
    for size in range(len(keys) - 1, -1, -1):
        kept = keys[:size]
        parts = sketches.withColumn("part", F.xxhash64(*keys))
        level = tree(parts.select(*kept, "part", "sketch"), kept)
        out = out.unionByName(level.select(*kept, *[F.lit(None).cast(types[k]).alias(k) for k in keys[size:]], "sketch"))
    return out


def cube_sketch(sketches: DataFrame, keys: list[str]) -> DataFrame:
    """Sketches of the finest groups -> one for every subset of keys, with a column for each key that was merged away (merged_<key>)."""
    out = None
    for size in range(len(keys), -1, -1):
        for kept in combinations(keys, size):
            parts = sketches.withColumn("part", F.xxhash64(*keys)).select(*kept, "part", "sketch")
            level = (sketches.select(*keys, "sketch") if size == len(keys) else tree(parts, list(kept))).withColumns({f"merged_{k}": F.lit(k not in kept) for k in keys})
            level = level.select(*[F.col(k) if k in kept else F.lit(None).cast(sketches.schema[k].dataType).alias(k) for k in keys], *[f"merged_{k}" for k in keys], "sketch")
            out = level if out is None else out.unionByName(level)
    return out


def pivot_quantiles(rows: DataFrame, key: str, fraction_values: list, name: str = "value") -> DataFrame:
    """(key, fraction, value) -> a column for each fraction."""
    return rows.groupBy(key).pivot("fraction", fraction_values).agg(F.first(name))


def gaps(points: DataFrame) -> DataFrame:
    """points with the weight and the distance in value since the one before."""
    line = Window.partitionBy(F.lit(0)).orderBy("value", "weight", "height")
    return points.withColumn("gap", F.col("value") - F.lag("value").over(line))
