"""SQL surface: functions over sketch rows and a table function.

sketch_rank(points, x) is a SQL function, inlined by the analyzer into plain
expressions; points is what sketch_points() puts beside each sketch.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankloom.functions.answer import points


def register_rank_function(spark: SparkSession, value_type: str = "DOUBLE", name: str = "sketch_rank") -> None:
    spark.sql(
        f"""CREATE OR REPLACE TEMPORARY FUNCTION {name}(pts ARRAY<STRUCT<value: {value_type}, weight: BIGINT, height: INT>>, x {value_type})
        RETURNS BIGINT RETURN aggregate(filter(pts, p -> p.value <= x), 0L, (acc, p) -> acc + p.weight)"""
    )


def with_points(sketches: DataFrame) -> DataFrame:
    """sketches with their points as a column for SQL."""
    return sketches.withColumn("points", points())


class SketchLevels:
    """Table function: (height, items, compactions) of the levels of one sketch given as JSON."""

    def eval(self, sketch: str) -> Iterator[tuple[int, int, int]]:
        import json

        for level in json.loads(sketch)["levels"]:
            yield level["height"], len(level.get("items", [])), level["compactions"]


def register_levels_function(spark: SparkSession) -> None:
    spark.udtf.register("sketch_levels", F.udtf(SketchLevels, returnType="height int, items int, compactions bigint"))


class SketchQuantiles:
    """Table function: (fraction, value) for the fractions asked of one sketch, given by its points as JSON."""

    def eval(self, points: str, fractions: list[float]) -> Iterator[tuple[float, float]]:
        import json

        held = sorted((p["value"], p["weight"]) for p in json.loads(points))
        total = sum(w for _, w in held)
        for fraction in fractions if held else ():
            seen = 0
            for value, weight in held:
                seen += weight
                if seen >= max(1, fraction * total):
                    break
            yield float(fraction), float(value)


def register_quantiles_function(spark: SparkSession) -> None:
    spark.udtf.register("sketch_quantiles", F.udtf(SketchQuantiles, returnType="fraction double, value double"))
