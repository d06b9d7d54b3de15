"""Answers from sketches as Catalyst expressions and DataFrames."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rankloom.operators.ordered import running_sums
from rankloom.plans.params import CONTROLS


def points(sketch: str = "sketch") -> Column:
    """ARRAY<STRUCT<value, weight, height>> of a sketch: cumulative weights estimate ranks."""
    s = lambda path: F.col(f"{sketch}.{path}")
    used = F.get(s("tops"), F.lit(0))
    has_top = F.size(s("tops")) > 0
    estimate = lambda t, i: (t[i]["low"] + F.greatest(F.coalesce(F.get(t, i + 1)["high"] - 1, used["seen"]), t[i]["low"])) / 2
    total = lambda t, i: F.when(i < 0, F.lit(0)).when(i == F.size(t) - 1, used["seen"]).otherwise(F.floor(estimate(t, i))).cast("long")
    tuples = used["tuples"]
    point = lambda value, weight, height: F.named_struct(F.lit("value"), value, F.lit("weight"), weight, F.lit("height"), height)
    before = lambda i: F.when(i > 0, total(tuples, i - 1)).otherwise(F.lit(0).cast("long"))
    scaled = F.transform(F.sequence(F.lit(0), F.size(tuples) - 1), lambda i: point(tuples[i]["value"], (total(tuples, i) - before(i)) * used["scale"], F.greatest(used["height"], F.lit(1))))
    low = F.filter(s("levels"), lambda x: ~has_top | (x["height"] < used["height"]))
    levels = F.flatten(F.transform(low, lambda x: F.transform(x["items"], lambda v: point(v, F.pow(F.lit(2.0), x["height"] - 1).cast("long"), x["height"]))))
    rest = F.when(s("sampler.weight") > 0, F.array(point(s("sampler.item"), s("sampler.weight"), s("sampler.height"))))
    none = F.slice(levels, 1, 0)
    return F.concat(F.when(has_top & (F.size(tuples) > 0), scaled).otherwise(none), levels, F.coalesce(rest, none))


def coreset(sketches: DataFrame, by: list[str] | None = None) -> DataFrame:
    """by..., sketch rows -> by..., value, weight, height."""
    return sketches.select(*(by or []), F.explode(points()).alias("p")).select(*(by or []), "p.value", "p.weight", "p.height")


def cdf(points_df: DataFrame, by: list[str] | None = None) -> DataFrame:
    """by..., value, weight -> the same with cum_weight (inclusive of ties) and rank_fraction."""
    by = by or []
    part = [F.col(b) for b in by] or [F.lit(0)]
    upto = Window.partitionBy(*part).orderBy("value").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    whole = Window.partitionBy(*part)
    cum = F.sum("weight").over(upto)
    return points_df.withColumn("cum_weight", cum).withColumn("rank_fraction", F.col("cum_weight") / F.sum("weight").over(whole))


def rank(points_array: Column, x: Column, inclusive: bool = True) -> Column:
    """Estimated number of items at or below x (or below it), from points(); no shuffle."""
    hit = F.filter(points_array, (lambda p: p["value"] <= x) if inclusive else (lambda p: p["value"] < x))
    return F.aggregate(hit, F.lit(0).cast("long"), lambda acc, p: acc + p["weight"])


def ranks(points_df: DataFrame, probes: DataFrame, method: str = "asof") -> DataFrame:
    """probes (probe) -> probe, est_rank.

    asof   probes and points are sorted together once; the last running sum at or before a probe answers it
    theta  a range join with the points, for a few probes
    """
    if method == "theta":
        hit = probes.join(points_df.select("value", "weight"), F.col("value") <= F.col("probe"), "left")
        return hit.groupBy("probe").agg(F.coalesce(F.sum("weight"), F.lit(0).cast("long")).alias("est_rank"))
    both = points_df.select(F.col("value").alias("at"), "weight", F.lit(False).alias("asks")).unionByName(probes.select(F.col("probe").alias("at"), F.lit(0).cast("long").alias("weight"), F.lit(True).alias("asks")))
    summed = running_sums(both, "at", {"est_rank": F.col("weight")})
    return summed.filter("asks").select(F.col("at").alias("probe"), "est_rank").distinct()


def value_at_rank(cdf_df: DataFrame, rank_col: Column, by: list[str] | None = None) -> DataFrame:
    """by..., value: the first point whose cumulative weight reaches a rank."""
    reached = cdf_df.filter(F.col("cum_weight") >= rank_col)
    return reached.groupBy(*(by or [])).agg(F.min("value").alias("value"))


def quantiles(sketches: DataFrame, fractions: list[float], by: list[str] | None = None) -> DataFrame:
    """by..., fraction, value: of each fraction's target rank the point that reaches it; one exchange, and no point is repeated."""
    by = by or []
    part = [F.col(b) for b in by] or [F.lit(0)]
    upto = Window.partitionBy(*part).orderBy("value").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    lines = coreset(sketches, by).withColumn("_upto", F.sum("weight").over(upto)).withColumn("_total", F.sum("weight").over(Window.partitionBy(*part)))
    target = lambda f: F.greatest(F.ceil(f * F.col("_total")), F.lit(1))
    reached = F.filter(F.array(*[F.lit(float(f)) for f in fractions]), lambda f: (target(f) <= F.col("_upto")) & (target(f) > F.col("_upto") - F.col("weight")))
    return lines.select(*by, F.explode(reached).alias("fraction"), "value")


def median(sketches: DataFrame, by: list[str] | None = None) -> DataFrame:
    return quantiles(sketches, [0.5], by)


def pmf(points_df: DataFrame, splits: list) -> DataFrame:
    """bucket, mass: weight between split points, bucket i at or below split i."""
    bucket = F.size(F.filter(F.array(*[F.lit(s) for s in splits]), lambda s: s < F.col("value")))
    return points_df.groupBy(bucket.alias("bucket")).agg(F.sum("weight").alias("mass"))


def equi_depth(cdf_df: DataFrame, buckets: int) -> DataFrame:
    """bucket, upper: the value at which each of equally heavy buckets ends."""
    lines = cdf_df.groupBy("value").agg(F.sum("weight").alias("weight"), F.max("cum_weight").alias("cum_weight"))
    lines = lines.crossJoin(F.broadcast(lines.agg(F.max("cum_weight").alias("_total"))))
    lines = lines.select(F.col("value").alias("upper"), F.expr(f"(cum_weight - weight) * {buckets} div _total + 1").alias("first"), F.expr(f"cum_weight * {buckets} div _total").alias("last"))
    return lines.filter("first <= last").select(F.explode(F.sequence(F.col("first").cast("int"), F.col("last").cast("int"))).alias("bucket"), "upper")


def sup_distance(a: DataFrame, b: DataFrame) -> DataFrame:
    """distance: largest difference of two cdfs given as points (value, weight)."""
    totals = lambda d: d.agg(F.sum("weight").cast("double").alias("t"))
    scaled = lambda d, sign: d.crossJoin(totals(d)).select("value", (F.lit(sign) * F.col("weight") / F.col("t")).alias("m"))
    both = scaled(a, 1.0).unionByName(scaled(b, -1.0)).groupBy("value").agg(F.sum("m").alias("m"))
    return running_sums(both, "value", {"d": F.col("m")}).agg(F.max(F.abs("d")).alias("distance"))


def certificate(sketch: str = "sketch", delta: float = 0.01) -> Column:
    """Error an answer exceeds with probability delta at most, from the operations that happened."""
    s = lambda path: F.col(f"{sketch}.{path}")
    random = F.when(s("variant").isin("equal-fixed", *CONTROLS), s("err_abs")).otherwise(F.sqrt(2 * s("err_sq") * F.log(F.lit(2 / delta))))
    used = F.get(s("tops"), F.lit(0))
    return F.least(s("err_abs"), random) + F.when(F.size(s("tops")) > 0, s("eps") * used["seen"] * used["scale"]).otherwise(0.0)
