"""The fluent surface, table functions, streams, merges of very many parts, and plans of builds."""

import json

import numpy as np
import pytest
from pyspark.sql import functions as F

from rankloom.api import ranks
from rankloom.functions.answer import coreset, points
from rankloom.functions.coins import scope_of
from rankloom.functions.sql import register_quantiles_function
from rankloom.operators.build import build, merge_rounds
from rankloom.operators.kernel import Sketch
from rankloom.operators.merge import tree
from rankloom.operators.sampler import stratified_sample
from rankloom.operators.state import Codec, state_schema, to_row
from rankloom.plans.params import plan
from rankloom.streaming.stream import rate_stream


def test_fluent_questions(spark):
    rows = spark.range(3000).select((F.col("id") % 3).alias("g"), F.col("id").cast("double").alias("v"), F.lit(2).alias("w"))
    asked = ranks(rows).of("v").by("g").within(0.05, 1e-6)
    assert {r.g for r in asked.median().collect()} == {0, 1, 2}
    assert all(abs(r.value - r.fraction * 3000) <= 0.05 * 3000 + 3 for r in asked.quantiles(0.1, 0.9).collect())
    for r in ranks(rows).of("v").using("geo").within(0.05).rank_of(1500.0).collect():
        assert abs(r.est_rank - 1501) <= r.certified_error
    assert ranks(rows).of("v").weighted("w").sketch().first()["sketch"]["n"] == 6000
    with pytest.raises(ValueError):
        ranks(rows).median()


def test_quantiles_table_function(spark):
    register_quantiles_function(spark)
    sketches = build(spark.range(1000).select(F.col("id").cast("double").alias("v")), "v", variant="geo", eps=0.05)
    sketches.select(F.to_json(points()).alias("pts")).createOrReplaceTempView("as_json")
    got = spark.sql("SELECT q.* FROM as_json, LATERAL sketch_quantiles(pts, array(0.25D, 0.5D)) q").collect()
    assert [abs(r.value - 1000 * r.fraction) <= 50 for r in got] == [True, True]


def test_plan_of_another_variant_is_refused(spark):
    rows = spark.range(10).toDF("v")
    with pytest.raises(ValueError):
        build(rows, "v", variant="tuple-topped", chosen=plan("geo", 0.1))
    assert build(rows, "v", chosen=plan("geo", 0.1)).first()["sketch"]["variant"] == "geo"


def test_scopes_differ():
    scopes = {scope_of(key, part, out) for key in ((), ("a",), (None,)) for part in range(40) for out in range(300)}
    assert len(scopes) == 3 * 40 * 300 and max(scopes) < 2**63


def test_seventy_thousand_parts(spark):
    """Three rounds of bounded fan-in: mass and rank survive, and no task takes more than a few hundred sketches."""
    p = plan("geo", 0.1, 0.01, k=16)
    kind = spark.range(1).schema["id"].dataType
    row = to_row(filled(Sketch(p, 1, 0, 0, np.int64), np.arange(8)), Codec(kind))
    one = spark.createDataFrame([(row,)], "sketch " + state_schema(kind).simpleString())
    parts = spark.range(70_000).withColumnRenamed("id", "part").crossJoin(F.broadcast(one))
    merged = tree(parts, [], fan_in=64, rounds=3)
    n, mass = merged.select("sketch.n").first()[0], coreset(merged).agg(F.sum("weight")).first()[0]
    assert n == mass == 560_000
    low = coreset(merged).filter("value <= 3").agg(F.sum("weight")).first()[0]
    assert abs(low - 280_000) < 0.1 * 560_000


def filled(sketch, values):
    sketch.insert(values)
    return sketch


def test_rounds_follow_the_size(spark, tiny):
    small = spark.read.parquet(f"{tiny}/lineitem.parquet")
    assert merge_rounds(small, 256) == 1
    huge = spark.range(10**13)
    assert merge_rounds(huge, 256) == 3


def test_builds_do_not_shuffle_rows(spark, tiny):
    """Every exchange of a build lies above the kernel that has read the rows."""
    rows = spark.read.parquet(f"{tiny}/lineitem.parquet").select("l_extendedprice")
    text = build(rows, "l_extendedprice", variant="banded", eps=0.02)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" in text and text.rindex("Exchange") < text.index("MapInArrow")


def test_stratified_sample(spark):
    rows = spark.range(900).select((F.col("id") % 3).alias("g"), "id")
    got = stratified_sample(rows, ["g"], "id", 10).groupBy("g").count().collect()
    assert {(r.g, r["count"]) for r in got} == {(0, 10), (1, 10), (2, 10)}
    again = stratified_sample(rows.repartition(7), ["g"], "id", 10).select("id").collect()
    assert sorted(again) == sorted(stratified_sample(rows, ["g"], "id", 10).select("id").collect())


def test_rate_source(spark):
    stream = rate_stream(spark, 50)
    assert stream.isStreaming and stream.columns == ["timestamp", "value"]
    query = stream.writeStream.format("memory").queryName("rated").trigger(processingTime="1 second").start()
    try:
        assert query.awaitTermination(4) is False and query.exception() is None
    finally:
        query.stop()


def test_median_as_a_grouped_function(spark):
    """A user-defined aggregate over one group at a time, as a reference for small groups."""
    import pandas as pd

    @F.pandas_udf("double")
    def sketch_median(v: pd.Series) -> float:
        s = Sketch(plan("geo", 0.05, 0.01), 3, 0)
        s.insert(v.to_numpy())
        return float(s.value_at_rank((s.n + 1) // 2))

    rows = spark.range(2000).select((F.col("id") % 2).alias("g"), F.col("id").cast("double").alias("v"))
    for r in rows.groupBy("g").agg(sketch_median("v").alias("m")).collect():
        assert abs(r.m - 1000) <= 100


def test_weighted_points_into_a_tuple_summary(spark):
    rows = spark.range(1, 101).select(F.col("id").cast("double").alias("v"), F.col("id").alias("w"))
    made = build(rows, "v", variant="tuple-summary", eps=0.05, weight="w")
    assert made.first()["sketch"]["n"] == 5050
    below = coreset(made).filter("value <= 50").agg(F.sum("weight")).first()[0]
    assert abs(below - 1275) <= 0.05 * 5050 + 100
    assert json.dumps(made.first()["sketch"]["variant"]) == '"tuple-summary"'


def test_moving_median_by_ranges(spark):
    from rankloom.operators.exact import moving_median

    rows = spark.range(1000).select("id", ((F.col("id") * 7919) % 1000).cast("double").alias("v"))
    whole = {r.id: r.moving_median for r in moving_median(rows, "v", "id", 21).collect()}
    cut = {r.id: r.moving_median for r in moving_median(rows, "v", "id", 21, rows_each=100).collect()}
    assert cut == whole and len(cut) == 1000


def test_ranges_of_two_levels(spark):
    """Running sums over many small ranges equal those of one."""
    from rankloom.operators.ordered import running_sums

    rows = spark.range(3000).select(((F.col("id") * 31) % 700).cast("double").alias("v"))
    got = {r.v: r.upto for r in running_sums(rows, "v", {"upto": F.lit(1)}, rows_each=40).distinct().collect()}
    want = {r.v: r.upto for r in running_sums(rows, "v", {"upto": F.lit(1)}).distinct().collect()}
    assert got == want and len(got) == 700


def test_runtime_is_measured(spark):
    from rankloom.operators.measure import runtime

    assert runtime(spark.range(10)) > 0
