"""Builds, answers, sources, streams and plans on Spark."""

import datetime

import numpy as np
import pytest
from pyspark.sql import functions as F

from rankloom.functions import answer
from rankloom.functions.sql import register_levels_function, register_rank_function, with_points
from rankloom.operators import exact, measure, ops
from rankloom.operators.build import build
from rankloom.operators.merge import chain, tree
from rankloom.operators.relational import compact_round
from rankloom.operators.sampler import block_filter
from rankloom.plans.params import VARIANTS, plan, thin_height
from rankloom.sources import io, ordered
from rankloom.workloads import sketches as sketch_queries
from rankloom.workloads.catalog import core_queries


@pytest.mark.parametrize("variant", list(VARIANTS))
def test_points_in_catalyst_equal_the_kernel(spark, small, variant):
    rows = io.load(spark, small, "events", "value")
    sketch = build(rows.repartition(3), "value", variant=variant, eps=0.05, n=1 << 20, rows_each=2048)
    sup = measure.sup_error(answer.coreset(sketch), rows, "value").collect()[0][0]
    assert sup <= 0.05 * 10_000


@pytest.mark.parametrize("kind", ["double", "float", "int", "bigint", "decimal(12,2)", "string", "date", "timestamp", "timestamp_ntz", "boolean", "interval day to second"])
def test_types_keep_order_and_values(spark, kind):
    base = spark.range(40).withColumn("x", (F.col("id") * 7) % 40)
    make = {
        "string": F.concat(F.lit("k"), F.lpad(F.col("x").cast("string"), 3, "0")),
        "date": F.date_add(F.lit(datetime.date(2024, 1, 1)), F.col("x").cast("int")),
        "timestamp": F.timestamp_seconds(F.col("x") * 1000),
        "timestamp_ntz": F.timestamp_seconds(F.col("x") * 1000).cast("timestamp_ntz"),
        "boolean": F.col("x") > 20,
        "interval day to second": F.timestamp_seconds(F.col("x") * 1000).cast("timestamp_ntz") - F.lit(datetime.datetime(1970, 1, 1)).cast("timestamp_ntz"),
    }
    column = make.get(kind, F.col("x").cast(kind))
    rows = base.select(F.when(F.col("id") < 38, column).alias("v"))
    sketch = build(rows, "v", variant="geo", eps=0.05)
    got = [r[0] for r in answer.coreset(sketch).orderBy("value").select("value").collect()]
    want = [r[0] for r in rows.filter("v is not null").orderBy("v").collect()]
    assert got == want
    assert sketch.select("sketch.n", "sketch.nulls").collect()[0] == (38, 2)


def test_groups_with_nulls_and_many_keys(spark):
    rows = spark.range(5000).select(F.when(F.col("id") % 5 > 0, F.col("id") % 5).alias("g"), (F.col("id") % 7).cast("string").alias("h"), F.col("id").cast("double").alias("v"))
    made = build(rows.repartition(4), "v", by=["g", "h"], variant="banded", eps=0.05)
    assert made.count() == 35
    truth = {(r.g, r.h): r.n for r in rows.groupBy("g", "h").agg(F.count("*").alias("n")).collect()}
    assert {(r.g, r.h): r.n for r in made.select("g", "h", "sketch.n").collect()} == truth


def test_empty_table(spark):
    made = build(spark.createDataFrame([], "v double"), "v", variant="banded")
    assert answer.quantiles(made, [0.5]).collect() == []


def test_no_raw_rows_are_shuffled(spark, small):
    made = build(io.load(spark, small, "lineitem", "l_extendedprice"), "l_extendedprice", variant="banded")
    text = made._jdf.queryExecution().executedPlan().toString()
    scan_side = text[text.index("MapInArrow") :]
    assert "Exchange" not in scan_side
    assert "ReadSchema: struct<l_extendedprice:double>" in text


def test_block_filter_is_narrow_and_fair(spark, small):
    rows = io.load(spark, small, "lineitem", "l_extendedprice")
    thin = block_filter(rows, 6)
    assert "Exchange" not in thin._jdf.queryExecution().executedPlan().toString()
    assert abs(thin.count() - 60_000 / 64) < 10
    dense = block_filter(io.load(spark, small, "events", "event_id", "value"), 3, 7, "event_id")
    assert dense.count() == 1250 and dense.agg(F.sum("weight")).collect()[0][0] == 10_000


def test_thinning_happens_in_the_scan_stage(spark, small):
    rows = io.load(spark, small, "lineitem", "l_extendedprice")
    made = build(rows, "l_extendedprice", variant="banded", eps=0.1, thin=4)
    text = made._jdf.queryExecution().executedPlan().toString()
    below = text[text.rindex("MapInArrow") :]
    assert "Filter" in below and "Exchange" not in below
    r = made.select("sketch.n", "sketch.sampler.height").collect()[0]
    assert abs(r.n - 60_000) <= 16 * 8 and r.height >= 4
    assert measure.sup_error(answer.coreset(made), rows, "l_extendedprice").collect()[0][0] <= 0.1 * 60_000


def test_thin_height():
    assert thin_height(10**12, 0.01, 1e-6, 10**7) == 17
    assert thin_height(1000, 0.01, 1e-6, 1000) == 0


def test_relational_round_equals_kernel(spark):
    rows = spark.range(11).select(F.lit(0).cast("long").alias("block"), F.col("id").cast("double").alias("v"), F.lit(1).cast("long").alias("weight"))
    done = compact_round(rows, "block", ["v"], "weight", 1, 7, "fixed_odd").collect()
    assert sorted((r.v, r.weight) for r in done) == [(0, 2), (2, 2), (4, 2), (6, 2), (8, 2), (10, 1)]


def test_merge_shapes_agree_in_mass(spark, small):
    rows = io.load(spark, small, "lineitem", "l_suppkey", "l_extendedprice").withColumn("m", F.col("l_suppkey") % 16)
    parts = build(rows, "l_extendedprice", by=["m"], variant="geo", eps=0.05).select(F.col("m").alias("part"), "sketch")
    for merged in (tree(parts, [], fan_in=3), chain(parts, [])):
        assert measure.mass(answer.coreset(merged)).collect()[0][0] == 60_000


def test_rollup_and_rank_filters(spark, small):
    rows = io.load(spark, small, "lineitem", "l_returnflag", "l_linestatus", "l_extendedprice")
    fine = build(rows, "l_extendedprice", by=["l_returnflag", "l_linestatus"], variant="geo", eps=0.02)
    rolled = ops.rollup_sketch(fine, ["l_returnflag", "l_linestatus"])
    assert rolled.count() == 6 + 3 + 1
    total = rolled.filter("l_returnflag is null").select("sketch.n").collect()[0][0]
    assert total == 60_000
    some = ops.where_rank(rows, "l_extendedprice", 0.25, 0.75, rolled.filter("l_returnflag is null").select("sketch"))
    assert abs(some.count() - 30_000) < 0.05 * 60_000


def test_answers(spark, small):
    rows = io.load(spark, small, "events", "value")
    points = answer.coreset(build(rows, "value", variant="geo", eps=0.02))
    probes = spark.createDataFrame([(5.0,), (34.59,), (1000.0,)], "probe double")
    a = {r.probe: r.est_rank for r in answer.ranks(points, probes, "asof").collect()}
    b = {r.probe: r.est_rank for r in answer.ranks(points, probes, "theta").collect()}
    assert a == b and a[1000.0] == 10_000 and abs(a[34.59] - 5000) < 200
    assert answer.equi_depth(answer.cdf(points), 4).count() == 4
    assert sum(r.mass for r in answer.pmf(points, [10.0, 100.0]).collect()) == 10_000
    assert answer.sup_distance(points, points).collect()[0][0] == 0


def test_exact_references(spark, small):
    rows = io.load(spark, small, "events", "value")
    assert exact.ranks(rows, "value", [34.59]).collect()[0].exact_rank >= 5000
    assert exact.counts_by_value(rows, "value").agg(F.max("exact_rank")).collect()[0][0] == 10_000


@pytest.mark.parametrize("column", ["value", "event_id", "ts", "event_type"])
def test_running_sums_by_ranges(spark, small, column):
    rows = io.load(spark, small, "events", column)
    one, many = (exact.counts_by_value(rows, column, n).orderBy("value").collect() for n in (1 << 20, 100))
    assert one == many and many[-1].exact_rank == 10_000
    ranks = exact.rank_column(rows, column, rows_each=500)
    assert ranks.agg(F.max("exact_rank"), F.count("*")).collect()[0] == (10_000, 10_000)


def test_sql_functions(spark, small):
    register_rank_function(spark)
    register_levels_function(spark)
    made = with_points(build(io.load(spark, small, "events", "value"), "value", variant="geo", eps=0.02))
    made.createOrReplaceTempView("made_sketches")
    assert abs(spark.sql("SELECT sketch_rank(points, CAST(34.59 AS DOUBLE)) AS r FROM made_sketches").collect()[0].r - 5000) < 200
    levels = spark.sql("SELECT l.* FROM made_sketches, LATERAL sketch_levels(to_json(sketch)) l").collect()
    assert sum(r["items"] for r in levels) == measure.stored_items(made).collect()[0].stored


@pytest.mark.parametrize("order", ["ascending", "descending", "ends", "blocks", "random"])
def test_ordered_source(spark, order):
    ordered.register(spark)
    rows = spark.read.format("ordered_stream").option("n", 5000).option("order", order).option("parts", 3).load()
    assert rows.count() == 5000 and rows.agg(F.sum("value")).collect()[0][0] == sum(range(5000))
    made = build(rows, "value", variant="geo-wsampled", eps=0.05)
    assert measure.sup_error(answer.coreset(made), rows, "value").collect()[0][0] <= 250


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_formats_round_trip(spark, small, fmt, tmp_path):
    rows = io.load(spark, small, "region")
    rows.write.format(fmt).save(str(tmp_path / "t"))
    back = io.read(spark, str(tmp_path / "t"), fmt, "r_regionkey int, r_name string")
    assert sorted(back.collect()) == sorted(rows.collect())


def test_footer_count(spark, small):
    assert io.estimated_rows(spark, f"{small}/lineitem.parquet") == 60_000


def test_join_strategies(spark, small):
    a, b = io.load(spark, small, "orders", "o_orderkey"), io.load(spark, small, "lineitem", "l_orderkey")
    on = a["o_orderkey"] == b["l_orderkey"]
    plan_of = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan_of(a.hint("merge").join(b, on))
    assert "ShuffledHashJoin" in plan_of(a.hint("shuffle_hash").join(b, on))


def test_stream_replay_does_not_double(spark, small, tmp_path):
    from rankloom.streaming import stream

    sink = stream.pane_sink(str(tmp_path / "p"), "ts", "1 day", "value", variant="geo", eps=0.05)
    batch = io.load(spark, small, "events", "ts", "value")
    for batch_id in (0, 0, 1):
        sink(batch, batch_id)
    panes = stream.compact_panes(stream.stored_panes(spark, str(tmp_path / "p")))
    assert panes.agg(F.sum("sketch.n")).collect()[0][0] == 20_000


def test_late_rows_are_dropped_by_the_watermark(spark, tmp_path):
    from rankloom.streaming import stream

    rows = [(i, datetime.datetime(2024, 1, 1) + datetime.timedelta(hours=i), float(i)) for i in range(48)]
    schema = "event_id long, ts timestamp_ntz, value double"
    spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / "in"))
    live = stream.with_lateness(stream.file_stream(spark, str(tmp_path / "in"), spark.createDataFrame([], schema).schema), "ts", "2 hours")
    counts = live.groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    q = counts.writeStream.format("memory").queryName("late_rows").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert [r.n for r in spark.table("late_rows").collect()] == [24]


def test_continuous_state_survives_restart(spark, tmp_path):
    from rankloom.streaming import stream

    schema = "k string, value double"
    folder, mark = str(tmp_path / "in"), str(tmp_path / "c")
    for i in range(2):
        spark.range(100 * i, 100 * i + 100).select(F.lit("a").alias("k"), F.col("id").cast("double").alias("value")).coalesce(1).write.mode("append").parquet(folder)
        live = stream.continuous(stream.file_stream(spark, folder, spark.createDataFrame([], schema).schema), "k", "value", plan("geo", 0.05))
        seen = []
        live.writeStream.foreachBatch(lambda df, _, seen=seen: seen.extend(df.collect())).outputMode("update").option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
        assert seen[-1].n == 100 * (i + 1)
    assert seen[-1]["median"] == 99.0


def test_certificate_covers_error(spark, small):
    rows = io.load(spark, small, "lineitem", "l_extendedprice")
    made = build(rows.repartition(8), "l_extendedprice", chosen=plan("geo", 0.05, k=64))
    bound = made.select(answer.certificate(delta=1e-6).alias("b")).collect()[0].b
    sup = measure.sup_error(answer.coreset(made), rows, "l_extendedprice").collect()[0][0]
    assert 0 < sup <= bound
    assert np.isfinite(bound)


def test_trials_read_every_row_once(spark, tiny):
    rows = spark.range(0, 3000, 1, 2).select((F.col("id") % 2).alias("k"), F.when(F.col("id") % 10 != 0, F.col("id").cast("double")).alias("v"))
    got = build(rows, "v", by=["k"], chosen=plan("geo", 0.2, 0.3, "single"), trials=5)
    assert got.columns == ["k", "trial", "sketch"]
    made = got.select("k", "trial", "sketch.n", "sketch.nulls", F.to_json("sketch.levels").alias("levels")).collect()
    assert sorted((r.k, r.trial, r.n, r.nulls) for r in made) == [(k, t, 1500 - 300 * (k == 0), 300 * (k == 0)) for k in (0, 1) for t in range(1, 6)]
    assert len({r.levels for r in made}) > 2
    plan_text = core_queries()["failure_rate_verdict"](spark, tiny)._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plan_text


@pytest.mark.parametrize("fraction", [0.0, 0.3, 0.5, 0.999, 1.0])
@pytest.mark.parametrize("case", ["spread", "ties", "one", "even", "nulls", "empty"])
def test_bracketed_quantile_is_exact(spark, fraction, case):
    x = {"spread": F.pmod(F.xxhash64("id"), F.lit(9973)) / 7, "ties": (F.col("id") % 3).cast("double"), "nulls": F.when(F.col("id") % 5 == 0, F.col("id") / 3)}.get(case, F.col("id") / 3)
    rows = spark.range({"one": 1, "even": 2, "empty": 0}.get(case, 5000)).select(x.alias("v"))
    want = rows.agg(F.percentile("v", F.lit(fraction)).alias("p")).first().p
    for accuracy in (10_000, 100):
        got = exact.bracketed(rows, "v", fraction, accuracy).collect()
        assert len(got) == 1 and (got[0].value == want if want is None else abs(got[0].value - want) < 1e-9)


def test_project_revenue_quantile_holds_no_map_of_all_values(spark, tiny):
    plan_text = core_queries()["project_revenue_quantile"](spark, tiny)._jdf.queryExecution().optimizedPlan().toString()
    assert "percentile(" not in plan_text


def test_trials_are_the_sketches_of_repeated_rows(spark):
    rows = spark.range(0, 12_000, 1, 2).select((F.col("id") * 7919 % 12_000).cast("double").alias("v"))
    many = rows.withColumn("trial", F.explode(F.sequence(F.lit(1), F.lit(100))))
    chosen = plan("geo", 0.1, 0.3, "single")
    ask = ["trial", "sketch.coins", F.to_json("sketch").alias("sketch")]
    want = build(many, "v", by=["trial"], chosen=chosen).select(*ask).collect()
    # An Arrow batch of 10,000 repeated rows brings 100 to each trial.
    got = build(rows, "v", chosen=chosen, trials=100, piece=100).select(*ask).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, want))
    assert min(r.coins for r in got) > 100


def test_failure_rates_have_controls_of_their_own(spark, small, monkeypatch):
    made, real = [], sketch_queries.build
    monkeypatch.setattr(sketch_queries, "build", lambda *a, **k: made.append(k) or real(*a, **k))
    rows = core_queries()["failure_rate_verdict"](spark, small).collect()
    assert len(rows) == 3 and all(r.within_delta and r.unbiased and r.biased_coin_found for r in rows)
    assert all(k["trials"] == 200 for k in made)
    assert sorted((k["chosen"].delta, k["chosen"].variant) for k in made) == [(d, v) for d in (0.02, 0.1, 0.3) for v in ("geo", "geo-biased")]
    assert len({(k["chosen"].delta, k["chosen"].k) for k in made}) == 3
    monkeypatch.setattr(sketch_queries, "replace", lambda p, **_: p)
    assert not any(r.biased_coin_found for r in core_queries()["failure_rate_verdict"](spark, small).collect())
