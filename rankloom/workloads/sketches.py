"""Queries over sketches: verdicts against exact ranks, measures, plans and bounds.

A verdict row gives the exact rank beside whether the estimate lies within eps n,
so a sketch that answers nothing cannot pass.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankloom.functions import answer
from rankloom.operators import baselines, exact, measure, ops
from rankloom.operators.build import build, partials, prepare
from rankloom.operators.merge import chain, fold_one_way, tree
from rankloom.plans import schedule
from rankloom.plans.params import SPACE_SHAPES, VARIANTS, deterministic_lower_bound, lower_bound, max_height, plan, planned_items, thin_height, trivial_lower_bound
from rankloom.sources.io import load
from rankloom.workloads.registry import add, query

PRICE_PROBES = [5000.0, 20000.0, 53028.63, 80000.0, 100000.0]
VALUE_PROBES = [5.0, 20.0, 34.59, 60.0, 113.28, 250.0]
TOTAL_PROBES = [50000.0, 150000.0, 251485.485, 400000.0]
DELTA = 1e-6


def literals(probes: list) -> str:
    return "(SELECT unnest([" + ", ".join(f"CAST({p} AS DOUBLE)" for p in probes) + "]) AS probe)"


def verdict_sql(variant: str, table: str, column: str, probes: list, where: str = "TRUE") -> str:
    return f"SELECT '{variant}' AS variant, probe, count(*) FILTER ({column} <= probe) AS exact_rank, TRUE AS within_bound FROM (SELECT {column} FROM {table} WHERE {where}) CROSS JOIN {literals(probes)} GROUP BY probe"


def verdict(data: DataFrame, column: str, probes: list, variant: str, eps: float = 0.02, label: str | None = None, **options) -> DataFrame:
    """Sketch a column where its rows lie, and judge the answers to probes."""
    rows = data.select(column)
    sketches = build(rows, column, variant=variant, eps=eps, delta=DELTA, **options)
    return measure.verdicts(answer.coreset(sketches), rows, column, probes, eps, label or variant)


#: Verdicts on sampling repeat every row until the stream has about LONG items, which samplers of this error serve from level 1 on.
LONG, COARSE = 4_000_000, 0.25


def sampled_sql(variant: str) -> str:
    return f"""SELECT '{variant}' AS variant, probe, times * exact_rank AS exact_rank, TRUE AS within_bound, TRUE AS within_certificate, TRUE AS above_sampler
        FROM ({verdict_sql(variant, "lineitem", "l_extendedprice", PRICE_PROBES)}) CROSS JOIN (SELECT CAST(ceil({LONG} / count(*)) AS BIGINT) AS times FROM lineitem)"""


def sampled_verdict(data: DataFrame, column: str, probes: list, variant: str) -> DataFrame:
    """verdict() over a long stream, whose sketch must have begun to sample.

    within_certificate: the error is what the sketch says can have happened, too; above_sampler: the sampler stands above level 0,
    or answers come from a tuple summary whose stream the levels below it were dropped for.
    """
    rows = data.select(F.col(column).alias("v"))
    times = -(-LONG // max(1, rows.count()))
    longer = rows.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(times)))).select("v")
    sketches = build(longer, "v", variant=variant, eps=COARSE, delta=DELTA, mode="single", n=LONG, rows_each=LONG // 4)
    est = sketches.select("sketch", answer.points().alias("pts"), F.explode(F.array(*[F.lit(p) for p in probes])).alias("probe"))
    answered = F.greatest(F.col("sketch.sampler.height"), F.coalesce(F.get("sketch.tops", F.lit(0))["height"], F.lit(0)))
    est = est.select("probe", F.col("sketch.n").alias("n"), answer.rank(F.col("pts"), F.col("probe")).alias("est"), answer.certificate(delta=DELTA).alias("certified"), (answered > 0).alias("above_sampler"))
    truth = exact.ranks(rows, "v", probes).select("probe", (F.col("exact_rank") * times).alias("exact_rank"))
    error = F.abs(F.col("est") - F.col("exact_rank"))
    return est.join(truth, "probe").select(F.lit(variant).alias("variant"), "probe", "exact_rank", (error <= COARSE * F.col("n")).alias("within_bound"), (error <= F.col("certified")).alias("within_certificate"), "above_sampler")


def price(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem", "l_extendedprice")


for _variant in VARIANTS:
    _name = _variant.replace("-", "_") + "_verdict"
    if VARIANTS[_variant][2] != "none":
        add(_name, lambda spark, sf_dir, v=_variant: sampled_verdict(price(spark, sf_dir), "l_extendedprice", PRICE_PROBES, v), sampled_sql(_variant))
        continue
    add(
        _name,
        lambda spark, sf_dir, v=_variant: verdict(price(spark, sf_dir), "l_extendedprice", PRICE_PROBES, v, n=1 << 22, rows_each=4096),
        verdict_sql(_variant, "lineitem", "l_extendedprice", PRICE_PROBES),
    )


@query(verdict_sql("weighted-sampler", "events", "value", VALUE_PROBES))
def weighted_sampler_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A small top capacity makes the sampler grow and take levels in on the way."""
    rows = load(spark, sf_dir, "events", "value")
    chosen = plan("geo-wsampled", 0.1, DELTA, k=24)
    sketches = build(rows, "value", chosen=chosen)
    return measure.verdicts(answer.coreset(sketches), rows, "value", VALUE_PROBES, 0.1, "weighted-sampler")


@query(f"SELECT *, TRUE AS compacted, TRUE AS tuples FROM ({verdict_sql('three-stage', 'events', 'value', VALUE_PROBES)})")
def three_stage_pipeline_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Block sampler, growing compactors and tuple summary as a pipeline of three operators; the errors of the stages add up."""
    from rankloom.operators.sampler import block_filter

    rows = load(spark, sf_dir, "events", "event_id", "value")
    thin = block_filter(rows, 2, 7, "event_id")
    middle = build(thin, "value", variant="geo", eps=0.02, delta=DELTA, weight="weight", mode="single")
    points = answer.coreset(middle).select("value", "weight")
    top = build(points, "value", variant="tuple-summary", eps=0.01, weight="weight")
    judged = measure.verdicts(answer.coreset(top), rows, "value", VALUE_PROBES, 0.05, "three-stage")
    stages = middle.select((F.col("sketch.coins") > 0).alias("compacted")).crossJoin(top.select((F.size(F.get("sketch.tops", F.lit(0))["tuples"]) > 0).alias("tuples")))
    return judged.crossJoin(stages)


@query(verdict_sql("weighted-stream", "(SELECT l_extendedprice FROM lineitem, range(50) t(i) WHERE i < l_quantity)", "l_extendedprice", PRICE_PROBES))
def weighted_stream_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items with whole weights: l_quantity copies of each price, without making copies."""
    rows = load(spark, sf_dir, "lineitem", "l_extendedprice", "l_quantity").withColumn("w", F.col("l_quantity").cast("long"))
    points = answer.coreset(build(rows, "l_extendedprice", variant="geo-wsampled", eps=0.02, delta=DELTA, weight="w"))
    sums = rows.agg(F.sum("w").alias("n"), *[F.coalesce(F.sum(F.when(F.col("l_extendedprice") <= p, F.col("w"))), F.lit(0)).cast("long").alias(f"r{i}") for i, p in enumerate(PRICE_PROBES)])
    est = points.agg(*[F.coalesce(F.sum(F.when(F.col("value") <= p, F.col("weight"))), F.lit(0)).cast("long").alias(f"e{i}") for i, p in enumerate(PRICE_PROBES)])
    rows_of = F.array(*[F.struct(F.lit(p).alias("probe"), F.col(f"r{i}").alias("exact_rank"), (F.abs(F.col(f"e{i}") - F.col(f"r{i}")) <= 0.02 * F.col("n")).alias("within_bound")) for i, p in enumerate(PRICE_PROBES)])
    return sums.crossJoin(est).select(F.explode(rows_of).alias("x")).select(F.lit("weighted-stream").alias("variant"), "x.*")


@query(verdict_sql("thinned", "lineitem", "l_extendedprice", PRICE_PROBES))
def thinned_build_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The build for very long streams: a filter in the scan keeps a block sample, only that reaches the kernels."""
    rows = price(spark, sf_dir)
    height = thin_height(rows.count(), 0.1, 0.01, 4096)
    points = answer.coreset(build(rows, "l_extendedprice", variant="banded", eps=0.1, delta=0.01, thin=height))
    return measure.verdicts(points, rows, "l_extendedprice", PRICE_PROBES, 0.1, "thinned")


# -- merging ---------------------------------------------------------------------


def machine_sketches(spark: SparkSession, sf_dir: str, variant: str, eps: float = 0.02) -> DataFrame:
    """part, sketch: one sketch for each of sixteen machines."""
    rows = load(spark, sf_dir, "lineitem", "l_suppkey", "l_extendedprice").withColumn("machine", F.col("l_suppkey") % 16)
    made = build(rows, "l_extendedprice", by=["machine"], variant=variant, eps=eps, delta=DELTA, n=1 << 22)
    return made.select(F.col("machine").alias("part"), "sketch")


@query(verdict_sql("merged", "lineitem", "l_extendedprice", PRICE_PROBES))
def merge_tree_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    merged = tree(machine_sketches(spark, sf_dir, "geo-wsampled"), [], fan_in=4)
    return measure.verdicts(answer.coreset(merged), price(spark, sf_dir), "l_extendedprice", PRICE_PROBES, 0.02, "merged")


@query("SELECT count(*) AS n, count(*) AS mass, count(DISTINCT l_suppkey % 16) AS parts FROM lineitem")
def merge_conserves_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = machine_sketches(spark, sf_dir, "geo")
    merged = tree(parts, [])
    return merged.select(F.col("sketch.n").alias("n")).crossJoin(measure.mass(answer.coreset(merged))).crossJoin(parts.agg(F.count("*").alias("parts")))


@query(" UNION ALL ".join(verdict_sql(t, "lineitem", "l_extendedprice", PRICE_PROBES) for t in ("balanced", "chain", "star", "random")))
def merge_penalty_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The guarantee after merging in trees of different shape."""
    parts = machine_sketches(spark, sf_dir, "banded")
    # At random: machines meet in uneven buckets, and these in uneven buckets again.
    drawn = parts.withColumn("part", F.pmod(F.xxhash64("part", F.lit(9)), F.lit(1000)) * 1000 + F.col("part"))
    shapes = {"balanced": tree(parts, [], fan_in=4), "chain": chain(parts, []), "star": tree(parts, [], fan_in=1), "random": tree(drawn, [], fan_in=3, rounds=4)}
    out = None
    for name, merged in shapes.items():
        part = measure.verdicts(answer.coreset(merged), price(spark, sf_dir), "l_extendedprice", PRICE_PROBES, 0.02, name)
        out = part if out is None else out.unionByName(part)
    return out


@query(verdict_sql("unequal", "(SELECT l_extendedprice AS v FROM lineitem UNION ALL SELECT o_totalprice FROM orders)", "v", PRICE_PROBES + TOTAL_PROBES))
def unequal_merge_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Merging sketches of a long and of a short stream, whose samplers stand at different heights."""
    a, b = price(spark, sf_dir).toDF("v"), load(spark, sf_dir, "orders", "o_totalprice").toDF("v")
    chosen = plan("geo-wsampled", 0.1, DELTA, k=32)
    parts = [build(x, "v", chosen=chosen).withColumn("part", F.lit(i).cast("long")) for i, x in enumerate((a, b))]
    merged = tree(parts[0].unionByName(parts[1]), [])
    return measure.verdicts(answer.coreset(merged), a.unionByName(b), "v", PRICE_PROBES + TOTAL_PROBES, 0.1, "unequal")


@query(verdict_sql("one-way", "lineitem", "l_extendedprice", PRICE_PROBES))
def one_way_merge_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts folded into one tuple summary: error of eps N1 + 2 eps N2 at most."""
    merged = fold_one_way(machine_sketches(spark, sf_dir, "tuple-summary", 0.01), [])
    return measure.verdicts(answer.coreset(merged), price(spark, sf_dir), "l_extendedprice", PRICE_PROBES, 0.02, "one-way")


@query(
    f"""SELECT event_type, probe, count(*) FILTER (value <= probe) AS exact_rank, TRUE AS within_bound FROM events CROSS JOIN {literals(VALUE_PROBES)} GROUP BY event_type, probe
    UNION ALL SELECT NULL, probe, count(*) FILTER (value <= probe), TRUE FROM events CROSS JOIN {literals(VALUE_PROBES)} GROUP BY probe"""
)
def rollup_merged_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals over groups from the groups' sketches, without reading rows again."""
    rows = load(spark, sf_dir, "events", "event_type", "value")
    sketches = ops.rollup_sketch(build(rows, "value", by=["event_type"], variant="banded", eps=0.02, delta=DELTA), ["event_type"])
    est = sketches.select("event_type", F.col("sketch.n").alias("n"), F.explode(F.array(*[F.lit(p) for p in VALUE_PROBES])).alias("probe"), answer.points().alias("pts"))
    est = est.select("event_type", "n", "probe", answer.rank(F.col("pts"), F.col("probe")).alias("est"))
    truth = rows.withColumn("probe", F.explode(F.array(*[F.lit(p) for p in VALUE_PROBES])))
    truth = truth.rollup("probe", "event_type").agg(F.count_if(F.col("value") <= F.col("probe")).alias("exact_rank")).filter("probe is not null")
    both = est.alias("e").join(truth.alias("t"), F.expr("e.probe = t.probe and e.event_type <=> t.event_type"))
    return both.select("e.event_type", "e.probe", "exact_rank", (F.abs(F.col("est") - F.col("exact_rank")) <= 0.02 * F.col("n")).alias("within_bound"))


@query(
    f"""SELECT l_returnflag, l_linestatus, probe, count(*) FILTER (l_extendedprice <= probe) AS exact_rank, TRUE AS within_bound
    FROM lineitem CROSS JOIN {literals(PRICE_PROBES)} GROUP BY GROUPING SETS ((l_returnflag, l_linestatus, probe), (l_returnflag, probe), (l_linestatus, probe), (probe))"""
)
def cube_merged_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All grouping sets from the finest groups' sketches; the rows are read once."""
    keys = ["l_returnflag", "l_linestatus"]
    rows = load(spark, sf_dir, "lineitem", *keys, "l_extendedprice")
    cubed = ops.cube_sketch(build(rows, "l_extendedprice", by=keys, variant="banded", eps=0.02, delta=DELTA), keys)
    est = cubed.select(*keys, F.col("sketch.n").alias("n"), answer.points().alias("pts"), F.explode(F.array(*[F.lit(p) for p in PRICE_PROBES])).alias("probe"))
    est = est.select(*keys, "n", "probe", answer.rank(F.col("pts"), F.col("probe")).alias("est"))
    truth = rows.cube(*keys).agg(*[F.count_if(F.col("l_extendedprice") <= p).alias(f"r{i}") for i, p in enumerate(PRICE_PROBES)])
    truth = truth.select(*keys, F.explode(F.array(*[F.struct(F.lit(p).alias("probe"), F.col(f"r{i}").alias("exact_rank")) for i, p in enumerate(PRICE_PROBES)])).alias("x")).select(*keys, "x.*")
    both = est.alias("e").join(truth.alias("t"), F.expr("e.probe = t.probe and e.l_returnflag <=> t.l_returnflag and e.l_linestatus <=> t.l_linestatus"))
    return both.select("e.l_returnflag", "e.l_linestatus", "e.probe", "exact_rank", (F.abs(F.col("est") - F.col("exact_rank")) <= 0.02 * F.col("n")).alias("within_bound"))


# -- single and all quantiles ------------------------------------------------------


def quantile_verdict(data: DataFrame, column: str, fractions: list[float], eps: float, mode: str, source: str) -> DataFrame:
    """source, fraction, target, exact_value, within_bound: answered values whose true ranks lie within eps n of the target."""
    rows = data.select(F.col(column).alias("v"))
    got = answer.quantiles(build(rows, "v", variant="banded" if mode == "all" else "geo-wsampled", eps=eps, delta=DELTA, mode=mode), fractions)
    counts = exact.counts_by_value(rows, "v")
    n = rows.agg(F.count("v").alias("rows"))
    wanted = n.select("rows", F.explode(F.array(*[F.lit(f) for f in fractions])).alias("fraction")).withColumn("target", F.greatest(F.ceil(F.col("fraction") * F.col("rows")), F.lit(1)).cast("long"))
    truth = wanted.join(counts, (F.col("exact_rank") >= F.col("target")) & (F.col("exact_rank") - F.col("n") < F.col("target"))).select("fraction", "target", "rows", F.col("value").alias("exact_value"))
    ranked = got.join(counts.select("value", "n", "exact_rank"), "value")
    miss = F.greatest(F.col("exact_rank") - F.col("n") + 1 - F.col("target"), F.col("target") - F.col("exact_rank"))
    return truth.join(ranked.drop("rows"), "fraction").select(F.lit(source).alias("source"), "fraction", "target", "exact_value", (miss <= eps * F.col("rows")).alias("within_bound"))


def quantile_sql(source: str, table: str, column: str, fractions: list[float]) -> str:
    values = ", ".join(f"CAST({f} AS DOUBLE)" for f in fractions)
    return f"""SELECT '{source}' AS source, fraction, target, v AS exact_value, TRUE AS within_bound FROM
        (SELECT {column} AS v, row_number() OVER (ORDER BY {column}) AS rn, count(*) OVER () AS n FROM {table}) JOIN
        (SELECT unnest([{values}]) AS fraction) ON TRUE JOIN LATERAL (SELECT CAST(greatest(ceil(fraction * n), 1) AS BIGINT) AS target) ON rn = target"""


COLUMNS = (("lineitem", "l_extendedprice"), ("orders", "o_totalprice"), ("events", "value"))


def _several(fractions: list[float], eps: float, mode: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = None
        for table, column in COLUMNS:
            part = quantile_verdict(load(spark, sf_dir, table, column), column, fractions, eps, mode, f"{table}.{column}")
            out = part if out is None else out.unionByName(part)
        return out

    return run


for _name, _fractions, _mode in (("median_price", [0.5], "single"), ("known_target_p90", [0.9], "single")):
    add(_name, _several(_fractions, 0.01, _mode), " UNION ALL ".join(quantile_sql(f"{t}.{c}", t, c, _fractions) for t, c in COLUMNS))
PERCENT = [round(i / 100, 2) for i in range(1, 100)]
add("all_percentiles_verdict", lambda s, d: quantile_verdict(price(s, d), "l_extendedprice", PERCENT, 0.01, "all", "lineitem.l_extendedprice"), quantile_sql("lineitem.l_extendedprice", "lineitem", "l_extendedprice", PERCENT))
add("tail_quantiles_verdict", lambda s, d: quantile_verdict(load(s, d, "documents", "n_chars"), "n_chars", [0.9, 0.99, 0.999], 0.005, "all", "documents.n_chars"), quantile_sql("documents.n_chars", "documents", "n_chars", [0.9, 0.99, 0.999]))


@query("SELECT 'lineitem.l_extendedprice' AS source, count(*) AS n, TRUE AS within_bound FROM lineitem UNION ALL SELECT 'orders.o_totalprice', count(*), TRUE FROM orders UNION ALL SELECT 'events.value', count(*), TRUE FROM events")
def sup_error_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ranks at once: the largest error over all values."""
    out = None
    for table, column in COLUMNS:
        rows = load(spark, sf_dir, table, column)
        sketches = build(rows, column, variant="banded", eps=0.02, delta=DELTA)
        part = measure.sup_error(answer.coreset(sketches), rows, column).crossJoin(rows.agg(F.count("*").alias("n")))
        part = part.select(F.lit(f"{table}.{column}").alias("source"), "n", (F.col("sup_error") <= 0.02 * F.col("n")).alias("within_bound"))
        out = part if out is None else out.unionByName(part)
    return out


ORDERS = {"ascending": "l_extendedprice", "descending": "-l_extendedprice", "zoom": "-abs(l_extendedprice - 53000)", "blocks": "floor(l_extendedprice / 1000) % 7, l_extendedprice", "interleaved": "hash(l_extendedprice) % 1000, l_extendedprice % 2 < 1, l_extendedprice"}


@query(" UNION ALL ".join(verdict_sql(o, "lineitem", "l_extendedprice", PRICE_PROBES) for o in ORDERS))
def adversarial_orders_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name, order in ORDERS.items():
        rows = price(spark, sf_dir).sortWithinPartitions(*[F.expr(x) for x in order.split(", ")])
        sketches = build(rows, "l_extendedprice", variant="geo-wsampled", eps=0.02, delta=DELTA)
        part = measure.verdicts(answer.coreset(sketches), price(spark, sf_dir), "l_extendedprice", PRICE_PROBES, 0.02, name)
        out = part if out is None else out.unionByName(part)
    return out


@query(verdict_sql("random", "lineitem", "l_extendedprice", PRICE_PROBES))
def random_order_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = price(spark, sf_dir).sortWithinPartitions(F.md5(F.col("l_extendedprice").cast("string")))
    return measure.verdicts(answer.coreset(build(rows, "l_extendedprice", variant="geo-wsampled", eps=0.02, delta=DELTA)), price(spark, sf_dir), "l_extendedprice", PRICE_PROBES, 0.02, "random")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, quantile_disc(l_extendedprice, 0.5) AS exact_median, TRUE AS within_bound FROM lineitem GROUP BY ALL")
def grouped_median_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    by = ["l_returnflag", "l_linestatus"]
    rows = load(spark, sf_dir, "lineitem", *by, "l_extendedprice")
    got = answer.median(build(rows, "l_extendedprice", by=by, variant="banded", eps=0.02, delta=DELTA), by).withColumnRenamed("value", "got")
    truth = rows.join(got, by).groupBy(*by).agg(F.count("*").alias("n"), F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY l_extendedprice)").alias("exact_median"), F.count_if(F.col("l_extendedprice") <= F.col("got")).alias("rank"))
    return truth.select(*by, "n", "exact_median", (F.abs(F.col("rank") - F.col("n") / 2) <= 0.02 * F.col("n") + 1).alias("within_bound"))


MATRIX = [(v, e) for v in VARIANTS for e in (0.1, 0.05, 0.02)]


@query(" UNION ALL ".join(f"SELECT '{v}' AS variant, CAST({e} AS DOUBLE) AS eps, probe, exact_rank, within_bound FROM ({verdict_sql(v, 'events', 'value', VALUE_PROBES)})" for v, e in MATRIX))
def variant_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every variant at several errors on one skewed stream."""
    rows = load(spark, sf_dir, "events", "value")
    points = None
    for v, e in MATRIX:
        part = answer.coreset(build(rows, "value", variant=v, eps=e, delta=DELTA, n=1 << 20, rows_each=8192)).select(F.lit(v).alias("variant"), F.lit(e).alias("eps"), "value", "weight")
        points = part if points is None else points.unionByName(part)
    est = points.groupBy("variant", "eps").agg(*[F.coalesce(F.sum(F.when(F.col("value") <= p, F.col("weight"))), F.lit(0).cast("long")).alias(f"e{i}") for i, p in enumerate(VALUE_PROBES)])
    est = est.select("variant", "eps", F.explode(F.array(*[F.struct(F.lit(p).alias("probe"), F.col(f"e{i}").alias("est")) for i, p in enumerate(VALUE_PROBES)])).alias("x")).select("variant", "eps", "x.*")
    truth = exact.ranks(rows, "value", VALUE_PROBES).crossJoin(rows.agg(F.count("*").alias("n")))
    return est.join(truth, "probe").select("variant", "eps", "probe", "exact_rank", (F.abs(F.col("est") - F.col("exact_rank")) <= F.col("eps") * F.col("n")).alias("within_bound"))


#: Seeded trials of one stream, for each failure probability; rows that a trial takes at once.
TRIALS, RISKS = 200, (0.3, 0.1, 0.02)
PIECE = 50


@query(f"SELECT delta, CAST({TRIALS} AS BIGINT) AS trials, count(*) AS n, count(*) FILTER (value <= 34.59) AS exact_rank, TRUE AS within_delta, TRUE AS unbiased, TRUE AS biased_coin_found FROM events CROSS JOIN (SELECT unnest({list(RISKS)}::DOUBLE[]) AS delta) GROUP BY delta")
def failure_rate_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two hundred sketches of one stream for each failure probability; a biased coin as the control must be found out.

    A trial has coins of its own; every task gives each batch of the stream to all of its trials, so no row is repeated.
    They take it in small pieces and compact as it comes. The control is as many sketches of the same plan by a biased coin.
    """
    rows = load(spark, sf_dir, "events", "value")
    truth = rows.agg(F.count("*").alias("n"), F.count_if(F.col("value") <= 34.59).alias("exact_rank"))
    error = answer.rank(answer.points(), F.lit(34.59)) - F.col("exact_rank")
    tried = lambda chosen: build(rows, "value", chosen=chosen, trials=TRIALS, piece=PIECE).crossJoin(truth).select("n", "exact_rank", error.alias("e"))
    out = None
    for delta in RISKS:
        fair = plan("geo", 0.05, delta, mode="single")
        biased = tried(replace(fair, variant="geo-biased")).agg(F.avg("e").alias("odd"))
        one = tried(fair).groupBy("n", "exact_rank").agg(F.count("*").alias("trials"), F.avg((F.abs("e") > 0.05 * F.col("n")).cast("int")).alias("rate"), F.avg("e").alias("mean"), F.stddev("e").alias("sd"))
        noise = 4 * F.col("sd") / math.sqrt(TRIALS)
        slack = 4 * math.sqrt(delta * (1 - delta) / TRIALS)
        part = one.crossJoin(biased).select(F.lit(delta).alias("delta"), "trials", "n", "exact_rank", (F.col("rate") <= delta + slack).alias("within_delta"), (F.abs("mean") <= noise).alias("unbiased"), (F.abs("odd") > noise).alias("biased_coin_found"))
        out = part if out is None else out.unionByName(part)
    return out


@query("SELECT 'lineitem' AS source, count(*) AS n, TRUE AS height_within_bound, TRUE AS compactions_within_bound FROM lineitem")
def height_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Levels, and compactions of each level against n / (k w)."""
    chosen = plan("geo", 0.05, DELTA, k=200)
    sketches = build(price(spark, sf_dir), "l_extendedprice", chosen=chosen)
    levels = sketches.select("sketch.n", "sketch.height", F.explode("sketch.levels").alias("l"))
    fits = F.col("l.compactions") <= F.col("n") / (F.lit(200.0) * F.pow(F.lit(chosen.c), F.col("height") - F.col("l.height")) * F.pow(F.lit(2.0), F.col("l.height") - 1)) + 1
    bound = F.floor(F.log2(F.col("n") / (chosen.c * 200)) + 2)
    return levels.groupBy("n").agg(F.bool_and(F.col("height") <= bound).alias("height_within_bound"), F.bool_and(fits).alias("compactions_within_bound")).select(F.lit("lineitem").alias("source"), "n", "height_within_bound", "compactions_within_bound")


@query("SELECT count(*) AS n, count(*) AS mass, TRUE AS levels_within_capacity, TRUE AS compactions_within_bound FROM lineitem")
def compactions_by_level(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items and compactions of every level: they weigh the stream, fit the capacities, and a level compacts no oftener than its input lets it."""
    chosen = plan("geo", 0.02, DELTA, mode="single")
    sketches = build(price(spark, sf_dir), "l_extendedprice", chosen=chosen)
    levels = measure.space(sketches, []).crossJoin(sketches.select("sketch.n", F.col("sketch.height").alias("top")))
    room = F.greatest(F.lit(2.0), F.ceil(F.lit(float(chosen.k)) * F.pow(F.lit(chosen.c), F.col("top") - F.col("height")))) + 1
    least = F.greatest(F.lit(2.0), F.lit(float(chosen.k)) * F.pow(F.lit(chosen.c), F.col("top") - F.col("height")))
    weight = F.pow(F.lit(2.0), F.col("height") - 1)
    return levels.groupBy("n").agg(F.sum(F.col("items") * weight).cast("long").alias("mass"), F.bool_and(F.col("items") <= room).alias("levels_within_capacity"), F.bool_and(F.col("compactions") <= 2 * F.col("n") / (least * weight) + 1).alias("compactions_within_bound"))


CURVE = [(e, d) for e in (0.1, 0.02) for d in (0.1, 1e-6)]


@query(f"SELECT variant, eps, delta, count(*) AS n, TRUE AS within_plan, TRUE AS above_lower_bound FROM lineitem CROSS JOIN (SELECT unnest({list(VARIANTS)}) AS variant) CROSS JOIN (SELECT unnest({[e for e, _ in CURVE]}::DOUBLE[]) AS eps, unnest({[d for _, d in CURVE]}::DOUBLE[]) AS delta) GROUP BY ALL")
def space_curve_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items stored by every variant over errors and failure probabilities, beside what was planned for the stream's length.

    above_lower_bound: no summary of this error holds fewer than 1 / (2 eps) items.
    """
    rows = price(spark, sf_dir)
    out = None
    for v in VARIANTS:
        for eps, delta in CURVE:
            p = plan(v, eps, delta, mode="single", n=1 << 22)
            sketches = build(rows, "l_extendedprice", chosen=p)
            held = measure.stored_items(sketches).crossJoin(sketches.select("sketch.n"))
            # A tuple summary holds a multiple of its planned size; two more are kept while the lowest is in use.
            most = planned_items(p, 1 << 22) * (3 if p.tuples else 1) + 1
            part = held.select(F.lit(v).alias("variant"), F.lit(eps).alias("eps"), F.lit(delta).alias("delta"), "n", (F.col("stored") <= most).alias("within_plan"), (F.col("stored") >= 1 / (2 * eps)).alias("above_lower_bound"))
            out = part if out is None else out.unionByName(part)
    return out


GROWTH = ("equal-fixed", "geo", "geo-wsampled", "banded")


@query(f"SELECT variant, times, CAST(count(*) * max(times) AS BIGINT) AS n, TRUE AS within_plan, TRUE AS levels_within_bound FROM lineitem CROSS JOIN (SELECT unnest({list(GROWTH)}) AS variant) CROSS JOIN (SELECT unnest([1, 4, 16]::BIGINT[]) AS times) GROUP BY variant, times")
def space_vs_n(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items stored for the same error as the stream grows: the stream one, four and sixteen times."""
    rows = price(spark, sf_dir)
    out = None
    for times in (1, 4, 16):
        longer = rows.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(times)))).select((F.col("l_extendedprice") + F.col("copy") / 1000).alias("v"))
        for v in GROWTH:
            p = plan(v, 0.05, 0.01, mode="single")
            sketches = build(longer, "v", chosen=p)
            part = measure.stored_items(sketches).crossJoin(sketches.select(F.col("sketch.n").alias("n"), F.col("sketch.height").alias("levels")))
            levels = F.floor(F.log2(F.col("n") / F.lit(p.c * p.k))) + 3
            part = part.select(F.lit(v).alias("variant"), F.lit(times).cast("long").alias("times"), "n", (F.col("stored") <= planned_items(p, 1 << 30) + 1).alias("within_plan"), (F.col("levels") <= F.greatest(levels, F.lit(1))).alias("levels_within_bound"))
            out = part if out is None else out.unionByName(part)
    return out


# -- baselines ---------------------------------------------------------------------


@query(quantile_sql("builtin", "lineitem", "l_extendedprice", [0.1, 0.5, 0.9]))
def builtin_percentile_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = price(spark, sf_dir)
    got = baselines.builtin_percentile(rows, "l_extendedprice", [0.1, 0.5, 0.9])
    counts = exact.counts_by_value(rows, "l_extendedprice")
    wanted = rows.agg(F.count("*").alias("rows")).select("rows", F.explode(F.array(F.lit(0.1), F.lit(0.5), F.lit(0.9))).alias("fraction")).withColumn("target", F.ceil(F.col("fraction") * F.col("rows")).cast("long"))
    truth = wanted.join(counts, (F.col("exact_rank") >= F.col("target")) & (F.col("exact_rank") - F.col("n") < F.col("target"))).select("fraction", "target", "rows", F.col("value").alias("exact_value"))
    ranked = truth.join(got.join(counts, "value").select("fraction", F.col("exact_rank").alias("r")), "fraction")
    return ranked.select(F.lit("builtin").alias("source"), "fraction", "target", "exact_value", (F.abs(F.col("r") - F.col("target")) <= 0.01 * F.col("rows")).alias("within_bound"))


@query(verdict_sql("builtin-sketch", "lineitem", "l_extendedprice", PRICE_PROBES))
def builtin_sketch_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = price(spark, sf_dir)
    est = baselines.builtin_sketch_ranks(rows, "l_extendedprice", PRICE_PROBES)
    truth = exact.ranks(rows, "l_extendedprice", PRICE_PROBES).crossJoin(rows.agg(F.count("*").alias("n")))
    return truth.join(est, "probe").select(F.lit("builtin-sketch").alias("variant"), "probe", "exact_rank", (F.abs(F.col("est_rank") - F.col("exact_rank")) <= 0.05 * F.col("n")).alias("within_bound"))


# -- plans and bounds ----------------------------------------------------------------

FINER = (1, 10, 100)


def asked_sql(finer: tuple = FINER) -> str:
    return f"""(SELECT l_returnflag, l_linestatus, n, share / 2 / finer AS eps, CASE WHEN squared THEN (1 / CAST(n AS DOUBLE)) * (1 / CAST(n AS DOUBLE)) ELSE 1 / CAST(n AS DOUBLE) END AS delta
    FROM (SELECT *, CAST(n AS DOUBLE) / CAST(sum(n) OVER () AS DOUBLE) AS share FROM (SELECT l_returnflag, l_linestatus, count(l_extendedprice) AS n FROM lineitem GROUP BY ALL HAVING count(l_extendedprice) > 4))
    CROSS JOIN (SELECT unnest({list(finer)}::DOUBLE[]) AS finer) CROSS JOIN (SELECT unnest([FALSE, TRUE]) AS squared))"""


def groups_of_prices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """l_returnflag, l_linestatus, n: the prices of every group; log log of 1 / delta needs five."""
    rows = load(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus", "l_extendedprice")
    return rows.groupBy("l_returnflag", "l_linestatus").agg(F.count("l_extendedprice").alias("n")).filter("n > 4")


def asked(spark: SparkSession, sf_dir: str) -> DataFrame:
    """l_returnflag, l_linestatus, n, eps, delta: what lineitem asks of a sketch of all prices.

    eps is half of a group's share, so that ranks tell the group from none, and parts of it; delta allows one failure in as
    many queries as the group has rows, or in the square of that.
    """
    groups = groups_of_prices(spark, sf_dir)
    groups = groups.crossJoin(F.broadcast(groups.agg(F.sum("n").alias("_all")))).withColumn("_d", 1 / F.col("n").cast("double"))
    grid = groups.withColumn("_finer", F.explode(F.array(*[F.lit(float(x)) for x in FINER]))).withColumn("delta", F.explode(F.array("_d", F.col("_d") * F.col("_d"))))
    return grid.select("l_returnflag", "l_linestatus", "n", (F.col("n").cast("double") / F.col("_all").cast("double") / 2 / F.col("_finer")).alias("eps"), "delta")


def planned(rows: DataFrame, lines: Callable[..., list[tuple]], args: list[str], schema: str) -> DataFrame:
    """rows with the lines that a function of some of their columns gives, on the executors; schema names the new columns."""
    made = F.udf(lambda *x: lines(*x), f"array<struct<{schema}>>")
    return rows.select("*", F.explode(made(*args)).alias("_x")).select(*rows.columns, "_x.*")


@query(
    f"""SELECT l_returnflag, l_linestatus, n, eps, delta, CAST(ceil(sqrt(ln(2 / delta) / ((2.0 / 3) * (2.0 / 3) * (2 * (2.0 / 3) - 1))) / eps) AS BIGINT) AS k_paper, CAST(ceil(sqrt(ln(2 / delta) / ((2 * (2.0 / 3) - 1) / 8)) / eps) AS BIGINT) AS k_safe
    FROM {asked_sql()}"""
)
def plan_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Top capacities of geometric sketches for one query, by published and by re-derived constants, for what lineitem asks."""
    lines = lambda e, d: [(plan("geo", e, d, "single", constants="paper").k, plan("geo", e, d, "single").k)]
    return planned(asked(spark, sf_dir), lines, ["eps", "delta"], "k_paper: long, k_safe: long")


@query(f"SELECT l_returnflag, l_linestatus, n, eps, delta, variant, mode, TRUE AS above_lower_bound, TRUE AS all_costs_more, TRUE AS smaller_error_costs_more FROM {asked_sql()} CROSS JOIN (SELECT unnest({[*VARIANTS, 'auto']}) AS variant) CROSS JOIN (SELECT unnest(['single', 'all']) AS mode)")
def plan_all_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Planned items of every variant for what lineitem asks, once groups are a million times as long: above the trivial lower bound, not fewer for all queries than for one, more for a smaller error."""

    def lines(n: int, e: float, d: float) -> list[tuple]:
        items = lambda v, m, e: planned_items(plan(v, e, d, m, n * 10**6), n * 10**6)
        return [(v, m, items(v, m, e) >= 1 / (2 * e), items(v, "all", e) >= items(v, "single", e), items(v, m, e / 2) > items(v, m, e)) for v in (*VARIANTS, "auto") for m in ("single", "all")]

    return planned(asked(spark, sf_dir), lines, ["n", "eps", "delta"], "variant: string, mode: string, above_lower_bound: boolean, all_costs_more: boolean, smaller_error_costs_more: boolean")


@query(" UNION ALL ".join(f"SELECT '{v}' AS variant, '{m}' AS mode, l_returnflag, l_linestatus, n, eps, delta, round({shape}, 4) AS shape FROM {asked_sql()}" for (v, m), shape in SPACE_SHAPES.items()))
def bounds_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shapes of the published space bounds for what lineitem asks; big-O rows carry no constants."""
    shapes = F.array(*[F.struct(F.lit(v).alias("variant"), F.lit(m).alias("mode"), F.round(F.expr(shape), 4).alias("shape")) for (v, m), shape in SPACE_SHAPES.items()])
    return asked(spark, sf_dir).select("*", F.explode(shapes).alias("_x")).select("l_returnflag", "l_linestatus", "n", "eps", "delta", "_x.*")


@query(f"SELECT l_returnflag, l_linestatus, n, eps, delta, round(1 / eps, 6) AS trivial, round(greatest(1, log2(greatest(2, log2(1 / delta)))) / eps, 4) AS randomized, round(log2(1 / eps) / eps, 4) AS deterministic FROM {asked_sql()}")
def lower_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lower bounds for what lineitem asks."""
    lines = lambda e, d: [(trivial_lower_bound(e), lower_bound(e, d), deterministic_lower_bound(e))]
    bounds = planned(asked(spark, sf_dir), lines, ["eps", "delta"], "trivial: double, randomized: double, deterministic: double")
    return bounds.withColumns({"trivial": F.round("trivial", 6), "randomized": F.round("randomized", 4), "deterministic": F.round("deterministic", 4)})


@query(f"SELECT l_returnflag, l_linestatus, n, eps, delta, round(sqrt(log2(1 / delta)) / log2(log2(1 / delta)), 6) AS compactors, round(log2(log2(1 / delta)), 6) AS banded, CAST(1 AS DOUBLE) AS tuple_topped FROM {asked_sql()}")
def optimality_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shapes of three constructions over the shape of the lower bound, for what lineitem asks."""
    least = F.log2(F.log2(1 / F.col("delta")))
    return asked(spark, sf_dir).select("*", F.round(F.sqrt(F.log2(1 / F.col("delta"))) / least, 6).alias("compactors"), F.round(least, 6).alias("banded"), F.lit(1.0).alias("tuple_topped"))


@query(
    """WITH t AS (SELECT l_returnflag, l_linestatus, n, times, CAST(greatest(1, floor(log2(greatest(1.0, n * times / (2.0 / 3 * 600))) + 2)) AS BIGINT) AS height
        FROM (SELECT l_returnflag, l_linestatus, count(l_extendedprice) AS n FROM lineitem GROUP BY ALL HAVING count(l_extendedprice) > 4) CROSS JOIN (SELECT unnest([1, 100, 10000]::BIGINT[]) AS times))
    SELECT l_returnflag, l_linestatus, n, times, h, height, CAST(greatest(2, ceil(600 * pow(2.0 / 3, height - h)) + 1) AS BIGINT) AS geometric, CAST(600 AS BIGINT) AS equal,
        CAST(CASE WHEN h > height - 4 THEN 600 ELSE greatest(2, ceil(600 * pow(2.0 / 3, height - 4 - h)) + 1) END AS BIGINT) AS banded, CAST(pow(2, h - 1) AS BIGINT) AS weight FROM t JOIN (SELECT unnest(range(1, 64)) AS h) ON h <= height"""
)
def capacity_schedule(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Capacities of the levels that the prices of a group need (k = 600, band of 4), and streams a hundred and ten thousand times as long."""

    def lines(n: int, times: int) -> list[tuple]:
        height = max_height(n * times, 600)
        g, e, b = schedule.geometric(600, 2 / 3, height), schedule.equal(600, height), schedule.banded(600, 2 / 3, height, 4)
        return [(h, height, g[h - 1], e[h - 1], b[h - 1], schedule.level_weight(h)) for h in range(1, height + 1)]

    streams = groups_of_prices(spark, sf_dir).withColumn("times", F.explode(F.array(*[F.lit(x).cast("long") for x in (1, 100, 10_000)])))
    return planned(streams, lines, ["n", "times"], "h: long, height: long, geometric: long, equal: long, banded: long, weight: long")


@query(
    """WITH s AS (SELECT l_returnflag, l_linestatus, n * CAST(pow(10, x) AS BIGINT) AS n FROM (SELECT l_returnflag, l_linestatus, count(l_extendedprice) AS n FROM lineitem GROUP BY ALL HAVING count(l_extendedprice) > 4) CROSS JOIN (SELECT unnest(range(0, 9)) AS x)),
    t AS (SELECT *, CAST(greatest(1, floor(log2(greatest(1.0, n / (2.0 / 3 * 600))) + 2)) AS BIGINT) AS height, unnest(['geo', 'geo-wsampled', 'banded', 'tuple-topped']) AS construction FROM s),
    u AS (SELECT *, CASE WHEN construction = 'geo-wsampled' THEN greatest(0, height - 16) WHEN construction = 'geo' THEN 0 ELSE greatest(0, height - 18) END AS sampled,
        CASE WHEN construction IN ('geo', 'geo-wsampled') THEN 0 ELSE least(height, 4) END AS top FROM t)
    SELECT l_returnflag, l_linestatus, n, height, construction, sampled, CASE WHEN construction = 'tuple-topped' THEN height - greatest(sampled, height - top) ELSE 0 END AS tupled,
        CASE WHEN construction = 'banded' THEN height - greatest(sampled, height - top) ELSE 0 END AS flat, greatest(sampled, height - top) - sampled AS shrinking FROM u"""
)
def structure_by_length(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many levels of a construction are served by the sampler, shrink, are flat or are a tuple summary's, for the prices of a group and growing streams of them (k = 600, band of 4)."""

    def lines(n: int) -> list[tuple]:
        height = max_height(n, 600)
        return [(height, name, *schedule.structure(name, VARIANTS[name], height, 600, 2 / 3, 4)) for name in ("geo", "geo-wsampled", "banded", "tuple-topped")]

    streams = groups_of_prices(spark, sf_dir).withColumn("n", F.explode(F.array(*[F.col("n") * 10**x for x in range(9)])))
    return planned(streams, lines, ["n"], "height: long, construction: string, sampled: long, shrinking: long, flat: long, tupled: long")


@query(f"SELECT variant, eps, count(*) AS n, TRUE AS above_trivial, TRUE AS ratio_within_plan FROM lineitem CROSS JOIN (SELECT unnest({list(GROWTH[1:])}) AS variant) CROSS JOIN (SELECT unnest([0.05, 0.02, 0.01]::DOUBLE[]) AS eps) GROUP BY ALL")
def measured_optimality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items really held over the shape of the randomised lower bound, beside the same ratio of the plan."""
    rows = price(spark, sf_dir)
    out = None
    for v in GROWTH[1:]:
        for eps in (0.05, 0.02, 0.01):
            p = plan(v, eps, DELTA, mode="single")
            sketches = build(rows, "l_extendedprice", chosen=p)
            held = measure.stored_items(sketches).crossJoin(sketches.select("sketch.n"))
            ratio, planned = F.col("stored") / lower_bound(eps, DELTA), (planned_items(p, 1 << 30) + 1) / lower_bound(eps, DELTA)
            part = held.select(F.lit(v).alias("variant"), F.lit(eps).alias("eps"), "n", (F.col("stored") >= trivial_lower_bound(eps) / 2).alias("above_trivial"), (ratio <= planned).alias("ratio_within_plan"))
            out = part if out is None else out.unionByName(part)
    return out


# -- stores and tables of sketches -----------------------------------------------------


@query(verdict_sql("stored", "lineitem", "l_extendedprice", PRICE_PROBES))
def sketch_store_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketches written to a store by return flag, read again and merged."""
    from rankloom.sources.io import load_sketches, save_sketches, shared_folder

    rows = load(spark, sf_dir, "lineitem", "l_returnflag", "l_extendedprice")
    path = f"{shared_folder(spark)}/store-{spark.sparkContext.applicationId}-{abs(hash(sf_dir))}"
    save_sketches(build(rows, "l_extendedprice", by=["l_returnflag"], variant="banded", eps=0.02, delta=DELTA), path, ["l_returnflag"], mode="overwrite")
    stored = load_sketches(spark, path).withColumn("part", F.xxhash64("l_returnflag"))
    return measure.verdicts(answer.coreset(tree(stored.select("part", "sketch"), [])), rows, "l_extendedprice", PRICE_PROBES, 0.02, "stored")


@query("SELECT count(*) AS n, count(*) FILTER (value <= 34.59) AS exact_rank, TRUE AS within_bound FROM events")
def sql_function_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rank function in SQL, inlined into plain expressions."""
    from rankloom.functions.sql import register_rank_function, with_points

    register_rank_function(spark)
    rows = load(spark, sf_dir, "events", "value")
    with_points(build(rows, "value", variant="geo", eps=0.02, delta=DELTA)).createOrReplaceTempView("value_sketches")
    got = spark.sql("SELECT sketch_rank(points, CAST(34.59 AS DOUBLE)) AS est FROM value_sketches")
    truth = rows.agg(F.count("*").alias("n"), F.count_if(F.col("value") <= 34.59).alias("exact_rank"))
    return truth.crossJoin(got).select("n", "exact_rank", (F.abs(F.col("est") - F.col("exact_rank")) <= 0.02 * F.col("n")).alias("within_bound"))


def partial_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The partial sketches of a build, as tests of plans look at them."""
    return partials(prepare(price(spark, sf_dir), "l_extendedprice", []), [], plan("banded", 0.02), 42, 0)
