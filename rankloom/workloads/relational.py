"""Queries over the relational form of compaction: equal rows in Spark and SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankloom.functions import answer
from rankloom.functions.coins import POLICIES, digest_coin, policy_coin
from rankloom.operators import measure
from rankloom.operators.relational import compact_array, compact_round, compact_tree, tree_sql
from rankloom.operators.sampler import block_filter, digest_slot, stratified_sample, uniform_sample
from rankloom.sources.io import load
from rankloom.workloads.registry import add, query

BLOCK, ROUNDS, SEED = 157, 3, 7
PROBES = [5.0, 20.0, 34.59, 60.0, 113.28, 250.0]
TREE = tree_sql("events", "value", f"event_id // {BLOCK}", ROUNDS, SEED)
PROBE_ROWS = "(SELECT unnest([" + ", ".join(f"CAST({p} AS DOUBLE)" for p in PROBES) + "]) AS probe)"
CDF = "cdf AS (SELECT value, weight, height, CAST(sum(weight) OVER (ORDER BY value RANGE UNBOUNDED PRECEDING) AS BIGINT) AS cum_weight FROM coreset)"
EXACT = "ex AS (SELECT probe, count(*) FILTER (value <= probe) AS exact_rank FROM events CROSS JOIN " + PROBE_ROWS + " GROUP BY probe)"
EST = "es AS (SELECT probe, CAST(coalesce(sum(weight) FILTER (value <= probe), 0) AS BIGINT) AS est_rank FROM coreset CROSS JOIN " + PROBE_ROWS + " GROUP BY probe)"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events", "event_id", "value")


def coreset(spark: SparkSession, sf_dir: str, policy: str = "fair", seed: int = SEED) -> DataFrame:
    return compact_tree(events(spark, sf_dir), ["value"], F.expr(f"event_id div {BLOCK}"), ROUNDS, seed, policy)


def probes(spark: SparkSession) -> DataFrame:
    return spark.range(1).select(F.explode(F.array(*[F.lit(p) for p in PROBES])).alias("probe"))


@query(
    f"""WITH r AS (SELECT event_id // {BLOCK} AS block, value, row_number() OVER (PARTITION BY event_id // {BLOCK} ORDER BY value, event_id) AS rn,
             count(*) OVER (PARTITION BY event_id // {BLOCK}) AS n FROM events),
    h AS (SELECT *, n % 2 = 1 AND rn = n AS held FROM r)
    SELECT block, value, held, CAST(CASE WHEN held THEN 1 ELSE 2 END AS BIGINT) AS weight FROM h
    WHERE held OR (rn % 2 = 1) = (instr('13579bdf', substr(md5('7|1|' || block), 1, 1)) > 0)"""
)
def compaction_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = events(spark, sf_dir).withColumn("block", F.expr(f"event_id div {BLOCK}")).withColumn("weight", F.lit(1).cast("long"))
    return compact_round(rows, "block", ["value", "event_id"], "weight", 1, SEED).select("block", "value", "held", "weight")


@query(
    """WITH r AS (SELECT p_partkey % 50 AS block, p_size AS value, row_number() OVER (PARTITION BY p_partkey % 50 ORDER BY p_size) AS rn,
             count(*) OVER (PARTITION BY p_partkey % 50) AS n FROM part)
    SELECT block, CAST(value AS INTEGER) AS value FROM r WHERE rn <= n - n % 2 AND (rn % 2 = 1) = (instr('13579bdf', substr(md5('7|1|' || block), 1, 1)) > 0)"""
)
def single_compaction_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The array form of one compaction; an odd block leaves its largest out."""
    rows = load(spark, sf_dir, "part", "p_partkey", "p_size").groupBy((F.col("p_partkey") % 50).alias("block")).agg(F.sort_array(F.collect_list("p_size")).alias("a"))
    even = F.slice("a", F.lit(1), F.size("a") - F.size("a") % 2)
    return rows.select("block", F.explode(compact_array(even, digest_coin(SEED, F.lit(1), F.col("block")))).alias("value"))


@query(
    f"""WITH r AS (SELECT event_id // {BLOCK} AS block, value, row_number() OVER (PARTITION BY event_id // {BLOCK} ORDER BY value, event_id) AS rn,
             count(*) OVER (PARTITION BY event_id // {BLOCK}) AS n FROM events),
    s AS (SELECT block, value, CASE WHEN n % 2 = 1 AND rn = n THEN 1 WHEN (rn % 2 = 1) = (instr('13579bdf', substr(md5('7|1|' || block), 1, 1)) > 0) THEN 2 ELSE 0 END AS w FROM r),
    q AS (SELECT block, probe, count(*) FILTER (value <= probe) AS inner_rank, CAST(coalesce(sum(w) FILTER (value <= probe), 0) AS BIGINT) AS after_rank
          FROM s CROSS JOIN {PROBE_ROWS} GROUP BY block, probe)
    SELECT block, probe, inner_rank, after_rank - inner_rank AS shift, abs(after_rank - inner_rank) <= inner_rank % 2 AS as_claimed FROM q"""
)
def compaction_rank_shift(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A rank stays where it is even within its block, and moves by one weight where it is odd."""
    rows = events(spark, sf_dir).withColumn("block", F.expr(f"event_id div {BLOCK}"))
    after = compact_round(rows.withColumn("weight", F.lit(1).cast("long")), "block", ["value", "event_id"], "weight", 1, SEED)
    both = rows.select("block", "value", F.lit(1).cast("long").alias("n"), F.lit(0).cast("long").alias("w")).unionByName(after.select("block", "value", F.lit(0).cast("long").alias("n"), F.col("weight").alias("w")))
    sums = both.groupBy("block").agg(*[F.struct(F.lit(p).alias("probe"), F.sum(F.when(F.col("value") <= p, F.col("n")).otherwise(0)).alias("inner_rank"), F.sum(F.when(F.col("value") <= p, F.col("w")).otherwise(0)).alias("after_rank")).alias(f"p{i}") for i, p in enumerate(PROBES)])
    rows = sums.select("block", F.explode(F.array(*[f"p{i}" for i in range(len(PROBES))])).alias("x")).select("block", "x.*")
    shift = F.col("after_rank") - F.col("inner_rank")
    return rows.select("block", "probe", "inner_rank", shift.alias("shift"), (F.abs(shift) <= F.col("inner_rank") % 2).alias("as_claimed"))


def _policies(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = events(spark, sf_dir).withColumn("block", F.expr(f"event_id div {BLOCK}")).withColumn("weight", F.lit(1).cast("long"))
    out = None
    for policy in POLICIES:
        part = compact_round(rows, "block", ["value", "event_id"], "weight", 1, SEED, policy).select(F.lit(policy).alias("policy"), "block", "value", "weight")
        out = part if out is None else out.unionByName(part)
    return out


_PARITY = {"fixed_odd": "TRUE", "fixed_even": "FALSE", "alternate": "block % 2 = 0", "fair": "instr('13579bdf', substr(md5('7|1|' || block), 1, 1)) > 0"}
add(
    "parity_policies",
    _policies,
    f"""WITH r AS (SELECT event_id // {BLOCK} AS block, value, row_number() OVER (PARTITION BY event_id // {BLOCK} ORDER BY value, event_id) AS rn,
             count(*) OVER (PARTITION BY event_id // {BLOCK}) AS n FROM events) """
    + " UNION ALL ".join(f"SELECT '{p}' AS policy, block, value, CAST(CASE WHEN n % 2 = 1 AND rn = n THEN 1 ELSE 2 END AS BIGINT) AS weight FROM r WHERE (n % 2 = 1 AND rn = n) OR (rn % 2 = 1) = ({_PARITY[p]})" for p in POLICIES),
)
add("compaction_tree", coreset, TREE + " SELECT value, weight, height FROM coreset")
add("equal_fixed_tree", lambda s, d: coreset(s, d, "fixed_odd"), tree_sql("events", "value", f"event_id // {BLOCK}", ROUNDS, SEED, "fixed_odd") + " SELECT value, weight, height FROM coreset")
add(
    "compaction_tree_lineitem",
    lambda s, d: compact_tree(load(s, d, "lineitem", "l_orderkey", "l_extendedprice").withColumnRenamed("l_extendedprice", "value"), ["value"], F.col("l_orderkey") % 64, ROUNDS),
    tree_sql("lineitem", "l_extendedprice", "l_orderkey % 64", ROUNDS, 7) + " SELECT value, weight, height FROM coreset",
)


@query(TREE + f", {CDF} SELECT value, weight, height, cum_weight, cum_weight / 1.0 / (SELECT sum(weight) FROM coreset) AS rank_fraction FROM cdf")
def coreset_cdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return answer.cdf(coreset(spark, sf_dir)).select("value", "weight", "height", "cum_weight", "rank_fraction")


@query(TREE + f", {CDF}, g AS (SELECT value, weight, height, value - lag(value) OVER (ORDER BY value, weight, height) AS gap FROM coreset) SELECT value, weight, height, round(gap, 6) AS gap FROM g")
def coreset_gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rankloom.operators.ops import gaps

    return gaps(coreset(spark, sf_dir)).withColumn("gap", F.round("gap", 6))


@query(TREE + " SELECT CAST((value > 10.0)::INT + (value > 50.0)::INT + (value > 120.0)::INT AS INTEGER) AS bucket, CAST(sum(weight) AS BIGINT) AS mass FROM coreset GROUP BY 1")
def coreset_pmf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return answer.pmf(coreset(spark, sf_dir), [10.0, 50.0, 120.0])


@query(TREE + f", {EST} SELECT * FROM es", name="rank_probes_theta")
def rank_probes_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    return answer.ranks(coreset(spark, sf_dir), probes(spark), "theta")


@query(TREE + f", {EST} SELECT * FROM es")
def rank_probes_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    return answer.ranks(coreset(spark, sf_dir), probes(spark), "asof")


@query(TREE + f", {EST} SELECT * FROM es")
def rank_by_higher_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ranks from one nested array, without a join of points."""
    held = coreset(spark, sf_dir).agg(F.collect_list(F.struct("value", "weight")).alias("points"))
    return held.crossJoin(probes(spark)).select("probe", answer.rank(F.col("points"), F.col("probe")).alias("est_rank"))


TARGETS = [100, 1000, 5000, 9000, 9900]
TARGET_ROWS = "(SELECT unnest([" + ", ".join(map(str, TARGETS)) + "])::BIGINT AS target)"


@query(TREE + f", {CDF} SELECT target, min(value) AS value FROM cdf JOIN {TARGET_ROWS} ON cum_weight >= target GROUP BY target")
def value_at_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = answer.cdf(coreset(spark, sf_dir)).withColumn("target", F.explode(F.array(*[F.lit(t).cast("long") for t in TARGETS])))
    return answer.value_at_rank(lines, F.col("target"), ["target"]).select("target", "value")


@query(TREE + f", {CDF}, v AS (SELECT target, min(value) AS value FROM cdf JOIN {TARGET_ROWS} ON cum_weight >= target GROUP BY target) SELECT target, v.value, CAST(sum(weight) AS BIGINT) AS rank_again FROM v JOIN coreset c ON c.value <= v.value GROUP BY target, v.value")
def rank_value_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = value_at_rank(spark, sf_dir)
    back = answer.ranks(coreset(spark, sf_dir), got.select(F.col("value").alias("probe")))
    return got.join(back, got["value"] == back["probe"]).select("target", "value", F.col("est_rank").alias("rank_again"))


@query(TREE + f", {EXACT}, {EST} SELECT probe, exact_rank, est_rank, est_rank - exact_rank AS signed_error FROM ex JOIN es USING (probe)")
def rank_error_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measure.errors(coreset(spark, sf_dir), events(spark, sf_dir), "value", PROBES)


SUP = """, b AS (SELECT value, CAST(1 AS BIGINT) AS n, CAST(0 AS BIGINT) AS w FROM events UNION ALL SELECT value, 0, weight FROM coreset),
    g AS (SELECT value, sum(w) - sum(n) AS d FROM b GROUP BY value), c AS (SELECT abs(sum(d) OVER (ORDER BY value)) AS e FROM g)"""


@query(TREE + SUP + " SELECT CAST(max(e) AS BIGINT) AS sup_error FROM c")
def sup_error_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measure.sup_error(coreset(spark, sf_dir), events(spark, sf_dir), "value")


@query(TREE + SUP + f", blocks AS (SELECT count(DISTINCT event_id // {BLOCK}) AS k FROM events) SELECT CAST(max(e) AS BIGINT) AS sup_error, any_value(k) * {ROUNDS} AS bound, TRUE AS within_bound FROM c, blocks")
def tree_worst_case(spark: SparkSession, sf_dir: str) -> DataFrame:
    blocks = events(spark, sf_dir).agg((F.count_distinct(F.expr(f"event_id div {BLOCK}")) * ROUNDS).alias("bound"))
    return sup_error_table(spark, sf_dir).crossJoin(blocks).withColumn("within_bound", F.col("sup_error") <= F.col("bound"))


@query(
    TREE
    + f""", {CDF}, v AS (SELECT target, min(value) AS value FROM cdf JOIN {TARGET_ROWS} ON cum_weight >= target GROUP BY target),
    x AS (SELECT target, v.value, count(*) FILTER (e.value < v.value) + 1 AS lo, count(*) FILTER (e.value <= v.value) AS hi FROM v CROSS JOIN events e GROUP BY target, v.value)
    SELECT target, value, greatest(0, lo - target, target - hi) AS rank_error FROM x"""
)
def inverse_error_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measure.inverse_errors(coreset(spark, sf_dir), events(spark, sf_dir), "value", TARGETS)


@query(
    TREE
    + """, l AS (SELECT CAST(1 AS BIGINT) AS level, count(DISTINCT block) AS compactions FROM r1 WHERE n > 1
        UNION ALL SELECT 2, count(DISTINCT block) FROM r2 WHERE n > 1 UNION ALL SELECT 3, count(DISTINCT block) FROM r3 WHERE n > 1)
    SELECT level, compactions, CAST(compactions * pow(2, level - 1) AS DOUBLE) AS err_abs, CAST(compactions * pow(4, level - 1) AS DOUBLE) AS err_sq FROM l"""
)
def certificate_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """By level: how often it compacted, and what that can have moved at most and in squares."""
    rows = events(spark, sf_dir).select("value", F.expr(f"event_id div {BLOCK}").alias("block"), F.lit(1).cast("long").alias("weight"))
    out = None
    for level in range(1, ROUNDS + 1):
        sizes = rows.groupBy("block").agg(F.count("*").alias("n")).agg(F.count_if(F.col("n") > 1).alias("compactions"))
        part = sizes.select(F.lit(level).cast("long").alias("level"), "compactions", (F.col("compactions") * 2.0 ** (level - 1)).alias("err_abs"), (F.col("compactions") * 4.0 ** (level - 1)).alias("err_sq"))
        out = part if out is None else out.unionByName(part)
        rows = compact_round(rows, "block", ["value"], "weight", level, SEED).filter("not held").select("value", F.expr("block div 2").alias("block"), "weight")
    return out


@query(TREE + " SELECT height, weight, count(*) AS items, CAST(count(*) * weight AS BIGINT) AS mass FROM coreset GROUP BY height, weight")
def space_by_level(spark: SparkSession, sf_dir: str) -> DataFrame:
    return coreset(spark, sf_dir).groupBy("height", "weight").agg(F.count("*").alias("items"), F.sum("weight").alias("mass"))


@query(TREE + " SELECT count(*) FILTER (e.value IS NULL) AS strangers FROM (SELECT DISTINCT value FROM coreset) c LEFT JOIN (SELECT DISTINCT value FROM events) e USING (value)")
def coreset_subset_of_input(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points that are no items of the stream: none."""
    return coreset(spark, sf_dir).select("value").exceptAll(events(spark, sf_dir).select("value")).agg(F.count("*").alias("strangers"))


SQL_BIAS = " UNION ALL ".join(
    f"SELECT {seed} AS seed, probe, est_rank - exact_rank AS signed_error FROM ({tree_sql('events', 'value', f'event_id // {BLOCK}', 2, seed)}, {EXACT}, {EST} SELECT probe, exact_rank, est_rank FROM ex JOIN es USING (probe))"
    for seed in range(1, 9)
)


@query(f"SELECT probe, CAST(sum(signed_error) AS BIGINT) AS total_error, count(*) AS trials FROM ({SQL_BIAS}) GROUP BY probe")
def coin_bias_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Signed errors of two-round trees summed over eight seeds."""
    data = events(spark, sf_dir)
    out = None
    for seed in range(1, 9):
        tree = compact_tree(data, ["value"], F.expr(f"event_id div {BLOCK}"), 2, seed)
        part = measure.errors(tree, data, "value", PROBES)
        out = part if out is None else out.unionByName(part)
    return out.groupBy("probe").agg(F.sum("signed_error").alias("total_error"), F.count("*").alias("trials"))


_PICK = "p0 AS (SELECT event_id, value, event_id // 16 AS block FROM events)"
for _r in range(1, 5):
    _PICK += f", q{_r} AS (SELECT *, row_number() OVER (PARTITION BY block ORDER BY value, event_id) AS rn FROM p{_r - 1}), p{_r} AS (SELECT event_id, value, block FROM q{_r} WHERE (rn % 2 = 1) = (instr('13579bdf', substr(md5('7|{_r}|' || block), 1, 1)) > 0))"


@query(f"WITH {_PICK} SELECT block, event_id, value, CAST(16 AS BIGINT) AS weight FROM p4")
def cap2_chain_equals_pick(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four halvings of blocks of 16 leave one item each, picked by the coins."""
    rows = events(spark, sf_dir).withColumn("block", F.expr("event_id div 16")).withColumn("weight", F.lit(1).cast("long"))
    for r in range(1, 5):
        rows = compact_round(rows, "block", ["value", "event_id"], "weight", r, SEED, holdback=False).drop("held")
    return rows.select("block", "event_id", "value", "weight")


@query("SELECT event_id, value, CAST(8 AS BIGINT) AS weight FROM events WHERE event_id % 8 = CAST('0x' || substr(md5('7|3|' || event_id // 8), 1, 7) AS BIGINT) % 8")
def block_sample_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return block_filter(events(spark, sf_dir), 3, SEED, "event_id")


@query(f"SELECT probe, 8 * count(*) FILTER (value <= probe) AS total_estimate FROM events CROSS JOIN {PROBE_ROWS} GROUP BY probe")
def block_sample_all_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Over all slots the sampler's estimates sum to 2**height times the exact rank: it is unbiased."""
    turn = F.explode(F.sequence(F.lit(0), F.lit(7))).alias("turn")
    rows = events(spark, sf_dir).select("event_id", "value", turn)
    kept = rows.filter(F.col("event_id") % 8 == (digest_slot(SEED, 3, F.expr("event_id div 8")) + F.col("turn")) % 8)
    sums = kept.agg(*[(F.count_if(F.col("value") <= p) * 8).alias(f"p{i}") for i, p in enumerate(PROBES)])
    return sums.select(F.explode(F.array(*[F.struct(F.lit(p).alias("probe"), F.col(f"p{i}").alias("total_estimate")) for i, p in enumerate(PROBES)])).alias("x")).select("x.*")


@query("SELECT event_id, value, md5('7|' || event_id) AS priority FROM events ORDER BY priority, event_id LIMIT 200")
def priority_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return uniform_sample(events(spark, sf_dir), "event_id", 200, SEED)


@query("SELECT event_type, event_id, value, md5('7|' || event_id) AS priority FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY md5('7|' || event_id), event_id) AS rn FROM events) WHERE rn <= 50")
def stratified_priority_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fifty rows of every event type."""
    rows = load(spark, sf_dir, "events", "event_type", "event_id", "value")
    return stratified_sample(rows, ["event_type"], "event_id", 50, SEED)


@query(
    f"""WITH m AS (SELECT max(event_id) // 2 AS cut FROM events), h AS (SELECT value, event_id > cut AS late FROM events, m),
    f AS (SELECT value, sum(CASE WHEN late THEN 0 ELSE 1 END) / (SELECT count(*) FROM h WHERE NOT late) - sum(CASE WHEN late THEN 1 ELSE 0 END) / (SELECT count(*) FROM h WHERE late) AS d FROM h GROUP BY value),
    c AS (SELECT abs(sum(d) OVER (ORDER BY value ROWS UNBOUNDED PRECEDING)) AS e FROM f) SELECT round(max(e), 9) AS distance FROM c"""
)
def drift_distance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest difference of the distributions of the first and the second half."""
    rows = events(spark, sf_dir)
    cut = rows.agg(F.expr("max(event_id) div 2").alias("cut"))
    halves = rows.crossJoin(F.broadcast(cut)).select("value", F.lit(1).cast("long").alias("weight"), (F.col("event_id") > F.col("cut")).alias("late"))
    return answer.sup_distance(halves.filter("not late"), halves.filter("late")).select(F.round("distance", 9).alias("distance"))


@query(
    """WITH t0 AS (SELECT l_shipdate, l_extendedprice, l_orderkey % 64 AS block FROM lineitem),
    r AS (SELECT *, row_number() OVER (PARTITION BY block ORDER BY l_shipdate, l_extendedprice) AS rn, count(*) OVER (PARTITION BY block) AS n FROM t0)
    SELECT l_shipdate, l_extendedprice, CAST(CASE WHEN n % 2 = 1 AND rn = n THEN 1 ELSE 2 END AS BIGINT) AS weight FROM r
    WHERE (n % 2 = 1 AND rn = n) OR (rn % 2 = 1) = (instr('13579bdf', substr(md5('7|1|' || block), 1, 1)) > 0)"""
)
def coreset_by_two_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Compaction in a composite order."""
    rows = load(spark, sf_dir, "lineitem", "l_orderkey", "l_shipdate", "l_extendedprice")
    tree = compact_tree(rows, ["l_shipdate", "l_extendedprice"], F.col("l_orderkey") % 64, 1)
    return tree.select("l_shipdate", "l_extendedprice", "weight")


@query(
    TREE + f""", c AS (SELECT DISTINCT CAST(1 AS BIGINT) AS level, block, instr('13579bdf', substr(md5('7|1|' || block), 1, 1)) > 0 AS odd FROM r1
    UNION ALL SELECT DISTINCT 2, block, instr('13579bdf', substr(md5('7|2|' || block), 1, 1)) > 0 FROM r2
    UNION ALL SELECT DISTINCT 3, block, instr('13579bdf', substr(md5('7|3|' || block), 1, 1)) > 0 FROM r3)
    SELECT level, count(*) AS coins, count(*) FILTER (odd) AS odd FROM c GROUP BY level"""
)
def coin_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Random bits used by level."""
    blocks = events(spark, sf_dir).select(F.expr(f"event_id div {BLOCK}").alias("block")).distinct()
    out = None
    for level in range(1, ROUNDS + 1):
        part = blocks.select(F.lit(level).cast("long").alias("level"), policy_coin("fair", SEED, F.lit(level), F.col("block")).alias("odd"))
        part = part.groupBy("level").agg(F.count("*").alias("coins"), F.count_if("odd").alias("odd"))
        out = part if out is None else out.unionByName(part)
        blocks = blocks.select(F.expr("block div 2").alias("block")).distinct()
    return out
