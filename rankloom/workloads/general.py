"""Queries of the operators around sketches: scans, joins, aggregates, windows, functions. All exact."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rankloom.functions import answer
from rankloom.operators import baselines, exact, ops
from rankloom.operators.build import build
from rankloom.operators.ordered import running_sums
from rankloom.sources.io import load
from rankloom.workloads.registry import query


@query("SELECT l_returnflag, count(*) AS n, min(l_extendedprice) AS least, max(l_extendedprice) AS most FROM lineitem GROUP BY l_returnflag")
def scan_lineitem_prices(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem", "l_returnflag", "l_extendedprice")
    return rows.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.min("l_extendedprice").alias("least"), F.max("l_extendedprice").alias("most"))


@query("SELECT round(quantile_cont(l_extendedprice * (1 - l_discount), 0.5), 4) AS median_revenue FROM lineitem")
def project_revenue_quantile(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = ops.value_column(load(spark, sf_dir, "lineitem", "l_extendedprice", "l_discount"), "l_extendedprice * (1 - l_discount)", "double")
    return exact.bracketed(rows, "value", 0.5).select(F.round("value", 4).alias("median_revenue"))


@query("SELECT count(*) AS n, round(quantile_cont(l_extendedprice, 0.5), 4) AS median_price FROM lineitem WHERE l_shipdate < TIMESTAMP '1998-01-01' AND l_quantity > 25")
def filtered_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem", "l_shipdate", "l_quantity", "l_extendedprice").filter("l_shipdate < timestamp_ntz'1998-01-01' and l_quantity > 25")
    return rows.agg(F.count("*").alias("n"), F.round(F.percentile("l_extendedprice", F.lit(0.5)), 4).alias("median_price"))


@query("SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem WHERE l_extendedprice > (SELECT quantile_disc(l_extendedprice, 0.99) FROM lineitem)")
def rows_above_p99(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_extendedprice")
    cut = rows.agg(F.expr("percentile_disc(0.99) WITHIN GROUP (ORDER BY l_extendedprice)").alias("value"))
    return ops.where_above(rows, "l_extendedprice", cut)


@query("SELECT count(*) FILTER (quality IS NULL) AS nulls, count(*) FILTER (quality <= 0) AS rank_of_0, count(*) FILTER (quality <= 1) AS rank_of_1 FROM documents LEFT JOIN labels USING (doc_id)")
def null_skipping_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "documents", "doc_id").join(load(spark, sf_dir, "labels", "doc_id", "quality"), "doc_id", "left")
    return rows.agg(F.count_if(F.col("quality").isNull()).alias("nulls"), F.count_if(F.col("quality") <= 0).alias("rank_of_0"), F.count_if(F.col("quality") <= 1).alias("rank_of_1"))


@query("SELECT n_name, round(quantile_cont(c_acctbal, 0.5), 4) AS median_balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def median_balance_by_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nation is a table of fixed size, so it is broadcast."""
    nations = load(spark, sf_dir, "nation", "n_nationkey", "n_name")
    rows = load(spark, sf_dir, "customer", "c_nationkey", "c_acctbal").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey"))
    return rows.groupBy("n_name").agg(F.round(F.percentile("c_acctbal", F.lit(0.5)), 4).alias("median_balance"))


@query("SELECT quantile_disc(date_diff('day', o_orderdate, l_shipdate), 0.5) AS p50, quantile_disc(date_diff('day', o_orderdate, l_shipdate), 0.9) AS p90 FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def ship_delay_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_shipdate").hint("merge")
    rows = lines.join(load(spark, sf_dir, "orders", "o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    days = rows.select(F.datediff("l_shipdate", "o_orderdate").cast("long").alias("days"))
    at = lambda f: F.expr(f"percentile_disc({f}) WITHIN GROUP (ORDER BY days)").cast("long")
    return days.agg(at(0.5).alias("p50"), at(0.9).alias("p90"))


@query("SELECT n_nationkey, n_name FROM nation WHERE n_nationkey NOT IN (SELECT c_nationkey FROM customer WHERE c_acctbal > 9990)")
def groups_without_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    rich = load(spark, sf_dir, "customer", "c_nationkey", "c_acctbal").filter("c_acctbal > 9990").select(F.col("c_nationkey").alias("n_nationkey"))
    return load(spark, sf_dir, "nation", "n_nationkey", "n_name").join(rich, "n_nationkey", "left_anti")


@query("SELECT o_orderkey, o_custkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal >= (SELECT quantile_disc(c_acctbal, 0.9) FROM customer))")
def customers_in_top_decile(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = load(spark, sf_dir, "customer", "c_custkey", "c_acctbal")
    cut = customers.agg(F.expr("percentile_disc(0.9) WITHIN GROUP (ORDER BY c_acctbal)").alias("cut"))
    top = customers.crossJoin(F.broadcast(cut)).filter("c_acctbal >= cut").select(F.col("c_custkey").alias("o_custkey"))
    return load(spark, sf_dir, "orders", "o_orderkey", "o_custkey").join(top, "o_custkey", "left_semi").select("o_orderkey", "o_custkey")


@query(
    """WITH v AS (SELECT DISTINCT value FROM events), t AS (SELECT DISTINCT event_type FROM events), k AS (SELECT event_type, value, count(*) AS n FROM events GROUP BY ALL),
    c AS (SELECT t.event_type, v.value, sum(coalesce(n, 0)) OVER (PARTITION BY t.event_type ORDER BY v.value) / (sum(coalesce(n, 0)) OVER (PARTITION BY t.event_type)) AS f FROM t CROSS JOIN v LEFT JOIN k USING (event_type, value))
    SELECT a.event_type AS one, b.event_type AS other, round(max(abs(a.f - b.f)), 9) AS distance FROM c a JOIN c b USING (value) WHERE a.event_type < b.event_type GROUP BY ALL"""
)
def pairwise_drift_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest difference of distributions for each pair of event types: one running count of each type over all values."""
    names = sorted(r[0] for r in load(spark, sf_dir, "events", "event_type").distinct().collect())
    counts = load(spark, sf_dir, "events", "event_type", "value").groupBy("value").pivot("event_type", names).count().fillna(0)
    summed = running_sums(counts, "value", {f"{n}_upto": F.col(n) for n in names})
    totals = counts.agg(*[F.sum(n).alias(f"{n}_all") for n in names])
    shares = summed.crossJoin(F.broadcast(totals)).select("value", *[(F.col(f"{n}_upto") / F.col(f"{n}_all")).alias(n) for n in names])
    pairs = [(a, b) for a in names for b in names if a < b]
    wide = shares.agg(*[F.max(F.abs(F.col(a) - F.col(b))).alias(f"{a}|{b}") for a, b in pairs])
    rows = F.array(*[F.struct(F.lit(a).alias("one"), F.lit(b).alias("other"), F.round(F.col(f"{a}|{b}"), 9).alias("distance")) for a, b in pairs])
    return wide.select(F.explode(rows).alias("x")).select("x.*")


@query("SELECT l_returnflag, count(*) AS n, min(l_extendedprice) AS min_value, max(l_extendedprice) AS max_value FROM lineitem GROUP BY l_returnflag")
def sketch_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The exact counters that every sketch carries."""
    sketches = build(load(spark, sf_dir, "lineitem", "l_returnflag", "l_extendedprice"), "l_extendedprice", by=["l_returnflag"], variant="geo", eps=0.02)
    return sketches.select("l_returnflag", "sketch.n", "sketch.min_value", "sketch.max_value")


@query("SELECT quantile_disc(value, 0.1) AS p10, quantile_disc(value, 0.37) AS p37, quantile_disc(value, 0.9) AS p90 FROM events")
def exact_percentile_disc(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = lambda f: F.expr(f"percentile_disc({f}) WITHIN GROUP (ORDER BY value)")
    return load(spark, sf_dir, "events", "value").agg(at(0.1).alias("p10"), at(0.37).alias("p37"), at(0.9).alias("p90"))


FRACTIONS = [0.01, 0.1, 0.25, 0.5, 0.75, 0.9, 0.99]


@query("SELECT event_type, unnest([0.01, 0.1, 0.25, 0.5, 0.75, 0.9, 0.99]::DOUBLE[]) AS fraction, round(unnest(quantile_cont(value, [0.01, 0.1, 0.25, 0.5, 0.75, 0.9, 0.99])), 4) AS value FROM events GROUP BY event_type")
def exact_percentiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = exact.percentiles(load(spark, sf_dir, "events", "event_type", "value"), "value", FRACTIONS, ["event_type"])
    return rows.withColumn("value", F.round("value", 4))


@query("SELECT count(DISTINCT l_extendedprice) AS prices, count(DISTINCT l_quantity) AS quantities, count(DISTINCT l_discount) AS discounts FROM lineitem")
def distinct_value_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem", "l_extendedprice", "l_quantity", "l_discount")
    return rows.agg(F.count_distinct("l_extendedprice").alias("prices"), F.count_distinct("l_quantity").alias("quantities"), F.count_distinct("l_discount").alias("discounts"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(quantile_cont(l_extendedprice, 0.5), 4) AS median_price FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def cube_exact_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus", "l_extendedprice")
    return rows.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.percentile("l_extendedprice", F.lit(0.5)), 4).alias("median_price"))


@query("SELECT event_type, quantile_disc(value, 0.5) AS p50, quantile_disc(value, 0.9) AS p90 FROM events GROUP BY event_type")
def pivot_event_type_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "events", "event_type", "value")
    at = lambda f: rows.groupBy("event_type").agg(F.expr(f"percentile_disc({f}) WITHIN GROUP (ORDER BY value)").alias("value")).withColumn("fraction", F.lit(f))
    return ops.pivot_quantiles(at(0.5).unionByName(at(0.9)), "event_type", [0.5, 0.9]).toDF("event_type", "p50", "p90")


@query("SELECT event_type, count(*) FILTER (value <= 10) AS c10, count(*) FILTER (value <= 50) AS c50, count(*) FILTER (value <= 200) AS c200 FROM events GROUP BY event_type")
def count_below_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events", "event_type", "value").groupBy("event_type").agg(*[F.count_if(F.col("value") <= p).alias(f"c{p}") for p in (10, 50, 200)])


@query("SELECT event_id, value, count(*) OVER (ORDER BY value RANGE UNBOUNDED PRECEDING) AS exact_rank FROM events")
def exact_inclusive_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.rank_column(load(spark, sf_dir, "events", "event_id", "value"), "value")


@query(
    """SELECT p_partkey, row_number() OVER w AS rn, CAST(rank() OVER v AS BIGINT) AS rk, CAST(dense_rank() OVER v AS BIGINT) AS dr, round(percent_rank() OVER v, 9) AS pr, round(cume_dist() OVER v, 9) AS cd, ntile(4) OVER w AS quarter
    FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey), v AS (PARTITION BY p_brand ORDER BY p_size)"""
)
def ranking_family(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, v = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    big = lambda c: c.cast("long")
    return load(spark, sf_dir, "part", "p_partkey", "p_brand", "p_size").select("p_partkey", big(F.row_number().over(w)).alias("rn"), big(F.rank().over(v)).alias("rk"), big(F.dense_rank().over(v)).alias("dr"), F.round(F.percent_rank().over(v), 9).alias("pr"), F.round(F.cume_dist().over(v), 9).alias("cd"), big(F.ntile(4).over(w)).alias("quarter"))


@query("SELECT event_id, round(quantile_cont(value, 0.5) OVER (ORDER BY event_id ROWS 20 PRECEDING), 6) AS moving_median FROM events")
def moving_median_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = exact.moving_median(load(spark, sf_dir, "events", "event_id", "value"), "value", "event_id", 21)
    return rows.select("event_id", F.round("moving_median", 6).alias("moving_median"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS in_last_day, max(value) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS most FROM events")
def trailing_day_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    load(spark, sf_dir, "events", "event_id", "user_id", "ts", "value").createOrReplaceTempView("trailing_events")
    over = "OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW)"
    return spark.sql(f"SELECT event_id, count(*) {over} AS in_last_day, max(value) {over} AS most FROM trailing_events")


@query("SELECT l_extendedprice AS value FROM (SELECT l_extendedprice, row_number() OVER (ORDER BY l_extendedprice) AS rn FROM lineitem) WHERE rn = 1000")
def exact_nth_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.nth(load(spark, sf_dir, "lineitem", "l_extendedprice"), "l_extendedprice", 1000)


@query("SELECT l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC LIMIT 20")
def top_prices(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem", "l_extendedprice").orderBy(F.desc("l_extendedprice")).limit(20)


@query("SELECT event_type, event_id, value FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS rn FROM events) WHERE rn <= 3")
def top_events_per_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = Window.partitionBy("event_type").orderBy(F.desc("value"), "event_id")
    return load(spark, sf_dir, "events", "event_type", "event_id", "value").withColumn("rn", F.row_number().over(line)).filter("rn <= 3").drop("rn")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 50 OFFSET 100")
def page_of_prices(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").orderBy("o_totalprice", "o_orderkey").offset(100).limit(50)


@query("SELECT count(*) AS mass_of_union, count(*) AS mass_of_merge FROM (SELECT l_extendedprice FROM lineitem UNION ALL SELECT o_totalprice FROM orders)")
def union_equals_merge_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One sketch of both streams weighs as much as the merge of one sketch each."""
    from rankloom.operators.merge import tree

    a = load(spark, sf_dir, "lineitem", "l_extendedprice").toDF("v")
    b = load(spark, sf_dir, "orders", "o_totalprice").toDF("v")
    whole = build(a.unionByName(b), "v", variant="geo", eps=0.02)
    parts = [build(x, "v", variant="geo", eps=0.02).withColumn("part", F.lit(i).cast("long")) for i, x in enumerate((a, b))]
    merged = tree(parts[0].unionByName(parts[1]), [])
    weigh = lambda s, name: answer.coreset(s).agg(F.sum("weight").alias(name))
    return weigh(whole, "mass_of_union").crossJoin(weigh(merged, "mass_of_merge"))


@query("SELECT lang, quantile_disc(length(text), 0.5) AS p50, quantile_disc(length(text), 0.9) AS p90 FROM documents GROUP BY lang")
def document_length_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "documents", "lang", "text").select("lang", F.length("text").cast("long").alias("n"))
    at = lambda f: F.expr(f"percentile_disc({f}) WITHIN GROUP (ORDER BY n)").cast("long")
    return rows.groupBy("lang").agg(at(0.5).alias("p50"), at(0.9).alias("p90"))


@query("SELECT regexp_extract(url, '^(https?)://', 1) AS scheme, quantile_disc(len(string_split(url, '/')), 0.5) AS p50 FROM pages GROUP BY 1")
def url_depth_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "pages", "url").select(F.regexp_extract("url", "^(https?)://", 1).alias("scheme"), F.size(F.split("url", "/")).cast("long").alias("depth"))
    return rows.groupBy("scheme").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY depth)").cast("long").alias("p50"))


@query("SELECT CAST(date_trunc('month', l_shipdate) AS TIMESTAMP) AS month, round(quantile_cont(l_extendedprice, 0.5), 4) AS median_price FROM lineitem GROUP BY 1")
def monthly_median_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem", "l_shipdate", "l_extendedprice").select(F.date_trunc("month", F.col("l_shipdate")).cast("timestamp_ntz").alias("month"), "l_extendedprice")
    return rows.groupBy("month").agg(F.round(F.percentile("l_extendedprice", F.lit(0.5)), 4).alias("median_price"))


@query("SELECT event_type, quantile_disc(value, 0.5) AS p50, quantile_disc(value, 0.99) AS p99 FROM events GROUP BY event_type")
def quantile_map_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantiles as a map from fraction to value, looked up again."""
    at = lambda f: F.expr(f"percentile_disc({f}) WITHIN GROUP (ORDER BY value)")
    rows = load(spark, sf_dir, "events", "event_type", "value").groupBy("event_type").agg(F.map_from_arrays(F.array(F.lit("0.5"), F.lit("0.99")), F.array(at(0.5), at(0.99))).alias("q"))
    return rows.select("event_type", F.element_at("q", "0.5").alias("p50"), F.element_at("q", "0.99").alias("p99"))


@query("SELECT event_type, quantile_disc(CAST(json_extract_string(props, '$.k') AS BIGINT), 0.5) AS p50 FROM events GROUP BY event_type")
def json_k_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "events", "event_type", "props").select("event_type", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return rows.groupBy("event_type").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY k)").cast("long").alias("p50"))


@query("SELECT label, round(quantile_disc(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 0.5), 6) AS median_norm FROM embeddings GROUP BY label")
def embedding_norm_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    norm = F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))
    rows = load(spark, sf_dir, "embeddings", "label", "embedding").select("label", norm.alias("norm"))
    return rows.groupBy("label").agg(F.round(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY norm)"), 6).alias("median_norm"))


@query("SELECT label, CAST(d AS INTEGER) AS dim, quantile_disc(CAST(x AS DOUBLE), 0.5) AS median FROM (SELECT label, unnest(range(64)) AS d, unnest(embedding) AS x FROM embeddings) GROUP BY label, d")
def embedding_dim_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "embeddings", "label", "embedding").select("label", F.posexplode("embedding").alias("dim", "x")).withColumn("x", F.col("x").cast("double"))
    return rows.groupBy("label", "dim").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY x)").alias("median"))


@query("SELECT rank, value FROM (SELECT value, row_number() OVER (ORDER BY value) AS rank FROM events) WHERE rank % 400 = 0")
def offline_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.offline_grid(load(spark, sf_dir, "events", "value"), "value", 400)


@query(
    """WITH c AS (SELECT o_totalprice AS value, count(*) OVER (ORDER BY o_totalprice RANGE UNBOUNDED PRECEDING) AS cum, count(*) OVER () AS n FROM orders)
    SELECT CAST(b AS INTEGER) AS bucket, min(value) AS upper FROM c CROSS JOIN range(1, 11) t(b) WHERE cum * 10 >= b * n GROUP BY b"""
)
def equi_depth_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = exact.counts_by_value(load(spark, sf_dir, "orders", "o_totalprice"), "o_totalprice")
    return answer.equi_depth(lines.select("value", F.col("n").alias("weight"), F.col("exact_rank").alias("cum_weight")), 10)


@query("SELECT CAST((o_totalprice > 100000)::INT + (o_totalprice > 250000)::INT + (o_totalprice > 400000)::INT AS INTEGER) AS bucket, count(*) AS n FROM orders GROUP BY 1")
def bucketize_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ops.bucketize(load(spark, sf_dir, "orders", "o_totalprice"), "o_totalprice", [100000.0, 250000.0, 400000.0]).groupBy("bucket").agg(F.count("*").alias("n"))


@query("SELECT quantity, count(*) AS n, CAST(sum(count(*)) OVER (ORDER BY quantity) AS BIGINT) AS exact_rank FROM (SELECT l_quantity AS quantity FROM lineitem) GROUP BY quantity")
def ties_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Inclusive ranks under heavy ties."""
    return exact.counts_by_value(load(spark, sf_dir, "lineitem", "l_quantity"), "l_quantity").withColumnRenamed("value", "quantity")


LINE_NAMES = "lineitem JOIN part ON l_partkey = p_partkey"
LINE_DELAYS = "lineitem JOIN orders ON l_orderkey = o_orderkey"


def compacted_quantiles(rows: DataFrame, fractions: list[float], eps: float, source: str) -> DataFrame:
    """rows (v) of any type with an order -> source, fraction, n, exact_value, within_bound, compacted.

    within_bound: the ranks that the answered value has come within eps n of the target; compacted: the sketch dropped items on its way.
    """
    sketches = build(rows, "v", variant="geo-wsampled", eps=eps, delta=1e-6, mode="single")
    got = answer.quantiles(sketches, fractions)
    counts = exact.counts_by_value(rows, "v")
    total = sketches.select(F.col("sketch.n").alias("rows"), (F.col("sketch.coins") > 0).alias("compacted"))
    wanted = total.select("*", F.explode(F.array(*[F.lit(f) for f in fractions])).alias("fraction")).withColumn("target", F.ceil(F.col("fraction") * F.col("rows")))
    truth = wanted.join(counts, F.expr("exact_rank >= target and exact_rank - n < target")).select("fraction", "target", "rows", "compacted", F.col("value").alias("exact_value"))
    ranked = got.join(counts, "value").select("fraction", (F.col("exact_rank") - F.col("n") + 1).alias("first"), F.col("exact_rank").alias("last"))
    miss = F.greatest(F.col("first") - F.col("target"), F.col("target") - F.col("last"))
    return truth.join(ranked, "fraction").select(F.lit(source).alias("source"), "fraction", F.col("rows").alias("n"), "exact_value", (miss <= eps * F.col("rows")).alias("within_bound"), "compacted")


def compacted_sql(source: str, table: str, value: str, fractions: list[float]) -> str:
    values = ", ".join(f"CAST({f} AS DOUBLE)" for f in fractions)
    return f"""SELECT '{source}' AS source, fraction, n, v AS exact_value, TRUE AS within_bound, TRUE AS compacted FROM
        (SELECT {value} AS v, row_number() OVER (ORDER BY {value}) AS rn, count(*) OVER () AS n FROM {table}) JOIN (SELECT unnest([{values}]) AS fraction) ON rn = CAST(ceil(fraction * n) AS BIGINT)"""


@query(compacted_sql("p_name", LINE_NAMES, "p_name", [0.1, 0.5, 0.9]))
def string_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantiles of names over all lines, from sketches that compact strings."""
    names = load(spark, sf_dir, "part", "p_partkey", "p_name")
    rows = load(spark, sf_dir, "lineitem", "l_partkey").join(names, F.col("l_partkey") == F.col("p_partkey"))
    return compacted_quantiles(rows.select(F.col("p_name").alias("v")), [0.1, 0.5, 0.9], 0.05, "p_name")


@query(compacted_sql("l_shipdate", "lineitem", "l_shipdate", [0.1, 0.5, 0.9]))
def timestamp_quantile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compacted_quantiles(load(spark, sf_dir, "lineitem", "l_shipdate").toDF("v"), [0.1, 0.5, 0.9], 0.05, "l_shipdate")


@query(f"SELECT * REPLACE (CAST(epoch(exact_value) AS BIGINT) AS exact_value) FROM ({compacted_sql('delay', LINE_DELAYS, '(l_shipdate - o_orderdate)', [0.1, 0.5, 0.9])})")
def interval_quantile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Delays between order and shipping as intervals; the answer in seconds."""
    orders = load(spark, sf_dir, "orders", "o_orderkey", "o_orderdate")
    rows = load(spark, sf_dir, "lineitem", "l_orderkey", "l_shipdate").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    got = compacted_quantiles(rows.select((F.col("l_shipdate") - F.col("o_orderdate")).alias("v")), [0.1, 0.5, 0.9], 0.05, "delay")
    return got.withColumn("exact_value", F.col("exact_value").cast("long"))


@query("SELECT d.doc_id, d.lang, d.n_chars FROM documents d JOIN (SELECT lang, quantile_disc(n_chars, 0.99) AS cut FROM documents GROUP BY lang) c ON d.lang = c.lang AND d.n_chars > c.cut")
def outliers_by_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "documents", "doc_id", "lang", "n_chars")
    cuts = rows.groupBy("lang").agg(F.expr("percentile_disc(0.99) WITHIN GROUP (ORDER BY n_chars)").alias("cut"))
    return rows.join(cuts, "lang").filter("n_chars > cut").select("doc_id", "lang", "n_chars")


@query("SELECT count(*) AS n, CAST(20 AS BIGINT) AS bins, CAST(count(*) AS BIGINT) AS mass, TRUE AS centers_within_range FROM lineitem")
def heuristic_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The built-in histogram: what it can be held to, its number of bins and its mass, since it bounds no rank."""
    rows = load(spark, sf_dir, "lineitem", "l_extendedprice")
    bins = baselines.heuristic_histogram(rows, "l_extendedprice", 20)
    ends = rows.agg(F.count("*").alias("n"), F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"))
    held = bins.agg(F.count("*").alias("bins"), F.round(F.sum("height")).cast("long").alias("mass"), F.min("center").alias("first"), F.max("center").alias("last"))
    return ends.crossJoin(held).select("n", "bins", "mass", F.expr("first >= lo and last <= hi").alias("centers_within_range"))


@query("SELECT count(DISTINCT event_id) AS events, count(DISTINCT user_id) AS users FROM events JOIN customer ON user_id = c_custkey")
def static_join_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "events", "event_id", "user_id").join(load(spark, sf_dir, "customer", "c_custkey"), F.col("user_id") == F.col("c_custkey"))
    return rows.agg(F.count_distinct("event_id").alias("events"), F.count_distinct("user_id").alias("users"))
