"""Queries over live streams: the events table read as a file stream."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rankloom.functions import answer
from rankloom.operators import measure
from rankloom.operators.merge import tree
from rankloom.plans.params import plan
from rankloom.sources.io import load, shared_folder
from rankloom.streaming import stream
from rankloom.workloads.registry import query
from rankloom.workloads.sketches import DELTA, VALUE_PROBES, literals

SCHEMA = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])
DAY = 86_400


def work_folder(spark: SparkSession) -> str:
    """A new folder that driver and executors share, or a temporary one on one machine."""
    return f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events file as a stream; the folder is watched for this file only."""
    return spark.readStream.schema(SCHEMA).option("pathGlobFilter", "events.parquet").parquet(sf_dir)


def stored_day_panes(spark: SparkSession, sf_dir: str, by: list[str] | None = None) -> DataFrame:
    folder = work_folder(spark)
    sink = stream.pane_sink(f"{folder}/panes", "ts", "1 day", "value", by, variant="banded", eps=0.02, delta=DELTA)
    stream.run_once(event_stream(spark, sf_dir), sink, f"{folder}/checkpoint")
    return stream.compact_panes(stream.stored_panes(spark, f"{folder}/panes"), by)


@query("SELECT date_trunc('day', ts)::DATE AS day, count(*) AS n, quantile_disc(value, 0.5) AS exact_median, TRUE AS within_bound FROM events GROUP BY 1")
def stream_tumbling_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily medians from panes that micro-batches stored."""
    panes = stored_day_panes(spark, sf_dir)
    got = answer.median(panes, ["pane"]).select(F.to_date("pane").alias("day"), F.col("value").alias("got"))
    rows = load(spark, sf_dir, "events", "ts", "value").withColumn("day", F.to_date("ts"))
    truth = rows.join(got, "day").groupBy("day").agg(F.count("*").alias("n"), F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY value)").alias("exact_median"), F.count_if(F.col("value") <= F.col("got")).alias("rank"))
    return truth.select("day", "n", "exact_median", (F.abs(F.col("rank") - F.col("n") / 2) <= 0.02 * F.col("n") + 1).alias("within_bound"))


@query(f"SELECT date_trunc('day', ts)::DATE + CAST(k AS INTEGER) AS window_end, probe, count(*) FILTER (value <= probe) AS exact_rank, TRUE AS within_bound FROM events CROSS JOIN range(1, 8) t(k) CROSS JOIN {literals(VALUE_PROBES)} GROUP BY 1, 2")
def sliding_week_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sliding weeks by merging seven daily panes each; no row is replicated."""
    from rankloom.streaming.stream import pane_sketches, slide

    rows = load(spark, sf_dir, "events", "ts", "value")
    weeks = slide(pane_sketches(rows, "ts", "1 day", "value", variant="banded", eps=0.02, delta=DELTA), 7, DAY)
    est = weeks.select(F.to_date("window_end").alias("window_end"), F.col("sketch.n").alias("n"), answer.points().alias("pts"), F.explode(F.array(*[F.lit(p) for p in VALUE_PROBES])).alias("probe"))
    est = est.select("window_end", "n", "probe", answer.rank(F.col("pts"), F.col("probe")).alias("est"))
    days = rows.withColumn("day", F.to_date("ts")).groupBy("day").agg(*[F.count_if(F.col("value") <= p).alias(f"c{i}") for i, p in enumerate(VALUE_PROBES)])
    flat = days.select("day", F.explode(F.array(*[F.struct(F.lit(p).alias("probe"), F.col(f"c{i}").alias("c")) for i, p in enumerate(VALUE_PROBES)])).alias("x")).select("day", "x.*")
    truth = flat.withColumn("window_end", F.explode(F.transform(F.sequence(F.lit(1), F.lit(7)), lambda k: F.date_add("day", k)))).groupBy("window_end", "probe").agg(F.sum("c").alias("exact_rank"))
    return est.join(truth, ["window_end", "probe"]).select("window_end", "probe", "exact_rank", (F.abs(F.col("est") - F.col("exact_rank")) <= 0.02 * F.col("n")).alias("within_bound"))


@query("SELECT event_type, count(*) AS n, TRUE AS within_bound FROM events GROUP BY event_type")
def stream_continuous_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One sketch for each event type in the state store, growing with every micro-batch."""
    folder = work_folder(spark)
    name = f"continuous_{uuid.uuid4().hex}"
    grown = stream.continuous(event_stream(spark, sf_dir), "event_type", "value", plan("geo", 0.02, DELTA))
    writer = grown.writeStream.format("memory").queryName(name).outputMode("update").option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True)
    writer.start().awaitTermination()
    got = spark.table(name).groupBy("event_type").agg(F.max("n").alias("n"), F.max_by("median", "n").alias("got"))
    rows = load(spark, sf_dir, "events", "event_type", "value")
    truth = rows.join(got.select("event_type", "got"), "event_type").groupBy("event_type").agg(F.count_if(F.col("value") <= F.col("got")).alias("rank"))
    return got.join(truth, "event_type").select("event_type", "n", (F.abs(F.col("rank") - F.col("n") / 2) <= 0.02 * F.col("n") + 1).alias("within_bound"))


@query(
    """WITH g AS (SELECT user_id, ts, value, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events),
    s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g)
    SELECT user_id, min(ts) AS began, count(*) AS n, max(value) AS most FROM s GROUP BY user_id, sid"""
)
def session_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions with a gap of 30 minutes."""
    rows = load(spark, sf_dir, "events", "user_id", "ts", "value").withColumn("at", F.col("ts").cast("timestamp"))
    return rows.groupBy("user_id", F.session_window("at", "30 minutes")).agg(F.min("ts").alias("began"), F.count("*").alias("n"), F.max("value").alias("most")).drop("session_window")


@query("SELECT count(*) AS n, count(DISTINCT event_id) AS events FROM events")
def stream_dedup_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Deduplication by id within the watermark, then one sketch of each batch: mass equals the number of events."""
    folder = work_folder(spark)
    rows = stream.with_lateness(event_stream(spark, sf_dir), "ts", "2 hours").dropDuplicatesWithinWatermark(["event_id"])
    sink = stream.pane_sink(f"{folder}/panes", "ts", "1 day", "value", variant="geo", eps=0.02, delta=DELTA)
    stream.run_once(rows, sink, f"{folder}/checkpoint")
    mass = measure.mass(answer.coreset(stream.compact_panes(stream.stored_panes(spark, f"{folder}/panes"))))
    ids = load(spark, sf_dir, "events", "event_id").agg(F.count_distinct("event_id").alias("events"))
    return mass.select(F.col("mass").alias("n")).crossJoin(ids)


@query(
    """WITH g AS (SELECT user_id, ts, value, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 1 DAY THEN 0 ELSE 1 END AS new FROM events),
    s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g)
    SELECT user_id, min(ts) AS began, count(*) AS n, quantile_disc(value, 0.5) AS median FROM s GROUP BY user_id, sid"""
)
def session_sketch_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sketch for each session with a gap of a day; sessions are shorter than its smallest level, so their medians are exact."""
    sessions = stream.session_sketches(load(spark, sf_dir, "events", "user_id", "ts", "value"), "ts", "1 DAY", "value", ["user_id"], variant="geo", eps=0.02)
    got = answer.median(sessions, ["user_id", "began"]).select("user_id", "began", F.col("value").alias("median"))
    return sessions.select("user_id", "began", "sketch.n").join(got, ["user_id", "began"])


@query("SELECT n_name, count(*) AS n, TRUE AS within_bound FROM events JOIN customer ON user_id = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def stream_static_join_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stream joined with tables at rest before it is sketched by nation."""
    folder = work_folder(spark)
    owners = load(spark, sf_dir, "customer", "c_custkey", "c_nationkey").join(F.broadcast(load(spark, sf_dir, "nation", "n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey"))
    rows = event_stream(spark, sf_dir).join(owners, F.col("user_id") == F.col("c_custkey"))
    sink = stream.pane_sink(f"{folder}/panes", "ts", "30 days", "value", ["n_name"], variant="geo", eps=0.02, delta=DELTA)
    stream.run_once(rows, sink, f"{folder}/checkpoint")
    panes = stream.stored_panes(spark, f"{folder}/panes").withColumn("part", F.xxhash64("batch_id", "pane"))
    merged = tree(panes.select("n_name", "part", "sketch"), ["n_name"])
    got = answer.median(merged, ["n_name"]).withColumnRenamed("value", "got")
    still = load(spark, sf_dir, "events", "user_id", "value").join(owners, F.col("user_id") == F.col("c_custkey")).join(got, "n_name")
    truth = still.groupBy("n_name").agg(F.count_if(F.col("value") <= F.col("got")).alias("upto"), F.count_if(F.col("value") < F.col("got")).alias("below"))
    judged = merged.select("n_name", "sketch.n").join(truth, "n_name")
    return judged.select("n_name", "n", ((F.col("upto") >= F.col("n") * 0.48 - 1) & (F.col("below") <= F.col("n") * 0.52 + 1)).alias("within_bound"))


@query("SELECT a.event_type AS one, b.event_type AS other, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY ALL")
def stream_stream_join_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of one user within an hour, from two streams with watermarks: state is kept for that hour only."""
    folder = work_folder(spark)
    side = lambda x: stream.with_lateness(event_stream(spark, sf_dir), "ts", "1 hour").select(*[F.col(c).alias(f"{x}_{c}") for c in ("user_id", "ts", "event_type")])
    both = side("a").join(side("b"), F.expr("a_user_id = b_user_id AND b_ts > a_ts AND b_ts <= a_ts + INTERVAL 1 HOUR"))

    def store(batch: DataFrame, batch_id: int) -> None:
        batch.groupBy(F.col("a_event_type").alias("one"), F.col("b_event_type").alias("other")).agg(F.count("*").alias("n")).write.mode("overwrite").parquet(f"{folder}/pairs/batch={batch_id}")

    stream.run_once(both, store, f"{folder}/checkpoint")
    return spark.read.option("recursiveFileLookup", "true").parquet(f"{folder}/pairs").groupBy("one", "other").agg(F.sum("n").alias("n"))
