"""Sketches of live streams: panes, their merges, and a continuous stateful sketch."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from rankloom.functions.coins import scope_of
from rankloom.operators.build import build
from rankloom.operators.kernel import Sketch
from rankloom.operators.merge import tree
from rankloom.operators.state import Codec, from_row, to_row
from rankloom.plans.params import Plan


def file_stream(spark: SparkSession, path: str, schema: T.StructType, per_trigger: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(schema)
    return (reader.option("maxFilesPerTrigger", per_trigger) if per_trigger else reader).parquet(path)


def rate_stream(spark: SparkSession, rows_per_second: int, partitions: int = 1) -> DataFrame:
    """value, timestamp at a steady rate: a source for load tests."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).option("numPartitions", partitions).load()


def session_sketches(df: DataFrame, time: str, gap: str, value: str, by: list[str], **options: Any) -> DataFrame:
    """Batch rows -> by..., began, sketch of every session: rows of a key that follow each other within gap."""
    line = Window.partitionBy(*by).orderBy(time)
    new = (F.col(time) - F.lag(time).over(line) >= F.expr(f"INTERVAL {gap}")) | F.lag(time).over(line).isNull()
    opened = df.withColumn("_new", F.when(new, F.col(time)))
    began = F.last("_new", ignorenulls=True).over(line.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return build(opened.withColumn("began", began), value, by=[*by, "began"], **options)


def with_lateness(df: DataFrame, column: str, delay: str) -> DataFrame:
    """Watermark on a time column; one without zone is taken as UTC first, since watermarks need a zone."""
    return df.withColumn(column, F.col(column).cast("timestamp")).withWatermark(column, delay)


def pane_sketches(df: DataFrame, time: str, width: str, value: str, by: list[str] | None = None, **options: Any) -> DataFrame:
    """Batch rows -> pane, by..., sketch."""
    keyed = df.withColumn("pane", F.window(F.col(time).cast("timestamp"), width)["start"])
    return build(keyed, value, by=["pane", *(by or [])], **options)


def slide(panes: DataFrame, panes_each: int, pane_seconds: int, by: list[str] | None = None) -> DataFrame:
    """pane, by..., sketch -> window_end, by..., sketch of every window of panes_each panes, by merging panes."""
    ends = F.sequence(F.lit(1), F.lit(panes_each))
    rows = panes.withColumn("_k", F.explode(ends)).withColumn("window_end", F.timestamp_seconds(F.unix_timestamp("pane") + F.col("_k") * pane_seconds))
    rows = rows.withColumn("part", F.unix_timestamp("pane"))
    return tree(rows.select("window_end", *(by or []), "part", "sketch"), ["window_end", *(by or [])])


def compact_panes(stored: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Several sketches of one pane (late data adds more) -> one each."""
    keys = ["pane", *(by or [])]
    return tree(stored.withColumn("part", F.xxhash64("batch_id", *keys)).select(*keys, "part", "sketch"), keys)


def pane_sink(path: str, time: str, width: str, value: str, by: list[str] | None = None, **options: Any) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: sketches of a micro-batch, one folder for each batch id, so that a replay overwrites itself."""

    def store(batch: DataFrame, batch_id: int) -> None:
        made = pane_sketches(batch, time, width, value, by, **options).withColumn("batch_id", F.lit(batch_id).cast("long"))
        made.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return store


def stored_panes(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.option("recursiveFileLookup", "true").parquet(path)


def continuous(df: DataFrame, key: str, value: str, plan: Plan, seed: int = 42) -> DataFrame:
    """key, n, median after every trigger, from one growing sketch for each key in the state store."""
    value_type, key_type = df.schema[value].dataType, df.schema[key].dataType
    out = T.StructType([T.StructField(key, key_type), T.StructField("n", T.LongType()), T.StructField("median", value_type)])
    state = T.StructType([T.StructField("row", T.StringType())])

    def grow(k: tuple, batches: Iterator[pd.DataFrame], held: GroupState) -> Iterator[pd.DataFrame]:
        import json

        codec = Codec(value_type)
        scope = scope_of("state", k)
        if held.exists:
            s = from_row(json.loads(held.get[0]), codec, scope)
        else:
            s = Sketch(plan, seed, scope, 0, codec.dtype)
        for b in batches:
            column = b[value].dropna().to_numpy()
            s.insert(column.astype(codec.dtype), int(b[value].isna().sum()))
        held.update((json.dumps(to_row(s, codec)),))
        yield pd.DataFrame({key: [k[0]], "n": [s.n], "median": [s.value_at_rank(max(1, (s.n + 1) // 2))]})

    return df.select(key, value).groupBy(key).applyInPandasWithState(grow, out, state, "update", GroupStateTimeout.NoTimeout)


def run_once(df: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str) -> StreamingQuery:
    """Reads all that is there in micro-batches, hands each to the sink, ends."""
    query = df.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return query
