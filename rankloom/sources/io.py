"""Sources and sinks: tables, sketch stores and row counts without a scan."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T


def load(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    """A table of the folder; naming columns prunes the scan to them."""
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, path: str, fmt: str, schema: str | T.StructType, **options: str) -> DataFrame:
    """CSV, JSON, ORC, text or Parquet with a given schema (inferring one would read everything twice)."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir, which driver and executors share; a temporary one on a single machine only."""
    found = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if found is None:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        found = tempfile.mkdtemp(prefix="shared-")
    return found


def save_sketches(df: DataFrame, path: str, partition_by: list[str] | None = None, mode: str = "append") -> None:
    """Sketch rows as nested Parquet; later reads of some partitions touch these only."""
    writer = df.write.mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)


def load_sketches(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def estimated_rows(spark: SparkSession, path: str) -> int:
    """Rows of Parquet files from their footers: a count without columns reads nothing else."""
    return spark.read.parquet(path).count()


def drain(df: DataFrame) -> None:
    """Computes all rows and keeps none."""
    df.write.format("noop").mode("overwrite").save()
