"""What the operators of this subpackage share: shared-folder tables and ranks."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; where that is unset (one machine), a temporary one."""
    if spark.sparkContext.getCheckpointDir() is None:
        chosen = spark.conf.get("spark.checkpoint.dir", None)
        if not chosen:
            master = spark.sparkContext.master
            if master != "local" and not master.startswith("local["):
                raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
            chosen = tempfile.mkdtemp(prefix="checkpoint-")
            atexit.register(shutil.rmtree, chosen, ignore_errors=True)
        spark.sparkContext.setCheckpointDir(chosen)
    return spark.sparkContext.getCheckpointDir()


ARROW_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"


def forget_shuffles(spark: SparkSession) -> None:
    """Has the driver collect garbage, so that shuffle files of plans that nobody holds any more go."""
    gc.collect()
    spark._jvm.System.gc()


class Scratch:
    """Working tables in one folder of the shared folder, dropped together."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark, self.path = spark, f"{shared_folder(spark)}/tables/{label}-{uuid.uuid4().hex}"

    def written(self, df: DataFrame, label: str) -> DataFrame:
        """df after a round trip through Parquet.

        Kernels on the way get batches of 2,048 rows, so that long texts fit. Cuts lineage: a lost executor costs the tasks that read, not the work
        before. Its size is known, so a small one is broadcast in joins.
        """
        path = f"{self.path}/{label}-{uuid.uuid4().hex[:8]}"
        rows = self.spark.conf.get(ARROW_ROWS)
        try:
            self.spark.conf.set(ARROW_ROWS, min(int(rows), 2048))
            df.write.parquet(path)
        finally:
            self.spark.conf.set(ARROW_ROWS, rows)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self) -> None:
        """Deletes the tables, and has the driver collect garbage so that shuffle files of what made them go as well."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
        forget_shuffles(self.spark)


def written(df: DataFrame, label: str) -> DataFrame:
    """df after a round trip through Parquet in the shared folder, where it stays."""
    return Scratch(df.sparkSession, label).written(df, label)


def load(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def gapless_rank(df: DataFrame, key: Column | None, part: str | None, out: str, buckets: int = 512) -> DataFrame:
    """Adds out: 0-based rank within part (or overall), ordered by a hash of key.

    Counts of hash buckets give each bucket its offset, so no task ever sorts
    more than one bucket of one part. Rows with equal key rank in any order.
    """
    parts = [F.col(part)] if part else [F.lit(0)]
    hashed = df.withColumn("_p", parts[0]).withColumn("_h", F.xxhash64(F.lit(out), key)).withColumn("_b", F.pmod("_h", F.lit(buckets)))
    counts = hashed.groupBy("_p", "_b").agg(F.count("*").alias("_c"))
    before = Window.partitionBy("_p").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("_p", "_b", F.coalesce(F.sum("_c").over(before), F.lit(0)).alias("_o"))
    inside = F.row_number().over(Window.partitionBy("_p", "_b").orderBy("_h"))
    return (
        hashed.withColumn("_i", inside)
        .join(offsets, (hashed["_p"].eqNullSafe(offsets["_p"])) & (hashed["_b"] == offsets["_b"]))
        .withColumn(out, F.col("_o") + F.col("_i") - 1)
        .select(*df.columns, out)
    )
