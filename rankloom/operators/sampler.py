"""Block sampling as a filter: one row of every 2**height, chosen by a hash."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def digest_slot(seed: int, height: int, block: Column) -> Column:
    """A slot below 2**height from seven hex digits of an md5 digest; DuckDB gives the same."""
    digest = F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(str(height)), block.cast("string")))
    return F.conv(F.substring(digest, 1, 7), 16, 10).cast("long") % (1 << height)


def block_filter(df: DataFrame, height: int, seed: int = 7, ordinal: str | None = None) -> DataFrame:
    """df with one row of every full block and weight 2**height; narrow, within one stage.

    ordinal, a dense number of the rows, makes it repeatable anywhere. Without one
    the place in the scan's partition serves, which must be the same in a retry:
    filters go before. An incomplete last block of W rows yields one with chance W / 2**height.
    """
    size = 1 << height
    if ordinal is not None:
        block = F.expr(f"{ordinal} div {size}")
        return df.filter(F.col(ordinal) % size == digest_slot(seed, height, block)).withColumn("weight", F.lit(size).cast("long"))
    place = df.withColumn("_id", F.monotonically_increasing_id())
    part, at = F.shiftright("_id", 33), F.col("_id").bitwiseAND(F.lit((1 << 33) - 1))
    slot = F.pmod(F.xxhash64(F.lit(seed), part, F.shiftright(at, height)), F.lit(size))
    return place.filter(at.bitwiseAND(F.lit(size - 1)) == slot).withColumn("weight", F.lit(size).cast("long")).drop("_id")


def uniform_sample(df: DataFrame, key: str, m: int, seed: int = 7) -> DataFrame:
    """The m rows of smallest digest priority: a uniform sample that merges by taking the smallest again."""
    return df.withColumn("priority", F.md5(F.concat_ws("|", F.lit(str(seed)), F.col(key).cast("string")))).orderBy("priority", key).limit(m)


def stratified_sample(df: DataFrame, strata: list[str], key: str, m: int, seed: int = 7) -> DataFrame:
    """The m rows of smallest digest priority in every stratum; tasks keep m rows of each before anything is shuffled."""
    ranked = df.withColumn("priority", F.md5(F.concat_ws("|", F.lit(str(seed)), F.col(key).cast("string"))))
    line = Window.partitionBy(*strata).orderBy("priority", key)
    return ranked.withColumn("_place", F.row_number().over(line)).filter(F.col("_place") <= m).drop("_place")
