"""Chat formatting with collapse of cumulative snapshots.

Logs often hold a conversation again and again, each time with the turns so
far. Every turn gets a rolling hash of the turns up to it; a conversation whose
last hash is an inner hash of another one is a prefix of that one and goes. Of
equal conversations the smallest id stays, a null one only where no other is. What
remains is rendered.

Edge cases: turns order by (turn, role, text), so that ties and repeated rows
have one result; a null role or text is empty; a row without conv_id is a
conversation of its own (equal such rows are one); an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

PREFIX = ["pos", "s0", "s1", "s2", "s3"]


def rolling_prefixes(turns: DataFrame) -> DataFrame:
    """conversations -> turns with pos and the rolling 128-bit hash of the turns up to it.

    The hash of a prefix is a sum of position-bound turn hashes, kept in four
    32-bit limbs with room for 2**31 turns, so a window keeps it running.
    """
    t = turns.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    t = t.withColumn("lone", F.when(F.col("conv_id").isNull(), F.xxhash64("turn", "role", "text")).otherwise(F.lit(0)))
    order = Window.partitionBy("conv_id", "lone").orderBy("turn", "role", "text")
    t = t.withColumn("pos", F.when(F.col("conv_id").isNull(), F.lit(1)).otherwise(F.row_number().over(order)))
    t = t.withColumn("h0", F.xxhash64(F.lit(17), "pos", "role", "text")).withColumn("h1", F.xxhash64(F.lit(71), "text", "role", "pos"))
    run = order.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    limbs = [F.shiftrightunsigned("h0", 32), F.col("h0").bitwiseAND(F.lit(0xFFFFFFFF)), F.shiftrightunsigned("h1", 32), F.col("h1").bitwiseAND(F.lit(0xFFFFFFFF))]
    t = t.select("*", *[F.when(F.col("conv_id").isNull(), x).otherwise(F.sum(x).over(run)).alias(f"s{i}") for i, x in enumerate(limbs)])
    whole = Window.partitionBy("conv_id", "lone")
    return t.withColumn("n_turns", F.when(F.col("conv_id").isNull(), F.lit(1)).otherwise(F.count("*").over(whole))).drop("h0", "h1")


def maximal_conversations(prefixes: DataFrame) -> DataFrame:
    """rolling_prefixes() -> conv_id, lone, n_copies of the conversations that prefix no other."""
    inner = prefixes.filter("pos < n_turns").select(*PREFIX).distinct()
    last = prefixes.filter("pos = n_turns").select("conv_id", "lone", *PREFIX)
    kept = last.groupBy(*PREFIX).agg(F.min(F.struct(F.col("conv_id").isNull().alias("unnamed"), "conv_id", "lone")).alias("first"), F.count("*").alias("n_copies"))
    return kept.join(inner, PREFIX, "left_anti").select("first.conv_id", "first.lone", "n_copies")


def render(prefixes: DataFrame, kept: DataFrame) -> DataFrame:
    """The kept conversations as conv_id, n_turns, n_copies, rendered."""
    mine = prefixes.select("conv_id", "lone", "pos", "role", "text")
    lines = mine.join(kept.withColumnRenamed("conv_id", "c").withColumnRenamed("lone", "l"), F.expr("conv_id <=> c and lone = l")).drop("c", "l")
    turns = F.sort_array(F.array_distinct(F.collect_list(F.struct("pos", "role", "text"))))
    out = lines.groupBy("conv_id", "lone", "n_copies").agg(turns.alias("turns"))
    said = F.transform("turns", lambda x: F.concat(F.lit("<|"), x["role"], F.lit("|>\n"), x["text"], F.lit("<|end|>\n")))
    return out.select("conv_id", F.size("turns").cast("long").alias("n_turns"), "n_copies", F.array_join(said, "").alias("rendered"))


def format_chats(turns: DataFrame) -> DataFrame:
    """op4: conversations -> conv_id, n_turns, n_copies, rendered of the maximal ones."""
    prefixes = rolling_prefixes(turns)
    return render(prefixes, maximal_conversations(prefixes))
