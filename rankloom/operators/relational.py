"""Compactions as relational operators: windows and filters only, replayable in SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rankloom.functions.coins import policy_coin


def compact_round(df: DataFrame, block: str, order: list[str], weight: str, level: int, seed: int, policy: str = "fair", holdback: bool = True) -> DataFrame:
    """One compaction of every block: df with column held (true: kept back at its weight).

    Survivors have doubled weight. One shuffle by block, at most a row of a block
    more than half of it stays. With an odd number of rows the largest is held
    back; without holdback it takes part like the others.
    """
    line = Window.partitionBy(block).orderBy(*order)
    rows = df.withColumn("_rn", F.row_number().over(line)).withColumn("_n", F.count("*").over(Window.partitionBy(block)))
    held = (F.col("_n") % 2 == 1) & (F.col("_rn") == F.col("_n")) if holdback else F.lit(False)
    odd = policy_coin(policy, seed, F.lit(level), F.col(block))
    chosen = F.when(odd, F.col("_rn") % 2 == 1).otherwise(F.col("_rn") % 2 == 0)
    rows = rows.withColumn("held", held).filter(F.col("held") | chosen)
    return rows.withColumn(weight, F.when(F.col("held"), F.col(weight)).otherwise(F.col(weight) * 2)).drop("_rn", "_n")


def compact_tree(df: DataFrame, order: list[str], block: Column, rounds: int, seed: int = 7, policy: str = "fair") -> DataFrame:
    """df -> order columns, weight, height: blocks are compacted and paired up, rounds times.

    Round r moves n / 2**(r - 1) rows. Items held back keep their weight and leave
    the tree. Any rank moves by the number of blocks times rounds at most.
    """
    rows = df.select(*order, block.cast("long").alias("block"), F.lit(1).cast("long").alias("weight"))
    aside = None
    for r in range(1, rounds + 1):
        done = compact_round(rows, "block", order, "weight", r, seed, policy)
        stay = done.filter("held").select(*order, "weight", F.lit(r).cast("long").alias("height"))
        aside = stay if aside is None else aside.unionByName(stay)
        rows = done.filter("not held").select(*order, F.expr("block div 2").alias("block"), "weight")
    top = rows.select(*order, "weight", F.lit(rounds + 1).cast("long").alias("height"))
    return top if aside is None else top.unionByName(aside)


def compact_array(values: Column, odd: Column) -> Column:
    """One compaction of a sorted array of even length, without a window."""
    return F.filter(values, lambda x, i: F.when(odd, i % 2 == 0).otherwise(i % 2 == 1))


def tree_sql(source: str, value: str, block: str, rounds: int, seed: int = 7, policy: str = "fair") -> str:
    """compact_tree() of one value column as common table expressions for DuckDB: the last one is coreset."""
    parity = {
        "fair": "instr('13579bdf', substr(md5('{seed}|{r}|' || block), 1, 1)) > 0",
        "fixed_odd": "TRUE",
        "fixed_even": "FALSE",
        "alternate": "block % 2 = 0",
    }[policy]
    parts = [f"t0 AS (SELECT {value} AS value, CAST({block} AS BIGINT) AS block, CAST(1 AS BIGINT) AS weight FROM {source})"]
    leave = []
    for r in range(1, rounds + 1):
        odd = parity.format(seed=seed, r=r)
        parts.append(f"r{r} AS (SELECT *, row_number() OVER (PARTITION BY block ORDER BY value) AS rn, count(*) OVER (PARTITION BY block) AS n FROM t{r - 1})")
        parts.append(f"t{r} AS (SELECT value, block // 2 AS block, weight * 2 AS weight FROM r{r} WHERE NOT (n % 2 = 1 AND rn = n) AND (rn % 2 = 1) = ({odd}))")
        leave.append(f"SELECT value, weight, CAST({r} AS BIGINT) AS height FROM r{r} WHERE n % 2 = 1 AND rn = n")
    leave.append(f"SELECT value, weight, CAST({rounds + 1} AS BIGINT) AS height FROM t{rounds}")
    parts.append("coreset AS (" + " UNION ALL ".join(leave) + ")")
    return "WITH " + ",\n".join(parts)
