"""Mixing sources to target weights by hierarchical budgeting.

A token budget runs down a domain - language - source tree. At each node the
children share it by weight; a child whose subtree cannot supply its share is
filled up and the shortage goes to its siblings, and only what a whole subtree
lacks reaches the level above. A leaf serves its allotment from seeded epochs:
every epoch is one permutation of the leaf's documents, and the allotment is a
token prefix of their concatenation.

Edge cases: a null language or source is the node "unknown"; a null text has
no tokens and rides along when the prefix passes it; rows of one doc_id
stand next to each other in an epoch and are taken one after the other; an empty table gives no rows; nodes
without a weight weigh default_weight, and nodes of weight 0 get nothing.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rankloom.llm.common import forget_shuffles, text_or_empty, written

WORD = r"[^\x20\x09-\x0D]+"
LEVELS = ("domain", "lang", "source")


def token_count(text: Column) -> Column:
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def weight_of(node: Column, weights: Mapping[str, int], default: int) -> Column:
    out = F.lit(default)
    for name, weight in sorted(weights.items()):
        out = F.when(node == name, F.lit(int(weight))).otherwise(out)
    return out.cast("long")


def share_among_children(nodes: DataFrame, parents: Sequence[str]) -> DataFrame:
    """nodes (parents..., name, supply, weight, budget) -> the same with grant.

    Weighted water-filling in closed form: children in order of supply / weight
    are full as long as the level that the rest could reach lies above them; the
    remaining ones split what is left by weight, in whole tokens without loss.
    """
    nodes = nodes.withColumn("_ratio", F.when(F.col("weight") > 0, F.col("supply").cast("double") / F.col("weight")).otherwise(F.lit(0.0)))
    nodes = nodes.withColumn("supply", F.when(F.col("weight") > 0, F.col("supply")).otherwise(F.lit(0).cast("long")))
    family = Window.partitionBy(*[F.col(p) for p in parents]) if parents else Window.partitionBy(F.lit(0))
    line = family.orderBy("_ratio", "name")
    earlier = line.rowsBetween(Window.unboundedPreceding, -1)
    sum0 = lambda c, w: F.coalesce(F.sum(c).over(w), F.lit(0).cast("long"))
    out = nodes.select(
        "*",
        F.least("budget", F.sum("supply").over(family)).alias("_total"),
        (F.sum("weight").over(family) - sum0("weight", earlier)).alias("_open"),
        sum0("supply", earlier).alias("_used"),
    )
    out = out.withColumn("_full", F.col("supply") * F.col("_open") <= (F.col("_total") - F.col("_used")) * F.col("weight"))
    loose = F.when(F.col("_full"), F.lit(0).cast("long")).otherwise(F.col("weight"))
    filled = F.when(F.col("_full"), F.col("supply")).otherwise(F.lit(0).cast("long"))
    out = out.select("*", (F.col("_total") - F.sum(filled).over(family)).alias("_left"), F.sum(loose).over(family).alias("_weights"), sum0(loose, earlier).alias("_from"))
    upto = lambda c: F.expr(f"_left * ({c}) div greatest(_weights, 1)")
    grant = F.when(F.col("_full"), F.col("supply")).otherwise(upto("_from + weight") - upto("_from"))
    return out.withColumn("grant", grant).drop("_ratio", "_total", "_open", "_used", "_full", "_left", "_weights", "_from")


def leaf_grants(leaves: DataFrame, weights: Mapping[str, Mapping[str, int]], budget: Column, max_epochs: int, default_weight: int = 1) -> DataFrame:
    """leaves (domain, lang, source, tokens) -> the same with supply and grant."""
    base = leaves.withColumn("supply", F.col("tokens") * max_epochs)
    known = None
    for depth, level in enumerate(LEVELS):
        path, parents = list(LEVELS[: depth + 1]), list(LEVELS[:depth])
        nodes = base.groupBy(*path).agg(F.sum("supply").alias("supply"), F.sum("tokens").alias("tokens"))
        if known is None:
            nodes = nodes.withColumn("budget", F.lit(None).cast("long")).withColumn("_all", F.sum("tokens").over(Window.partitionBy(F.lit(0))))
            nodes = nodes.withColumn("budget", budget).drop("_all")
        else:
            nodes = nodes.join(known.select(*parents, F.col("grant").alias("budget")), parents)
        nodes = nodes.withColumn("name", F.col(level)).withColumn("weight", weight_of(F.col(level), weights.get(level, {}), default_weight))
        known = share_among_children(nodes, parents)
    return known.select(*LEVELS, "tokens", "supply", "grant")


def epoch_key(seed: int, epoch: Column, doc_id: Column) -> Column:
    """60-bit place of a document in the epoch's permutation."""
    digest = F.md5(F.concat_ws("|", F.lit(str(seed)), epoch.cast("string"), doc_id.cast("string")))
    return F.conv(F.substring(digest, 1, 15), 16, 10).cast("long")


def mix_plan(rows: DataFrame, weights: Mapping[str, Mapping[str, int]], budget: Column, max_epochs: int, seed: int, default_weight: int = 1) -> DataFrame:
    """rows (rid, domain, lang, source, doc_id, tokens) -> a row for each leaf.

    full_epochs  whole passes over the leaf; cut_key, cut_id, cut_spread, cut_rid  last row of
    the prefix of the epoch after them, cut_take  its tokens taken (null: no such prefix).
    """
    leaves = written(rows.groupBy(*LEVELS).agg(F.sum("tokens").alias("tokens")), "leaves")
    grants = written(leaf_grants(leaves, weights, budget, max_epochs, default_weight), "grants")
    grants = grants.withColumn("full_epochs", F.expr("if(tokens > 0, grant div greatest(tokens, 1), 0)")).withColumn("rest", F.expr("if(tokens > 0, grant % greatest(tokens, 1), 0)"))
    placed = rows.withColumnRenamed("tokens", "tokens_").join(grants.filter("rest > 0").drop("tokens"), list(LEVELS))
    placed = placed.withColumn("key", epoch_key(seed, F.col("full_epochs"), F.col("doc_id"))).select(*LEVELS, "rest", "tokens_", *epoch_place("key"))
    placed = placed.withColumn("s1", F.shiftright("key", 52)).withColumn("s2", F.shiftright("key", 40))
    for step in (["s1"], ["s2"], ["key", "id"], ["spread"], ["spread", "rid"]):
        # The part in which the prefix ends, and what it takes of that: finer and finer, so that no task sorts a leaf or all rows of one doc_id.
        run = Window.partitionBy(*LEVELS).orderBy(*step).rowsBetween(Window.unboundedPreceding, -1)
        sums = placed.groupBy(*LEVELS, *step).agg(F.sum("tokens_").alias("here"), F.max("rest").alias("rest"))
        sums = sums.withColumn("before", F.coalesce(F.sum("here").over(run), F.lit(0))).filter("before < rest and before + here >= rest")
        last = written(sums.select(*LEVELS, *step, (F.col("rest") - F.col("before")).alias("rest")), "cut")
        placed = placed.drop("rest").join(last, [*LEVELS, *step])
        if step in (["s1"], ["s2"]):
            # A small table from here on: later steps neither repeat the joins of earlier ones nor read all rows again.
            placed = written(placed, "part")
            forget_shuffles(rows.sparkSession)
    last = placed.select(*LEVELS, F.col("key").alias("cut_key"), F.col("id").alias("cut_id"), F.col("spread").alias("cut_spread"), F.col("rid").alias("cut_rid"), F.least("tokens_", "rest").alias("cut_take"))
    plan = grants.join(last, list(LEVELS), "left").select(*LEVELS, "tokens", "supply", "grant", "full_epochs", "cut_key", "cut_id", "cut_spread", "cut_rid", "cut_take")
    return written(plan, "plan")


def epoch_place(key: str) -> list[Column]:
    """The order of rows in an epoch: by key and doc_id, rows of one doc_id in an order of their own."""
    return [F.col(key), F.coalesce("doc_id", F.lit(-(2**63))).alias("id"), F.pmod(F.xxhash64("rid"), F.lit(4096)).cast("int").alias("spread"), F.col("rid")]


def with_copies(rows: DataFrame, plan: DataFrame, seed: int) -> DataFrame:
    """rows -> those in the mix, with copies (whole or begun passes) and, from tokens, take_tokens."""
    small = plan.select(*LEVELS, "full_epochs", "cut_key", "cut_id", "cut_spread", "cut_rid", "cut_take")
    out = rows.join(small, list(LEVELS)).withColumn("key", epoch_key(seed, F.col("full_epochs"), F.col("doc_id")))
    here = F.struct(*(c.alias(f"o{i}") for i, c in enumerate(epoch_place("key"))))
    cut = F.struct(*(F.col(f"cut_{c}").alias(f"o{i}") for i, c in enumerate(("key", "id", "spread", "rid"))))
    part = F.when(F.col("cut_key").isNull() | (here > cut), F.lit(0)).when(here == cut, F.col("cut_take")).otherwise(F.col("tokens"))
    begun = F.when(F.col("cut_key").isNull() | (here > cut), F.lit(0)).otherwise(F.lit(1))
    return (
        out.withColumn("copies", F.col("full_epochs") + begun)
        .withColumn("take_tokens", F.col("full_epochs") * F.col("tokens") + part)
        .filter("copies > 0")
        .drop("full_epochs", "key", "rid", "cut_key", "cut_id", "cut_spread", "cut_rid", "cut_take")
    )


def with_tree(docs: DataFrame, domain: Column) -> DataFrame:
    """documents -> the same with their place in the tree, tokens and rid (place in the table)."""
    return docs.select(
        *[c for c in docs.columns if c not in ("tokens", "domain", "lang", "source")],
        domain.alias("domain"),
        F.coalesce("lang", F.lit("unknown")).alias("lang"),
        F.coalesce("source", F.lit("unknown")).alias("source"),
        token_count(text_or_empty()).alias("tokens"),
        F.monotonically_increasing_id().alias("rid"),
    )


#: The mix of the registered query and of the pipeline; the budget is an expression of all tokens.
WEIGHTS = {"domain": {"open": 3, "edited": 2}, "lang": {"en": 4, "de": 2, "fr": 2, "es": 1}, "source": {"src0": 2}}
SEED, MAX_EPOCHS = 11, 2
BUDGET = "_all * 6 div 10"


def domain_of() -> Column:
    """Sources with an odd number are edited collections, all others open crawls."""
    return F.when(F.col("source").rlike("^src[0-9]*[13579]$"), F.lit("edited")).otherwise(F.lit("open"))


def mix_documents(docs: DataFrame) -> DataFrame:
    """op1: a row for each document in the mix, with copies and take_tokens."""
    rows = written(with_tree(docs.select("doc_id", "lang", "source", "text"), domain_of()).drop("text"), "mix")
    plan = mix_plan(rows, WEIGHTS, F.expr(BUDGET), MAX_EPOCHS, SEED)
    return with_copies(rows, plan, SEED).select("doc_id", "domain", "lang", "source", "tokens", "copies", "take_tokens")


def mix_stage(docs: DataFrame) -> DataFrame:
    """documents -> documents in the mix, each as often as it is served; the last of a leaf stays whole.

    docs is scanned twice and must be a table: rows of one doc_id are told apart by their place in it.
    """
    rows = with_tree(docs.select("doc_id", "lang", "source", "text"), domain_of()).drop("text")
    rows = written(rows, "mix")
    plan = mix_plan(rows, WEIGHTS, F.expr(BUDGET), MAX_EPOCHS, SEED)
    own = docs.select("doc_id", F.struct(*docs.columns).alias("doc"), domain_of().alias("domain"), F.coalesce("lang", F.lit("unknown")).alias("lang"), F.coalesce("source", F.lit("unknown")).alias("source"), F.lit(0).cast("long").alias("tokens"), F.monotonically_increasing_id().alias("rid"))
    served = with_copies(own, plan, SEED)
    return served.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select("doc.*")
