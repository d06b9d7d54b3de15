"""Sharding by balanced label propagation, under the law `rows`.

Documents with equal texts are linked, through a hub for each text, so that a
group of m copies costs m links. Groups are settled by levels of size, the large
ones first, so that small ones do not take their room. The documents of a level
start in one line of groups, cut over the room that is left; in each round the part of a group in a shard asks for the shard that
holds most of the group among those that have not refused, if more of the group
is there. Moves are granted as far as they leave no shard above its quota of
rows, counting granted departures only. When no shard is left to ask, refusals
are forgotten, and it ends when nothing moves any more, so that no granted move
would lower the number of linked pairs in different shards. Copies of a text
are alike, so what moves is counts of a group's rows; rows get their shards at
the end. Documents without links, which cut nothing wherever they go, then fill
every shard up to a count that differs from the others by one at most.

Edge cases: a null text is linked with nothing and has size 1; a group larger
than a shard fills one after the other; equal rows are separate rows with slots
of their own; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rankloom.llm.common import gapless_rank, text_or_empty, written

#: Groups queue for a move by slices of a hash, so that no task sorts all of them.
SLICES = 512


def digests(docs: DataFrame) -> DataFrame:
    """documents -> a narrow row for each: rid, doc_id, size, text_crc32, hub (null: no text)."""
    text = text_or_empty()
    return docs.select(
        F.monotonically_increasing_id().alias("rid"),
        F.col("doc_id"),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.when(F.col("text").isNotNull(), F.md5(text.cast("binary"))).alias("hub"),
    )


def granted_moves(asked: dict[tuple[int, int], int], load: list[int], quota: list[int]) -> dict[tuple[int, int], int]:
    """(from, to) -> rows that may move, so that no shard that kept its quota ends above it."""
    grant, after = dict(asked), list(load)
    for (origin, to), c in asked.items():
        after[origin] -= c
        after[to] += c
    over = [s for s in range(len(quota)) if after[s] > quota[s]]
    while over:
        to = over.pop()
        # Rows stay where there is room for them first.
        sources = sorted((i for i, j in grant if j == to and grant[i, j]), key=lambda i: (after[i] - quota[i], i))
        for origin in sources:
            back = min(grant[origin, to], max(0, quota[origin] - after[origin]), max(0, after[to] - quota[to]))
            grant[origin, to] -= back
            after[origin], after[to] = after[origin] + back, after[to] - back
        for origin in sources:
            back = min(grant[origin, to], max(0, after[to] - quota[to]))
            grant[origin, to] -= back
            after[origin], after[to] = after[origin] + back, after[to] - back
            if back and after[origin] > quota[origin] and origin not in over:
                over.append(origin)
    return grant


def propagate(cells: DataFrame, quota: list[int]) -> DataFrame:
    """cells (hub, shard, c: rows) -> the same after rounds of granted moves, until none is left."""
    spark = cells.sparkSession
    load = [0] * len(quota)
    for r in cells.groupBy("shard").agg(F.sum("c").alias("c")).collect():
        load[r["shard"]] = r["c"]
    before = Window.partitionBy("hub").orderBy(F.desc("c"), F.xxhash64("hub", "shard"), "shard").rowsBetween(Window.unboundedPreceding, -1)
    pair = Window.partitionBy("shard", "to")
    closed, moved = set(), False
    while True:
        target = F.when(~F.col("shard").isin(*closed), F.col("shard")) if closed else F.col("shard")
        wishes = cells.withColumn("to", F.first(target, ignorenulls=True).over(before)).withColumn("slice", F.pmod(F.xxhash64("hub"), F.lit(SLICES)))
        asked = {(r["shard"], r["to"]): r["c"] for r in wishes.filter("to is not null").groupBy("shard", "to").agg(F.sum("c").alias("c")).collect()}
        if not asked:
            if not (closed and moved):
                return cells
            closed, moved = set(), False
            continue
        grant = granted_moves(asked, load, quota)
        closed |= {to for (origin, to), c in asked.items() if grant[origin, to] < c}
        if not any(grant.values()):
            continue
        moved = True
        for (origin, to), c in grant.items():
            load[origin] -= c
            load[to] += c
        table = spark.createDataFrame([(i, j, c) for (i, j), c in grant.items()], "shard int, to int, allowed long")
        asking = wishes.filter("to is not null")
        slices = asking.groupBy("shard", "to", "slice").agg(F.sum("c").alias("s"))
        slices = slices.withColumn("ahead", F.coalesce(F.sum("s").over(pair.orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("s")
        inside = F.coalesce(F.sum("c").over(Window.partitionBy("shard", "to", "slice").orderBy("hub").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        going = asking.withColumn("inside", inside).join(F.broadcast(slices), ["shard", "to", "slice"]).join(F.broadcast(table), ["shard", "to"])
        going = going.withColumn("got", F.greatest(F.lit(0), F.least("c", F.col("allowed") - F.col("ahead") - F.col("inside"))))
        parts = going.select("hub", F.explode(F.array(F.struct("shard", (F.col("c") - F.col("got")).alias("c")), F.struct(F.col("to").alias("shard"), F.col("got").alias("c")))).alias("p")).select("hub", "p.shard", "p.c")
        parts = parts.unionByName(wishes.filter("to is null").select("hub", "shard", "c"))
        cells = written(parts.groupBy("hub", "shard").agg(F.sum("c").alias("c")).filter("c > 0"), "cells")


def in_line(hubs: DataFrame, room: list[int]) -> DataFrame:
    """hubs (hub, c: rows) -> cells (hub, shard, c): all rows in one line, by a hash of their hub, cut in proportion to room.

    Only groups at a cut begin split. Offsets come from counts by buckets, so that no task sorts all groups.
    """
    placed = hubs.select("hub", "c", F.pmod(F.xxhash64("hub"), F.lit(8 * SLICES)).alias("bucket"))
    before = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = placed.groupBy("bucket").agg(F.sum("c").alias("here"))
    offsets = sums.select("bucket", F.coalesce(F.sum("here").over(before), F.lit(0)).alias("offset"))
    inside = F.coalesce(F.sum("c").over(Window.partitionBy("bucket").orderBy("hub").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    placed = placed.withColumn("inside", inside).join(F.broadcast(offsets), "bucket").withColumn("lo", F.col("offset") + F.col("inside"))
    rows = sums.agg(F.sum("here")).first()[0]
    ends = [rows * sum(room[:s]) // sum(room) for s in range(len(room) + 1)]
    here = lambda s: F.least(F.col("lo") + F.col("c"), F.lit(ends[s + 1])) - F.greatest("lo", F.lit(ends[s]))
    parts = F.array(*(F.struct(F.lit(s).alias("shard"), here(s).alias("c")) for s in range(len(room))))
    return placed.select("hub", F.explode(F.filter(parts, lambda p: p["c"] > 0)).alias("p")).select("hub", "p.shard", "p.c")


def settled(linked: DataFrame, cells: DataFrame) -> DataFrame:
    """linked rows with the shards of cells: the rows of a hub go to its shards by their rank."""
    upto = F.sum("c").over(Window.partitionBy("hub").orderBy("shard"))
    plan = cells.withColumn("upto", upto).groupBy("hub").agg(F.sort_array(F.collect_list(F.struct("upto", "shard"))).alias("plan"))
    ranked = gapless_rank(linked, F.col("rid"), "hub", "of_hub").join(plan, "hub")
    return ranked.withColumn("shard", F.filter("plan", lambda p: p["upto"] > F.col("of_hub"))[0]["shard"]).drop("plan", "of_hub")


def shard_documents(docs: DataFrame, shards: int = 16) -> DataFrame:
    """op6: documents -> doc_id, size, text_crc32, law, shard, slot, grown_shard, linked."""
    rows = written(digests(docs), "digests")
    total = rows.count()
    quota = [total // shards + (s < total % shards) for s in range(shards)]
    hubs = rows.filter("hub is not null").groupBy("hub").agg(F.count("*").alias("c")).filter("c > 1")
    hubs = written(hubs.withColumn("level", F.floor(F.log2("c") / 2).cast("int")), "hubs")
    linked = rows.join(hubs.select("hub"), "hub")
    room, cells = list(quota), hubs.select("hub", F.lit(0).alias("shard"), "c").limit(0)
    for level in sorted((r["level"] for r in hubs.select("level").distinct().collect()), reverse=True):
        found = propagate(written(in_line(hubs.filter(F.col("level") == level), room), "cells"), room)
        for r in found.groupBy("shard").agg(F.sum("c").alias("c")).collect():
            room[r["shard"]] -= r["c"]
        cells = cells.unionByName(found)
    ranked = written(gapless_rank(settled(linked, cells), F.col("rid"), "shard", "slot"), "ranked")
    kept = [q - r for q, r in zip(quota, room, strict=True)]
    free = rows.join(hubs, "hub", "left_anti").select("rid", "doc_id", "size", "text_crc32", F.lit(False).alias("linked"))
    place = gapless_rank(free, F.col("rid"), None, "place", buckets=4096)
    begin, shard, slot = 0, F.lit(0), F.lit(0)
    bounds = []
    for s in range(shards):
        need = quota[s] - kept[s]
        bounds.append((s, begin, begin + need, kept[s]))
        begin += need
    for s, lo, hi, have in bounds:
        here = (F.col("place") >= lo) & (F.col("place") < hi)
        shard = F.when(here, F.lit(s)).otherwise(shard)
        slot = F.when(here, F.col("place") - lo + have).otherwise(slot)
    filled = place.select("doc_id", "size", "text_crc32", shard.alias("shard"), slot.cast("long").alias("slot"), "linked")
    stayed = ranked.select("doc_id", "size", "text_crc32", "shard", "slot", F.lit(True).alias("linked"))
    out = stayed.unionByName(filled)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.col("shard").cast("int").alias("shard"), F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "linked")
