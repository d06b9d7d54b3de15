"""Document fingerprints: 64-bit SimHash and search within a Hamming radius.

The terms of a text are its pairs of neighbouring lower-cased words (a lone word
is a term by itself), weighted by how often they occur. Every occurrence votes
on 64 bits; 32 running sums hold two 32-bit counters each, so a text of up to
2**31 terms is counted exactly. A bit is set where more than half of the weight
votes for it.

Edge cases: a null text is empty; a text without words has fingerprint 0; equal
texts have equal fingerprints; rows of equal doc_id stand in order of their text;
a null doc_id comes first; a single row is its own successor.
"""

from __future__ import annotations

import math
from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rankloom.llm.common import text_or_empty, written

BITS, LANES = 64, 32
LANE_MASK = 0x0000000100000001
WHITE = r"[ \t-\r]+"


def terms(text: Column) -> Column:
    """Hashes of the pairs of neighbouring words, one for each occurrence."""
    words = F.filter(F.split(F.lower(text), WHITE), lambda w: w != "")
    codes = F.transform(words, lambda w: F.xxhash64(w))
    pairs = lambda c: F.when(F.size(c) < 2, c).otherwise(F.zip_with(F.slice(c, 1, F.size(c) - 1), F.slice(c, 2, F.size(c) - 1), lambda a, b: F.xxhash64(a, b)))
    return F.transform(F.array(codes), pairs)[0]


def vote_sums(term: str) -> list[Column]:
    """Aggregates: for each lane the votes on bits k and k + 32, and the total weight."""
    bit = lambda k: F.shiftrightunsigned(term, k).bitwiseAND(F.lit(LANE_MASK))
    return [F.sum(bit(k)).alias(f"v{k}") for k in range(LANES)] + [F.count(term).alias("weight")]


def fingerprint_of_votes() -> Column:
    """The fingerprint as a signed 64-bit number, from vote_sums()."""
    out = F.lit(0).cast("long")
    for k in range(BITS):
        lane = F.col(f"v{k % LANES}")
        ones = lane.bitwiseAND(F.lit(0xFFFFFFFF)) if k < LANES else F.shiftrightunsigned(lane, 32)
        flag = F.shiftleft(F.lit(1).cast("long"), k)
        out = out.bitwiseOR(F.when(ones * 2 > F.col("weight"), flag).otherwise(F.lit(0).cast("long")))
    return out


def as_text(fingerprint: Column) -> Column:
    return F.lpad(F.lower(F.hex(fingerprint)), 16, "0")


def likeness(a: Column, b: Column) -> Column:
    return 1.0 - F.bit_count(a.bitwiseXOR(b)) / float(BITS)


def ordered_buckets(docs: DataFrame, rows_each: int, fan: int = 128) -> tuple[DataFrame, int]:
    """docs with bucket: ranges of doc_id of about rows_each rows, by one or two levels of cut points.

    The driver holds the cut points only, fan * fan at most.
    """
    total = docs.agg(F.count("*")).collect()[0][0]
    wanted = max(1, min(fan * fan, total // rows_each))
    if wanted == 1:
        return docs.withColumn("bucket", F.lit(0)), 1
    cuts = docs.agg(F.percentile_approx("doc_id", [i / wanted for i in range(1, wanted)], max(10_000, 20 * wanted))).collect()[0][0]
    cuts = sorted(set(cuts or []))
    if len(cuts) <= fan:
        low = F.array(*[F.lit(int(c)) for c in cuts]) if cuts else F.array().cast("array<bigint>")
        return docs.withColumn("bucket", F.coalesce(F.size(F.filter(low, lambda c: c <= F.col("doc_id"))), F.lit(0))), len(cuts) + 1
    step = -(-len(cuts) // fan)
    groups = [cuts[i : i + step] for i in range(0, len(cuts), step)]
    heads = F.array(*[F.lit(int(g[0])) for g in groups[1:]])
    fine = F.array(*[F.array(*[F.lit(int(c)) for c in g]) for g in groups])
    coarse = F.size(F.filter(heads, lambda c: c <= F.col("doc_id")))
    inner = F.size(F.filter(F.element_at(fine, coarse + 1), lambda c: c <= F.col("doc_id")))
    return docs.withColumn("bucket", F.coalesce(coarse * (step + 1) + inner, F.lit(0))), len(cuts) + 1


def with_next(docs: DataFrame, rows_each: int = 2048) -> DataFrame:
    """documents -> bucket, rn, doc_id, text, next_text, last: each with the next by doc_id, cyclically.

    Only the first text of a bucket crosses to another one.
    """
    rows = docs.select("doc_id", text_or_empty().alias("text"))
    rows, _ = ordered_buckets(rows, rows_each)
    firsts = rows.groupBy("bucket").agg(F.min(F.struct("doc_id", "text")).alias("f")).select(F.col("bucket").alias("behind"), F.col("f.text").alias("edge"))
    line = Window.partitionBy(F.lit(0)).orderBy("bucket")
    ring = rows.select("bucket").distinct().withColumn("behind", F.coalesce(F.lead("bucket").over(line), F.first("bucket").over(line)))
    firsts = ring.join(firsts, "behind").drop("behind")
    order = Window.partitionBy("bucket").orderBy("doc_id", "text")
    out = rows.withColumn("rn", F.row_number().over(order)).withColumn("follows", F.lead("text").over(order))
    # The rows lie by bucket already, so that a merge moves the firsts only; they hold texts and are not broadcast.
    out = out.join(firsts.hint("merge"), "bucket")
    return out.select("bucket", "rn", "doc_id", "text", F.coalesce("follows", "edge").alias("next_text"), F.col("follows").isNull().alias("last"))


def fingerprint_edits(docs: DataFrame) -> DataFrame:
    """documents -> doc_id, n_chars, edited_sha256 and fp, edited_fp, next_fp as numbers.

    Text, edited text and, at a bucket's end, the next text are voted on together
    and every step keeps the bucket's partitioning: one shuffle of the texts.
    """
    rows = with_next(docs)
    n = F.length("text")
    cut = F.expr("length(text) div 4").cast("int")
    rows = rows.withColumn("n_chars", n.cast("long")).withColumn("edited", F.concat(F.expr("substring(text, 1, length(text) - int(length(text) div 4))"), F.substring(F.col("next_text"), F.lit(1), cut)))
    kinds = F.array(
        F.struct(F.lit(0).alias("kind"), F.col("text").alias("t")),
        F.struct(F.lit(1).alias("kind"), F.col("edited").alias("t")),
        F.struct(F.lit(2).alias("kind"), F.when(F.col("last"), F.col("next_text")).alias("t")),
    )
    keys = ["bucket", "rn", "doc_id", "n_chars", "edited_sha256"]
    rows = rows.select("bucket", "rn", "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), F.explode(kinds).alias("k")).filter("k.t is not null")
    votes = rows.select(*keys, "k.kind", F.explode_outer(terms(F.col("k.t"))).alias("term"))
    prints = votes.groupBy(*keys, "kind").agg(*vote_sums("term")).select(*keys, "kind", fingerprint_of_votes().alias("fp"))
    one = lambda kind: F.max(F.when(F.col("kind") == kind, F.col("fp")))
    wide = prints.groupBy(*keys).agg(one(0).alias("fp"), one(1).alias("edited_fp"), one(2).alias("edge_fp"))
    order = Window.partitionBy("bucket").orderBy("rn")
    wide = wide.withColumn("next_fp", F.coalesce(F.lead("fp").over(order), F.col("edge_fp")))
    return wide.select("doc_id", "n_chars", "edited_sha256", "fp", "edited_fp", "next_fp")


def block_masks(blocks: int, kept: int) -> list[int]:
    """Signed 64-bit masks of every choice of kept out of blocks nearly equal bit blocks."""
    edges = [BITS * i // blocks for i in range(blocks + 1)]
    out = []
    for choice in combinations(range(blocks), kept):
        mask = sum(((1 << (edges[b + 1] - edges[b])) - 1) << edges[b] for b in choice)
        out.append(mask - 2**64 if mask >= 2**63 else mask)
    return out


def blocks_for(n: int, radius: int) -> int:
    """So many blocks that the keys of a table, blocks - radius of them, tell n numbers apart; one more than the radius at least."""
    blocks = radius + 2
    while BITS * (blocks - radius) // blocks < math.log2(max(2, n)) and blocks < 2 * radius + 3:
        blocks += 1
    return blocks


def within_radius(queries: DataFrame, prints: DataFrame, radius: int = 3, blocks: int = 5) -> DataFrame:
    """queries (fp), prints (fp) -> all pairs q, d of different numbers with at most radius different bits.

    radius different bits leave blocks - radius blocks untouched: some permuted
    table, keyed by such a choice of blocks, holds both. Exact for any input.
    """
    masks = block_masks(blocks, blocks - radius)
    table = lambda name: F.posexplode(F.array(*[F.col(name).bitwiseAND(F.lit(m)) for m in masks])).alias("t", "key")
    q = queries.select(F.col("fp").alias("q")).distinct().select("q", table("q"))
    d = prints.select(F.col("fp").alias("d")).distinct().select("d", table("d"))
    near = F.bit_count(F.col("q").bitwiseXOR(F.col("d"))) <= radius
    return q.join(d, (q["t"] == d["t"]) & (q["key"] == d["key"]) & near).select("q", "d").distinct()


def simhash_documents(docs: DataFrame, radius: int = 3) -> DataFrame:
    """op2: fingerprints of every text and its edited text, and their likeness.

    n_within, for a doc_id divisible by 20: the documents, itself included, whose
    fingerprint lies within radius of its own.
    """
    rows = written(fingerprint_edits(docs), "prints")
    counts = rows.groupBy("fp").agg(F.count("*").alias("c"))
    asked = rows.filter("doc_id % 20 = 0").select("fp").distinct()
    hits = within_radius(asked, counts, radius, blocks_for(rows.count(), radius)).join(counts.withColumnRenamed("fp", "d"), "d").groupBy("q").agg(F.sum("c").alias("n_within"))
    asks = F.when(F.col("doc_id") % 20 == 0, F.col("fp"))
    return rows.withColumn("q", asks).join(hits, "q", "left").select(
        "doc_id",
        "n_chars",
        "edited_sha256",
        as_text(F.col("fp")).alias("fingerprint"),
        as_text(F.col("edited_fp")).alias("edited_fingerprint"),
        likeness(F.col("fp"), F.col("edited_fp")).alias("near_edited"),
        likeness(F.col("fp"), F.col("next_fp")).alias("near_next"),
        "n_within",
    )
