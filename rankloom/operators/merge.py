"""Merging sketches: pairwise, as a tree over the cluster, and one way."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from rankloom.functions.coins import scope_of
from rankloom.operators.kernel import Sketch
from rankloom.operators.state import Codec, from_row, to_row


def merge_many(sketches: list[Sketch]) -> Sketch:
    """One sketch of all streams; sketches must be of one mergeable variant and equal shape parameters."""
    kinds = {(s.plan.variant, s.plan.k, s.plan.c, s.plan.band, s.plan.anchor) for s in sketches}
    if len(kinds) != 1 or not sketches[0].plan.mergeable:
        raise ValueError(f"cannot be merged: {sorted(map(str, kinds))}")
    # The one with the highest sampler takes the others in.
    order = sorted(range(len(sketches)), key=lambda i: (-sketches[i].sampler.height, i))
    first = sketches[order[0]]
    return first.absorb([sketches[i] for i in order[1:]]) if len(order) > 1 else first


def fold(sketches: list[Sketch]) -> Sketch:
    """Parts into one accumulator of tuples, with the levels and the sampler below it.

    Summaries of equal height are merged with their bounds, so the accumulator answers from where its parts did: above
    what they sampled, or above the levels they dropped summaries of.
    """
    if len(sketches) == 1:
        return sketches[0]
    if sketches[0].plan.kind != "none":
        # The tallest has dropped the most summaries; a part without one of the others has no level that high.
        order = sorted(range(len(sketches)), key=lambda i: (-sketches[i].height, -sketches[i].sampler.height, i))
        out, others = sketches[order[0]], [sketches[i] for i in order[1:]]
        for h, top in out.tops.items():
            for s in others:
                if h in s.tops:
                    top.absorb(s.tops[h])
        return out.absorb(others)
    # The lowest sampler stays: summaries and rests of higher ones count several times in its units.
    order = sorted(range(len(sketches)), key=lambda i: (sketches[i].sampler.height, i))
    out, unit = sketches[order[0]], sketches[order[0]].sampler.height
    for s in (sketches[i] for i in order[1:]):
        out.count(s)
        out.tops[0].absorb(s.tops[0], 1 << (s.sampler.height - unit))
        whole, rest = s.sampler.weight >> unit, s.sampler.weight & ((1 << unit) - 1)
        if whole:
            out.tops[0].insert_weighted(np.array([s.sampler.item], out.dtype), np.array([whole]))
        if rest:
            out.sample(s.sampler.item, rest)
    return out


def _combine(df: DataFrame, keys: list[str], out: list[str], how: str, seed: int) -> DataFrame:
    kind = df.schema["sketch"].dataType["min_value"].dataType
    schema = df.select(*out, "part", "sketch").schema
    arrow = to_arrow_schema(schema)

    def run(table: pa.Table) -> pa.Table:
        codec = Codec(kind)
        table = table.sort_by("part")
        parts = table["part"].to_pylist()
        sketches = [from_row(r, codec, scope_of("merge", parts, seed, i)) for i, r in enumerate(table["sketch"].to_pylist())]
        merged = merge_many(sketches) if how == "merge" else fold(sketches)
        row = {**{k: table[k][0].as_py() for k in out}, "part": parts[0], "sketch": to_row(merged, codec)}
        return pa.Table.from_pylist([row], schema=arrow)

    return df.withColumn("_all", F.lit(0)).groupBy("_all", *keys).applyInArrow(run, schema)


def tree(parts: DataFrame, by: list[str], fan_in: int = 256, seed: int = 42, keep_part: bool = False, rounds: int = 2) -> DataFrame:
    """by..., part, sketch rows -> one sketch for each group, in rounds of bounded fan-in.

    Only sketches are shuffled. Before the last round, a group's parts are split over
    fan_in ** (rounds - 1) buckets, then over a fan_in-th of these and so on, so that a
    task takes fan_in sketches of a group, about, if it has fan_in ** rounds; this also evens out a hot group.
    """
    done = parts
    for left in range(rounds - 1, -1, -1):
        split = done.withColumn("_bucket", F.pmod(F.xxhash64("part"), F.lit(fan_in**left)))
        done = _combine(split, [*by, "_bucket"], by, "merge", seed + rounds - 1 - left)
    return done if keep_part else done.drop("part")


def fold_one_way(parts: DataFrame, by: list[str], seed: int = 42) -> DataFrame:
    """by..., part, sketch rows -> one sketch for each group, all parts folded into one accumulator in order of part."""
    return _combine(parts, by, by, "fold", seed).drop("part")


def chain(parts: DataFrame, by: list[str], seed: int = 42) -> DataFrame:
    """Merges parts one after another instead of together (a tree of greatest depth), for tests of mergeability."""
    kind = parts.schema["sketch"].dataType["min_value"].dataType
    schema = parts.select(*by, "sketch").schema
    arrow = to_arrow_schema(schema)

    def run(table: pa.Table) -> pa.Table:
        codec = Codec(kind)
        table = table.sort_by("part")
        rows = table["sketch"].to_pylist()
        merged = from_row(rows[0], codec, seed)
        for i, r in enumerate(rows[1:]):
            merged = merge_many([merged, from_row(r, codec, seed + i + 1)])
        return pa.Table.from_pylist([{**{k: table[k][0].as_py() for k in by}, "sketch": to_row(merged, codec)}], schema=arrow)

    return parts.withColumn("_all", F.lit(0)).groupBy("_all", *by).applyInArrow(run, schema)
