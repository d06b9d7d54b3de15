"""Building sketches of a column: partial sketches where the rows lie, then merges.

Rows are read once and never shuffled. Every task keeps one small sketch for each
group it meets and hands it on when it has met too many; sketches are merged in
rounds of bounded fan-in.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from rankloom.functions.coins import scope_of
from rankloom.operators.kernel import Sketch, Trials
from rankloom.operators.merge import fold_one_way, tree
from rankloom.operators.sampler import block_filter
from rankloom.operators.state import Codec, state_schema, to_row
from rankloom.plans.params import Plan, max_height, plan
from rankloom.plans.schedule import sampled_levels

#: A task hands its sketches on when it holds this many groups.
MOST_GROUPS = 4096


def prepare(df: DataFrame, value: str | Column, by: list[str], weight: str | Column | None = None) -> DataFrame:
    """Only the group columns, the value and maybe its weight, so that the scan reads no more."""
    picked = [F.col(b) for b in by] + [(F.col(value) if isinstance(value, str) else value).alias("_value")]
    if weight is not None:
        picked.append((F.col(weight) if isinstance(weight, str) else weight).cast("long").alias("_weight"))
    return df.select(*picked)


def start_height(p: Plan, rows_each: int | None) -> int:
    """Sampler height known from the start, for variants with a plain sampler; each task must have a block at least."""
    if p.variant not in ("geo-sampled", "equal-fair-sampled", "sampled-tuple") or not rows_each:
        return 0
    k = max(2, p.k)
    if p.kind == "none":
        # Sampling may add half of eps; one of 2**h rows keeps the certified part below that.
        h = 0
        while rows_each * 4.0 ** (h + 1) / 2 ** (h + 1) * 8 < (p.eps / 2 * rows_each) ** 2 and 2 ** (h + 1) * 4 <= rows_each:
            h += 1
        return h
    return min(sampled_levels(p.rule, max_height(rows_each, k, p.c), k, p.c, p.band), max(0, rows_each.bit_length() - 2))


def partials(rows: DataFrame, by: list[str], p: Plan, seed: int, start: int, lazy: bool = False, picked: bool = False, trials: int = 0, piece: int = 0) -> DataFrame:
    """rows of prepare() -> by..., part, sketch: one or more for each task and group; with trials by..., trial, part, sketch, as many of every group's rows."""
    kind = rows.schema["_value"].dataType
    weighted = "_weight" in rows.columns
    keys, tried = len(by), [T.StructField("trial", T.IntegerType())] if trials else []
    by = [*by, *(x.name for x in tried)]
    schema = T.StructType([*[rows.schema[b] for b in by[:keys]], *tried, T.StructField("part", T.LongType()), T.StructField("sketch", state_schema(kind))])
    arrow = to_arrow_schema(schema)
    together = trials and Trials.fits(p) and not (start or weighted or picked)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(kind)
        context = TaskContext.get()
        part = context.partitionId() if context else 0
        held: dict[tuple, list[Sketch]] = {}
        out = 0

        def hand_on() -> pa.RecordBatch:
            nonlocal out
            lists: dict[str, list] = {name: [] for name in arrow.names}
            made = [((*key, t) if trials else key, s) for key, kernels in held.items() for t, s in enumerate((s for x in kernels for s in x.apart()), 1)]
            for i, (key, sketch) in enumerate(made):
                for name, k in zip(by, key, strict=True):
                    lists[name].append(k)
                lists["part"].append((part << 24) + out + i)
                lists["sketch"].append(to_row(sketch, codec))
            out += len(made)
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(lists[f.name], f.type) for f in arrow], schema=arrow)

        def kernels_of(key: tuple) -> list[Sketch]:
            if key not in held:
                scopes = [scope_of(x, part, out) for x in ([(*key, t) for t in range(1, trials + 1)] if trials else [key])]
                held[key] = [Trials(p, seed, scopes, codec.dtype, lazy)] if together else [Sketch(p, seed, x, start, codec.dtype, lazy=lazy) for x in scopes]
            return held[key]

        for batch in batches:
            for key, values, weights in grouped(batch, keys, weighted):
                nulls = values.null_count
                if nulls:
                    weights = weights.filter(values.is_valid()) if weighted else None
                    values = values.drop_null()
                values = codec.decode(values)
                step = piece or max(1, len(values))
                for s in kernels_of(key):
                    if weighted:
                        s.nulls += nulls
                        s.insert_weighted(values, weights.fill_null(0).to_numpy())
                    elif picked:
                        s.insert_picked(values, nulls)
                    else:
                        s.insert(values[:step], nulls)
                        for at in range(step, len(values), step):
                            s.insert(values[at : at + step])
            if len(held) * max(1, trials) > MOST_GROUPS:
                yield hand_on()
        if held:
            yield hand_on()

    return rows.mapInArrow(run, schema)


def grouped(batch: pa.RecordBatch, keys: int, weighted: bool) -> Iterator[tuple[tuple, pa.Array, pa.Array | None]]:
    """(key, values, weights) for each group in a batch."""
    values = batch.column(keys)
    weights = batch.column(keys + 1) if weighted else None
    if not batch.num_rows:
        return
    if not keys:
        yield (), values, weights
        return
    code = np.zeros(batch.num_rows, np.int64)
    for k in range(keys):
        column = pc.dictionary_encode(batch.column(k), null_encoding="encode")
        code = code * max(1, len(column.dictionary)) + column.indices.to_numpy(zero_copy_only=False)
        _, code = np.unique(code, return_inverse=True)
    order = np.argsort(code, kind="stable")
    edges = np.flatnonzero(np.r_[True, np.diff(code[order]) != 0, True])
    for a, b in zip(edges[:-1], edges[1:], strict=True):
        rows = pa.array(order[a:b])
        key = tuple(batch.column(k)[int(order[a])].as_py() for k in range(keys))
        yield key, values.take(rows), weights.take(rows) if weighted else None


def merge_rounds(df: DataFrame, fan_in: int) -> int:
    """Rounds after which the sketches of all tasks are one, by the bytes that the optimizer expects of df; fan_in tasks take one."""
    spark = df.sparkSession
    try:
        size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    except AttributeError:  # no plan to ask, as with a remote session
        return 3
    each = spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get("spark.sql.files.maxPartitionBytes"))
    tasks = min(max(1, size // max(1, each)), 1 << 24)
    return max(1, math.ceil(math.log(tasks, max(2, fan_in))))


def build(
    df: DataFrame,
    value: str | Column,
    *,
    by: list[str] | None = None,
    variant: str | None = None,
    eps: float = 0.01,
    delta: float = 0.01,
    mode: str = "all",
    seed: int = 42,
    weight: str | Column | None = None,
    n: int | None = None,
    rows_each: int | None = None,
    chosen: Plan | None = None,
    lazy: bool = False,
    fan_in: int = 256,
    thin: int = 0,
    trials: int = 0,
    piece: int = 0,
) -> DataFrame:
    """by..., sketch: the sketch of value in every group.

    variant    'banded' unless given; a plan that is handed over in chosen has its own
    n          rows expected in a group, for variants whose size depends on it
    rows_each  rows expected in each task, for variants with a plain sampler
    thin       keep one row of every 2**thin by a filter in the scan's stage, before any Python
               (params.thin_height chooses it); the sketch starts above these levels, and its
               n is what the kept rows stand for
    trials     as many sketches of every group's rows with coins of their own, told apart by a column
               trial (1 to trials); rows are read once for all of them
    piece      most unweighted rows of a group that a sketch takes before it compacts what is full; whole batches unless given
    """
    by = list(by or [])
    if chosen is not None and variant not in (None, chosen.variant):
        raise ValueError(f"a plan for {chosen.variant} builds no {variant}")
    p = chosen or plan(variant or "banded", eps, delta, mode, n)
    rows = prepare(df, value, by, weight)
    if thin:
        if weight is not None or not p.mergeable:
            raise ValueError("only unweighted rows of mergeable variants are thinned")
        rows = block_filter(rows, thin, seed).drop("weight")
    parts = partials(rows, by, p, seed, thin or start_height(p, rows_each), lazy, bool(thin), trials, piece)
    by += ["trial"] if trials else []
    if p.mergeable:
        return tree(parts, by, fan_in=fan_in, seed=seed, rounds=merge_rounds(df, fan_in))
    return fold_one_way(parts, by, seed=seed)
