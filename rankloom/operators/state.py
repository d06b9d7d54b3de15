"""Sketch rows: the Spark schema of a sketch and its conversion from and to kernels."""

from __future__ import annotations

import datetime
import decimal
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from rankloom.operators.kernel import Sketch
from rankloom.operators.tuples import TupleSummary
from rankloom.plans.params import Plan

#: Types that numpy holds as they are; the others are listed in Codec.
PLAIN = {
    T.DoubleType: np.float64,
    T.FloatType: np.float32,
    T.ByteType: np.int8,
    T.ShortType: np.int16,
    T.IntegerType: np.int32,
    T.LongType: np.int64,
    T.BooleanType: np.bool_,
}


class Codec:
    """Values of one Spark type as numpy arrays in the same order.

    Dates, timestamps and intervals are whole numbers; decimals of up to 18 digits
    are unscaled; strings are Python strings, whose order by code point is that of
    their UTF-8 bytes. Minus zero is zero, and NaN is larger than all numbers.
    """

    def __init__(self, kind: T.DataType):
        self.kind = kind
        self.arrow = to_arrow_type(kind)
        if type(kind) in PLAIN:
            self.dtype: Any = PLAIN[type(kind)]
        elif isinstance(kind, T.DecimalType) and kind.precision <= 18 or isinstance(kind, (T.DateType, T.TimestampType, T.TimestampNTZType, T.DayTimeIntervalType)):
            self.dtype = np.int64
        elif isinstance(kind, T.StringType):
            self.dtype = object
        else:
            raise TypeError(f"no order of {kind.simpleString()} in kernels; use the relational form")

    def decode(self, column: pa.Array) -> np.ndarray:
        """An Arrow column without nulls."""
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], column.type)
        if self.dtype is object:
            out = np.empty(len(column), object)
            out[:] = column.to_pylist()
            return out
        if isinstance(self.kind, T.DecimalType):
            scale = decimal.Decimal(10) ** self.kind.scale
            return np.array([int(x * scale) for x in column.to_pylist()], np.int64)
        if isinstance(self.kind, T.DateType):
            return column.cast(pa.int32()).to_numpy().astype(np.int64)
        if self.dtype is np.int64 and not isinstance(self.kind, T.LongType):
            return column.cast(pa.duration("us")).cast(pa.int64()).to_numpy() if pa.types.is_duration(column.type) else column.cast(pa.timestamp("us", column.type.tz)).cast(pa.int64()).to_numpy()
        out = column.to_numpy(zero_copy_only=False).astype(self.dtype)
        return out + 0.0 if out.dtype.kind == "f" else out

    def encode(self, values: Any) -> list:
        """Python values for Arrow of an array of this codec."""
        raw = [x.item() if isinstance(x, np.generic) else x for x in values]
        if isinstance(self.kind, T.DecimalType):
            return [None if x is None else decimal.Decimal(x).scaleb(-self.kind.scale) for x in raw]
        if isinstance(self.kind, T.DateType):
            return [None if x is None else datetime.date(1970, 1, 1) + datetime.timedelta(days=x) for x in raw]
        if isinstance(self.kind, T.DayTimeIntervalType):
            return [None if x is None else datetime.timedelta(microseconds=x) for x in raw]
        if isinstance(self.kind, (T.TimestampType, T.TimestampNTZType)):
            zone = datetime.timezone.utc if isinstance(self.kind, T.TimestampType) else None
            return [None if x is None else datetime.datetime(1970, 1, 1, tzinfo=zone) + datetime.timedelta(microseconds=x) for x in raw]
        return raw

    def of_python(self, values: list) -> np.ndarray:
        return self.decode(pa.array(values, self.arrow)) if values else np.zeros(0, self.dtype)


def state_schema(kind: T.DataType) -> T.StructType:
    """The struct of a sketch over values of one type."""
    long, double = T.LongType(), T.DoubleType()
    fields = T.StructField
    level = T.StructType([fields("height", T.IntegerType()), fields("items", T.ArrayType(kind)), fields("compactions", long)])
    tuples = T.StructType([fields("value", kind), fields("low", long), fields("high", long)])
    top = T.StructType([fields("height", T.IntegerType()), fields("seen", long), fields("scale", long), fields("tuples", T.ArrayType(tuples))])
    sampler = T.StructType([fields("height", T.IntegerType()), fields("item", kind), fields("weight", long)])
    return T.StructType(
        [
            fields("variant", T.StringType()),
            fields("k", T.IntegerType()),
            fields("c", double),
            fields("band", T.IntegerType()),
            fields("anchor", T.StringType()),
            fields("eps", double),
            fields("delta", double),
            fields("seed", long),
            fields("n", long),
            fields("nulls", long),
            fields("min_value", kind),
            fields("max_value", kind),
            fields("height", T.IntegerType()),
            fields("sampler", sampler),
            fields("levels", T.ArrayType(level)),
            fields("tops", T.ArrayType(top)),
            fields("coins", long),
            fields("samples", long),
            fields("err_sq", double),
            fields("err_abs", double),
        ]
    )


def to_row(s: Sketch, codec: Codec) -> dict:
    p = s.plan
    one = lambda x: codec.encode([x])[0] if x is not None else None
    return {
        "variant": p.variant,
        "k": p.k,
        "c": p.c,
        "band": p.band,
        "anchor": p.anchor,
        "eps": p.eps,
        "delta": p.delta,
        "seed": s.seed,
        "n": s.n,
        "nulls": s.nulls,
        "min_value": one(s.least),
        "max_value": one(s.most),
        "height": s.height,
        "sampler": {"height": s.sampler.height, "item": one(s.sampler.item) if s.sampler.weight else None, "weight": s.sampler.weight},
        "levels": [{"height": h, "items": codec.encode(np.sort(s.levels[h])), "compactions": s.compactions.get(h, 0)} for h in sorted(s.levels)],
        "tops": [
            {"height": h, "seen": t.n, "scale": 1 << (h - 1 if h else s.sampler.height if p.kind == "none" else 0), "tuples": [{"value": v, "low": int(a), "high": int(b)} for v, a, b in zip(codec.encode(t.values), t.low, t.high, strict=True)]}
            for h, t in sorted(s.tops.items())
        ],
        "coins": s.flips,
        "samples": s.samples,
        "err_sq": s.err_sq,
        "err_abs": s.err_abs,
    }


def from_row(row: dict, codec: Codec, scope: int) -> Sketch:
    p = Plan(row["variant"], row["eps"], row["delta"], row["k"], row["c"], row["band"], row["anchor"])
    s = Sketch(p, row["seed"], scope, row["sampler"]["height"], codec.dtype)
    s.n, s.nulls, s.flips, s.samples = row["n"], row["nulls"], row["coins"], row["samples"]
    s.err_sq, s.err_abs = row["err_sq"], row["err_abs"]
    if row["n"]:
        s.least, s.most = (codec.of_python([row[k]])[0] for k in ("min_value", "max_value"))
    if row["sampler"]["weight"]:
        s.sampler.item, s.sampler.weight = codec.of_python([row["sampler"]["item"]])[0], row["sampler"]["weight"]
    s.levels = {x["height"]: codec.of_python(x["items"]) for x in row["levels"]}
    s.compactions = {x["height"]: x["compactions"] for x in row["levels"] if x["compactions"]}
    s.tops = {}
    for x in row["tops"]:
        t = TupleSummary(p.eps if p.variant == "tuple-summary" else p.eps / 2, codec.dtype)
        t.n = x["seen"]
        t.values = codec.of_python([q["value"] for q in x["tuples"]])
        t.low = np.array([q["low"] for q in x["tuples"]], np.int64)
        t.high = np.array([q["high"] for q in x["tuples"]], np.int64)
        s.tops[x["height"]] = t
    return s
