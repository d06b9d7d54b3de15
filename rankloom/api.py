"""A fluent way to say what to sketch and what to ask.

    ranks(df).of("price").by("country").within(0.01, delta=1e-6).quantiles(0.5, 0.9)
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rankloom.functions import answer
from rankloom.operators.build import build


@dataclass(frozen=True)
class Ranks:
    """A question about the order of one column; every step gives a new one."""

    rows: DataFrame
    value: str | Column | None = None
    groups: tuple[str, ...] = ()
    options: dict[str, Any] = field(default_factory=dict)

    def of(self, value: str | Column) -> Ranks:
        return replace(self, value=value)

    def by(self, *groups: str) -> Ranks:
        return replace(self, groups=groups)

    def within(self, eps: float, delta: float = 0.01, mode: str = "all") -> Ranks:
        return replace(self, options=self.options | {"eps": eps, "delta": delta, "mode": mode})

    def using(self, variant: str, **options: Any) -> Ranks:
        return replace(self, options=self.options | {"variant": variant} | options)

    def weighted(self, weight: str | Column) -> Ranks:
        return replace(self, options=self.options | {"weight": weight})

    def sketch(self) -> DataFrame:
        if self.value is None:
            raise ValueError("of() names the column")
        return build(self.rows, self.value, by=list(self.groups), **self.options)

    def quantiles(self, *fractions: float) -> DataFrame:
        return answer.quantiles(self.sketch(), list(fractions), list(self.groups))

    def median(self) -> DataFrame:
        return answer.median(self.sketch(), list(self.groups))

    def rank_of(self, *values: Any) -> DataFrame:
        """groups..., probe, est_rank, certified_error."""
        probes = F.explode(F.array(*[F.lit(v) for v in values])).alias("probe")
        asked = self.sketch().select(*self.groups, answer.points().alias("_points"), answer.certificate().alias("certified_error"), probes)
        return asked.select(*self.groups, "probe", answer.rank(F.col("_points"), F.col("probe")).alias("est_rank"), "certified_error")


def ranks(rows: DataFrame) -> Ranks:
    return Ranks(rows)
