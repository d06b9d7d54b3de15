"""All registered queries of the rank engine."""

from __future__ import annotations

from rankloom.workloads import general, relational, sketches, streams
from rankloom.workloads.registry import QUERIES, SQL, Query

MODULES = (relational, general, sketches, streams)


def core_queries() -> dict[str, Query]:
    return dict(QUERIES)


def core_sql() -> dict[str, str]:
    return dict(SQL)
