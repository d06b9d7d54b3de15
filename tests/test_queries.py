"""Every registered query of the engine against its SQL, at the smallest scale."""

import math

import duckdb
import pytest

from rankloom.workloads.catalog import core_queries, core_sql

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else float(f"{v:.9g}")
    return v


@pytest.fixture(scope="module")
def duck(tiny):
    c = duckdb.connect()
    c.execute("SET TimeZone='UTC'")
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    return c


def table(rows, names):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in rows), key=lambda r: tuple((x is None, str(x)) for x in r))


@pytest.mark.parametrize("name", list(core_queries()))
def test_query(spark, duck, tiny, name):
    df = core_queries()[name](spark, tiny)
    rows = df.collect()
    if name not in core_sql():
        assert rows
        return
    got = duck.execute(core_sql()[name])
    names = [d[0] for d in got.description]
    assert sorted(names) == sorted(df.columns)
    assert table(rows, df.columns) == table(got.fetchall(), names)


@pytest.mark.parametrize("name", ["bounds_table", "capacity_schedule", "lower_bounds", "optimality_ratio", "plan_all_variants", "plan_table", "structure_by_length"])
def test_plans_and_bounds_are_of_a_table(spark, tiny, name):
    assert [f for f in core_queries()[name](spark, tiny).inputFiles() if "lineitem.parquet" in f]


def test_entry(spark):
    from __spark_entry__ import entry

    assert entry(spark).count() == 9
