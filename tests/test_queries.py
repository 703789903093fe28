"""Every query with an equivalent in SQL against DuckDB on the smallest tables; plans of the hot paths."""

import math
import os

import duckdb
import pytest

import __spark_entry__ as entry_module
from askcheck.sources.tables import TABLES

OWN = sorted(k for k in entry_module.oracle_sql() if k.startswith(("w_", "op_")))


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path if os.path.isfile(path) else path + '/*.parquet'}'")
    return con


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else round(v + 0.0, 9)
    return v


def rows_of(names, rows):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted([repr(tuple(plain(r[i]) for i in order)) for r in rows])


@pytest.mark.parametrize("name", OWN)
def test_equal_to_duckdb(spark, sf, duck, name):
    df = entry_module.queries()[name](spark, sf)
    cur = duck.execute(entry_module.oracle_sql()[name])
    names = [d[0] for d in cur.description]
    assert sorted(df.columns) == sorted(names)
    assert rows_of(df.columns, [tuple(r) for r in df.collect()]) == rows_of(names, cur.fetchall())


@pytest.mark.parametrize("name", ["w_air", "w_ex_fb", "w_council_majority", "w_mask_dedup", "w_rec_cls", "w_balanced", "op_join_theta", "op_join_interval"])
def test_hot_paths_have_no_python_and_no_cartesian(spark, sf, name):
    plan = entry_module.queries()[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert not any(w in plan for w in ("Python", "Arrow", "Pandas", "Cartesian", "NestedLoop"))


def test_filters_and_columns_reach_the_scan(spark, sf):
    plan = entry_module.queries()["op_filter_pred"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(l_quantity" in plan and "l_extendedprice" not in plan


def test_streams_end_as_batches(spark, sf):
    q = entry_module.queries()
    assert tuple(q["op_st_stateful"](spark, sf).first()) == tuple(q["op_st_air_batch"](spark, sf).first())
