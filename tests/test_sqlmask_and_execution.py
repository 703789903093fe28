import time

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from askcheck.functions import sqlmask
from askcheck.plans import execsql
from askcheck.sources.tables import register_views
from askcheck.workloads import EXECUTION_CASES

CASES = [
    ("SELECT * FROM t WHERE a = 'it''s' AND b = 5", "select * from t where a = ? and b = ?"),
    ("SELECT  a FROM t\nWHERE x > -1.5e3", "select a from t where x > ?"),
    ("SELECT a1, b2c FROM t3 WHERE d = DATE '2020-01-01'", "select a1, b2c from t3 where d = ?"),
    ("SELECT a FROM t WHERE a IN (1, 2, 3)", "select a from t where a in (?)"),
    ("SELECT a -- note 7\nFROM t", "select a from t"),
    ("SELECT a /* 1 */ FROM t LIMIT 10", "select a from t limit ?"),
]


def test_masking(spark):
    df = spark.createDataFrame(CASES, "raw string, want string")
    for r in df.select("raw", "want", sqlmask.mask_values("raw").alias("got")).collect():
        assert r.got == r.want
    again = df.select(sqlmask.mask_values(sqlmask.mask_values("raw")).alias("twice"), sqlmask.mask_values("raw").alias("once")).collect()
    assert all(r.twice == r.once for r in again)


def test_the_tokenizer_keeps_quoted_names():
    assert sqlmask.mask_exact('SELECT "A 1" FROM t WHERE b = -5 AND c - 5 > 2') == 'select "A 1" from t where b = ? and c - ? > ?'


@settings(max_examples=200, deadline=None)
@given(st.integers(-(10**6), 10**6), st.integers(-(10**6), 10**6), st.text("abc' ", max_size=6), st.text("xyz' ", max_size=6))
def test_only_values_are_lost(a, b, s, t):
    make = lambda n, v: f"SELECT x FROM t WHERE y = {n} AND z = '{v.replace(chr(39), chr(39) * 2)}'"
    assert sqlmask.mask_exact(make(a, s)) == sqlmask.mask_exact(make(b, t))


@pytest.mark.parametrize(("case", "sql", "status"), EXECUTION_CASES)
def test_outcomes(spark, sf, case, sql, status):
    register_views(spark, sf)
    assert execsql.probe(spark, sql).status == status


@pytest.mark.parametrize("sql", ["CREATE TABLE x AS SELECT 1", "SET a = 1", "SELECT * FROM csv.`/etc/passwd`", "CACHE TABLE nation", "INSERT OVERWRITE DIRECTORY '/tmp/x' USING parquet SELECT 1", "SELECT java_method('java.util.UUID', 'randomUUID')"])
def test_refusals_run_nothing(spark, sf, sql):
    register_views(spark, sf)
    assert execsql.probe(spark, sql).status == "refused"


def test_a_nested_path_is_refused(spark, sf):
    register_views(spark, sf)
    assert execsql.probe(spark, "SELECT * FROM nation WHERE n_nationkey IN (SELECT id FROM parquet.`/tmp/y`)").status == "refused"


def test_the_time_limit(spark):
    began = time.time()
    slow = "SELECT count(*) AS n FROM range(100000000) a CROSS JOIN range(100000) b WHERE a.id + b.id = -1"
    assert execsql.probe(spark, slow, timeout_s=2).status == "timeout"
    assert time.time() - began < 30
