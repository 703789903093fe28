from collections import Counter
from itertools import permutations, product

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from askcheck.plans import council, equivalence
from askcheck.plans.members import RuleJudge
from askcheck.plans.members import council as judges


@pytest.mark.parametrize("size", [1, 2, 3, 4])
def test_majority_and_plurality_over_all_ballots(spark, size):
    combos = list(product("RTI", repeat=size))
    rows = [(i, f"m{k}", v) for i, c in enumerate(combos) for k, v in enumerate(c)]
    ballots = spark.createDataFrame(rows, "item_id int, member string, vote string")
    strict = {r.item_id: r.kept for r in council.majority(ballots, size, "R").collect()}
    won = {r.item_id: (r.winner, r.tied) for r in council.plurality(ballots, "I").collect()}
    for i, c in enumerate(combos):
        n = Counter(c)
        top = [v for v in n if n[v] == max(n.values())]
        assert strict[i] == (2 * n["R"] > size)
        assert won[i] == (("I", True) if len(top) > 1 else (top[0], False))


def test_a_missing_ballot_is_a_no(spark):
    ballots = spark.createDataFrame([("a", "m1", "yes"), ("b", "m1", "yes"), ("b", "m2", "yes")], "item_id string, member string, vote string")
    assert {r.item_id: r.kept for r in council.majority(ballots, 3).collect()} == {"a": False, "b": True}


def test_early_exit_gives_the_same_verdicts(spark):
    rows = [(f"i{k}", nl, "web") for k, nl in enumerate(["What is the number of pages per url?", "hey, get me the poem about pages, ok", "nothing known"] * 5)]
    df = spark.createDataFrame(rows, "item_id string, nl string, db_id string").withColumn("hidden", F.lit("ask about pages"))
    members = judges(3, 0.4)
    full = {(r.item_id, r.kept) for r in council.majority(council.collect_ballots(df, members, "feedback_quality"), 3).collect()}
    assert {(r.item_id, r.kept) for r in council.early_exit(df, members, "feedback_quality").collect()} == full


def test_members_see_only_their_columns(spark):
    df = spark.createDataFrame([("a", "q", "db", "SELECT 1", "secret")], "item_id string, nl string, db_id string, gold_sql string, hidden string")
    plan = council.collect_ballots(df, judges(), "sql_without_hidden")._jdf.queryExecution().optimizedPlan().toString()
    assert "gold_sql" not in plan.split("MapInPandas")[1].split("LogicalRDD")[0]
    assert "hidden" not in council.for_call(df, "sql_without_hidden", "item_id").columns
    assert "gold_sql" not in council.for_call(df, "sql_without_evidence", "item_id").columns
    assert RuleJudge("x", 0).vote("style", df.toPandas()) == ["formal"]


VALUES = st.one_of(st.none(), st.integers(-2, 2), st.sampled_from([0.0, -0.0, 0.5]))


def brute_equal(a, b, na, nb, superset):
    if superset == "none" and na != nb:
        return False
    rows = lambda data, cols: Counter(tuple(("~" if r[c] is None else float(r[c]) + 0.0) for c in cols) for r in data)
    return any(rows(a, range(na)) == rows(b, p) for p in permutations(range(nb), na)) if na <= nb else False


@settings(max_examples=25, deadline=None)
@given(st.integers(1, 3), st.integers(1, 3), st.data())
def test_equivalence_against_all_column_maps(spark, na, nb, data):
    n = data.draw(st.integers(0, 3))
    a = data.draw(st.lists(st.tuples(*[VALUES] * na), min_size=n, max_size=n))
    picks = data.draw(st.lists(st.integers(0, na - 1), min_size=nb, max_size=nb))
    b = [tuple(r[k] for k in picks) for r in data.draw(st.permutations(a))]
    if b and data.draw(st.booleans()):
        b[0] = (data.draw(VALUES), *b[0][1:])
    frame = lambda rows, k: spark.createDataFrame([tuple(None if v is None else float(v) for v in r) for r in rows], ", ".join(f"x{i} double" for i in range(k)))
    for superset in ("candidate", "none"):
        assert equivalence.equivalent(frame(a, na), frame(b, nb), superset) == brute_equal(a, b, na, nb, superset)


def test_columns_that_agree_one_by_one_may_still_pair_differently(spark):
    a = spark.createDataFrame([(1, "x"), (2, "y")], "a int, b string")
    b = spark.createDataFrame([(1, "y"), (2, "x")], "a int, b string")
    assert equivalence.fingerprint(a).columns == equivalence.fingerprint(b).columns
    assert not equivalence.equivalent(a, b)
    assert equivalence.equivalent(a, a, exact=True) and not equivalence.exact_confirm(a, b, {0: 0, 1: 1})


def test_many_columns_of_one_multiset(spark):
    """Ten columns with the same values: equal ones are interchangeable, rows so far prune the others."""
    rows = [[(i * k) % 11 for k in range(1, 11)] for i in range(11)]
    a = spark.createDataFrame(rows, ", ".join(f"c{k} int" for k in range(10)))
    b = a.select(*reversed(a.columns))
    assert equivalence.equivalent(a, b) and equivalence.equivalent(b, a, "none")
    torn = spark.createDataFrame([[*r[:9], (r[9] + (i < 2)) % 11] for i, r in enumerate(rows)], a.schema)
    assert not equivalence.equivalent(a, torn)
    same = spark.range(5).select(*(F.col("id").alias(f"c{k}") for k in range(12)))
    assert equivalence.equivalent(same, same.select(*reversed(same.columns)))


def test_strict_order_by_place(spark):
    q = spark.createDataFrame([(i % 5, i) for i in range(60)], "a int, b int")
    ordered = q.repartition(7).orderBy("b")
    assert equivalence.strict_equal(ordered, q.coalesce(1).orderBy("b").toDF("x", "y"))
    assert not equivalence.strict_equal(ordered, q.orderBy(F.desc("b"))) and not equivalence.strict_equal(ordered, ordered.select("b", "a"))
    swapped = spark.createDataFrame([(i % 5, {10: 11, 11: 10}.get(i, i)) for i in range(60)], "a int, b int")
    assert not equivalence.strict_equal(ordered, swapped.withColumn("b", F.col("b")).coalesce(1))
    assert equivalence.strict_equal(q.limit(0), q.filter("a > 9")) and not equivalence.strict_equal(q.limit(1), q.limit(2))


def test_cached_results_equal_direct_ones(spark):
    spark.range(20).selectExpr("id", "id % 3 AS g", "id % 3 AS h", "cast(id as string) AS s").createOrReplaceTempView("numbers")
    texts = ["SELECT id, g FROM numbers", "SELECT g, id FROM numbers ORDER BY id DESC", "SELECT id, h, g FROM numbers", "SELECT g FROM numbers", "SELECT id, (id + 1) % 3 FROM numbers WHERE id < 18", "SELECT id, g FROM numbers WHERE id < 18",
             "SELECT id AS a, id AS b, g AS c FROM numbers", "SELECT DISTINCT g FROM numbers", "SELECT 1 / (id - id) FROM numbers", "SELECT absent FROM numbers", "SELEKT 1", "DROP VIEW numbers", "SELECT id FROM numbers WHERE id < 0", "SELECT s FROM numbers WHERE id < 0"]
    runs = texts[:8] + texts[12:]
    cache = equivalence.ResultCache(spark)
    for superset in ("candidate", "none"):
        got = cache.equal_many([(a, b) for a in texts for b in texts], superset)
        for a in texts:
            for b in texts:
                assert got[a, b] == (a in runs and b in runs and equivalence.equivalent(spark.sql(a), spark.sql(b), superset)), (a, b, superset)


def test_candidates_cannot_touch_data_or_run_on(spark, tmp_path):
    spark.range(5).write.parquet(f"{tmp_path}/t")
    spark.read.parquet(f"{tmp_path}/t").createOrReplaceTempView("victim")
    gold = "SELECT count(*) AS n FROM victim"
    hostile = ["DROP VIEW victim", "INSERT INTO victim SELECT * FROM victim", "CREATE OR REPLACE TEMP VIEW victim AS SELECT 1 AS id", f"SELECT count(*) AS n FROM parquet.`{tmp_path}/t`", "SELECT reflect('java.lang.System', 'exit', 0) AS n",
               "SET spark.sql.shuffle.partitions = 1", "SELECT count(*) AS n FROM range(10000000000) a CROSS JOIN range(100000) b WHERE a.id + b.id = -1"]
    cache = equivalence.ResultCache(spark, timeout_s=3)
    got = cache.equal_many([(gold, h) for h in [*hostile, "SELECT 5 AS n"]])
    assert got == {(gold, h): False for h in hostile} | {(gold, "SELECT 5 AS n"): True}
    assert spark.table("victim").count() == 5 and spark.read.parquet(f"{tmp_path}/t").count() == 5


def test_types_share_a_canonical_form(spark):
    one = lambda sql: equivalence.canonical(spark.sql(f"SELECT {sql} AS v")).first()[0]
    assert one("CAST(1 AS INT)") == one("CAST(1 AS BIGINT)") == one("CAST(1.0 AS DOUBLE)") == one("CAST(1.00 AS DECIMAL(10,2))") == "=1"
    assert one("CAST('-0.0' AS DOUBLE)") == one("0") == "=0"
    assert one("CAST(NULL AS INT)") != one("'~'") and one("CAST('NaN' AS DOUBLE)") == "=NaN"
    assert one("DATE '2020-01-02'") == one("TIMESTAMP_NTZ '2020-01-02 00:00:00'")
    assert one("map('b', 1, 'a', 2)") == one("map('a', 2, 'b', 1)")


def test_candidates_join_by_result(spark):
    cols = lambda *v: [__import__("decimal").Decimal(x) for x in v]
    c = spark.createDataFrame([("c1", "d", 2, cols(1, 2)), ("c2", "d", 3, cols(1, 2))], "id string, db_id string, n_rows long, cols array<decimal(38,0)>")
    g = spark.createDataFrame([("g1", "d", 2, cols(2, 1))], "id string, db_id string, n_rows long, cols array<decimal(38,0)>")
    assert [tuple(r) for r in equivalence.equivalence_join(c, g).collect()] == [("c1", "g1")]
