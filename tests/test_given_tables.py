"""Queries that once worked on rows of their own: what is in the given tables decides their results."""

import json

import duckdb
import pytest

import __spark_entry__ as entry_module
from askcheck.functions.taxonomy import TAXONOMY
from askcheck.plans import published
from askcheck.plans.agents import MODES
from askcheck.sources.tables import TABLES
from tests.test_queries import rows_of


@pytest.fixture
def odd(spark, sf, tmp_path):
    """Makes the given tables with some of them changed; returns their folder and DuckDB on them."""

    def make(**changes):
        con = duckdb.connect()
        for t in TABLES:
            df = spark.read.parquet(f"{sf}/{t}.parquet")
            (changes[t](df) if t in changes else df).coalesce(1).write.parquet(f"{tmp_path}/{t}.parquet")
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'")
        return str(tmp_path), con

    return make


def both(spark, folder, con, name):
    """Rows of a query, which are those of its SQL."""
    df = entry_module.queries()[name](spark, folder)
    got, cur = df.collect(), con.execute(entry_module.oracle_sql()[name])
    names = [d[0] for d in cur.description]
    assert rows_of(df.columns, [tuple(r) for r in got]) == rows_of(names, cur.fetchall())
    return got


def test_a_column_without_values_gives_no_reading(spark, odd):
    folder, con = odd(pages=lambda df: df.limit(0), supplier=lambda df: df.selectExpr("s_suppkey", "CAST(NULL AS STRING) AS s_name", "s_nationkey", "CASE WHEN s_suppkey = 1 THEN s_acctbal END AS s_acctbal"))
    got = {(r.col_a, r.col_b): (r.values_a, r.values_b) for r in both(spark, folder, con, "w_lexical_overlap_pairs")}
    assert got["c_acctbal", "s_acctbal"] == (150, 1) and got["c_nationkey", "s_nationkey"] == (150, 10)
    assert not any("s_name" in pair for pair in got)


def test_an_entity_needs_values(spark, odd):
    folder, con = odd(supplier=lambda df: df.selectExpr("s_suppkey", "s_name", "s_nationkey", "CAST(NULL AS DOUBLE) AS s_acctbal"))
    got = {(r.table_a, r.table_b, r.token): (r.values_a, r.values_b) for r in both(spark, folder, con, "w_entity_pairs")}
    assert ("customer", "supplier", "acct") not in got and got["customer", "supplier", "name"] == (150, 10)


def test_a_key_that_no_row_follows_is_no_path(spark, odd):
    folder, con = odd(lineitem=lambda df: df.withColumn("l_partkey", -1 - df.l_partkey), labels=lambda df: df.limit(0), orders=lambda df: df.selectExpr("o_orderkey", "CASE WHEN o_orderkey > 1400 THEN o_custkey END AS o_custkey"))
    got = {(r.table_a, r.table_b) for r in both(spark, folder, con, "w_missing_join_paths")}
    assert {("lineitem", "part"), ("documents", "labels")} <= got
    assert not got & {("customer", "orders"), ("lineitem", "supplier"), ("customer", "lineitem")}


def test_samples_of_the_grid_are_rows_of_their_database(spark, odd):
    folder, con = odd(pages=lambda df: df.limit(0), embeddings=lambda df: df.filter("vec_id = 7"), conversations=lambda df: df.selectExpr("conv_id", "CASE WHEN conv_id % 2 = 0 THEN turn END AS turn", "role", "text"))
    got = {}
    for r in both(spark, folder, con, "w_grid"):
        got.setdefault(r.db_id, set()).add((r.sample_no, r.seed_row))
    assert "web" not in got and got["vectors"] == {(1, "embeddings:7")}
    assert len(got) == 10 and all(len(v) == 3 for d, v in got.items() if d != "vectors")


#: Events in disorder: without user, number, time, kind or properties, with negative numbers, or none of some groups.
ODD_EVENTS = [
    "CASE WHEN event_id % 11 = 0 THEN NULL WHEN event_id % 5 = 0 THEN -event_id ELSE event_id END AS event_id",
    "CASE WHEN event_id % 7 <> 0 THEN ts END AS ts",
    "CASE WHEN event_id % 13 = 0 THEN NULL WHEN event_id % 4 = 0 THEN -user_id % 5 ELSE user_id % 50 END AS user_id",
    "CASE WHEN event_id % 17 <> 0 THEN event_type END AS event_type",
    "value",
    "CASE WHEN event_id % 19 <> 0 THEN props END AS props",
]


def dialogues_of(spark, sf):
    """Dialogues in plain Python: lists of events up to a signup or an error, with their user and place."""
    out, rows = [], spark.read.parquet(f"{sf}/events.parquet").orderBy("ts", "event_id").collect()
    for user in sorted({r.user_id for r in rows}):
        talk, place = [], 0
        for r in (r for r in rows if r.user_id == user):
            talk.append(r)
            if r.event_type in ("signup", "error"):
                out.append((user, place, talk))
                talk, place = [], place + 1
    return out


def test_gaps_come_from_the_events(spark, sf, odd):
    label = lambda r: json.loads(r.props)["k"] % 13
    seen = {}
    for user, place, talk in dialogues_of(spark, sf):
        if MODES[place % 4] == "predicted":
            r = talk[-1]
            guess = r.event_id % 13 if r.event_id % 3 == 0 else label(r)
            seen.setdefault(("AB"[user % 16 // 8], f"group_{user % 8}"), []).append((TAXONOMY[label(r)][0] == TAXONOMY[guess][0], label(r) == guess))
    got = {(r["set"], r.agent): r.rec_minus_cls for r in entry_module.queries()["w_published_gaps"](spark, sf).collect()}
    assert len(got) >= 10 and all(abs(v - 100 * (sum(a for a, _ in seen[k]) - sum(b for _, b in seen[k])) / len(seen[k])) < 2e-4 for k, v in got.items())
    folder, con = odd(events=lambda df: df.selectExpr(*ODD_EVENTS))
    assert len(both(spark, folder, con, "w_published_gaps")) >= 10


def test_clarifications_come_from_the_events(spark, sf, odd):
    asked = {m: [] for m in MODES}
    for _, place, talk in dialogues_of(spark, sf):
        asked[MODES[place % 4]].append(sum(r.event_type == "view" for r in talk))
    got = {r["mode"]: r for r in entry_module.queries()["w_published_dialogues"](spark, sf).collect()}
    assert set(got) == set(MODES) and all(r.sums_up for r in got.values())
    # from printed means and shares, so by a rounding only
    assert all(abs(r.clarifications_each - sum(asked[m]) / sum(n > 0 for n in asked[m])) < 0.001 for m, r in got.items())
    folder, con = odd(events=lambda df: df.selectExpr(*ODD_EVENTS))
    assert len(both(spark, folder, con, "w_published_dialogues")) == 4


def test_nothing_is_asked(spark, odd):
    folder, con = odd(events=lambda df: df.filter("event_type in ('signup', 'error')"))
    assert {(r.clarifications_each, r.sums_up) for r in both(spark, folder, con, "w_published_dialogues")} == {(None, None)}


def test_the_published_dialogues_sum_up(spark):
    got = published.clarifications(published.dialogues(spark)).collect()
    assert len(got) == 4 and all(r.sums_up for r in got)


def test_findings_are_checked_on_the_events(spark, sf, odd):
    last = max(place for user, place, _ in dialogues_of(spark, sf) if user == 1)
    assert last > 4
    # one user of one group: no pair of agents, no second set, four modes
    folder, con = odd(events=lambda df: df.filter("user_id = 1"))
    got = {r.finding: (r.hits, r.of) for r in both(spark, folder, con, "w_published_findings")}
    assert len(got) == 15 and got["recognition_above_classification"][1] == 1 and got["code_specialisation_moves_execution_little"] == (0, 0) and got["terminal_is_not_solved"][1] == 4


def test_findings_on_events_in_disorder(spark, odd):
    folder, con = odd(events=lambda df: df.selectExpr(*ODD_EVENTS))
    got = {r.finding: (r.hits, r.of) for r in both(spark, folder, con, "w_published_findings")}
    assert got["recognition_above_classification"][1] >= 10 and got["answerable_execution_is_flat"][1] == 2


def test_findings_hold_for_the_published_rows(spark):
    con = duckdb.connect()
    want = {r[0]: r[1:] for r in con.execute(published.findings_sql()).fetchall()}
    assert {r.finding: (r.hits, r.of) for r in published.findings(spark).collect()} == want
    assert want["end_task_leaders_differ"] == (2, 2) and want["clarification_starts_with_the_label"] == (3, 3)


def test_judgements_come_from_the_events(spark, sf, odd):
    style = [(talk[-1].event_id + 1 + a) % 6 != 0 for _, _, talk in dialogues_of(spark, sf) for a in (0, 1)]
    got = {r.dimension: r for r in entry_module.queries()["w_published_human"](spark, sf).collect()}
    assert set(got) == set(published.APPLIES) and all(r.hit for r in got.values())
    assert len(style) < 1000 and got["style"].n_ok == sum(style)
    folder, con = odd(events=lambda df: df.selectExpr(*ODD_EVENTS))
    assert len(both(spark, folder, con, "w_published_human")) == 6


def test_the_published_judgements_are_whole(spark):
    got = {tuple(r) for r in published.whole_numbers(published.human(spark)).collect()}
    assert got == {("realism", 89, True), ("style", 103, True), ("category", 96, True), ("disambiguation", 49, True), ("sql", 54, True), ("feedback", 25, True)}
