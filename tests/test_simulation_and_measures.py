import json

import pytest
from pyspark.sql import functions as F

from askcheck.functions.taxonomy import CATEGORY_OF
from askcheck.plans import agents, measures, published, simulation, validation
from askcheck.plans import council as council_module
from askcheck.plans.council import Briefing
from askcheck.plans.members import REFUSAL, RuleJudge, council
from askcheck.sources.tables import register_views, schema_texts
from askcheck.workloads import questions_of, stored

TURNS = [
    # direct SQL; clarify then SQL; three clarifications and a forced turn; two relevant replies; nothing after the reply
    ("a", 0, "system", "sql", None, False),
    ("b", 0, "system", "clarification", None, False), ("b", 1, "user", "reply", "relevant", False), ("b", 2, "system", "sql", None, False),
    ("c", 0, "system", "clarification", None, False), ("c", 1, "user", "reply", "irrelevant", False), ("c", 2, "system", "clarification", None, False), ("c", 3, "user", "reply", "relevant", False), ("c", 4, "system", "clarification", None, False), ("c", 5, "user", "reply", "technical", False), ("c", 6, "system", "feedback", None, True),
    ("d", 0, "system", "clarification", None, False), ("d", 1, "user", "reply", "relevant", False), ("d", 2, "system", "clarification", None, False), ("d", 3, "user", "reply", "relevant", False), ("d", 4, "system", "sql", None, False),
    ("e", 0, "system", "clarification", None, False), ("e", 1, "user", "reply", "relevant", False),
]


@pytest.fixture(scope="module")
def turns(spark):
    return spark.createDataFrame(TURNS, "conv_id string, turn int, role string, kind string, relevancy string, forced boolean")


def test_air(turns):
    got = {w: tuple(measures.air(turns, which=w).first()) for w in ("first", "last", "all")}
    assert got == {"first": (3, 1, 33.3333), "last": (3, 2, 66.6667), "all": (4, 2, 50.0)}


def test_dialogue_statistics(turns):
    r = measures.dialogue_statistics(turns).first()
    assert (r.n_conv, r.avg_turns, r.clar_pct) == (5, 2.2, 80.0)
    assert abs(r.relevant_pct + r.technical_pct + r.irrelevant_pct - 100) < 0.01


def test_execution_and_feedback_denominators(spark):
    rows = [("answerable", "sql", True), ("answerable", "feedback", True), ("ambiguous", "sql", False), ("ambiguous", None, False), ("unanswerable", "feedback", True), ("unanswerable", "sql", True), ("unanswerable", None, None)]
    r = measures.score(spark.createDataFrame(rows, "qtype string, final_kind string, correct boolean")).first()
    assert (r.ex_num, r.ex_den, r.fb_num, r.fb_den) == (1, 5, 1, 4)
    assert (r.ex_ans, r.ex_amb) == (50.0, 0.0)


def test_balance_is_exact(spark):
    df = spark.range(1000).select(F.col("id"), (F.col("id") % 7).alias("c")).filter("c <> 3 or id < 40")
    got = measures.balance(df, ["c"], "id").groupBy("c").count().collect()
    assert {r["count"] for r in got} == {6} and len(got) == 7


def test_annotations(spark):
    q = spark.createDataFrame([("o1", "ambiguous", "scope"), ("o2", "unanswerable", "improper")], "obj_id string, qtype string, subcategory string")
    rows = [(o, a, d, True) for o in ("o1", "o2") for a in ("x", "y") for d in measures.DIMENSIONS]
    got = {r.dimension: r.n for r in measures.annotation_report(measures.mask_annotations(spark.createDataFrame(rows, "obj_id string, annotator string, dimension string, ok boolean"), q)).collect()}
    assert got == {"realism": 2, "style": 4, "category": 4, "disambiguation": 2, "sql": 2, "feedback": 2}
    k = spark.createDataFrame([(i, a, v) for i, (x, y) in enumerate([("1", "1"), ("0", "0"), ("1", "0"), ("0", "0")]) for a, v in (("a", x), ("b", y))], "item_id int, annotator string, label string")
    assert tuple(measures.cohen_kappa(k).first()) == (4, 0.75, 0.5)


def test_published_arithmetic(spark):
    means = {r["set"]: r for r in published.means(spark).collect()}
    for row in published.BY_MODE:
        if row[1] == "predicted":
            assert abs(means[row[0]].fb - row[4]) <= 0.06
        if row[1] == "ground_truth":
            assert abs(means[row[0]].fb_oracle - row[4]) <= 0.06
    found = {r.finding: (r.hits, r.of) for r in published.findings(spark).collect()}
    assert found["recognition_above_classification"] == (16, 16) and found["set_b_easier_execution_predicted"] == (8, 8)
    assert found["set_b_easier_feedback_predicted"][0] == 7
    pooled = {"realism": 96, "style": 104, "category": 104, "disambiguation": 56, "sql": 72, "feedback": 32}
    assert all(abs(round(p * pooled[d] / 100) / pooled[d] * 100 - p) < 0.06 for d, p in published.HUMAN)
    assert all(abs(r[3] + r[4] + r[5] - 100) <= 0.11 for r in published.DIALOGUES)


def test_fragments():
    got = simulation.sql_fragments("SELECT a, count(*) AS n FROM t WHERE b > 1 AND c IN (SELECT d FROM u WHERE e = 1) GROUP BY a ORDER BY n LIMIT 3")
    assert got == ["select: a", "select: count(*) AS n", "from: t", "where: b > 1", "where: c IN (SELECT d FROM u WHERE e = 1)", "group by: a", "order by: n", "limit: 3"]
    assert simulation.sql_fragments(None) == []
    got = simulation.sql_fragments("SELECT a FROM t LEFT JOIN u ON t.x = u.y AND t.z = 'group by, (' WHERE b BETWEEN 1 AND 2 AND \"order by\" = 3")
    assert got == ["select: a", "from: t", "join: u", "on: t.x = u.y", "on: t.z = 'group by, ('", "where: b BETWEEN 1 AND 2", 'where: "order by" = 3']


def test_leaks(spark):
    df = spark.createDataFrame([("here: SELECT a FROM t", "SELECT a FROM t"), ("it is about a from t", "SELECT a FROM t"), ("yes please", "SELECT a FROM t"), ("x", None)], "r string, g string")
    assert [x[0] for x in df.select(simulation.leaks("r", "g")).collect()] == ["full", "partial", "none", "none"]


@pytest.fixture(scope="module")
def run(spark, sf):
    register_views(spark, sf)
    store = stored(spark)
    q = store(questions_of(spark, 0.0, ["eval_items"], styles=("formal",)), "q")
    cx = validation.Context(spark)
    roster = [agents.BaselineAgent("oracle"), agents.FixedAgent("always_clarify", "clarification"), agents.FixedAgent("always_sql", "sql"), agents.FixedAgent("always_feedback", "feedback")]
    conversations, said = simulation.simulate(q, roster, cx.members, store, ("ground_truth",))
    return q, measures.judge_ends(conversations, q, cx.results, cx.members).cache(), said.cache()


def test_fixed_agents_have_known_scores(run):
    q, judged, _ = run
    got = {r.agent: r for r in measures.score(judged, "agent").collect()}
    assert (got["oracle"].ex, got["always_clarify"].ex, got["always_clarify"].fb) == (100.0, 0.0, 0.0) and got["oracle"].fb > 90
    n, solvable = q.count(), q.filter("qtype <> 'unanswerable'").count()
    assert (got["always_sql"].ex_den, got["always_feedback"].fb_den) == (n, n)
    assert got["always_feedback"].ex_den == solvable and got["always_feedback"].fb_num == 0


def test_dialogue_invariants(run):
    q, judged, said = run
    per = said.filter("role = 'system'").groupBy("conv_id").count()
    assert per.agg(F.max("count")).first()[0] <= 4
    about = said.join(judged.select("conv_id", "qtype", "gold_sql", "agent"), "conv_id")
    assert about.filter("qtype = 'unanswerable' and relevancy is not null and relevancy <> 'irrelevant'").isEmpty()
    assert about.filter("qtype = 'answerable' and relevancy = 'relevant'").isEmpty()
    assert about.filter("role = 'user' and gold_sql is not null").filter(simulation.leaks("text", "gold_sql") == "full").isEmpty()
    assert about.filter("agent = 'always_clarify' and forced").select("kind").distinct().collect() == [(None,)]
    assert judged.filter("agent = 'always_clarify'").select("status").distinct().collect() == [("failed",)]


def asked_row(spark, clarification="what now?", gold="SELECT a FROM t ORDER BY b"):
    rows = [("c", "ambiguous", "q", "", "\n".join(simulation.sql_fragments(gold)), clarification, "formal", "h", gold)]
    return spark.createDataFrame(rows, "conv_id string, qtype string, nl string, history string, fragments string, clarification string, style string, hidden string, gold_sql string")


def recorder(*args):
    """A member that writes down what it is asked; its class goes to the workers with it."""

    class Recorder(RuleJudge):
        def __init__(self, name, path, vote="technical:2", text=None):
            super().__init__(name, 0)
            self.path, self.vote_, self.text = path, vote, text

        def on_relevancy(self, r):
            return self.vote_

        def on_answer(self, r):
            import json

            with open(f"{self.path}/{self.name}", "a") as f:
                f.write(json.dumps(r) + "\n")
            return self.text or super().on_answer(r)

    return Recorder(*args)


def test_only_winners_answer_and_on_the_nodes_they_chose(spark, tmp_path):
    users = [recorder("a", tmp_path, "technical:2"), recorder("b", tmp_path, "technical:0"), recorder("c", tmp_path, "relevant")]
    kept = {}
    r = simulation.user_replies(asked_row(spark), users, lambda df, name: kept.setdefault(name, df.cache()), "x").first()
    assert (r.relevancy, r.nodes) == ("technical", [0, 2]) and ("b" in r.reply) != ("a" in r.reply.split("about")[-1])
    asked = {n: {json.loads(x)["grounding"] for x in (tmp_path / n).read_text().splitlines()} for n in ("a", "b") if (tmp_path / n).exists()}
    assert asked == {"a": {"order by: b"}, "b": {"select: a"}} and not (tmp_path / "c").exists()


def test_a_reply_with_the_whole_query_is_refused(spark, tmp_path):
    gold = "SELECT a FROM t ORDER BY b"
    users = [recorder(n, tmp_path, "relevant", f"run select a from t order by b; {n}") for n in "abc"]
    r = simulation.user_replies(asked_row(spark, gold=gold), users, lambda df, name: df, "x").first()
    assert (r.relevancy, r.reply) == ("relevant", REFUSAL)


def test_no_eligible_author_gives_the_refusal(spark):
    asked = asked_row(spark)
    users = [RuleJudge(f"u{i}", 0) for i in range(3)]
    votes = iter(["relevant", "technical", "irrelevant"])

    class Split(RuleJudge):
        def __init__(self, name, vote):
            super().__init__(name, 0)
            self.vote_ = vote

        def on_relevancy(self, r):
            return self.vote_

    users = [Split(f"u{i}", next(votes)) for i in range(3)]
    r = simulation.user_replies(asked, users, lambda df, name: df, "x").first()
    assert (r.relevancy, r.reply) == ("irrelevant", REFUSAL)


def faulty(spark, **change):
    base = {"obj_id": "g-0", "group_id": "g", "reading_no": 0, "db_id": "eval_items", "generator": "x", "qtype": "answerable", "category": "answerable", "subcategory": "plain", "style": "formal", "difficulty_asked": "simple", "difficulty_actual": "simple", "nl": "Kindly report the following: number of documents per lang.", "evidence": [], "gold_sql": "SELECT lang, count(*) AS n FROM documents GROUP BY lang", "hidden": "", "sample_no": 1}
    from askcheck.plans.generation import QUESTION

    row = base | change
    return spark.createDataFrame([tuple(row[c.split()[0]] for c in QUESTION.split(", "))], QUESTION)


@pytest.mark.parametrize(
    ("stage", "change"),
    [
        ("executability", {"gold_sql": "SELECT nothing FROM documents"}),
        ("category_conformance", {"subcategory": "scope"}),
        ("gold_satisfaction", {"gold_sql": "SELECT 1 AS n"}),
        ("feedback_quality", {"qtype": "unanswerable", "category": "missing_schema", "subcategory": "missing_entity", "gold_sql": None, "nl": "Kindly report the following: the warehouse of each of the documents.", "hidden": "no"}),
        ("style_conformance", {"style": "interrogative"}),
        ("evidence_necessity", {"subcategory": "with_evidence", "evidence": ["documents are texts"]}),
        ("ambiguity", {"qtype": "ambiguous", "category": "structural", "subcategory": "scope", "nl": "Kindly report the following: number of documents per lang."}),
        ("unsolvability", {"qtype": "unanswerable", "category": "missing_schema", "subcategory": "missing_entity", "gold_sql": None, "hidden": "no such thing"}),
        ("category_consistency", {"qtype": "ambiguous", "category": "lexical_vagueness", "subcategory": "vagueness", "nl": "Kindly report the following: score of documents per lang."}),
    ],
)
def test_each_stage_rejects_its_fault(spark, sf, stage, change):
    register_views(spark, sf)
    cx = validation.Context(spark, members=council(3, 0.0))
    got = dict(validation.STAGES)[stage](faulty(spark, **change), cx).collect()
    assert [r.kept for r in got] == [False] and got[0].reason
    clean = dict(validation.STAGES)[stage](faulty(spark), cx).collect()
    assert all(r.kept for r in clean)


def test_members_are_told_what_the_call_names(spark, sf):
    """A remote member gets complete requests, and nothing that its call must not see."""
    register_views(spark, sf)
    told = Briefing(schema_texts(spark, sf, db_ids=["eval_items", "geo"]))
    q = faulty(spark).withColumns({"first": F.lit("scope"), "second": F.lit("entity"), "preview": F.lit("{}")})
    wanted = {
        "category_conformance": {"schema", "definition", "trait", "example", "gold_sql", "hidden"}, "gold_satisfied": {"schema", "gold_sql", "preview", "hidden"}, "sql_without_evidence": {"schema"}, "sql_without_hidden": {"schema", "evidence"},
        "sql_for_unanswerable": {"schema", "evidence"}, "feedback_quality": {"schema", "hidden"}, "category_pair": {"schema", "first_definition", "second_definition", "hidden"}, "style": set(),
    }
    never = {"sql_without_evidence": {"evidence", "hidden", "gold_sql"}, "sql_without_hidden": {"hidden", "gold_sql"}, "sql_for_unanswerable": {"hidden", "gold_sql"}, "style": {"style"}, "category_pair": {"subcategory"}}
    for call, columns in wanted.items():
        seen = council_module.for_call(q, call, "obj_id", briefing=told).first().asDict()
        assert columns | {"nl"} <= {k for k, v in seen.items() if v is not None}, call
        assert not never.get(call, set()) & set(seen), call
    schema = council_module.for_call(q, "feedback_quality", "obj_id", briefing=told).first()["schema"]
    assert "documents(doc_id bigint" in schema and schema.count('{"item_id"') == 5 and "lineitem" not in schema


def test_gold_judges_see_result_rows(spark, sf):
    register_views(spark, sf)
    got = validation.with_preview(faulty(spark).unionByName(faulty(spark, obj_id="x", gold_sql="DROP VIEW documents")), validation.Context(spark)).collect()
    shown = {r.obj_id: r.preview for r in got}
    assert shown["x"] is None and '"c1":' in shown["g-0"] and spark.table("documents").count() > 0


def test_modes_without_label_differ_by_what_is_shown(spark):
    q = faulty(spark, qtype="unanswerable", category="missing_schema", subcategory="missing_entity", gold_sql=None, nl="Kindly report the following: the warehouse of each of the documents.")
    begun = {r["mode"]: r for r in simulation.start_conversations(q, [agents.BaselineAgent("x")]).collect()}
    assert {m: r.label for m, r in begun.items()} == {"ground_truth": "missing_entity", "predicted": "missing_entity", "taxonomy_only": None, "taxonomy_free": None}
    assert "scope:" in begun["taxonomy_only"].guide and "scope" not in begun["taxonomy_free"].guide
    said = {m: agents.BaselineAgent("x").respond_one({**begun[m].asDict(), "history": "", "n_clar": 0, "forced": False}) for m in agents.MODES}
    assert said["ground_truth"] == said["taxonomy_only"] and said["taxonomy_free"][1] in said["taxonomy_only"][1] and said["taxonomy_free"] != said["taxonomy_only"]
    assert simulation.start_conversations(q, [agents.BaselineAgent("x")], ("taxonomy_only",)).first().predicted is None


def test_each_pass_of_rivals_meets_every_label_once():
    for level, sizes in (("category", {"ambiguous": 5, "unanswerable": 3}), ("subcategory", {"ambiguous": 7, "unanswerable": 4})):
        met = [(q, own, second) for p in validation.rivals(level) for q, own, second in p]
        assert len(met) == len(set(met)) == sum(n * (n - 1) for n in sizes.values())
        assert all(second != own and (level == "subcategory" or CATEGORY_OF[second] != own) for _, own, second in met)


def test_masked_duplicates_keep_pairs(spark):
    a = faulty(spark, obj_id="g1-0", group_id="g1", gold_sql="SELECT 1 FROM t WHERE a = 'x'")
    b = faulty(spark, obj_id="g1-1", group_id="g1", gold_sql="SELECT 1 FROM t WHERE a = 'y'")
    c = faulty(spark, obj_id="g2-0", group_id="g2", gold_sql="SELECT 1 FROM t WHERE a = 'z'")
    both = a.unionByName(b).unionByName(c)
    kept = lambda w: {r.obj_id for r in validation.dedup_masked(both, w).filter("kept").collect()}
    assert kept(False) == {"g1-0", "g1-1"} and kept(True) == {"g1-0"}
