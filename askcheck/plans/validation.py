"""The validation cascade: ten stages in a fixed order, each on the survivors of the one before.

A stage maps questions to verdicts (obj_id, kept, reason, n_yes, n_members); the
runner materialises survivors after each, so no member is called twice.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import sqlmask
from ..functions.taxonomy import TAXONOMY
from .council import Briefing, collect_ballots, majority
from .equivalence import ResultCache, union_all
from .execsql import check_executable
from .members import council as default_council

VERDICT = ("obj_id", "kept", "reason", "n_yes", "n_members")


@dataclass
class Context:
    spark: SparkSession
    members: list = field(default_factory=default_council)
    results: ResultCache | None = None
    timeout_s: float = 20.0
    drop: str = "reading"  # or "group": what a majority for one reading removes
    level: str = "category"  # or "subcategory": what the consistency stage compares
    within_group: bool = False  # whether masked duplicates inside a pair count
    superset: str = "candidate"
    briefing: Briefing | None = None  # schema texts for members
    store: Callable[[DataFrame, str], DataFrame] | None = None  # how steps inside a stage are materialised

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        return self.store(df, name) if self.store else df

    def ballots(self, df: DataFrame, call: str, item: str = "item_id", members: list | None = None) -> DataFrame:
        return collect_ballots(df, members or self.members, call, item, self.briefing)

    def __post_init__(self) -> None:
        self.results = self.results or ResultCache(self.spark, timeout_s=self.timeout_s)


def verdicts(kept: DataFrame, reason: str, n_yes: str | None = None, n_members: str | None = None) -> DataFrame:
    null = F.lit(None).cast("bigint")
    return kept.select("obj_id", "kept", F.when(~F.col("kept"), reason).alias("reason"), (F.col(n_yes) if n_yes else null).cast("bigint").alias("n_yes"), (F.col(n_members) if n_members else null).cast("bigint").alias("n_members"))


def dedup_exact(df: DataFrame, keys: list[str], order: str) -> DataFrame:
    """``df`` with kept: the first of equal rows in ``order``. One shuffle, on a hash of the keys; equal hashes are checked by the keys themselves."""
    key = F.xxhash64(*keys)
    first = Window.partitionBy("_key", *keys).orderBy(order)
    return df.withColumn("_key", key).withColumn("kept", F.row_number().over(first) == 1).drop("_key")


def dedup_masked(df: DataFrame, within_group: bool = False) -> DataFrame:
    """``df`` with kept: no other group produced the same masked query on the database before."""
    masked = df.withColumn("_masked", sqlmask.mask_values("gold_sql"))
    owner = F.min("obj_id" if within_group else "group_id").over(Window.partitionBy("db_id", "_masked"))
    own = F.col("obj_id") if within_group else F.col("group_id")
    return masked.withColumn("kept", F.col("gold_sql").isNull() | (own == owner)).drop("_masked")


def stage_duplicates(df: DataFrame, cx: Context) -> DataFrame:
    keyed = df.withColumn("_evidence", F.to_json("evidence"))
    exact = dedup_exact(keyed, ["db_id", "nl", "subcategory", "style", "_evidence", "hidden", "gold_sql"], "obj_id").drop("_evidence")
    left = exact.filter("kept").drop("kept")
    masked = verdicts(dedup_masked(left, cx.within_group), "masked duplicate")
    return masked.unionByName(verdicts(exact.filter("not kept"), "exact duplicate"))


def stage_executable(df: DataFrame, cx: Context) -> DataFrame:
    ran = check_executable(df.filter("qtype <> 'unanswerable'"), "gold_sql", cx.results.outcomes_of)
    return ran.select("obj_id", F.coalesce(F.col("status") == "ok", F.lit(False)).alias("kept"), F.when(F.coalesce(F.col("status"), F.lit("")) != "ok", F.coalesce("status", F.lit("no query"))).alias("reason"), F.lit(None).cast("bigint").alias("n_yes"), F.lit(None).cast("bigint").alias("n_members"))


def _by_majority(df: DataFrame, cx: Context, call: str, reason: str, yes: str = "yes") -> DataFrame:
    return verdicts(majority(cx.ballots(df, call, "obj_id"), len(cx.members), yes, "obj_id"), reason, "n_yes", "n_members")


def stage_conformance(df: DataFrame, cx: Context) -> DataFrame:
    return _by_majority(df, cx, "category_conformance", "does not fit its category")


def stage_gold(df: DataFrame, cx: Context) -> DataFrame:
    """Members see the query and the first rows of its result."""
    return _by_majority(with_preview(df.filter("qtype <> 'unanswerable'"), cx), cx, "gold_satisfied", "query does not answer the question")


def with_preview(df: DataFrame, cx: Context) -> DataFrame:
    """``df`` with preview: the first rows of the result of gold_sql as JSON, null where it has none."""
    texts = [r[0] for r in df.select("gold_sql").distinct().collect() if r[0]]  # as many as there are candidate queries
    found = cx.spark.createDataFrame(list(cx.results.previews(texts).items()), "gold_sql string, preview string")
    return df.join(found, "gold_sql", "left")


def equal_to_gold(ballots: DataFrame, df: DataFrame, cx: Context) -> DataFrame:
    """ballots with vote yes where the member's query is equivalent to the object's gold query. Distinct pairs run once."""
    joined = ballots.withColumnRenamed("vote", "candidate").join(df.select("obj_id", "gold_sql"), "obj_id")
    pairs = [(r["gold_sql"], r["candidate"]) for r in joined.select("gold_sql", "candidate").distinct().collect()]  # as many as candidate queries
    equal = cx.results.equal_many([(g, c) for g, c in pairs if c], cx.superset)
    found = [(g, c, equal.get((g, c), False)) for g, c in pairs]
    known = cx.spark.createDataFrame(found, "gold_sql string, candidate string, equal boolean")
    return joined.join(known, ["gold_sql", "candidate"]).select("obj_id", "member", F.when(F.col("equal"), "yes").otherwise("no").alias("vote"))


def stage_evidence(df: DataFrame, cx: Context) -> DataFrame:
    asked = df.filter("qtype = 'answerable' and size(evidence) > 0")
    votes = equal_to_gold(cx.ballots(asked, "sql_without_evidence", "obj_id"), asked, cx)
    needless = majority(votes, len(cx.members), item="obj_id")
    return verdicts(needless.withColumn("kept", ~F.col("kept")), "evidence is not needed", "n_yes", "n_members")


def stage_ambiguity(df: DataFrame, cx: Context) -> DataFrame:
    """Members answer once for each group, since its readings share the text; each reading is compared on its own."""
    asked = df.filter("qtype = 'ambiguous'")
    once = asked.groupBy("group_id").agg(*(F.first(c).alias(c) for c in ("nl", "db_id", "evidence")))
    ballots = cx.ballots(once, "sql_without_hidden", "group_id")
    spread = asked.select("obj_id", "group_id").join(ballots, "group_id").select("obj_id", "member", "vote")
    taken = majority(equal_to_gold(spread, asked, cx), len(cx.members), item="obj_id")
    out = taken.withColumn("kept", ~F.col("kept"))
    if cx.drop == "group":
        groups = out.join(asked.select("obj_id", "group_id"), "obj_id")
        out = groups.withColumn("kept", F.min("kept").over(Window.partitionBy("group_id"))).drop("group_id")
    return verdicts(out, "one reading dominates", "n_yes", "n_members")


def stage_unsolvable(df: DataFrame, cx: Context) -> DataFrame:
    """Any member's query that runs and is judged to answer the question removes it. No proof, a conservative attempt.

    Members try one after another, each on what nobody has solved yet.
    """
    asked = df.filter("qtype = 'unanswerable'")
    live, solved = asked, []
    for m in cx.members:
        tries = cx.keep(cx.ballots(live, "sql_for_unanswerable", "obj_id", [m]).filter("vote <> ''"), f"tries-{m.name}")
        texts = [r["vote"] for r in tries.select("vote").distinct().collect()]  # as many as candidate queries
        ok = [t for t, o in cx.results.outcomes_of(texts).items() if o.status == "ok"]
        if not ok:
            continue
        running = tries.join(F.broadcast(cx.spark.createDataFrame([(t,) for t in ok], "vote string")), "vote", "left_semi")
        judged = running.drop("member").join(live.select("obj_id", "nl", "db_id", "hidden"), "obj_id").withColumn("gold_sql", F.col("vote"))
        answers = majority(cx.ballots(with_preview(judged, cx), "gold_satisfied", "obj_id"), len(cx.members), item="obj_id").filter("kept")
        solved.append(cx.keep(answers.select("obj_id"), f"solved-{m.name}"))
        live = live.join(solved[-1], "obj_id", "left_anti")
    if not solved:
        return verdicts(asked.withColumn("kept", F.lit(True)), "")
    all_solved = union_all(solved).withColumn("solved", F.lit(True))
    return verdicts(asked.select("obj_id").join(all_solved, "obj_id", "left").withColumn("kept", F.col("solved").isNull()), "a query answers it")


def stage_feedback(df: DataFrame, cx: Context) -> DataFrame:
    return _by_majority(df.filter("qtype = 'unanswerable'"), cx, "feedback_quality", "feedback is vague or wrong")


def rivals(level: str = "category") -> list[list[tuple[str, str, str]]]:
    """Passes of (qtype, own, second): in each, every label meets one other of its type that it has not met."""
    at = 1 if level == "category" else 2
    passes: list[list[tuple[str, str, str]]] = []
    for qtype in ("ambiguous", "unanswerable"):
        firsts = {t[at]: t[2] for t in reversed(TAXONOMY) if t[0] == qtype}  # the first subcategory stands for its category
        names = sorted(firsts)
        for k in range(1, len(names)):
            if len(passes) < k:
                passes.append([])
            passes[k - 1] += [(qtype, own, firsts[names[(i + k) % len(names)]]) for i, own in enumerate(names)]
    return passes


def stage_consistency(df: DataFrame, cx: Context) -> DataFrame:
    """The assigned category must win a strict majority against each other one of its type. One pass for each competitor, on who has not lost yet."""
    own = "category" if cx.level == "category" else "subcategory"
    live = df.filter("qtype in ('ambiguous', 'unanswerable')").select("obj_id", "nl", "db_id", "hidden", "qtype", F.col(own).alias("own"), F.col("subcategory").alias("first"))
    lost = []
    for k, pairs in enumerate(rivals(cx.level), 1):
        items = live.join(F.broadcast(cx.spark.createDataFrame(pairs, "qtype string, own string, second string")), ["qtype", "own"])
        wins = cx.ballots(items, "category_pair", "obj_id").join(items.select("obj_id", "first"), "obj_id").withColumn("vote", F.when(F.col("vote") == F.col("first"), "yes").otherwise("no"))
        judged = cx.keep(majority(wins, len(cx.members), item="obj_id"), f"rivals-{k}")
        lost.append(judged.filter("not kept"))
        if k == 1:
            n_yes = judged.select("obj_id", "n_yes")
        else:
            n_yes = union_all([n_yes, judged.select("obj_id", "n_yes")]).groupBy("obj_id").agg(F.min("n_yes").alias("n_yes"))
        live = live.join(lost[-1], "obj_id", "left_anti")
    out = n_yes.withColumns({"kept": 2 * F.col("n_yes") > len(cx.members), "n_members": F.lit(len(cx.members))})
    return verdicts(out, "another category fits better", "n_yes", "n_members")


def stage_style(df: DataFrame, cx: Context) -> DataFrame:
    votes = cx.ballots(df.select("obj_id", "nl"), "style", "obj_id").join(df.select("obj_id", "style"), "obj_id")
    agreed = majority(votes.withColumn("vote", F.when(F.col("vote") == F.col("style"), "yes").otherwise("no")), len(cx.members), item="obj_id")
    return verdicts(agreed, "another style", "n_yes", "n_members")


STAGES: tuple[tuple[str, Callable[[DataFrame, Context], DataFrame]], ...] = (
    ("duplicates", stage_duplicates),
    ("executability", stage_executable),
    ("category_conformance", stage_conformance),
    ("gold_satisfaction", stage_gold),
    ("evidence_necessity", stage_evidence),
    ("ambiguity", stage_ambiguity),
    ("unsolvability", stage_unsolvable),
    ("feedback_quality", stage_feedback),
    ("category_consistency", stage_consistency),
    ("style_conformance", stage_style),
)


def run_cascade(df: DataFrame, cx: Context, store: Callable[[DataFrame, str], DataFrame], skip: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """(survivors, log of all verdicts with stage number and name). ``store(df, name)`` materialises a table.

    An object that a stage does not apply to has no verdict there and stays.
    """
    cx.store = store
    live, log = store(df, "questions"), []
    for number, (name, stage) in enumerate(STAGES, 1):
        if name in skip:
            continue
        got = store(stage(live, cx).select(*VERDICT), f"verdicts-{number}")
        log.append(got.select(F.lit(number).alias("stage"), F.lit(name).alias("stage_name"), *VERDICT))
        live = store(live.join(got.filter("not kept"), "obj_id", "left_anti"), f"survivors-{number}")
    return live, union_all(log)


def rejection_report(log: DataFrame, questions: DataFrame) -> DataFrame:
    """stage, stage_name, subcategory (null: all), n_in, n_rejected, rejected_pct."""
    joined = log.join(questions.select("obj_id", "subcategory"), "obj_id")
    counted = joined.groupingSets([[F.col("stage"), F.col("stage_name"), F.col("subcategory")], [F.col("stage"), F.col("stage_name")]], "stage", "stage_name", "subcategory").agg(F.count(F.lit(1)).alias("n_in"), F.count_if(~F.col("kept")).alias("n_rejected"))
    return counted.withColumn("rejected_pct", F.round(100.0 * F.col("n_rejected") / F.col("n_in"), 4))
