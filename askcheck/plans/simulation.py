"""Dialogues between a system agent and a simulated user, in batch rounds.

A round handles all live conversations at once: agents respond, SQL or feedback
ends a conversation, clarifications are answered by a council of users. There
are at most ``max_clar + 1`` rounds; each is written before the next one reads
it, so a lost executor repeats one round and no member is asked twice.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from .agents import CLASSIFY_INPUTS, GUIDES, MODES, TAXONOMY_GUIDE, TURN_INPUTS, Agent
from .council import Briefing, ask, collect_ballots, plurality
from .equivalence import union_all
from .members import REFUSAL

Store = Callable[[DataFrame, str], DataFrame]
#: Labels that a clarification can get, by type of question; unanswerable ones are refused without a vote.
ALLOWED = {"answerable": "technical,irrelevant", "ambiguous": "relevant,technical,irrelevant", "unanswerable": "irrelevant"}
TURN = "conv_id string, turn int, role string, kind string, text string, relevancy string, nodes array<int>, forced boolean"


#: Quoted parts, parentheses, clause words, and what separates the parts of a clause.
_MARKS = re.compile(
    r"'(?:[^']|'')*'|`[^`]*`|\"[^\"]*\"|[()]|,|\b(?P<clause>select|from|(?:(?:left|right|full|inner|cross|outer|semi|anti)\s+)*join|on|where|group\s+by|having|order\s+by|limit)\b|\b(?P<word>and|between)\b",
    re.I,
)


def sql_fragments(sql: str | None) -> list[str]:
    """Parts of a query as nodes (clause: text): select items, tables, join conditions, predicates, groups, order, limit. Quoted text and what stands in parentheses is not cut."""
    out: list[str] = []
    clause, start, depth, between = "", 0, 0, False

    def done(end: int) -> None:
        text = (sql or "")[start:end].strip()
        if clause and text:
            out.append(f"{clause}: {text}")

    for m in _MARKS.finditer(sql or ""):
        mark = m.group().lower()
        depth += (mark == "(") - (mark == ")")
        if depth or mark == ")":
            continue
        if m["clause"]:
            done(m.start())
            clause, start, between = " ".join(mark.split()), m.end(), False
            clause = "join" if clause.endswith("join") else clause
        elif mark == "," and clause in ("select", "group by", "order by", "from"):
            done(m.start())
            start = m.end()
        elif m["word"] and clause in ("where", "having", "on"):
            if mark == "between":
                between = True
            elif between:
                between = False
            else:
                done(m.start())
                start = m.end()
    done(len(sql or ""))
    return out


@F.pandas_udf(StringType())
def fragment_lines(sql: pd.Series) -> pd.Series:
    """The fragments of each query, a line each."""
    return sql.map(lambda q: "\n".join(" ".join(f.split()) for f in sql_fragments(q)))


def start_conversations(questions: DataFrame, agents: list[Agent], modes: tuple[str, ...] = MODES, briefing: Briefing | None = None) -> DataFrame:
    """One row for each question, agent and mode, with the mode's guide; the label is the true one, the predicted one, or none.

    Without the predicted mode nobody is asked to classify.
    """
    spark = questions.sparkSession
    side = spark.createDataFrame([(a.name, m, GUIDES[m]) for a in agents for m in modes], "agent string, mode string, guide string")
    conv = questions.crossJoin(F.broadcast(side)).withColumn("conv_id", F.concat_ws("|", "obj_id", "agent", "mode"))
    if "predicted" in modes:
        conv = conv.join(classify(questions, agents, briefing).select("obj_id", "agent", "predicted"), ["obj_id", "agent"])
    else:
        conv = conv.withColumn("predicted", F.lit(None).cast("string"))
    return conv.withColumn("label", F.when(F.col("mode") == "ground_truth", F.col("subcategory")).when(F.col("mode") == "predicted", F.col("predicted")))


def shown(df: DataFrame, inputs: tuple[str, ...], briefing: Briefing | None) -> DataFrame:
    """The agent's name and what it may see."""
    known = (briefing or Briefing()).add(df, inputs)
    return known.select("agent", *(c for c in inputs if c in known.columns))


def classify(questions: DataFrame, agents: list[Agent], briefing: Briefing | None = None) -> DataFrame:
    """obj_id, agent, predicted: the optional first phase, one label for each question and agent."""
    spark = questions.sparkSession
    by_name = {a.name: a for a in agents}
    names = spark.createDataFrame([(a.name,) for a in agents], "agent string")
    asked = questions.select(F.col("obj_id").alias("conv_id"), "nl", "db_id", "evidence", F.lit(TAXONOMY_GUIDE).alias("guide")).crossJoin(F.broadcast(names))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for name, part in frame.groupby("agent", sort=True):
                yield pd.DataFrame({"obj_id": part["conv_id"].to_numpy(), "agent": name, "predicted": by_name[name].classify(part.drop(columns="agent").reset_index(drop=True))})

    return shown(asked, CLASSIFY_INPUTS, briefing).mapInPandas(run, "obj_id string, agent string, predicted string")


def agent_turns(live: DataFrame, agents: list[Agent], briefing: Briefing | None = None) -> DataFrame:
    """conv_id, kind, text. On a forced turn a clarification has no kind: the conversation failed."""
    by_name = {a.name: a for a in agents}
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for name, part in frame.groupby("agent", sort=True):
                got = by_name[name].respond(part.drop(columns="agent").reset_index(drop=True))
                kinds = [None if f and k == "clarification" else k for (k, _), f in zip(got, part["forced"], strict=True)]
                yield pd.DataFrame({"conv_id": part["conv_id"].to_numpy(), "kind": kinds, "text": [t for _, t in got]})

    return shown(live, TURN_INPUTS, briefing).mapInPandas(run, "conv_id string, kind string, text string")


def user_replies(asked: DataFrame, users: list, store: Store, name: str) -> DataFrame:
    """conv_id, relevancy, nodes, reply. ``asked``: conversations with their clarification and the hidden side of the question.

    Votes first, with the fragments that a technical question is about; then
    only members whose own vote won are asked for an answer, each on the
    fragments it chose; a tournament chooses where answers differ. An answer that
    holds the whole query is replaced by the refusal.
    """
    staged = asked.withColumn("allowed", F.create_map(*(F.lit(x) for kv in ALLOWED.items() for x in kv))[F.col("qtype")])
    no_nodes = F.lit(None).cast("array<int>")
    refused = staged.filter("qtype = 'unanswerable'").select("conv_id", F.lit("irrelevant").alias("relevancy"), no_nodes.alias("nodes"), F.lit(REFUSAL).alias("reply"))
    voted = staged.filter("qtype <> 'unanswerable'")
    raw = collect_ballots(voted.select("conv_id", "nl", "history", "fragments", "clarification", "allowed"), users, "relevancy", "conv_id")
    cast = F.split("vote", ":")
    label, nodes = F.get(cast, F.lit(0)), F.transform(F.split(F.coalesce(F.get(cast, F.lit(1)), F.lit("")), ","), lambda x: x.try_cast("int"))
    known = raw.join(voted.select("conv_id", "allowed"), "conv_id").withColumns({"nodes": F.filter(nodes, lambda x: x.isNotNull()), "vote": F.when(F.array_contains(F.split("allowed", ","), label), label).otherwise("irrelevant")})
    ballots = store(known, f"{name}-ballots")
    winners = plurality(ballots, "irrelevant", "conv_id")
    # who lost is not asked: rows name the member they are for
    eligible = ballots.join(winners, "conv_id").filter("vote = winner").select("conv_id", "member", "nodes", F.col("winner").alias("label"))
    lines = F.split("fragments", "\n")
    chosen_lines = F.array_join(F.filter(F.transform("nodes", lambda i: F.get(lines, i)), lambda x: x.isNotNull()), "\n")
    grounding = F.when(F.col("label") == "relevant", F.col("hidden")).when(F.col("label") == "technical", chosen_lines)
    ground = voted.select("conv_id", "clarification", "style", "hidden", "fragments").join(eligible, "conv_id").select("conv_id", "member", "clarification", "style", "label", grounding.alias("grounding"))
    said = ask(ground, users, "answer", "conv_id").withColumnRenamed("vote", "text").withColumnRenamed("member", "author")
    safe = said.join(voted.select("conv_id", "gold_sql"), "conv_id").withColumn("text", F.when(leaks("text", "gold_sql") == "full", REFUSAL).otherwise(F.col("text")))
    answers = store(safe.select("conv_id", "author", "text"), f"{name}-answers")
    chosen = tournament(answers, voted.select("conv_id", "clarification", "style"), users)
    used = eligible.groupBy("conv_id").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("nodes")))).alias("nodes"))
    replied = winners.select("conv_id", F.col("winner").alias("relevancy")).join(used, "conv_id", "left").join(chosen, "conv_id", "left")
    return replied.select("conv_id", "relevancy", F.when(F.col("relevancy") == "technical", F.col("nodes")).alias("nodes"), F.coalesce("text", F.lit(REFUSAL)).alias("reply")).unionByName(refused)


def tournament(answers: DataFrame, about: DataFrame, users: list) -> DataFrame:
    """conv_id, text: the only distinct answer, or the one that wins most comparisons (ties: the first author)."""
    distinct = answers.groupBy("conv_id", "text").agg(F.min("author").alias("author"))
    a, b = distinct.alias("a"), distinct.alias("b")
    pairs = a.join(b, (F.col("a.conv_id") == F.col("b.conv_id")) & (F.col("a.author") < F.col("b.author"))).select(
        F.col("a.conv_id").alias("conv_id"), F.col("a.author").alias("x"), F.col("b.author").alias("y"), F.col("a.text").alias("first"), F.col("b.text").alias("second")
    )
    items = pairs.join(about, "conv_id").withColumn("item_id", F.concat_ws("#", "conv_id", "x", "y"))
    won = plurality(collect_ballots(items, users, "compare"), "first").join(items, "item_id").select("conv_id", F.when(F.col("winner") == "first", F.col("x")).otherwise(F.col("y")).alias("author"))
    wins = won.groupBy("conv_id", "author").agg(F.count(F.lit(1)).alias("wins"))
    ranked = distinct.join(wins, ["conv_id", "author"], "left").select("conv_id", "text", "author", F.coalesce("wins", F.lit(0)).alias("wins"))
    return ranked.groupBy("conv_id").agg(F.min_by("text", F.struct(-F.col("wins"), F.col("author"))).alias("text"))


def leaks(reply: str, gold: str) -> F.Column:
    """full: the reply holds the whole query; partial: three tokens of it in a row; none."""
    words = lambda c: F.filter(F.split(F.lower(F.regexp_replace(c, r"[^A-Za-z0-9_*]+", " ")), " "), lambda w: w != "")

    def threes(c: str):
        w = words(F.col(c))
        return F.when(F.size(w) < 3, F.array().cast("array<string>")).otherwise(F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.concat_ws(" ", F.slice(w, i + 1, F.lit(3)))))

    whole = F.contains(F.array_join(words(F.col(reply)), " "), F.array_join(words(F.col(gold)), " "))
    return F.when(F.col(gold).isNull() | (F.col(gold) == ""), "none").when(whole, "full").when(F.arrays_overlap(threes(reply), threes(gold)), "partial").otherwise("none")


def simulate(questions: DataFrame, agents: list[Agent], users: list, store: Store, modes: tuple[str, ...] = MODES, max_clar: int = 3, briefing: Briefing | None = None) -> tuple[DataFrame, DataFrame]:
    """(conversations, turns)."""
    hidden_side = store(questions.select("obj_id", "qtype", "category", "subcategory", "style", "hidden", "gold_sql", fragment_lines("gold_sql").alias("fragments")), "hidden")
    begun = store(start_conversations(questions, agents, modes, briefing).select("conv_id", "obj_id", "agent", "mode", "nl", "db_id", "evidence", "label", "guide", "predicted"), "begun")
    live = begun.withColumns({"history": F.lit(""), "n_clar": F.lit(0), "forced": F.lit(max_clar == 0)})
    turns, ends = [], []
    for r in range(max_clar + 1):
        said = store(live.join(agent_turns(live, agents, briefing), "conv_id"), f"round-{r}")
        turns.append(said.select("conv_id", F.lit(2 * r).alias("turn"), F.lit("system").alias("role"), "kind", "text", F.lit(None).cast("string").alias("relevancy"), F.lit(None).cast("array<int>").alias("nodes"), "forced"))
        ends.append(said.filter(F.col("kind").isNull() | (F.col("kind") != "clarification")).select("conv_id", F.lit(r + 1).alias("n_rounds"), F.col("kind").alias("final_kind"), F.col("text").alias("final_text")))
        if r == max_clar:
            break
        asked = said.filter("kind = 'clarification'").join(hidden_side, "obj_id").withColumn("clarification", F.col("text"))
        replies = store(user_replies(asked, users, store, f"replies-{r}"), f"replies-{r}")
        turns.append(replies.select("conv_id", F.lit(2 * r + 1).alias("turn"), F.lit("user").alias("role"), F.lit("reply").alias("kind"), F.col("reply").alias("text"), "relevancy", "nodes", F.lit(False).alias("forced")))
        live = said.filter("kind = 'clarification'").join(replies, "conv_id").select(*begun.columns, F.concat("history", F.lit("\nsystem: "), "text", F.lit("\nuser: "), "reply").alias("history"), (F.col("n_clar") + 1).alias("n_clar"), F.lit(r + 1 == max_clar).alias("forced"))
    ended = union_all(ends)
    conversations = begun.select("conv_id", "obj_id", "agent", "mode", "predicted").join(ended, "conv_id").withColumn("status", F.when(F.col("final_kind").isNull(), "failed").otherwise("done"))
    return store(conversations, "conversations"), store(union_all(turns), "turns")


def replay_static(questions: DataFrame, agent: Agent) -> DataFrame:
    """conv_id, obj_id, kind, text: the contrast with a fixed history, in which the clarification is already answered and only the last turn is asked for."""
    told = questions.filter("qtype <> 'unanswerable'").select(
        F.concat_ws("|", "obj_id", F.lit(agent.name), F.lit("static")).alias("conv_id"), "obj_id", "nl", "db_id", "evidence", F.lit(TAXONOMY_GUIDE).alias("guide"), F.col("subcategory").alias("label"),
        F.concat(F.lit("\nsystem: Which reading do you mean?\nuser: I mean that "), F.coalesce("hidden", F.lit(""))).alias("history"), F.lit(1).alias("n_clar"), F.lit(True).alias("forced"), F.lit(agent.name).alias("agent"),
    )
    return told.select("conv_id", "obj_id").join(agent_turns(told, [agent]), "conv_id")
