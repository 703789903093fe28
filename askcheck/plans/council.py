"""Councils: ballots of several members, and the rules that decide by them.

A member is any object with ``name`` and ``vote(call, frame) -> list[str]``; it
sees only the columns that its call may see. Ballots are one row per item and
member. A missing ballot counts as a no.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.taxonomy import taxonomy

#: What each kind of call is given. Nothing else reaches a member, and column pruning keeps it out of the plan.
#: ``schema`` is a database's tables with sample rows; definition, trait and example are those of a label.
CALL_INPUTS = {
    "category_conformance": ("nl", "db_id", "schema", "gold_sql", "hidden", "subcategory", "definition", "trait", "example"),
    "gold_satisfied": ("nl", "db_id", "schema", "gold_sql", "hidden", "preview"),
    "sql_without_evidence": ("nl", "db_id", "schema"),
    "sql_without_hidden": ("nl", "db_id", "schema", "evidence"),
    "sql_for_unanswerable": ("nl", "db_id", "schema", "evidence"),
    "feedback_quality": ("nl", "db_id", "schema", "hidden"),
    "category_pair": ("nl", "db_id", "schema", "hidden", "first", "second", "first_definition", "second_definition"),
    "style": ("nl",),
    "classify": ("nl", "db_id", "schema", "evidence"),
    "relevancy": ("nl", "history", "fragments", "clarification", "allowed"),
    "answer": ("label", "style", "grounding", "clarification"),
    "compare": ("clarification", "style", "first", "second"),
    "feedback_match": ("text", "hidden"),
}


@dataclass(frozen=True)
class Briefing:
    """What members are told beside a row: schema texts by database and the labels' definitions. Both are short fixed lists, joined on by broadcast."""

    schemas: DataFrame | None = None  # db_id, schema

    def add(self, df: DataFrame, wanted: tuple[str, ...]) -> DataFrame:
        if "schema" in wanted and self.schemas is not None and "db_id" in df.columns and "schema" not in df.columns:
            df = df.join(F.broadcast(self.schemas), "db_id", "left")
        labels = taxonomy(df.sparkSession).select("subcategory", "definition", "trait", "example")
        if "definition" in wanted and "subcategory" in df.columns:
            df = df.join(F.broadcast(labels), "subcategory", "left")
        for side in ("first", "second"):
            if f"{side}_definition" in wanted and side in df.columns:
                df = df.join(F.broadcast(labels.select(F.col("subcategory").alias(side), F.concat_ws(" ", "definition", "trait").alias(f"{side}_definition"))), side, "left")
        return df


def for_call(df: DataFrame, call: str, *keys: str, briefing: Briefing | None = None) -> DataFrame:
    """Only the key columns and what ``call`` may see."""
    known = (briefing or Briefing()).add(df, CALL_INPUTS[call])
    return known.select(*keys, *(c for c in CALL_INPUTS[call] if c in known.columns and c not in keys))


def ask(df: DataFrame, members: list, call: str, item: str = "item_id", briefing: Briefing | None = None) -> DataFrame:
    """item, member, vote for rows that name the member they are for."""
    by_name = {m.name: m for m in members}
    seen = for_call(df, call, item, "member", briefing=briefing)
    kind = seen.schema[item].dataType.simpleString()

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for name, part in frame.groupby("member", sort=True):
                votes = by_name[name].vote(call, part.drop(columns="member").reset_index(drop=True))
                yield pd.DataFrame({item: part[item].to_numpy(), "member": name, "vote": votes})

    return seen.mapInPandas(run, f"{item} {kind}, member string, vote string")


def collect_ballots(df: DataFrame, members: list, call: str, item: str = "item_id", briefing: Briefing | None = None) -> DataFrame:
    """item, member, vote: every member on every item.

    Items are spread by item and member, so three members don't mean three
    tasks; each Python worker holds the members once.
    """
    names = df.sparkSession.createDataFrame([(m.name,) for m in members], "member string")
    return ask(df.crossJoin(F.broadcast(names)), members, call, item, briefing)


def majority(ballots: DataFrame, council_size: int, yes: str = "yes", item: str = "item_id") -> DataFrame:
    """item, n_yes, n_members, kept: strictly more than half of the council said yes."""
    return (
        ballots.groupBy(item)
        .agg(F.count_if(F.col("vote") == yes).alias("n_yes"))
        .select(item, "n_yes", F.lit(council_size).cast("bigint").alias("n_members"), (2 * F.col("n_yes") > council_size).alias("kept"))
    )


def plurality(ballots: DataFrame, default: str, item: str = "item_id") -> DataFrame:
    """item, winner, tied: the most frequent vote; ``default`` where several share the top.

    Two aggregations, the second on the first one's partitioning by item.
    """
    counts = ballots.groupBy(item, "vote").agg(F.count(F.lit(1)).alias("n"))
    top = counts.groupBy(item).agg(F.max("n").alias("most"), F.collect_list(F.struct("n", "vote")).alias("votes"))
    leaders = F.filter("votes", lambda v: v["n"] == F.col("most"))
    tied = F.size(leaders) > 1
    return top.select(item, F.when(tied, default).otherwise(F.get(leaders, F.lit(0))["vote"]).alias("winner"), tied.alias("tied"))


def any_yes(ballots: DataFrame, yes: str = "yes", item: str = "item_id") -> DataFrame:
    return ballots.groupBy(item).agg(F.bool_or(F.col("vote") == yes).alias("any_yes"))
