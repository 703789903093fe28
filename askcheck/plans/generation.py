"""Question objects: the diversity grid, generation by pluggable generators, SQL grounding, difficulty."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import sqlmask
from ..functions.taxonomy import CATEGORY_OF, DIFFICULTIES, STYLES, SUBCATEGORIES, TYPE_OF, taxonomy
from ..sources.tables import DATABASES
from .grammar import ROLES, fill, restyle

QUESTION = (
    "obj_id string, group_id string, reading_no int, db_id string, generator string, qtype string, category string, subcategory string, style string, "
    "difficulty_asked string, difficulty_actual string, nl string, evidence array<string>, gold_sql string, hidden string, sample_no int"
)


@dataclass(frozen=True)
class MemberConfig:
    """Decoding settings handed to members: sampling for generation, greedy for validation."""

    temperature: float = 0.7
    frequency_penalty: float = 0.2
    seed: int = 7
    greedy: bool = False


def digest(*parts: object) -> int:
    """A reproducible number from 0 to 2**32 - 1."""
    return int(hashlib.md5("\x1f".join(map(str, parts)).encode()).hexdigest()[:8], 16)


def generation_grid(spark: SparkSession, generators: list[str], db_ids: list[str] | None = None, samples: int = 3) -> DataFrame:
    """One row for each generator, subcategory, style, difficulty, database and sample: all sides are lists of a handful."""

    def column(name: str, values) -> DataFrame:
        return spark.createDataFrame([(v,) for v in values], f"{name} string")

    grid = column("generator", generators)
    for name, values in (("subcategory", SUBCATEGORIES), ("style", STYLES), ("difficulty_asked", DIFFICULTIES), ("db_id", db_ids or list(DATABASES))):
        grid = grid.crossJoin(F.broadcast(column(name, values)))
    return grid.withColumn("sample_no", F.explode(F.sequence(F.lit(1), F.lit(samples))))


class RuleGenerator:
    """A stand-in: fills a template by the grid's row. ``faults``: share of rows made faulty on purpose, so that every stage has something to reject."""

    def __init__(self, name: str, faults: float = 0.0, config: MemberConfig | None = None, aware: bool = True):
        self.name, self.faults, self.config, self.aware = name, faults, config or MemberConfig(), aware

    def generate(self, row: dict) -> list[dict]:
        tables = [t for t in DATABASES[row["db_id"]] if t in ROLES]
        draw = digest(self.name, row["subcategory"], row["style"], row["difficulty_asked"], row["db_id"], row["sample_no"], self.config.seed)
        subcategory = row["subcategory"] if self.aware else SUBCATEGORIES[draw % len(SUBCATEGORIES)]
        filled = None
        for k in range(len(tables)):
            filled = fill(subcategory, row["db_id"], tables[(draw + k) % len(tables)], draw // 7)
            if filled:
                break
        if filled is None:
            return []
        nl = restyle(filled.nl, row["style"])
        readings = filled.readings or (None,)
        fault = FAULTS[draw // 11 % len(FAULTS)] if draw % 1000 < 1000 * self.faults else ""
        out = []
        for i, r in enumerate(readings):
            one = {"nl": nl, "evidence": list(filled.evidence), "hidden": (r.hidden if r else filled.feedback), "sql_draft": r.sql if r else None, "reading_no": i}
            out.append(spoil(one, fault, row["style"]))
        return out


FAULTS = ("syntax", "empty", "missing_table", "wrong_style", "vague_feedback", "repeat", "wrong_sql")


def spoil(q: dict, fault: str, style: str) -> dict:
    """The fault, where it applies to the kind of question."""
    sql = q["sql_draft"]
    if sql and fault == "syntax":
        q["sql_draft"] = sql.replace("SELECT", "SELEKT", 1)
    elif sql and fault == "empty":
        q["sql_draft"] = f"SELECT * FROM ({sql}) AS x WHERE 1 = 0"
    elif sql and fault == "missing_table":
        q["sql_draft"] = sql.replace(" FROM ", " FROM absent_", 1)
    elif sql and fault == "wrong_sql":
        q["sql_draft"] = "SELECT 1 AS n"
    elif fault == "wrong_style":
        core = q["nl"].removeprefix("Kindly report the following: ").removeprefix("hey, get me the ").removeprefix("What is the ").removesuffix(", ok").rstrip("?.")
        q["nl"] = restyle(core, "colloquial" if style != "colloquial" else "formal")
    elif not sql and fault == "vague_feedback":
        q["hidden"] = "this cannot be answered"
    return q


def generate_questions(grid: DataFrame, generators: dict[str, RuleGenerator], context: DataFrame | None = None) -> DataFrame:
    """Step 1: question, evidence and hidden knowledge; one object, or two that share the text for an ambiguous one.

    ``context`` (schema and sample rows of each database) is joined on for
    generators that build prompts; the stand-ins know the schema already.
    """
    fields = "generator string, subcategory string, style string, difficulty_asked string, db_id string, sample_no int, group_id string, reading_no int, nl string, evidence array<string>, hidden string, sql_draft string"
    src = grid if context is None else grid.join(F.broadcast(context), "db_id", "left")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = []
            for row in frame.to_dict("records"):
                base = {k: row[k] for k in ("generator", "subcategory", "style", "difficulty_asked", "db_id", "sample_no")}
                group = hashlib.md5("|".join(str(v) for v in base.values()).encode()).hexdigest()[:16]
                rows += [base | {"group_id": group} | q for q in generators[row["generator"]].generate(row)]
            yield pd.DataFrame(rows, columns=[f.split()[0] for f in fields.split(", ")])

    return src.mapInPandas(run, fields)


def ground_sql(df: DataFrame, context: DataFrame | None = None, grounder=None) -> DataFrame:
    """Step 2: gold_sql for solvable objects, by ``grounder(row) -> sql``; unanswerable ones bypass it."""
    typed = with_type(df)
    if grounder is None:
        return typed.withColumn("gold_sql", F.when(F.col("qtype") != "unanswerable", F.col("sql_draft"))).drop("sql_draft")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            yield frame.assign(gold_sql=[grounder(r) for r in frame.to_dict("records")])

    solvable = typed.filter("qtype <> 'unanswerable'").drop("sql_draft")
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in solvable.schema) + ", gold_sql string"
    bypass = typed.filter("qtype = 'unanswerable'").drop("sql_draft").withColumn("gold_sql", F.lit(None).cast("string"))
    return solvable.mapInPandas(run, schema).unionByName(bypass)


def with_type(df: DataFrame) -> DataFrame:
    kinds = taxonomy(df.sparkSession).select("subcategory", "qtype", "category")
    return df.join(F.broadcast(kinds), "subcategory")


def as_questions(df: DataFrame) -> DataFrame:
    """The question schema: ids, difficulty by the query's constructs."""
    out = df.withColumn("obj_id", F.concat_ws("-", "group_id", "reading_no")).withColumn("difficulty_actual", F.coalesce(sqlmask.difficulty("gold_sql"), F.col("difficulty_asked")))
    return out.select(*(c.split()[0] for c in QUESTION.split(", ")))


def build(spark: SparkSession, generators: list[RuleGenerator], db_ids: list[str] | None = None, samples: int = 1, styles=STYLES, difficulties=DIFFICULTIES[:1]) -> DataFrame:
    grid = generation_grid(spark, [g.name for g in generators], db_ids, samples).filter(F.col("style").isin(*styles) & F.col("difficulty_asked").isin(*difficulties))
    return as_questions(ground_sql(generate_questions(grid, {g.name: g for g in generators})))


def link_schema(questions: DataFrame, catalog: DataFrame) -> DataFrame:
    """obj_id, table_name, col_name, hits: columns whose words occur in the question, or nearly (one edit in words of five letters and more).

    An equi-join on words with the catalog as the small side; edits are checked within a shared first letter.
    """
    words = questions.select("obj_id", "db_id", F.explode(F.array_distinct(F.filter(F.split(F.lower("nl"), "[^a-z]+"), lambda w: F.length(w) > 2))).alias("word")).withColumn("initial", F.substring("word", 1, 1))
    parts = catalog.select("db_id", "table_name", "col_name", F.explode("tokens").alias("part")).withColumn("initial", F.substring("part", 1, 1))
    near = (F.col("word") == F.col("part")) | ((F.length("part") >= 5) & (F.levenshtein("word", "part") <= 1))
    return words.join(F.broadcast(parts), ["db_id", "initial"]).filter(near).groupBy("obj_id", "table_name", "col_name").agg(F.countDistinct("part").alias("hits"))


def label_columns(df: DataFrame) -> DataFrame:
    """qtype and category of each subcategory, from the fixed table."""
    types = F.create_map(*(F.lit(x) for kv in TYPE_OF.items() for x in kv))
    categories = F.create_map(*(F.lit(x) for kv in CATEGORY_OF.items() for x in kv))
    return df.withColumns({"qtype": types[F.col("subcategory")], "category": categories[F.col("subcategory")]})
