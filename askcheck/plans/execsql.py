"""Safe execution of candidate SQL: parse, refuse what is no query, run with a time limit.

``spark.sql`` runs commands at once, so a text is parsed first, and only plans
made of query operators over named relations go on. Distinct texts run once, and
texts of which a row each is wanted share jobs.
"""

from __future__ import annotations

import re
import threading
import uuid
from collections.abc import Iterable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from functools import reduce

from pyspark.errors import AnalysisException, ParseException, PySparkException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_PATH_RELATION = re.compile(r"UnresolvedRelation \[([^\]]*)\]")
_PATH_FORMATS = {"parquet", "json", "csv", "orc", "text", "avro", "delta", "binaryfile", "jdbc", "hive"}
_QUERY_NODES = {
    "Project", "Filter", "Join", "Aggregate", "Sort", "Distinct", "Union", "Intersect", "Except", "GlobalLimit", "LocalLimit", "Limit", "SubqueryAlias", "UnresolvedRelation",
    "UnresolvedSubqueryColumnAliases", "UnresolvedWith", "CTE", "UnresolvedHaving", "OneRowRelation", "UnresolvedInlineTable", "WithWindowDefinition", "Window", "LateralJoin",
    "Generate", "Pivot", "Unpivot", "UnresolvedTableValuedFunction", "Offset", "Tail", "Sample", "LocalRelation", "View", "ResolvedInlineTable", "UnresolvedOrdinal", "Expand",
}
#: Functions that read files, run code outside the plan, or only waste time.
_REFUSED_CALLS = re.compile(r"\b(reflect|java_method|read_files|input_file_name|assert_true|raise_error|try_reflect)\s*\(", re.I)


@dataclass
class Outcome:
    status: str  # ok, empty, syntax, analysis, runtime, timeout, refused
    condition: str = ""
    rows: int = 0


def parse(spark: SparkSession, sql: str):
    """The unresolved plan of a text; raises ParseException. The only use of a private handle."""
    return spark._jsparkSession.sessionState().sqlParser().parsePlan(sql)


def _nodes(plan) -> Iterable:
    yield plan
    children = plan.children()
    for i in range(children.size()):
        yield from _nodes(children.apply(i))


def refusal(spark: SparkSession, sql: str) -> str:
    """Why a text must not run; empty if it may. Raises ParseException."""
    if _REFUSED_CALLS.search(sql):
        return "refused function"
    plan = parse(spark, sql)
    for node in _nodes(plan):
        if node.nodeName() not in _QUERY_NODES:
            return f"no query: {node.nodeName()}"
    for name in _PATH_RELATION.findall(plan.toString()):
        parts = [p.strip().lower() for p in name.split(",")]
        if len(parts) > 1 and (parts[0] in _PATH_FORMATS or "/" in parts[-1]):
            return f"path relation {name}"
    return ""


def classify_error(e: Exception) -> Outcome:
    condition = e.getCondition() or "" if isinstance(e, PySparkException) else type(e).__name__
    if isinstance(e, ParseException):
        return Outcome("syntax", condition)
    if isinstance(e, AnalysisException):
        return Outcome("analysis", condition)
    return Outcome("runtime", condition)


def timed(spark: SparkSession, work, timeout_s: float):
    """``work()`` in a job group that is cancelled after ``timeout_s``; (result, timed out)."""
    sc = spark.sparkContext
    group, late = f"candidate-{uuid.uuid4().hex}", threading.Event()

    def stop() -> None:
        late.set()
        sc.cancelJobGroup(group)

    sc.setJobGroup(group, "candidate query", interruptOnCancel=True)
    timer = threading.Timer(timeout_s, stop)
    timer.start()
    try:
        return work(), late.is_set()
    except Exception:
        if late.is_set():
            return None, True
        raise
    finally:
        timer.cancel()
        sc.setLocalProperty("spark.jobGroup.id", None)


def look(spark: SparkSession, sql: str, timeout_s: float = 20.0, n: int = 1, widest: int = 400) -> tuple[Outcome, str | None]:
    """Whether a text is a query that runs in time and returns a row, and its first ``n`` rows as JSON lines.

    By ``LIMIT``, which reads partitions until it has enough: no full scan where none is needed.
    """
    found = examine(spark, sql)
    if isinstance(found, Outcome):
        return found, None
    try:
        named = found.toDF(*(f"c{i}" for i in range(len(found.columns))))
        lines = named.limit(n).select(F.substring(F.to_json(F.struct("*")), 1, widest))
        rows, late = timed(spark, lines.collect, timeout_s)
    except Exception as e:  # noqa: BLE001  whatever a candidate raises is its outcome
        return classify_error(e), None
    if late:
        return Outcome("timeout"), None
    return (Outcome("ok", rows=len(rows)), "\n".join(r[0] for r in rows)) if rows else (Outcome("empty"), None)


def probe(spark: SparkSession, sql: str, timeout_s: float = 20.0) -> Outcome:
    """Whether a text is a query that runs in time and returns at least one row."""
    return look(spark, sql, timeout_s)[0]


def look_all(spark: SparkSession, texts: Iterable[str], timeout_s: float = 20.0, n: int = 1, at_once: int = 8) -> dict[str, tuple[Outcome, str | None]]:
    distinct = sorted(set(texts))
    with ThreadPoolExecutor(at_once) as pool:
        return dict(zip(distinct, pool.map(lambda s: look(spark, s, timeout_s, n), distinct), strict=True))


def probe_all(spark: SparkSession, texts: Iterable[str], timeout_s: float = 20.0, at_once: int = 6) -> dict[str, Outcome]:
    distinct = sorted(set(texts))
    with ThreadPoolExecutor(at_once) as pool:
        return dict(zip(distinct, pool.map(lambda s: probe(spark, s, timeout_s), distinct), strict=True))


def examine(spark: SparkSession, sql: str) -> DataFrame | Outcome:
    """The analysed query of a text, which has not run; or why there is none."""
    try:
        why = refusal(spark, sql)
        return Outcome("refused", why) if why else spark.sql(sql)
    except Exception as e:  # noqa: BLE001  whatever a candidate raises is its outcome
        return classify_error(e)


def examine_all(spark: SparkSession, texts: Iterable[str], at_once: int = 6) -> dict[str, DataFrame | Outcome]:
    distinct = sorted(set(texts))
    with ThreadPoolExecutor(at_once) as pool:
        return dict(zip(distinct, pool.map(lambda s: examine(spark, s), distinct), strict=True))


def first_rows(spark: SparkSession, frames: dict, timeout_s: float = 20.0, together: int = 24, at_once: int = 4) -> dict:
    """The single row of each of ``frames`` (of one schema), or the outcome of what fails or takes too long.

    Frames are read ``together`` by one job. If that fails or takes too long, its halves
    run by themselves, down to the frame that is to blame.
    """

    def run(keys: list) -> list[tuple]:
        try:
            union = reduce(DataFrame.unionByName, [frames[k].withColumn("_at", F.lit(i)) for i, k in enumerate(keys)])
            rows, late = timed(spark, union.collect, timeout_s)
            if not late:
                by_place = {r["_at"]: r for r in rows}
                return [(k, by_place[i]) for i, k in enumerate(keys)]
            blame = Outcome("timeout")
        except Exception as e:  # noqa: BLE001  whatever a candidate raises is its outcome
            blame = classify_error(e)
        if len(keys) == 1:
            return [(keys[0], blame)]
        return run(keys[: len(keys) // 2]) + run(keys[len(keys) // 2 :])

    keys = list(frames)
    parts = [keys[i : i + together] for i in range(0, len(keys), together)]
    with ThreadPoolExecutor(at_once) as pool:
        return dict(x for part in pool.map(run, parts) for x in part)


def check_executable(df: DataFrame, sql_col: str = "gold_sql", outcomes_of=None) -> DataFrame:
    """``df`` with status and condition; each distinct text of the candidates runs once. ``outcomes_of`` maps texts to outcomes (default: probe them all)."""
    spark = df.sparkSession
    texts = [r[0] for r in df.select(sql_col).distinct().collect() if r[0] is not None]  # as many as there are candidate queries
    outcomes = (outcomes_of or (lambda t: probe_all(spark, t)))(texts)
    found = [(t, o.status, o.condition) for t, o in outcomes.items()]
    return df.join(spark.createDataFrame(found, f"{sql_col} string, status string, condition string"), sql_col, "left")
