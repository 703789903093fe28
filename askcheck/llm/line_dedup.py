"""Site-relative line frequency: lines that many pages of a site share are dropped.

Only DataFrame expressions. Pages are grouped by host; a line's pages on a host
are divided by all pages of that host, and a line on at least ``min_pages``
pages whose ratio is above ``ratio`` is boilerplate there. Lines are compared without outer white space of any kind (a
carriage return or a tab is no part of a line); blank lines are never counted or dropped.

A page counts once for each of its distinct lines, so counting is one
aggregation with map-side combination: a line on every page of a hot host is one
row for each task. A host has at most (mean lines of a page) / ratio lines of
boilerplate. They go to the pages as one array for each host: by broadcast if
all hosts together have at most ``BROADCAST_LINES``, else by a join on the host
that adaptive execution splits where a host is hot (it has one row on the
array's side).

Defined results: a null text stays null and has no lines; a null host is a host
of its own; rows with the same id count as pages of their own; all other columns
pass through; a text from which nothing is dropped comes back unchanged; an
empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import checkpointed

#: The white space that separates words, as a part of a character class.
SPACES = " \\t\\n\\x0B\\f\\r"
_TRIMMED = " \t\n\x0b\f\r"
#: Hashes of boilerplate lines, 8 bytes each, that may be broadcast.
BROADCAST_LINES = 500_000


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, f"[{SPACES}]+"), "")


def trimmed(line: Column) -> Column:
    return F.trim(line, F.lit(_TRIMMED))


def line_hashes(text: Column) -> Column:
    """The distinct hashes of a text's lines that aren't blank."""
    return F.array_distinct(F.transform(F.filter(F.transform(F.split(text, "\n"), trimmed), lambda x: x != ""), lambda x: F.xxhash64(x)))


def lines_above(pages: DataFrame, min_pages: int, ratio: float) -> DataFrame:
    """host, line (hash), n, ratio: of ``pages`` (host, text), the lines above both limits."""
    totals = pages.groupBy("host").agg(F.count(F.lit(1)).alias("pages"))
    counts = pages.select("host", F.explode(line_hashes(F.col("text"))).alias("line")).groupBy("host", "line").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= min_pages)
    joined = counts.alias("c").join(totals.alias("t"), F.col("c.host").eqNullSafe(F.col("t.host")))
    return joined.withColumn("ratio", F.col("n") / F.col("pages")).filter(F.col("ratio") > ratio).select("c.host", "line", "n", "ratio")


def lookup_of(above: DataFrame) -> DataFrame:
    """above_host, above: the array of lines of each host that has some."""
    return checkpointed(above.groupBy("host").agg(F.collect_list("line").alias("above")).withColumnRenamed("host", "above_host"))


def with_lookup(pages: DataFrame, lookup: DataFrame) -> DataFrame:
    """``pages`` with ``above``, null for hosts without such lines."""
    n = lookup.agg(F.sum(F.size("above"))).first()[0] or 0
    side = F.broadcast(lookup) if n <= BROADCAST_LINES else lookup
    return pages.join(side, pages["host"].eqNullSafe(side["above_host"]), "left").drop("above_host")


def drop_boilerplate(pages: DataFrame, text_col: str = "text", host_col: str = "source", ratio: float = 0.1, min_pages: int = 5) -> DataFrame:
    """``pages`` with the text's boilerplate lines dropped, and n_lines, n_dropped."""
    src = pages.select(F.struct("*").alias("_row"), F.col(text_col).cast("string").alias("text"), F.col(host_col).alias("host"))
    found = with_lookup(src, lookup_of(lines_above(src.select("host", "text"), min_pages, ratio)))
    lines = F.split("text", "\n")
    # the hash of a blank line is not counted, so it is in no lookup
    stay = F.filter(lines, lambda x: ~F.array_contains("above", F.xxhash64(trimmed(x))))
    cleaned = F.when(F.col("above").isNull(), F.col("text")).otherwise(F.array_join(stay, "\n"))
    dropped = F.when(F.col("above").isNull() | F.col("text").isNull(), F.lit(0)).otherwise(F.size(lines) - F.size(stay))
    # two steps, so that no column of the pages is taken for one of those named here
    done = found.select(
        "_row",
        cleaned.alias("_cleaned"),
        F.when(F.col("text").isNull(), 0).otherwise(F.size(lines)).cast("long").alias("_n_lines"),
        dropped.cast("long").alias("_n_dropped"),
    )
    own = [F.col("_cleaned").alias(c) if c == text_col else F.col("_row")[c].alias(c) for c in pages.columns if c not in ("n_lines", "n_dropped")]
    return done.select(*own, F.col("_n_lines").alias("n_lines"), F.col("_n_dropped").alias("n_dropped"))
