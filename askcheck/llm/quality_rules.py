"""Rule-based quality with the frequency of lines across documents of a host.

Only DataFrame expressions. Base rules look at one document: its words, symbols,
repeated lines and words in repeated three-word windows. Then normalised lines
(lower case, digits as 0, outer white space off) are hashed and the documents of
a host that hold each are counted. A line that stands in at least ``min_docs``
documents of its host and in more than ``share`` of them is above the limit. It
is removed, and a document that thereby loses more than ``most_lost`` of the
characters of its lines is depleted and rejected.

A host has at most (mean number of lines of its documents) / share lines above
the limit, whatever its size. Counting combines in the map tasks, so a line that
stands in a third of all documents is one row for each task.

Defined results: a null text has no words and fails the base; a null host is a
host of its own; rows with the same doc_id count as documents of their own; an
empty table gives an empty result. Windows of three words and lines are told
apart by 64-bit hashes.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty
from .line_dedup import SPACES, lines_above, lookup_of, trimmed, with_lookup, words_of

SYMBOLS = "[#*$%&|<>]"


def let(value: Column, body) -> Column:
    """``body(value)`` with the value computed once, where lambdas would compute it again and again."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def window_hashes(words: Column) -> Column:
    """A hash for each window of three words; empty if there are fewer words."""
    return F.when(F.size(words) < 3, F.array().cast("array<bigint>")).otherwise(
        F.transform(F.sequence(F.lit(0), F.size(words) - 3), lambda i: F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)))
    )


def repeated_words(hashes: Column) -> Column:
    """How many words lie in windows whose hash occurs twice or more.

    Windows are sorted with their places; a window is repeated if a neighbour
    has its hash. The union of the windows' words is summed up in text order.
    """

    def places(placed: Column) -> Column:
        twice = F.transform(
            placed,
            lambda x, k: F.when(F.coalesce(F.get(placed, k - 1)["h"] == x["h"], F.lit(False)) | F.coalesce(F.get(placed, k + 1)["h"] == x["h"], F.lit(False)), x["i"]).otherwise(F.lit(-1)),
        )
        return F.sort_array(F.array_remove(twice, -1))

    placed = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    start = F.struct(F.lit(0).alias("n"), F.lit(0).alias("end"))
    return F.aggregate(let(placed, places), start, lambda acc, i: F.struct((acc["n"] + i + 3 - F.greatest(i, acc["end"])).alias("n"), (i + 3).alias("end")), lambda acc: acc["n"])


def base_counts(docs: DataFrame, text: str) -> DataFrame:
    """``docs`` with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    worded = F.filter(F.split(F.col(text), "\n"), lambda x: x.rlike(f"[^{SPACES}]"))
    return (
        docs.withColumn("_words", words_of(F.col(text)))
        .withColumn("_hashes", window_hashes(F.col("_words")))
        .withColumn("_lines", worded)
        .withColumns(
            {
                "n_words": F.size("_words").cast("long"),
                "word_chars": F.length(F.array_join("_words", "")).cast("long"),
                "n_symbols": F.regexp_count(text, F.lit(SYMBOLS)).cast("long"),
                "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
                # most texts repeat no window; one set of longs shows that
                "n_repeat_words": F.when(F.size(F.array_distinct("_hashes")) == F.size("_hashes"), F.lit(0)).otherwise(repeated_words(F.col("_hashes"))).cast("long"),
            }
        )
        .drop("_words", "_hashes", "_lines")
    )


def normalised(text: str) -> Column:
    return F.regexp_replace(F.lower(F.col(text)), "[0-9]", "0")


def judge(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    host_col: str = "source",
    min_words: int = 50,
    repeat_percent: int = 50,
    min_docs: int = 10,
    share: float = 0.1,
    most_lost: float = 0.5,
) -> DataFrame:
    """doc_id, the five base counts, base_failed, lost_chars, line_chars, kept."""
    src = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"), F.col(host_col).alias("host"))
    above = lines_above(src.select("host", normalised("text").alias("text")), min_docs, share)
    judged = base_counts(with_lookup(src, lookup_of(above)), "text")
    lines = F.transform(F.split(normalised("text"), "\n"), trimmed)
    sizes = F.transform(lines, lambda x: F.when(F.array_contains(F.coalesce("above", F.array().cast("array<bigint>")), F.xxhash64(x)), F.length(x)).otherwise(0))
    total = F.aggregate(lines, F.lit(0), lambda a, x: a + F.length(x))
    lost = F.when(F.col("above").isNull(), F.lit(0)).otherwise(F.aggregate(sizes, F.lit(0), lambda a, n: a + n))
    failed = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > repeat_percent * F.col("n_words"))
    return (
        judged.withColumns({"lost_chars": lost.cast("long"), "line_chars": total.cast("long"), "base_failed": failed})
        # most hosts have no line above the limit: their documents' lines needn't be measured
        .withColumn("kept", ~F.col("base_failed") & F.when(F.col("above").isNull(), True).otherwise(F.col("lost_chars") <= most_lost * F.col("line_chars")))
        .drop("text", "host", "above")
    )
