"""SQL with its literal values masked, so that queries which differ only in values are equal."""

from __future__ import annotations

import re
from functools import reduce

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

#: (pattern, replacement), applied in order. No look-behind, so other engines can run them too.
STEPS = (
    (r"--[^\n]*", " "),
    (r"/\*[^*]*\*+([^/*][^*]*\*+)*/", " "),
    (r"'([^']|'')*'", "?"),
    (r"(^|[^A-Za-z0-9_.?])[0-9]+(\.[0-9]*)?([eE][-+]?[0-9]+)?", r"\1?"),
    (r"([=<>(,]\s*)[-+]\s*\?", r"\1?"),
    (r"\b([dD][aA][tT][eE]|[tT][iI][mM][eE][sS][tT][aA][mM][pP])\s*\?", "?"),
    (r"\s+", " "),
)
IN_LIST = (r"\( ?\?( ?, ?\?)+ ?\)", "(?)")


def mask_values(sql: str | Column, collapse_lists: bool = True) -> Column:
    """Comments off, literals as ``?``, white space and case levelled: JVM expressions only.

    Quotes inside quoted identifiers are not told apart; ``mask_exact`` does that.
    """
    steps = [*STEPS, IN_LIST] if collapse_lists else STEPS
    c = F.col(sql) if isinstance(sql, str) else sql
    return F.lower(F.trim(reduce(lambda x, s: F.regexp_replace(x, s[0], s[1].replace("\\1", "$1")), steps, c)))


def mask_sql_text(column: str, collapse_lists: bool = True) -> str:
    """The same chain as SQL text for an engine whose regexp_replace takes 'g' and backslash groups."""
    steps = [*STEPS, IN_LIST] if collapse_lists else STEPS
    quoted = lambda s: s.replace("'", "''")
    return f"lower(trim({reduce(lambda x, s: f"regexp_replace({x}, '{quoted(s[0])}', '{quoted(s[1])}', 'g')", steps, column)}))"


_TOKEN = re.compile(
    r"""(?P<gap>\s+|--[^\n]*|/\*.*?\*/)|(?P<text>[nN]?'(?:[^'\\]|''|\\.)*')|(?P<name>"(?:[^"]|"")*"|`(?:[^`]|``)*`|[A-Za-z_][A-Za-z0-9_$]*)|(?P<number>(?:\d+\.?\d*|\.\d+)(?:[eE][-+]?\d+)?)|(?P<mark><=>|<>|!=|<=|>=|\|\||::|.)""",
    re.S,
)


def mask_exact(sql: str, collapse_lists: bool = True) -> str:
    """The same by a tokenizer: quoted names stay as they are, a sign goes with its number where a value can begin."""
    out: list[str] = []
    for m in _TOKEN.finditer(sql):
        kind, token = m.lastgroup, m.group()
        if kind == "gap":
            continue
        if kind in ("text", "number"):
            if out and out[-1] in "+-" and (len(out) == 1 or out[-2] in ("=", "<", ">", "<=", ">=", "<>", "!=", "(", ",", "and", "or", "then", "else", "when", "between", "select", "where")):
                out.pop()
            if out and out[-1] in ("date", "timestamp") and kind == "text":
                out.pop()
            out.append("?")
        else:
            out.append(token if token[0] in "\"`" else token.lower())
    text = " ".join(out)
    return re.sub(r"\( \?(?: , \?)+ \)", "( ? )", text) if collapse_lists else text


@F.pandas_udf(StringType())
def mask_values_exact(sql: pd.Series) -> pd.Series:
    return sql.map(lambda s: None if s is None else mask_exact(s))


def difficulty(sql: str | Column) -> Column:
    """Level of a query from counts of its constructs: joins, aggregates, HAVING, subqueries, CTEs, windows, set operations."""
    c = F.lower(F.col(sql) if isinstance(sql, str) else sql)
    points = (
        F.regexp_count(c, F.lit(r"\bjoin\b"))
        + F.least(F.lit(2), F.regexp_count(c, F.lit(r"\b(count|sum|avg|min|max|percentile|stddev)\s*\(")))
        + F.regexp_count(c, F.lit(r"\bgroup by\b"))
        + 2 * F.regexp_count(c, F.lit(r"\bhaving\b"))
        + 2 * F.regexp_count(c, F.lit(r"\(\s*select\b"))
        + 2 * F.regexp_count(c, F.lit(r"\bwith\b"))
        + 3 * F.regexp_count(c, F.lit(r"\bover\s*\("))
        + 2 * F.regexp_count(c, F.lit(r"\b(union|intersect|except)\b"))
    )
    return F.when(c.isNull(), F.lit(None).cast("string")).when(points <= 1, "simple").when(points <= 3, "moderate").when(points <= 5, "complex").otherwise("highly_complex")
