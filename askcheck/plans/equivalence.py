"""Relaxed equivalence of results: row order, column names and column order don't count, further columns may be allowed.

Results are compared by fingerprints, never shipped. Each column gets two sums
of hashes of its values in canonical form, so a column's multiset is known; then
columns are matched, and whole rows confirmed, since columns that agree one by
one may still pair their values differently. Where columns have several partners
they are matched one after another, each partner confirmed by the rows so far.

Candidate texts are untrusted: they are refused or run with a time limit by
``execsql``, the fingerprints of many in one job.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .execsql import Outcome, examine_all, first_rows, look_all


def canon(col: Column, kind: T.DataType, digits: int = 6) -> Column:
    """One text for equal values of any type; NULL has a marker of its own.

    Numbers of all types share a form: rounded, without trailing zeros, zero without a sign.
    """
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        rounded = F.round(col.cast("double"), digits)
        plain = F.when(F.abs(rounded) < 1e15, F.regexp_replace(F.format_string(f"%.{digits}f", rounded), r"\.?0+$", "")).otherwise(F.format_string("%.12e", rounded))
        text = F.when(F.isnan(col), "NaN").when(rounded == 0, "0").otherwise(plain)
    elif isinstance(kind, T.DecimalType):
        s = F.round(col, min(digits, kind.scale)).cast("string") if kind.scale else col.cast("string")
        s = F.when(s.contains("."), F.regexp_replace(s, r"\.?0+$", "")).otherwise(s)
        text = F.when(s == "-0", "0").otherwise(s)
    elif isinstance(kind, T.IntegralType):
        text = col.cast("string")
    elif isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        text = F.date_format(col, "yyyy-MM-dd'T'HH:mm:ss.SSSSSS")
    elif isinstance(kind, T.DateType):
        text = F.concat(F.date_format(col, "yyyy-MM-dd"), F.lit("T00:00:00.000000"))
    elif isinstance(kind, T.MapType):
        text = F.to_json(F.array_sort(F.map_entries(col)))
    elif isinstance(kind, (T.StructType, T.ArrayType)):
        text = F.to_json(F.struct(col.alias("v")))
    elif isinstance(kind, T.BinaryType):
        text = F.hex(col)
    else:
        text = col.cast("string")
    return F.coalesce(F.concat(F.lit("="), text), F.lit("~"))


def canonical(df: DataFrame, digits: int = 6) -> DataFrame:
    """``df`` with every value in canonical form and columns named c0, c1, ..., so that equal names don't matter."""
    plain = df.toDF(*(f"c{i}" for i in range(len(df.columns))))
    return plain.select(*(canon(F.col(f.name), f.dataType, digits).alias(f.name) for f in plain.schema))


@dataclass(frozen=True)
class Fingerprint:
    """Row count, two hash sums for each column, two for whole rows in the order of columns, and one for each column's place among the rows (equal for columns that are equal row by row)."""

    rows: int
    columns: tuple[tuple[int, int], ...]
    whole: tuple[int, int] = (0, 0)
    placed: tuple[int, ...] = ()

    @classmethod
    def of(cls, n: int, sums: list) -> Fingerprint:
        sums = [int(x or 0) for x in sums]
        k = (len(sums) - 2) // 3
        return cls(n, tuple(zip(sums[:k], sums[k : 2 * k], strict=True)), (sums[3 * k], sums[3 * k + 1]), tuple(sums[2 * k : 3 * k]))


def _sum(*of) -> Column:
    """Sums of decimals and not exclusive-or, which would let equal pairs cancel."""
    return F.sum(F.xxhash64(*of).cast("decimal(38,0)"))


def fingerprint_row(df: DataFrame, digits: int = 6) -> DataFrame:
    """n, sums: one aggregate with a single row of partial results for each task."""
    rows = canonical(df, digits)
    names = rows.columns
    held = rows.withColumn("r", F.xxhash64(F.lit("row"), *names))
    sums = [*(_sum(c) for c in names), *(_sum(F.lit("salt"), c) for c in names), *(_sum("r", c) for c in names), _sum(F.lit("x"), *names), _sum(F.lit("y"), *names)]
    return held.agg(F.count(F.lit(1)).alias("n"), F.array(*sums).alias("sums"))


def fingerprint(df: DataFrame, digits: int = 6) -> Fingerprint:
    return Fingerprint.of(*fingerprint_row(df, digits).first())


def partners(gold: Fingerprint, candidate: Fingerprint, superset: str = "candidate") -> list[list[int]] | None:
    """For each column of ``gold`` those of ``candidate`` with the same multiset; None if the results can't be equal.

    ``superset``: which side may have columns that are left over: candidate, none.
    """
    if gold.rows != candidate.rows or len(gold.columns) > len(candidate.columns) or (superset == "none" and len(gold.columns) != len(candidate.columns)):
        return None
    found = [[j for j, c in enumerate(candidate.columns) if c == g] for g in gold.columns]
    return found if all(found) else None


def match_columns(gold: Fingerprint, candidate: Fingerprint, superset: str = "candidate", fits=lambda chosen: True) -> Iterator[dict[int, int]]:
    """Ways to give each column of ``gold`` one of its own in ``candidate``, gold to candidate.

    Columns with one partner come first. ``fits`` is asked about a part of a way
    whenever a column had several partners, and prunes what it refuses. Of
    candidate columns that are equal row by row only the first free one is tried.
    """
    choices = partners(gold, candidate, superset)
    if choices is None:
        return
    order = sorted(range(len(choices)), key=lambda i: (len(choices[i]), i))
    alike = candidate.placed or tuple(range(len(candidate.columns)))

    def extend(chosen: dict[int, int]) -> Iterator[dict[int, int]]:
        if len(chosen) == len(order):
            yield dict(chosen)
            return
        i, tried = order[len(chosen)], set()
        for j in choices[i]:
            if j in chosen.values() or alike[j] in tried:
                continue
            tried.add(alike[j])
            longer = {**chosen, i: j}
            if len(choices[i]) == 1 or fits(longer):
                yield from extend(longer)

    yield from extend({})


def rows_row(df: DataFrame, columns: list[int], digits: int = 6) -> DataFrame:
    """n, sums: of the rows of the chosen columns, in their order."""
    names = [f"c{j}" for j in columns]
    return canonical(df, digits).agg(F.count(F.lit(1)).alias("n"), F.array(_sum(F.lit("x"), *names), _sum(F.lit("y"), *names)).alias("sums"))


def same_rows(a: DataFrame, b: DataFrame, chosen: dict[int, int], digits: int = 6) -> bool:
    """Equal multisets of canonical rows of the matched columns."""
    left, right = rows_row(a, list(chosen), digits), rows_row(b, list(chosen.values()), digits)
    return tuple(left.first()) == tuple(right.first())


def decided(gold: Fingerprint, candidate: Fingerprint, chosen: dict[int, int]) -> bool | None:
    """What the fingerprints alone tell about a whole way; None if rows must be asked."""
    if len(chosen) == 1:
        return True
    if len(gold.columns) == len(candidate.columns) and all(i == j for i, j in chosen.items()):
        return gold.whole == candidate.whole
    return None


def equivalent(gold: DataFrame, candidate: DataFrame, superset: str = "candidate", strict_order: bool = False, digits: int = 6, exact: bool = False) -> bool:
    """``superset``: "candidate" lets the candidate have further columns, "either" also the gold result, "none" neither.

    ``exact`` confirms by rows what the hashes say.
    """
    if superset == "either":
        return equivalent(gold, candidate, "candidate", strict_order, digits, exact) or equivalent(candidate, gold, "candidate", strict_order, digits, exact)
    if strict_order:
        return strict_equal(gold, candidate, digits)
    a, b = fingerprint(gold, digits), fingerprint(candidate, digits)
    for chosen in match_columns(a, b, superset, lambda part: len(part) == 1 or same_rows(gold, candidate, part, digits)):
        known = decided(a, b, chosen)
        if known or (known is None and same_rows(gold, candidate, chosen, digits)):
            return not exact or exact_confirm(gold, candidate, chosen, digits)
    return False


def exact_confirm(gold: DataFrame, candidate: DataFrame, chosen: dict[int, int], digits: int = 6) -> bool:
    """The same without hashes: nothing of the matched columns is left over either way."""
    a = canonical(gold, digits).select(*(F.col(f"c{i}") for i in chosen))
    b = canonical(candidate, digits).select(*(F.col(f"c{j}").alias(f"c{i}") for i, j in chosen.items()))
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def ordered_fingerprint(df: DataFrame, digits: int = 6) -> tuple:
    """Row count and sums of row hashes, plain and weighted by the place of a row, from one row for each partition.

    Places inside a partition are weighted there; with the rows of the
    partitions before it known, the sums follow for the whole.
    """
    rows = canonical(df, digits)
    hashes = {k: F.xxhash64(F.lit(k), *rows.columns).cast("decimal(38,0)") for k in ("x", "y")}
    at = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    held = rows.select(F.spark_partition_id().alias("p"), at.cast("decimal(10,0)").alias("at"), *(h.alias(k) for k, h in hashes.items()))
    weighted = [F.sum((F.col(k).cast("decimal(20,0)") * F.col("at")).cast("decimal(38,0)")).alias(f"{k}_at") for k in hashes]
    parts = held.groupBy("p").agg(F.count(F.lit(1)).alias("n"), *(F.sum(k).alias(k) for k in hashes), *weighted).collect()
    before, sums = 0, [0, 0, 0, 0]
    for r in sorted(parts, key=lambda r: r["p"]):
        sums = [sums[0] + int(r["x"]), sums[1] + int(r["y"]), sums[2] + int(r["x_at"]) + before * int(r["x"]), sums[3] + int(r["y_at"]) + before * int(r["y"])]
        before += r["n"]
    return before, *sums


def strict_equal(gold: DataFrame, candidate: DataFrame, digits: int = 6) -> bool:
    """The contrast without relaxation: the same columns in the same order, the same rows in the same order."""
    return len(gold.columns) == len(candidate.columns) and ordered_fingerprint(gold, digits) == ordered_fingerprint(candidate, digits)


def equivalence_join(candidates: DataFrame, golds: DataFrame) -> DataFrame:
    """Pairs of candidate and gold ids that can be equal: same row count and same set of column sums (columns not superset).

    Both sides: id, db_id, n_rows, cols array<decimal(38,0)>. Rows still have to be confirmed.
    """
    key = F.array_sort("cols")
    a = candidates.select(F.col("id").alias("candidate_id"), "db_id", "n_rows", key.alias("key"))
    b = golds.select(F.col("id").alias("gold_id"), "db_id", "n_rows", key.alias("key"))
    return a.join(b, ["db_id", "n_rows", "key"]).select("candidate_id", "gold_id")


def readings_differ(df: DataFrame) -> DataFrame:
    """group_id, n_results, differ: an ambiguous group must have two readings with different results. ``df``: group_id, result (any key of a result)."""
    return df.groupBy("group_id").agg(F.countDistinct("result").alias("n_results")).withColumn("differ", F.col("n_results") >= 2)


def refute_on_sample(gold: DataFrame, candidate: DataFrame, key: str, share: float = 0.1, seed: int = 7) -> bool:
    """True if rows of a key-consistent sample already separate two results that both carry ``key``. Opt-in: a sample is another state of the data than the one compared on."""

    def part(df: DataFrame) -> DataFrame:
        draw = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string"))), 1, 8), 16, 10).cast("bigint")
        return df.filter(draw < int(share * (1 << 32)))

    return not equivalent(part(gold), part(candidate))


class ResultCache:
    """Fingerprints of distinct SQL texts; each text runs once for each version of the data.

    A text that is refused, fails or takes too long has no result and equals none.
    """

    def __init__(self, spark, digits: int = 6, timeout_s: float = 20.0):
        self.spark, self.digits, self.timeout_s = spark, digits, timeout_s
        self.frames: dict[str, DataFrame | None] = {}
        self.found: dict[str, Fingerprint | None] = {}
        self.rows: dict[tuple[str, tuple[int, ...]], tuple | None] = {}
        self.pairs: dict[tuple[str, str, str], bool] = {}
        self.seen: dict[str, tuple[Outcome, str | None]] = {}

    def look(self, texts) -> dict[str, tuple[Outcome, str | None]]:
        """The outcome of each text and its first five rows as JSON lines."""
        texts = set(texts)
        self.seen.update(look_all(self.spark, texts.difference(self.seen), self.timeout_s, 5))
        return {t: self.seen[t] for t in texts}

    def outcomes_of(self, texts) -> dict[str, Outcome]:
        return {t: outcome for t, (outcome, _) in self.look(texts).items()}

    def previews(self, texts) -> dict[str, str | None]:
        return {t: rows for t, (_, rows) in self.look(texts).items()}

    def prepare(self, texts) -> None:
        """Fingerprints of those not known yet, in few jobs."""
        new = sorted({t for t in texts if t not in self.found})
        examined = examine_all(self.spark, new)
        self.frames.update({t: None if isinstance(x, Outcome) else x for t, x in examined.items()})
        self.found.update(dict.fromkeys(new))
        asked = {t: fingerprint_row(self.frames[t], self.digits) for t in new if self.frames[t] is not None}
        for t, row in first_rows(self.spark, asked, self.timeout_s).items():
            self.found[t] = None if isinstance(row, Outcome) else Fingerprint.of(row["n"], row["sums"])

    def of(self, sql: str) -> Fingerprint | None:
        self.prepare([sql])
        return self.found[sql]

    def rows_of(self, keys) -> None:
        """Sums of the rows of chosen columns, of many texts in few jobs. ``keys``: (text, columns)."""
        new = {k: rows_row(self.frames[k[0]], list(k[1]), self.digits) for k in set(keys) if k not in self.rows}
        for k, row in first_rows(self.spark, new, self.timeout_s).items():
            self.rows[k] = None if isinstance(row, Outcome) else (row["n"], *row["sums"])

    def _same(self, gold: str, candidate: str, chosen: dict[int, int]) -> bool:
        keys = (gold, tuple(chosen)), (candidate, tuple(chosen.values()))
        self.rows_of(keys)
        return self.rows[keys[0]] is not None and self.rows[keys[0]] == self.rows[keys[1]]

    def equal_many(self, pairs, superset: str = "candidate") -> dict[tuple[str, str], bool]:
        """For (gold, candidate) texts whether their results are equal."""
        pairs = set(pairs)
        new = [(g, c) for g, c in sorted(pairs) if (g, c, superset) not in self.pairs]
        self.prepare(t for p in new for t in p)
        # most pairs have one way to match columns: their rows are asked for together
        single = {}
        for g, c in new:
            a, b = self.found[g], self.found[c]
            choices = partners(a, b, superset) if a and b else None
            if choices and all(len(x) == 1 for x in choices):
                single[g, c] = {i: x[0] for i, x in enumerate(choices)}
        open_ones = {p: m for p, m in single.items() if len(set(m.values())) == len(m) and decided(self.found[p[0]], self.found[p[1]], m) is None}
        self.rows_of(k for (g, c), m in open_ones.items() for k in ((g, tuple(m)), (c, tuple(m.values()))))
        for g, c in new:
            self.pairs[g, c, superset] = self._compare(g, c, superset)
        return {(g, c): self.pairs[g, c, superset] for g, c in pairs}

    def equal(self, gold: str, candidate: str, superset: str = "candidate") -> bool:
        return self.equal_many([(gold, candidate)], superset)[gold, candidate]

    def _compare(self, gold: str, candidate: str, superset: str) -> bool:
        a, b = self.found[gold], self.found[candidate]
        if a is None or b is None:
            return False
        for chosen in match_columns(a, b, superset, lambda part: len(part) == 1 or self._same(gold, candidate, part)):
            known = decided(a, b, chosen)
            if known or (known is None and self._same(gold, candidate, chosen)):
                return True
        return False


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
