"""Quality classifier: a sparse ensemble of rules over text statistics.

Statistics of a text are DataFrame expressions. Small trees are boosted on them;
every path from a root to a node is a conjunctive rule; an L1-penalised logistic
model over the rules keeps few of them. Those are compiled into one column
expression, so scoring runs in the JVM without Python.

The model is fitted on the driver, on at most ``max_rows`` labelled rows (the
first by hash of their id: the bound is a parameter, 20,000 by default), of
which only the statistics are collected. Every document is scored, whole.

Defined results: a null text counts as empty, and empty texts are scored like
any other; rows with the same doc_id are scored each; without labels, or with
one class only, the score is the smoothed share of label 1; labels that are not 0
or 1, or lack an id, are left out, and so are ids with both labels; an empty table
gives an empty result. The columns of a table are held in one struct and the
statistics in another, so columns of any name, those of the statistics included,
are told apart; only the id and the text are read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty
from .line_dedup import words_of

STATISTICS = ("n_chars", "n_words", "word_length", "upper", "symbols", "digits", "marks", "richness", "stutter", "line_words", "repeated_lines")


def statistics(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """row (a struct of the columns of ``docs``) and stats (a struct of a double for each of STATISTICS).

    The statistics come out of a generator of one row: a filter on a score is then
    not pushed below them, which would compute them anew for every term of a rule.
    """
    text = F.col("text")
    n = F.greatest(F.col("n"), F.lit(1))
    chars = F.greatest(F.length(text), F.lit(1))
    counted = {
        "n_chars": F.length(text).cast("double"),
        "n_words": F.col("n").cast("double"),
        "word_length": F.length(F.array_join("words", "")) / n,
        "upper": F.regexp_count(text, F.lit(r"\p{Lu}")) / chars,
        "symbols": F.regexp_count(text, F.lit(r"[#*$%&|<>]")) / n,
        "digits": F.regexp_count(text, F.lit("[0-9]")) / chars,
        "marks": F.regexp_count(text, F.lit("[!?]")) / n,
        # the logarithms' ratio hardly depends on the length of a text
        "richness": F.log1p(F.size(F.array_distinct("words"))) / F.log1p(n),
        "stutter": F.size(F.filter("words", lambda w, i: F.coalesce(w == F.get("words", i - 1), F.lit(False)))) / n,
        "line_words": F.col("n") / F.size("lines"),
        "repeated_lines": 1 - F.size(F.array_distinct("lines")) / F.size("lines"),
    }
    held = docs.select(F.struct("*").alias("row"), text_or_empty(text_col).alias("text"))
    parts = held.withColumns({"words": words_of(text), "lines": F.split(text, "\n")}).withColumn("n", F.size("words"))
    return parts.select("row", F.explode(F.array(F.struct(*(c.alias(k) for k, c in counted.items())))).alias("stats"))


@dataclass(frozen=True)
class Rule:
    """All of (statistic, at most or above, threshold) hold."""

    terms: tuple[tuple[str, bool, float], ...]

    def holds(self, x: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), bool)
        for name, at_most, cut in self.terms:
            v = x[:, STATISTICS.index(name)]
            out &= v <= cut if at_most else v > cut
        return out

    def column(self) -> Column:
        """Over the stats of ``statistics``."""
        out = F.lit(True)
        for name, at_most, cut in self.terms:
            out = out & (F.col("stats")[name] <= cut if at_most else F.col("stats")[name] > cut)
        return out


@dataclass(frozen=True)
class RuleModel:
    intercept: float
    rules: tuple[tuple[Rule, float], ...]

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.intercept)
        for rule, w in self.rules:
            z += w * rule.holds(x)
        return 1 / (1 + np.exp(-z))

    def column(self) -> Column:
        z = F.lit(self.intercept)
        for rule, w in self.rules:
            z = z + F.when(rule.column(), w).otherwise(0.0)
        return 1 / (1 + F.exp(-z))


def grow(x: np.ndarray, slope: np.ndarray, curve: np.ndarray, cuts: list[np.ndarray], depth: int, least: int, path: tuple = ()) -> list[tuple[tuple, float]]:
    """Nodes of one tree as (path, value); a split must gain in the second-order loss."""
    value = -slope.sum() / (curve.sum() + 1.0)
    nodes = [(path, value)]
    if depth == 0 or len(x) < 2 * least:
        return nodes
    base, best = slope.sum() ** 2 / (curve.sum() + 1), (1e-6, None)
    for f, edges in enumerate(cuts):
        if not len(edges):
            continue
        bins = np.searchsorted(edges, x[:, f], side="left")
        g, h, n = (np.bincount(bins, w, len(edges) + 1).cumsum()[:-1] for w in (slope, curve, None))
        gain = g**2 / (h + 1) + (slope.sum() - g) ** 2 / (curve.sum() - h + 1) - base
        gain[(n < least) | (len(x) - n < least)] = -1
        k = int(gain.argmax())
        if gain[k] > best[0]:
            best = (gain[k], (f, float(edges[k])))
    if best[1] is None:
        return nodes
    f, cut = best[1]
    for at_most in (True, False):
        part = x[:, f] <= cut if at_most else x[:, f] > cut
        nodes += grow(x[part], slope[part], curve[part], cuts, depth - 1, least, (*path, (STATISTICS[f], at_most, cut)))
    return nodes


def extract_rules(x: np.ndarray, y: np.ndarray, trees: int = 24, depth: int = 3, least: int | None = None, rate: float = 0.3) -> list[Rule]:
    least = least or min(10, max(3, len(y) // 20))
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0.01, 0.99, 60))) for f in range(x.shape[1])]
    z = np.full(len(y), np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)))
    rules: dict[frozenset, Rule] = {}
    for _ in range(trees):
        p = 1 / (1 + np.exp(-z))
        nodes = grow(x, p - y, p * (1 - p), cuts, depth, least)
        inner = {path[:-1] for path, _ in nodes if path}
        for path, value in nodes:
            if path:
                rules.setdefault(frozenset(path), Rule(path))
            if path not in inner:
                z += rate * value * Rule(path).holds(x)
    return list(rules.values())


def lasso_logistic(a: np.ndarray, y: np.ndarray, penalty: float, steps: int = 400) -> tuple[float, np.ndarray]:
    """Weights of least logistic loss plus ``penalty`` times their absolute sum, by accelerated proximal steps."""
    n, k = a.shape
    mean = a.mean(0)
    centred = a - mean
    rate = 4 / (np.linalg.norm(centred, 2) ** 2 / n + 1)
    w, b = np.zeros(k), np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6))
    look_w, look_b, t = w, b, 1.0
    for _ in range(steps):
        r = 1 / (1 + np.exp(-(centred @ look_w + look_b))) - y
        step = look_w - rate * (centred.T @ r) / n
        new_w = np.sign(step) * np.maximum(np.abs(step) - rate * penalty, 0)
        new_b = look_b - rate * r.mean()
        new_t = (1 + np.sqrt(1 + 4 * t * t)) / 2
        look_w, look_b = new_w + (t - 1) / new_t * (new_w - w), new_b + (t - 1) / new_t * (new_b - b)
        w, b, t = new_w, new_b, new_t
    return float(b - mean @ w), w


def fit(x: np.ndarray, y: np.ndarray, penalty: float = 5e-4) -> RuleModel:
    """The penalty grows where rows are few, so that a handful of them doesn't carry many rules."""
    if len(y) < 20 or y.min() == y.max():
        share = (y.sum() + 1) / (len(y) + 2)
        return RuleModel(float(np.log(share / (1 - share))), ())
    rules = extract_rules(x, y.astype(float))
    a = np.stack([r.holds(x) for r in rules], 1).astype(float)
    b, w = lasso_logistic(a, y.astype(float), penalty + 1 / len(y))
    return RuleModel(b, tuple((r, float(v)) for r, v in zip(rules, w, strict=True) if v != 0))


def held_out(id_col: str = "doc_id") -> Column:
    return F.crc32(F.col(id_col).cast("string")) % 3 == 1


def train(docs: DataFrame, labels: DataFrame, max_rows: int = 20_000, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> RuleModel:
    """Fit on labelled rows outside the held-out third."""
    known = labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("y")).filter(F.col("y").isin(0, 1) & F.col("id").isNotNull()).filter(~held_out("id"))
    single = known.groupBy("id").agg(F.min("y").alias("y"), F.max("y").alias("most")).filter("y = most").drop("most")
    sample = single.orderBy(F.xxhash64("id"), "id").limit(max_rows)
    texts = docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text"))
    rows = statistics(texts.join(F.broadcast(sample), "id").select("id", "y", "text")).select("row.id", "row.y", "stats.*")
    got = rows.toPandas().sort_values(["id", "y", *STATISTICS])
    return fit(got[list(STATISTICS)].to_numpy(float), got["y"].to_numpy(int))


def score_documents(docs: DataFrame, model: RuleModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score, predicted."""
    stats = statistics(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")))
    return stats.select(F.col("row.doc_id").alias("doc_id"), model.column().alias("score")).withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def keep_good(docs: DataFrame, model: RuleModel, text_col: str = "text", least: float = 0.5) -> DataFrame:
    """The rows of ``docs`` that score ``least`` and more."""
    return statistics(docs, text_col).filter(model.column() >= least).select("row.*")
