"""Measures of dialogues and of annotated samples, as aggregates without Python."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .council import collect_ballots, majority
from .equivalence import ResultCache


def pct(num: Column, den: Column) -> Column:
    return F.round(F.try_divide(100.0 * num, den.cast("double")), 4)


def share(condition: Column) -> Column:
    return pct(F.count_if(condition), F.count(F.lit(1)))


def recognition_and_classification(df: DataFrame, *by: str) -> DataFrame:
    """n, rec, cls. ``df``: qtype, pred_qtype, subcategory, pred_subcategory."""
    return df.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), share(F.col("qtype") == F.col("pred_qtype")).alias("rec"), share(F.col("subcategory") == F.col("pred_subcategory")).alias("cls"))


def score(df: DataFrame, *by: str) -> DataFrame:
    """ex_num, ex_den, ex, fb_num, fb_den, fb and ex_ans, ex_amb in one pass.

    ``df``: qtype, final_kind, correct (the query is equivalent, or the feedback accepted).
    An unanswerable question that ended in SQL is a wrong execution and also a
    wrong feedback; one with an answer that ended in feedback is wrong in both.
    """
    solvable, sql, feedback = F.col("qtype") != "unanswerable", F.coalesce(F.col("final_kind") == "sql", F.lit(False)), F.coalesce(F.col("final_kind") == "feedback", F.lit(False))
    right = F.coalesce(F.col("correct"), F.lit(False))
    ex_num, ex_den = F.count_if(solvable & sql & right), F.count_if(solvable | sql)
    fb_num, fb_den = F.count_if(~solvable & feedback & right), F.count_if(~solvable | feedback)
    out = df.groupBy(*by).agg(
        ex_num.alias("ex_num"), ex_den.alias("ex_den"), fb_num.alias("fb_num"), fb_den.alias("fb_den"),
        pct(F.count_if((F.col("qtype") == "answerable") & sql & right), F.count_if(F.col("qtype") == "answerable")).alias("ex_ans"),
        pct(F.count_if((F.col("qtype") == "ambiguous") & sql & right), F.count_if(F.col("qtype") == "ambiguous")).alias("ex_amb"),
    )
    return out.withColumns({"ex": pct(F.col("ex_num"), F.col("ex_den")), "fb": pct(F.col("fb_num"), F.col("fb_den"))})


def judge_ends(conversations: DataFrame, questions: DataFrame, results: ResultCache, users: list) -> DataFrame:
    """conversations with the question's type and ``correct``: equivalence of final SQL, a council's majority on final feedback."""
    spark = conversations.sparkSession
    joined = conversations.join(questions.select("obj_id", "qtype", "category", "subcategory", "gold_sql", "hidden"), "obj_id")
    finals = joined.filter("final_kind = 'sql' and gold_sql is not null").select("gold_sql", "final_text").distinct().collect()  # as many as candidate queries
    equal = spark.createDataFrame([(g, c, same) for (g, c), same in results.equal_many([tuple(r) for r in finals]).items()], "gold_sql string, final_text string, equal boolean")
    said = joined.filter("final_kind = 'feedback' and qtype = 'unanswerable'").select(F.md5(F.concat_ws("|", "final_text", "hidden")).alias("item_id"), F.col("final_text").alias("text"), "hidden").distinct()
    accepted = majority(collect_ballots(said, users, "feedback_match"), len(users)).select("item_id", F.col("kept").alias("accepted"))
    out = joined.join(equal, ["gold_sql", "final_text"], "left").withColumn("item_id", F.md5(F.concat_ws("|", "final_text", "hidden"))).join(accepted, "item_id", "left")
    return out.withColumn("correct", F.coalesce(F.when(F.col("final_kind") == "sql", F.col("equal")).when((F.col("final_kind") == "feedback") & (F.col("qtype") == "unanswerable"), F.col("accepted")), F.lit(False))).drop("equal", "accepted", "item_id")


def air(turns: DataFrame, *by: str, which: str = "first", exclude_forced: bool = False, conv: str = "conv_id", order: tuple[str, ...] = ("turn",)) -> DataFrame:
    """n_conv, n_terminal, air: how often the system's turn after a relevant reply ends the conversation.

    ``turns``: conv_id, turn, kind (sql, feedback, clarification, reply),
    relevancy, forced. A reply that nothing follows is left out. ``which``
    relevant reply counts: first, last, or all of them. One shuffle on the
    conversation.
    """
    at = Window.partitionBy(conv).orderBy(*order)
    nexts = turns.withColumns({"_next": F.lead("kind").over(at), "_forced": F.lead("forced").over(at), "_order": F.struct(*order)})
    asked = nexts.filter((F.col("relevancy") == "relevant") & F.col("_next").isNotNull())
    if exclude_forced:
        asked = asked.filter(~F.coalesce("_forced", F.lit(False)))
    if which != "all":
        pick = F.min_by if which == "first" else F.max_by
        asked = asked.groupBy(conv, *by).agg(pick("_next", "_order").alias("_next"))
    terminal = F.count_if(F.col("_next").isin("sql", "feedback"))
    return asked.groupBy(*by).agg(F.count(F.lit(1)).alias("n_conv"), terminal.alias("n_terminal"), pct(terminal, F.count(F.lit(1))).alias("air"))


def dialogue_statistics(turns: DataFrame, *by: str, conv: str = "conv_id") -> DataFrame:
    """n_conv, avg_turns (of the system), clar_pct, relevant_pct, technical_pct, irrelevant_pct."""
    per = turns.groupBy(conv, *by).agg(
        F.count_if(F.col("role") == "system").alias("s"), F.bool_or(F.coalesce(F.col("kind") == "clarification", F.lit(False))).alias("asks"),
        *(F.count_if(F.col("relevancy") == k).alias(k) for k in ("relevant", "technical", "irrelevant")),
    )
    replies = F.sum("relevant") + F.sum("technical") + F.sum("irrelevant")
    return per.groupBy(*by).agg(F.count(F.lit(1)).alias("n_conv"), F.round(F.avg("s"), 4).alias("avg_turns"), share(F.col("asks")).alias("clar_pct"), *(pct(F.sum(k), replies).alias(f"{k}_pct") for k in ("relevant", "technical", "irrelevant")))


def balance(df: DataFrame, by: list[str], key: str, k: int | None = None, seed: int = 7) -> DataFrame:
    """Exactly ``k`` rows of each class (default: the smallest class), the first by md5 of seed and key.

    A few classes would mean a few tasks; so each class is cut to k within
    hash parts first, and only those are merged.
    """
    if k is None:
        k = df.groupBy(*by).agg(F.count(F.lit(1)).alias("n")).agg(F.min("n")).first()[0] or 0
    drawn = df.withColumn("_draw", F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string"))))
    part = F.pmod(F.xxhash64(key), F.lit(64))
    first = drawn.withColumn("_part", part).withColumn("_r", F.row_number().over(Window.partitionBy(*by, "_part").orderBy("_draw", key))).filter(F.col("_r") <= k)
    return first.withColumn("_r", F.row_number().over(Window.partitionBy(*by).orderBy("_draw", key))).filter(F.col("_r") <= k).drop("_draw", "_part", "_r")


def mode_impact(scores: DataFrame, measures: tuple[str, ...] = ("ex_ans", "ex_amb", "fb")) -> DataFrame:
    """Mean over agents of each agent's score, by set and mode."""
    return scores.groupBy("set", "mode").agg(*(F.round(F.avg(m), 4).alias(m) for m in measures))


def per_category(judged: DataFrame) -> DataFrame:
    """set, mode, subcategory, metric (EX or FB), value: mean over agents."""
    of_agent = score(judged, "set", "mode", "agent", "subcategory", "qtype")
    named = of_agent.withColumn("metric", F.when(F.col("qtype") == "unanswerable", "FB").otherwise("EX")).withColumn("value", F.when(F.col("qtype") == "unanswerable", F.col("fb")).otherwise(F.col("ex")))
    return named.groupBy("set", "mode", "subcategory", "metric").agg(F.round(F.avg("value"), 4).alias("value"))


def bottlenecks(scores: DataFrame) -> DataFrame:
    """set, agent and four gaps: Rec over Cls; true label over predicted in EX and FB; AIR over EX of ambiguous questions. ``scores``: set, agent, rec, cls, ex, fb, ex_oracle, fb_oracle, air, ex_amb."""
    gap = lambda a, b: F.round(F.col(a) - F.col(b), 4)
    return scores.select("set", "agent", gap("rec", "cls").alias("rec_minus_cls"), gap("ex_oracle", "ex").alias("ex_gain"), gap("fb_oracle", "fb").alias("fb_gain"), gap("air", "ex_amb").alias("air_minus_ex_amb"))


def annotation_report(annotations: DataFrame) -> DataFrame:
    """dimension, n, ok_pct over all annotators. ``annotations``: dimension, ok; rows where a dimension does not apply have a null ok."""
    return annotations.filter("ok is not null").groupBy("dimension").agg(F.count(F.lit(1)).alias("n"), share(F.col("ok")).alias("ok_pct"))


#: Dimensions of a human check and the questions they apply to.
DIMENSIONS = {"realism": "subcategory <> 'improper'", "style": "true", "category": "true", "disambiguation": "qtype = 'ambiguous'", "sql": "qtype <> 'unanswerable'", "feedback": "qtype = 'unanswerable'"}


def mask_annotations(annotations: DataFrame, questions: DataFrame) -> DataFrame:
    """``annotations`` (obj_id, annotator, dimension, ok) with ok null where the dimension does not apply to the question."""
    applies = F.lit(False)
    for d, rule in DIMENSIONS.items():
        applies = applies | ((F.col("dimension") == d) & F.expr(rule))
    return annotations.join(questions.select("obj_id", "qtype", "subcategory"), "obj_id").withColumn("ok", F.when(applies, F.col("ok"))).select("obj_id", "annotator", "dimension", "ok")


def sample_conversations(df: DataFrame, key: str = "conv_id", n: int = 150, seed: int = 7) -> DataFrame:
    """``n`` conversations, the first by md5 of seed and key."""
    return df.select(key).distinct().orderBy(F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string"))), key).limit(n)


def cohen_kappa(annotations: DataFrame) -> DataFrame:
    """n, agreement, kappa over items with two annotations. ``annotations``: item_id, annotator, label (text)."""
    pair = annotations.groupBy("item_id").agg(F.min_by("label", "annotator").alias("a"), F.max_by("label", "annotator").alias("b"), F.count(F.lit(1)).alias("n")).filter("n = 2")
    cells = pair.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))
    sides = cells.select(F.col("a").alias("label"), F.col("n").alias("na"), F.lit(0).alias("nb"), F.when(F.col("a") == F.col("b"), F.col("n")).otherwise(0).alias("same")).unionByName(cells.select(F.col("b").alias("label"), F.lit(0).alias("na"), F.col("n").alias("nb"), F.lit(0).alias("same")))
    by_label = sides.groupBy("label").agg(F.sum("na").alias("na"), F.sum("nb").alias("nb"), F.sum("same").alias("same"))
    total = by_label.agg(F.sum("na").alias("n"), F.sum("same").alias("same"), F.sum(F.col("na").cast("double") * F.col("nb")).alias("cross"))
    po, pe = F.col("same") / F.col("n"), F.col("cross") / (F.col("n").cast("double") * F.col("n"))
    return total.select("n", F.round(po, 6).alias("agreement"), F.round(F.try_divide(po - pe, 1 - pe), 6).alias("kappa"))


def confusion(df: DataFrame, labels: tuple[str, ...], true: str = "subcategory", predicted: str = "pred_subcategory") -> DataFrame:
    return df.groupBy(true).pivot(predicted, list(labels)).agg(F.count(F.lit(1))).na.fill(0)


def category_distribution(df: DataFrame) -> DataFrame:
    return df.rollup("qtype", "subcategory").agg(F.count(F.lit(1)).alias("n"))
