"""A training corpus in five stages over the documents table.

Quality classifier (rejected documents go), line dedup, SimHash near-dedup (one
document of each group stays), personal data (spans replaced), packing. Each
stage works on all that its predecessor kept; every stage but the last returns
the columns of documents, the last one a row per packed piece.
"""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from askcheck.llm import line_dedup, packing, pii, rule_ensemble, simhash
from askcheck.llm.common import remove, scratch_path, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _as_documents(df: DataFrame) -> DataFrame:
    return df.select("doc_id", "text", "lang", "source", F.length("text").cast("bigint").alias("n_chars"))


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Score below 0.5 rejects a document; the model is fitted on the labelled rows outside the held-out third."""
    model = rule_ensemble.train(docs, table(spark, sf_dir, "labels"))
    return rule_ensemble.keep_good(docs.select(*COLUMNS), model)


def line_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _as_documents(line_dedup.drop_boilerplate(docs))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Shingles of five words; the smallest doc_id of each group stays."""
    return simhash.keep_one(docs, shingle=5, radius=4).select(*COLUMNS)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _as_documents(pii.redact_documents(docs.select(*COLUMNS)))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of 2,048 ids. A smaller cache than the operator's own, as workers still hold what earlier stages needed."""
    pieces = packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), 2048, end_id=1, block_bytes=4 << 20, cached_units=100_000)
    return pieces.select("sequence_id", "offset", "doc_id", "start", "length", "doc_tokens", "ids")


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_classifier", quality_classifier),
    ("line_dedup", line_dedup_stage),
    ("near_dedup", near_dedup),
    ("personal_data", personal_data),
    ("pack", pack),
]

#: The classifier and the fingerprints can't be stated in SQL; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), []
    for name, stage in STAGES:
        path = scratch_path(spark, f"pipeline-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs, before = spark.read.parquet(path), [*before, path]
        if len(before) > 1:
            remove(spark, before.pop(0))  # the next stage's table holds all that is still needed
    return docs
