"""Sources and sinks of transcripts and benchmarks: JSON lines, CSV, ORC, text, Parquet by database, and a Python data source."""

from __future__ import annotations

import glob
import json
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

TURN_SCHEMA = "conv_id string, turn int, role string, kind string, text string, relevancy string, forced boolean"


def write_questions(df: DataFrame, path: str) -> None:
    """Parquet by database, so that a run over one database prunes the others."""
    df.write.partitionBy("db_id").mode("overwrite").parquet(path)


def export_benchmark(df: DataFrame, path: str) -> None:
    """JSON lines, one object per line, evidence as a list."""
    df.write.mode("overwrite").json(path)


def read_benchmark(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """Rows that don't parse keep their text in ``_corrupt``."""
    return spark.read.schema(f"{schema}, _corrupt string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt").json(path)


def write_report(df: DataFrame, path: str) -> None:
    df.coalesce(1).write.mode("overwrite").option("header", True).csv(path)  # reports have some hundred rows


def read_any(spark: SparkSession, path: str, form: str, schema: str | None = None, **options: object) -> DataFrame:
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema else reader).format(form).load(path)


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _TranscriptReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        return [_File(p) for p in sorted(glob.glob(f"{self.path}/*.json*"))] or [_File("")]

    def read(self, partition: _File) -> Iterator[tuple]:
        if not partition.path:
            return
        with open(partition.path, encoding="utf-8") as f:
            for line in f:
                if line.strip():
                    r = json.loads(line)
                    for i, t in enumerate(r["turns"]):
                        yield (r["conv_id"], i, t.get("role"), t.get("kind"), t.get("text"), t.get("relevancy"), bool(t.get("forced", False)))


class TranscriptSource(DataSource):
    """``spark.read.format("transcripts").load(folder)``: files of JSON lines {"conv_id", "turns": [...]} as one row per turn.

    For folders that every executor can open; elsewhere use read_transcripts.
    """

    @classmethod
    def name(cls) -> str:
        return "transcripts"

    def schema(self) -> str:
        return TURN_SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _TranscriptReader(self.options["path"])


def read_transcripts(spark: SparkSession, path: str) -> DataFrame:
    """The same through Spark's own JSON reader, on any file system."""
    turn = "struct<role: string, kind: string, text: string, relevancy: string, forced: boolean>"
    rows = spark.read.schema(f"conv_id string, turns array<{turn}>").json(path)
    flat = rows.select("conv_id", F.posexplode("turns").alias("turn", "t"))
    return flat.select("conv_id", "turn", "t.role", "t.kind", "t.text", "t.relevancy", F.coalesce("t.forced", F.lit(False)).alias("forced"))
