"""Streaming forms of the dialogue measures and the windowed operators.

A query is run to the end of what is there (``availableNow``) and its result
read back, so that it can be compared with the batch form on the same rows.
Event times are cast to TIMESTAMP, since watermarks refuse the zone-less type.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def shared_dir(spark: SparkSession) -> str:
    """Where sources, checkpoints and sinks of a finite run live: the session's shared folder, else a local one."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if found is None:
        import tempfile

        found = tempfile.mkdtemp(prefix="askcheck-")
    return found.rstrip("/")


def run_to_end(stream: DataFrame, mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    """Write a stream with ``availableNow`` and read the result. Append goes to Parquet files; complete is the table of the last batch; update is the last state of each of ``keys``."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).outputMode(mode)
    if mode == "append":
        writer.format("parquet").option("path", f"{base}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("_batch", F.lit(number)).write.mode("overwrite").parquet(f"{base}/out/_b={number}")

    writer.foreachBatch(keep).start().awaitTermination()
    got = spark.read.parquet(f"{base}/out").drop("_b")
    if mode == "complete":
        return got.filter(F.col("_batch") == got.agg(F.max("_batch")).first()[0]).drop("_batch")
    if not keys:
        raise ValueError("a stream of updates needs the keys of its rows")
    rest = [c for c in stream.columns if c not in keys]
    return got.groupBy(*keys).agg(F.max_by(F.struct(*rest), "_batch").alias("_last")).select(*keys, *(F.col("_last")[c].alias(c) for c in rest))


def file_stream(spark: SparkSession, path: str, files_per_batch: int | None = None) -> DataFrame:
    """A Parquet folder, or the folder of one file, as a stream."""
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    folder, _, name = path.rpartition("/")
    one_file = not spark.read.parquet(path).inputFiles()[0].rsplit("/", 1)[0].endswith(name)
    return reader.option("pathGlobFilter", name).parquet(folder) if one_file else reader.parquet(path)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return file_stream(spark, f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(stream: DataFrame, width: str, late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(stream: DataFrame, width: str, step: str, late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str, late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def without_repeats(stream: DataFrame, key: str, late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def stream_votes(ballots: DataFrame, yes: str, item: str = "item_id") -> DataFrame:
    """Running council majorities; state is two counts for each item, and in update mode only items with new ballots are written."""
    return ballots.groupBy(item).agg(F.count_if(F.col("vote") == yes).alias("n_yes"), F.count(F.lit(1)).alias("n_members")).withColumn("kept", 2 * F.col("n_yes") > F.col("n_members"))


def stream_clar_rate(turns: DataFrame, width: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Per conversation (and window of ``ts``) whether it holds a clarification; the share is an aggregate of that result."""
    asks = F.bool_or(F.col("kind") == "clarification").alias("asks")
    if width is None:
        return turns.groupBy("conv_id").agg(asks)
    return turns.withWatermark("ts", late).groupBy(F.window("ts", width), "conv_id").agg(asks).select(F.col("window.start").alias("start"), "conv_id", "asks")


AIR_STATE = "turn long, pending boolean, done boolean"


def stream_air(turns: DataFrame, patience_ms: int = 3_600_000, timeout=GroupStateTimeout.NoTimeout) -> DataFrame:
    """conv_id, terminal: for each conversation the kind of turn after its first relevant reply.

    State is three values for each conversation; with a timeout it is dropped
    when the user's patience ends. ``turns``: conv_id, turn, kind, relevancy;
    turns of a conversation come in order across batches.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        last, pending, done = state.get if state.exists else (-1, False, False)
        rows = pd.concat(list(frames)).sort_values("turn")
        found = []
        for r in rows.itertuples():
            if pending and not done:
                found.append(r.kind in ("sql", "feedback"))
                done = True
            if not done and r.relevancy == "relevant":
                pending = True
            last = max(last, int(r.turn))
        state.update((last, pending, done))
        if timeout == GroupStateTimeout.ProcessingTimeTimeout:
            state.setTimeoutDuration(patience_ms)
        if found:
            yield pd.DataFrame({"conv_id": [key[0]], "terminal": [bool(found[0])]})

    kind = turns.schema["conv_id"].dataType.simpleString()
    return turns.groupBy("conv_id").applyInPandasWithState(step, f"conv_id {kind}, terminal boolean", AIR_STATE, "append", timeout)


def late_rows(base: str, late: str, sink: Callable[[DataFrame, int], None]) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: rows that are behind the greatest time of all batches before theirs by more than ``late``.

    Each batch leaves its greatest time under ``base``, by its number, so a
    repeated batch, or a query that starts again, judges alike.
    """

    def route(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch.agg(F.max("ts").alias("top")).withColumn("number", F.lit(number)).write.mode("overwrite").parquet(f"{base}/tops/_n={number}")
        before = spark.read.parquet(f"{base}/tops").filter(F.col("number") < number).agg(F.max("top").alias("_top"))
        behind = batch.crossJoin(F.broadcast(before)).filter(F.col("ts") < F.col("_top") - F.expr(f"INTERVAL {late}")).drop("_top")
        sink(behind, number)

    return route
