"""Token ids in files: frequency-ranked, byte-aligned variable-length coding.

Ids are replaced by their rank of frequency over all documents, so the common
ones need one byte. The lengths stand apart from the data: two bits per value in
control bytes, four values to a byte. Decoding reads control bytes through a
table of the 256 possible ones and gathers the data bytes, all by numpy.

A store is a folder with ``shards`` (Parquet as the container, one row per
document in ascending doc_id order within ascending shards: doc_id, its start in
the shard, its number of ids, control bytes and data bytes) and ``ranks`` (the
vocabulary by rank). Parquet is written by Spark's commit protocol, so lost
tasks are repeated safely and the store can be on any file system Spark knows.

Steps: encode once into a compressed scratch table, with the counts of ids of
each slice in a column of their own; sum those counts (at most one row per id
and task is shuffled); recode and send each document to the shard of its range
of doc_ids; sort the shards.

Defined results: a null or empty text is the end id alone; rows with the same
doc_id are all kept, next to each other; null doc_ids come first; an empty table
gives a store without documents.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

from .common import by_bytes, partitions_of, remove, scratch_path, text_or_empty
from .units import byte_level_encoder

#: Bytes of plain ids that a shard holds at most, about.
SHARD_BYTES = 256 << 20
#: By control byte: the lengths of its four values, low bits first.
LENGTHS = ((np.arange(256)[:, None] >> np.array([0, 2, 4, 6]) & 3) + 1).astype(np.uint8)


def code_many(values: np.ndarray, sizes: np.ndarray) -> tuple[bytes, np.ndarray, bytes, np.ndarray]:
    """Control bytes and data bytes of several documents' values, end to end, with the ends of each.

    Each document begins a control byte of its own.
    """
    v = values.astype("<u4", copy=False)
    short = (v > 0xFF).astype(np.uint8) + (v > 0xFFFF) + (v > 0xFFFFFF)
    quads = -(-sizes // 4)
    starts, padded = np.cumsum(sizes) - sizes, 4 * (np.cumsum(quads) - quads)
    places = np.zeros(4 * int(quads.sum()), np.uint8)
    places[np.arange(len(v)) + np.repeat(padded - starts, sizes)] = short
    fours = places.reshape(-1, 4)
    control = (fours[:, 0] | fours[:, 1] << 2 | fours[:, 2] << 4 | fours[:, 3] << 6).astype(np.uint8)
    data = v.view(np.uint8).reshape(-1, 4)[np.arange(4) <= short[:, None]]
    ends = np.concatenate([[0], np.cumsum(short, dtype=np.int64)]) + np.arange(len(v) + 1)
    return control.tobytes(), np.cumsum(quads), data.tobytes(), ends[np.cumsum(sizes)]


def code(values: np.ndarray) -> tuple[bytes, bytes]:
    """Control bytes and data bytes of one document's values."""
    control, _, data, _ = code_many(np.ascontiguousarray(values, "<u4"), np.array([len(values)]))
    return control, data


def decode(control: np.ndarray, data: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The values of documents of ``sizes`` values each from control and data bytes, end to end."""
    quads = -(-sizes // 4)
    starts, padded = np.cumsum(sizes) - sizes, 4 * (np.cumsum(quads) - quads)
    lengths = LENGTHS[control].reshape(-1)[np.arange(int(sizes.sum())) + np.repeat(padded - starts, sizes)]
    at = np.cumsum(lengths, dtype=np.int64) - lengths
    out = data[at].astype("<u4")
    for k in (1, 2, 3):
        longer = np.flatnonzero(lengths > k)
        if not len(longer):
            break
        out[longer] |= data[at[longer] + k].astype("<u4") << (8 * k)
    return out


def binary_array(data: bytes, ends: np.ndarray) -> pa.Array:
    offsets = np.concatenate([[0], ends]).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(ends), [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(data)])


def binary_values(column: pa.Array, dtype: str) -> np.ndarray:
    """All values of a binary column without nulls, end to end."""
    offsets = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(column.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]].view(dtype)


def _plain(docs: DataFrame, tokenizer: str, end_id: int, width: str, id_col: str, text_col: str) -> DataFrame:
    """doc_id, n, ids (each of ``width``), and in the first row of each slice a tally of its ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = byte_level_encoder(tokenizer)
        end = end_id.to_bytes(4, "little")
        for batch in by_bytes(batches, "text"):
            got = encoder.encode(batch.column(1).to_pylist())
            sizes = np.array([len(x) // 4 + 1 for x in got])
            ids = np.frombuffer(end.join([*got, b""]), "<u4").astype(width)
            counts = np.bincount(ids)
            seen = np.flatnonzero(counts)
            tally = [seen.astype("<u4").tobytes() + counts[seen].astype("<i8").tobytes(), *[None] * (len(got) - 1)]
            coded = binary_array(ids.tobytes(), np.cumsum(sizes) * ids.itemsize)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), coded, pa.array(tally, pa.binary())], ["doc_id", "n", "ids", "tally"])

    src = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, n long, ids binary, tally binary")


def frequency_ranks(plain: DataFrame) -> np.ndarray:
    """All ids that occur, the most frequent first, ties by id. At most as many as the vocabulary."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(1 << 16, np.int64)
        for batch in batches:
            for tally in batch.column(0).to_pylist():
                n = len(tally) // 12
                ids = np.frombuffer(tally, "<u4", n)
                if n and ids[-1] >= len(counts):
                    counts = np.concatenate([counts, np.zeros(int(ids[-1]) + 1, np.int64)])
                counts[ids] += np.frombuffer(tally, "<i8", n, 4 * n)
        ids = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(counts[ids], pa.int64())], ["id", "n"])

    counted = plain.select("tally").filter("tally is not null").mapInArrow(run, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))
    rows = counted.collect()  # one row for each id of the vocabulary at most
    return np.array([r["id"] for r in sorted(rows, key=lambda r: (-r["n"], r["id"]))], np.int64)


def write_token_files(docs: DataFrame, tokenizer: str, end_id: int = 0, path: str | None = None, id_col: str = "doc_id", text_col: str = "text", shards: int | None = None) -> str:
    """Write a store of the ids of all documents; returns its path."""
    spark = docs.sparkSession
    path = path or scratch_path(spark, "token-files")
    held = scratch_path(spark, "token-ids")
    width = "<u2" if max(largest_id(tokenizer), end_id) < 1 << 16 else "<u4"
    _plain(docs, tokenizer, end_id, width, id_col, text_col).write.option("compression", "zstd").parquet(held)
    plain = spark.read.parquet(held)
    if shards is None:
        # a task sorts a shard; three quarters of an id's bytes remain once ids are ranked, if that
        total = plain.agg(F.sum("n")).first()[0] or 0
        shards = max(partitions_of(spark), -(-total * int(width[2]) // SHARD_BYTES))
    ranked = frequency_ranks(plain)
    spark.createDataFrame([(i, int(t)) for i, t in enumerate(ranked)], "rank long, id long").coalesce(1).write.parquet(f"{path}/ranks")
    rank_of = np.zeros(int(ranked.max()) + 1 if len(ranked) else 1, "<u4")
    rank_of[ranked] = np.arange(len(ranked))
    shared = spark.sparkContext.broadcast(rank_of)  # as long as the vocabulary
    kind = plain.schema["doc_id"].dataType
    whole = isinstance(kind, IntegralType)
    cuts = plain.agg(F.percentile_approx("doc_id", [i / shards for i in range(1, shards)], max(10_000, 4 * shards))).first()[0] if whole and shards > 1 else None
    bounds = np.array(cuts or [], np.int64)  # one for each shard

    def recode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in by_bytes(batches, "ids"):
            sizes = batch.column(1).to_numpy()
            control, control_ends, data, data_ends = code_many(shared.value[binary_values(batch.column(2), width)], sizes)
            ids = batch.column(0)
            shard = np.where(ids.is_null().to_numpy(zero_copy_only=False), 0, np.searchsorted(bounds, ids.fill_null(0).to_numpy(), side="left")) if whole else np.zeros(len(ids))
            yield pa.RecordBatch.from_arrays(
                [pa.array(shard.astype(np.int32)), ids, batch.column(1), binary_array(control, control_ends), binary_array(data, data_ends)],
                ["shard", "doc_id", "n_tokens", "control", "data"],
            )

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = 0
        for batch in batches:
            ns = batch.column(2).to_numpy()
            yield batch.add_column(2, "shard_start", pa.array(at + np.cumsum(ns) - ns))
            at += int(ns.sum())

    fields = f"shard int, doc_id {kind.simpleString()}, {{}}n_tokens long, control binary, data binary"
    coded = plain.select("doc_id", "n", "ids").mapInArrow(recode, fields.format(""))
    dealt = coded.repartitionById(shards, "shard") if whole else coded.repartitionByRange(shards, "doc_id").withColumn("shard", F.spark_partition_id())
    stored = dealt.sortWithinPartitions("doc_id").mapInArrow(place, fields.format("shard_start long, "))
    stored.write.option("compression", "none").parquet(f"{path}/shards")
    remove(spark, held)
    return path


def largest_id(tokenizer: str) -> int:
    with open(tokenizer, encoding="utf-8") as f:
        spec = json.load(f)
    return max(max(spec["model"]["vocab"].values()), *(t["id"] for t in spec["added_tokens"]), 0)


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, control, data.

    The totals of the shards, a row each, are summed up on the driver.
    """
    shards = spark.read.parquet(f"{path}/shards")
    totals = shards.groupBy("shard").agg(F.sum("n_tokens").alias("n")).orderBy("shard").collect()
    before, at = [], 0
    for r in totals:
        before.append((r["shard"], at))
        at += r["n"]
    base = spark.createDataFrame(before, "shard int, before long")
    return shards.join(F.broadcast(base), "shard").select("doc_id", (F.col("before") + F.col("shard_start")).alias("start"), "n_tokens", "control", "data")


def decode_batch(batch: pa.RecordBatch, ids: np.ndarray) -> tuple[np.ndarray, list[int]]:
    """The ids of all documents of a batch of read_token_files, end to end, and each one's end."""
    sizes = batch.column(2).to_numpy()
    values = decode(binary_values(batch.column(3), "u1"), binary_values(batch.column(4), "u1"), sizes)
    return ids[values], np.cumsum(sizes).tolist()


def vocabulary(spark: SparkSession, path: str) -> np.ndarray:
    rows = spark.read.parquet(f"{path}/ranks").orderBy("rank").collect()  # as long as the vocabulary
    return np.array([r["id"] for r in rows], "<u4")


def decode_token_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, ids array<int> from the files."""
    shared = spark.sparkContext.broadcast(vocabulary(spark, path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in by_bytes(batches, "data"):
            ids, ends = decode_batch(batch, shared.value)
            lists = pa.ListArray.from_arrays(pa.array([0, *ends], pa.int32()), pa.array(ids.astype(np.int32)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), lists], ["doc_id", "start", "ids"])

    src = read_token_files(spark, path)
    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, start long, ids array<int>")


def read_digests(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32, all from the files."""
    shared = spark.sparkContext.broadcast(vocabulary(spark, path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in by_bytes(batches, "data"):
            ids, ends = decode_batch(batch, shared.value)
            crc = [zlib.crc32(ids[a:b]) for a, b in zip([0, *ends], ends, strict=False)]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(3)), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    src = read_token_files(spark, path)
    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, start long, n_tokens long, ids_crc32 long")
