"""Packing of documents into windows of a fixed number of tokens.

A document's ids, with an end id, are cut into full windows and one rest. The
rests of a block are placed by best-fit decreasing: longest first, each into
the open window with the least room that still holds it. A segment tree over
the possible amounts of room finds that window in log(capacity) steps.

Windows stay open from block to block, so short rests fill old gaps. When many
are open, or at the end of a partition, the emptiest are dissolved and their
pieces, cut where need be, fill gaps of at least ``min_fragment`` ids in the
others; smaller gaps stay padding. Each partition packs its own documents, so
nothing is shuffled and memory is bounded by the block, not by the partition.

Defined results: a null or empty text is the end id alone; ids are cut, never
dropped; repeated rows are packed each; a window id holds the partition's number
in its upper bits, so ids are unique and a repeated task gives the same.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, lean_worker, text_or_empty
from .units import byte_level_encoder, ids_array


class RoomTree:
    """Counts of open windows by room; finds the least room of at least some size."""

    def __init__(self, capacity: int):
        self.size = 1 << capacity.bit_length()
        self.count = [0] * (2 * self.size)

    def add(self, room: int, by: int) -> None:
        at = room + self.size
        while at:
            self.count[at] += by
            at >>= 1

    def tightest(self, need: int) -> int | None:
        """The least room >= need that some window has."""
        at = need + self.size
        if self.count[at]:
            return need
        while at > 1:
            if not at & 1 and self.count[at + 1]:
                at += 1
                while at < self.size:
                    at = 2 * at if self.count[2 * at] else 2 * at + 1
                return at - self.size
            at >>= 1
        return None


class Packer:
    """Pieces in, closed windows out. A piece is (key, start, ids)."""

    def __init__(self, capacity: int = 2048, min_fragment: int = 32, most_open: int = 2048):
        self.capacity, self.min_fragment, self.most_open = capacity, min_fragment, most_open
        self.tree = RoomTree(capacity)
        self.by_room: dict[int, list[list]] = defaultdict(list)
        self.n_open = 0

    def _open(self, window: list, room: int) -> None:
        self.by_room[room].append(window)
        self.tree.add(room, 1)
        self.n_open += 1

    def _take(self, room: int) -> list:
        self.tree.add(room, -1)
        self.n_open -= 1
        return self.by_room[room].pop()

    def place(self, pieces: list[tuple]) -> Iterator[list[tuple]]:
        """Best-fit decreasing; yields the windows that are full, or nearly so."""
        for piece in sorted(pieces, key=lambda p: (-len(p[2]), p[0], p[1])):
            n = len(piece[2])
            room = self.tree.tightest(n) if self.n_open else None
            window = [] if room is None else self._take(room)
            window.append(piece)
            left = (self.capacity if room is None else room) - n
            if left == 0:
                yield window
            else:
                self._open(window, left)
        if self.n_open > self.most_open:
            yield from self.settle(self.most_open // 2)

    def settle(self, keep: int = 0) -> Iterator[list[tuple]]:
        """Close all but the ``keep`` emptiest windows, filling their gaps from the emptiest."""
        windows = [(room, w) for room in sorted(self.by_room) for w in self.by_room[room]]
        self.by_room.clear()
        self.tree = RoomTree(self.capacity)
        self.n_open = 0
        loose: list[tuple] = []
        low, high = 0, len(windows) - 1
        while low <= high - keep:
            room, window = windows[low]
            low += 1
            while room >= self.min_fragment and (loose or low <= high):
                if not loose:
                    loose = sorted(windows[high][1], key=lambda p: len(p[2]))
                    high -= 1
                key, start, ids = loose.pop()
                if len(ids) > room:
                    loose.append((key, start + room, ids[room:]))
                    ids = ids[:room]
                window.append((key, start, ids))
                room -= len(ids)
            yield window
        for room, window in windows[low : high + 1]:
            self._open(window, room)
        if loose:
            if keep:
                self._open(loose, self.capacity - sum(len(p[2]) for p in loose))
            else:
                yield loose


def pack_documents(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = 8 << 20, cached_units: int = 600_000) -> DataFrame:
    """One row per piece: doc_id, start, length, ids array<int>, doc_tokens, sequence_id, offset."""

    def rows(windows: Iterator[list[tuple]], serial: Iterator[int], id_type: pa.DataType) -> Iterator[pa.RecordBatch]:
        cols: list[list] = [[] for _ in range(6)]
        ids: list[np.ndarray] = []
        held = 0

        def flush() -> pa.RecordBatch:
            ends = np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(ids).astype(np.int32)))
            arrays = [pa.array(cols[0], id_type), *(pa.array(c, pa.int64()) for c in cols[1:3]), lists, *(pa.array(c, pa.int64()) for c in cols[3:])]
            return pa.RecordBatch.from_arrays(arrays, ["doc_id", "start", "length", "ids", "doc_tokens", "sequence_id", "offset"])

        for window in windows:
            number, at = next(serial), 0
            for (_, doc, total), start, part in window:
                for c, v in zip(cols, (doc, start, len(part), total, number, at), strict=True):
                    c.append(v)
                ids.append(part)
                at += len(part)
            held += at
            if held > 1 << 20:
                yield flush()
                cols, ids, held = [[] for _ in range(6)], [], 0
        if ids:
            yield flush()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_worker(byte_level_encoder)
        encoder = byte_level_encoder(tokenizer, cached_units)
        packer = Packer(capacity)
        first = TaskContext.get().partitionId() << 40
        serial = iter(range(first, first + (1 << 40)))
        end = np.array([end_id], "<u4")
        seen, id_type = 0, None
        for batch in by_bytes(batches, "text", block_bytes):
            id_type = batch.schema.field(0).type
            full, rests = [], []
            doc_ids = batch.column(0).to_pylist()
            for part in by_bytes([batch], "text"):
                for got in encoder.encode(part.column(1).to_pylist()):
                    ids = np.concatenate([ids_array(got), end])
                    doc = (seen, doc_ids[len(rests)], len(ids))
                    seen += 1
                    cut = len(ids) - len(ids) % capacity
                    full += [[(doc, s, ids[s : s + capacity])] for s in range(0, cut, capacity)]
                    rests.append((doc, cut, ids[cut:]))
            yield from rows(iter(full), serial, id_type)
            yield from rows(packer.place([r for r in rests if len(r[2])]), serial, id_type)
        if id_type is not None:
            yield from rows(packer.settle(), serial, id_type)
        lean_worker(byte_level_encoder)

    src = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    kind = src.schema["doc_id"].dataType.simpleString()
    return src.mapInArrow(run, f"doc_id {kind}, start long, length long, ids array<int>, doc_tokens long, sequence_id long, offset long")


def with_crc(pieces: DataFrame) -> DataFrame:
    """``ids`` replaced by ids_crc32: the CRC of little-endian unsigned 32-bit ids."""
    import zlib

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.get_field_index("ids")
            lists = batch.column(at)
            values, ends = lists.values.to_numpy(), lists.offsets.to_numpy()
            crc = pa.array([zlib.crc32(values[a:b].tobytes()) for a, b in zip(ends[:-1], ends[1:], strict=True)], pa.int64())
            yield batch.set_column(at, "ids_crc32", crc)

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" if f.name != "ids" else "ids_crc32 long" for f in pieces.schema)
    return pieces.mapInArrow(run, schema)
