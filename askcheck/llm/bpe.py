"""Byte-level BPE by prefix dynamic programming, and its decoding.

For every prefix of a byte string the last token of its encoding is unique. A
table of those last tokens therefore holds the encodings of all prefixes at
once: the token that ends at a position is the one token of the vocabulary
which ends there and can stand behind the last token of the prefix before it.
Appending bytes extends the table, an edit keeps the table up to the edit.

Two tokens can stand side by side if no merge crosses their seam while both are
built up; ``PrefixBpe.adjacent`` replays the merges on both sides of the seam.

Defined results: a null text counts as empty; an empty text has no ids, the
SHA-256 of nothing, and decodes to nothing; repeated rows are encoded each.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, text_or_empty
from .units import TextEncoder, UnitCache, ids_array

NEVER = 1 << 60


class PrefixBpe:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.bytes_of = {i: b for b, i in ranks.items()}
        self.pattern = regex.compile(pattern)
        self.pieces = self.pattern.findall
        #: Every suffix of a token: its own id, or -1 if it is none itself.
        self.suffixes = {b[k:]: -1 for b in ranks for k in range(1, len(b))} | ranks
        self._halves: dict[int, tuple[int, int] | None] = {}
        self._adjacent: dict[tuple[int, int], bool] = {}

    def halves(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge gives ``token``; None for a single byte, or if no merges lead to it."""
        if token not in self._halves:
            parts = [bytes([b]) for b in self.bytes_of[token]]
            while len(parts) > 2:
                rank, at = min((self.ranks.get(parts[i] + parts[i + 1], NEVER), i) for i in range(len(parts) - 1))
                if rank >= token:
                    break
                parts[at : at + 2] = [parts[at] + parts[at + 1]]
            self._halves[token] = (self.ranks[parts[0]], self.ranks[parts[1]]) if len(parts) == 2 else None
        return self._halves[token]

    def reachable(self, token: int) -> bool:
        return len(self.bytes_of[token]) == 1 or self.halves(token) is not None

    def _edge(self, token: int, side: int) -> list[int]:
        """The tokens that stand at one edge of ``token`` while it is built up, smallest first."""
        chain = [token]
        while (two := self.halves(chain[-1])) is not None:
            chain.append(two[side])
        return chain[::-1]

    def adjacent(self, left: int, right: int) -> bool:
        key = (left, right)
        known = self._adjacent.get(key)
        if known is None:
            if len(self._adjacent) > 400_000:
                self._adjacent.clear()
            known = self._adjacent[key] = self._replay(left, right)
        return known

    def _replay(self, left: int, right: int) -> bool:
        a, b = self._edge(left, 1), self._edge(right, 0)
        i = j = 0
        while True:
            grow_a = a[i + 1] if i + 1 < len(a) else NEVER
            grow_b = b[j + 1] if j + 1 < len(b) else NEVER
            across = self.ranks.get(self.bytes_of[a[i]] + self.bytes_of[b[j]], NEVER)
            if across < grow_a and across <= grow_b and across < NEVER:
                return False  # of equal merges the one further left comes first
            if grow_a == grow_b == NEVER:
                return True
            if grow_a <= grow_b:
                i += 1
            else:
                j += 1

    def extend(self, data: bytes, last: list[int]) -> None:
        """Append to ``last`` until it holds the last token of every prefix of ``data``."""
        get, adjacent, known = self.suffixes.get, self.adjacent, self._adjacent.get
        for end in range(len(last) + 1, len(data) + 1):
            begin = end - 1
            while True:
                token = get(data[begin:end])
                if token is None:
                    raise ValueError(f"no token ends at byte {end}; the vocabulary lacks single bytes")
                if token >= 0:
                    if begin:
                        fits = known((last[begin - 1], token))
                        if fits if fits is not None else adjacent(last[begin - 1], token):
                            break
                    elif self.reachable(token):
                        break
                begin -= 1
            last.append(token)

    def walk_back(self, data: bytes, last: list[int]) -> list[int]:
        out, at = [], len(data)
        while at:
            out.append(last[at - 1])
            at -= len(self.bytes_of[out[-1]])
        return out[::-1]

    def encode_piece(self, data: bytes) -> list[int]:
        whole = self.ranks.get(data)
        if whole is not None:
            return [whole]
        last: list[int] = []
        self.extend(data, last)
        return self.walk_back(data, last)

    def encode_sorted(self, pieces: list[str]) -> list[list[int]]:
        """The ids of each piece. They are taken in ascending order: each keeps the table of the prefix it shares with the one before."""
        out: dict[str, list[int]] = {}
        before, last = b"", []
        for data, piece in sorted((p.encode(), p) for p in pieces):
            whole = self.ranks.get(data)
            if whole is not None:
                out[piece] = [whole]
                continue
            del last[_common(data, before) :]
            self.extend(data, last)
            out[piece] = self.walk_back(data, last)
            before = data
        return [out[p] for p in pieces]

    def encode(self, text: str) -> list[int]:
        out: list[int] = []
        for piece in self.pieces(text):
            out += self.encode_piece(piece.encode())
        return out


class EditableEncoding:
    """The ids of a text that grows or is edited.

    Each piece of the pattern keeps its prefix table. An append or an edit
    splits again only from the piece before the change (white space looks one
    character ahead) up to where the old pieces line up again; a piece that only
    grew continues its table.
    """

    def __init__(self, model: PrefixBpe, text: str = ""):
        self.model, self.text = model, ""
        self.pieces: list[tuple[str, bytes, list[int]]] = []
        self.edit(0, 0, text)

    def ids(self) -> list[int]:
        out: list[int] = []
        for _, data, last in self.pieces:
            whole = self.model.ranks.get(data)
            out += [whole] if whole is not None else self.model.walk_back(data, last)
        return out

    def append(self, text: str) -> None:
        self.edit(len(self.text), 0, text)

    def edit(self, at: int, removed: int, inserted: str) -> int:
        """Replace ``removed`` characters at ``at``; returns how many pieces were split anew."""
        new_text = self.text[:at] + inserted + self.text[at + removed :]
        first, begin = 0, 0
        while first < len(self.pieces) and begin + len(self.pieces[first][0]) < at:
            begin += len(self.pieces[first][0])
            first += 1
        for _ in range(2):
            if first:
                first -= 1
                begin -= len(self.pieces[first][0])
        shift = len(inserted) - removed
        old_at, resume = {}, begin
        for k in range(first, len(self.pieces)):
            if resume >= at + removed:
                old_at[resume + shift] = k
            resume += len(self.pieces[k][0])
        fresh, rest = [], len(self.pieces)
        for m in self.model.pattern.finditer(new_text, begin):
            if m.start() in old_at and m.start() >= at + len(inserted) and fresh:
                rest = old_at[m.start()]
                break
            fresh.append(m.group())
        reused = self.pieces[first:rest]
        built = []
        for i, piece in enumerate(fresh):
            data = piece.encode()
            table: list[int] = []
            if i < len(reused):
                same = _common(data, reused[i][1])
                table = reused[i][2][:same]
            self.model.extend(data, table)
            built.append((piece, data, table))
        self.pieces[first:rest] = built
        self.text = new_text
        return len(built)


def _common(a: bytes, b: bytes) -> int:
    n = 0
    for x, y in zip(a, b, strict=False):
        if x != y:
            break
        n += 1
    return n


class TokenBytes:
    """Decoding by numpy lookup in one table of all tokens' bytes."""

    def __init__(self, ranks: dict[bytes, int]):
        size = max(ranks.values()) + 1
        self.length = np.zeros(size, np.int64)
        for b, i in ranks.items():
            self.length[i] = len(b)
        self.start = np.cumsum(self.length) - self.length
        blob = bytearray(int(self.length.sum()))
        for b, i in ranks.items():
            blob[self.start[i] : self.start[i] + len(b)] = b
        self.blob = np.frombuffer(bytes(blob), np.uint8)

    def decode(self, ids: np.ndarray) -> bytes:
        if not len(ids):
            return b""
        n = self.length[ids]
        ends = np.cumsum(n)
        where = np.repeat(self.start[ids] - (ends - n), n) + np.arange(ends[-1])
        return self.blob[where].tobytes()


@lru_cache(maxsize=2)
def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


@lru_cache(maxsize=2)
def worker_model(path: str, pattern: str) -> tuple[PrefixBpe, TextEncoder, TokenBytes, list[str]]:
    """One model for a Python worker, kept over tasks."""
    ranks = load_ranks(path)
    model = PrefixBpe(ranks, pattern)
    known = UnitCache(model.encode_sorted, 400_000)

    def encode_many(units: list[str]) -> list[list[int]]:
        split = [model.pieces(u) for u in units]
        got = known.resolve([p for pieces in split for p in pieces])
        return [list(chain.from_iterable(map(got.__getitem__, pieces))) for pieces in split]

    return model, TextEncoder(encode_many, 400_000), TokenBytes(ranks), [str(i) for i in range(max(ranks.values()) + 1)]


def encode_documents(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids array<int>: the encoding of every whole text, without special tokens."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, encoder, _, _ = worker_model(path, pattern)
        for batch in by_bytes(batches, "text"):
            got = encoder.encode(batch.column(1).to_pylist())
            ids = pa.ListArray.from_arrays(
                pa.array(np.concatenate([[0], np.cumsum([len(x) // 4 for x in got])]).astype(np.int32)),
                pa.array(np.frombuffer(b"".join(got), "<i4")),
            )
            yield pa.RecordBatch.from_arrays([batch.column(0), ids], ["doc_id", "ids"])

    src = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, ids array<int>")


def decode_documents(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, decoded binary: the bytes of the ids of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = worker_model(path, pattern)[2]
        for batch in batches:
            for i in range(0, len(batch), 256):
                part = batch.slice(i, 256)
                texts = [table.decode(x.values.to_numpy(zero_copy_only=False)) if x.is_valid else b"" for x in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(texts, pa.binary())], ["doc_id", "decoded"])

    src = encoded.select("doc_id", "ids")
    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, decoded binary")


def round_trip_digests(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode and decode in one pass: doc_id, n_tokens, ids_sha256, decoded_sha256.

    No shuffle: one pass over the scan's partitions, and only digests leave Python.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, encoder, table, decimal = worker_model(path, pattern)
        for batch in by_bytes(batches, "text"):
            counts, ids_hash, text_hash = [], [], []
            for got in encoder.encode(batch.column(1).to_pylist()):
                ids = ids_array(got)
                counts.append(len(ids))
                ids_hash.append(hashlib.sha256(" ".join(map(decimal.__getitem__, ids.tolist())).encode()).hexdigest())
                text_hash.append(hashlib.sha256(table.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(counts, pa.int64()), pa.array(ids_hash, pa.string()), pa.array(text_hash, pa.string())],
                ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    src = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string")
