"""Links between texts whose sets of word shingles are similar, without a loss.

Shingles have one order for all texts: those frequent in a sample of the corpus
come last, the others by their hash. Two sets with a similarity of ``threshold``
share a shingle among the first ``n - ceil(threshold * n) + 1`` of each; those are
a text's keys, and texts meet at a key they share. The sample only decides the
order and which keys travel apart, so which texts it holds changes no result.

Most keys stand in one text only. So keys travel packed, 48 bits of each with its
node, by ranges to tasks that sort them; what comes out are the runs of nodes that
share a key. Runs of the same nodes under several keys are one. Keys that are hot in
the sample don't meet in one task: they go on as plain rows and are split there.

Inside a bucket a pair is dropped if its sizes, or the parities of its shingles,
show that it can't reach the threshold: shingles are dealt over as many bits as
there are, a bit is the parity of its shingles, and so two sets differ in at least
as many shingles as bits. What remains makes components of candidates, a superset
of the links. A text comes to the cells of its component once, with the whole set
of its hashes, and these decide. Pairs already connected are not compared.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, checkpointed, lean_worker, partitions_of, text_or_empty
from .simhash import TILE, in_cells, majority_bits, shingle_hashes, star_components

#: Documents that decide which shingles are frequent, and how many of those are kept.
SAMPLE, FREQUENT = 4_000, 20_000
#: A shingle in this share of the sample, or more, is hot.
HOT = 0.005
#: Packed bytes that are sorted together, about; buckets of that size are dealt to at most so many tasks, which take one after another.
BUCKET_BYTES, MOST_TASKS = 8 << 20, 20_000
#: Keys that are packed together.
PACK = 1 << 18
#: Nodes of a run that stand in one row.
CHUNK = 512


@dataclass(frozen=True)
class Order:
    """``frequent``: ascending hashes of shingles that come last; ``rank`` among them; ``hot`` ones."""

    frequent: np.ndarray
    rank: np.ndarray
    hot: np.ndarray

    @classmethod
    def of(cls, hashes: np.ndarray, counts: np.ndarray | None = None, least: float = math.inf) -> Order:
        """``hashes`` from the least to the most frequent."""
        order = np.argsort(hashes)
        hot = np.zeros(len(hashes), bool) if counts is None else counts >= least
        return cls(hashes[order], order, hot[order])

    def keys(self, own: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray]:
        """The first shingles of an ascending set, and those of them that are hot: sets at ``threshold`` share one of either kind."""
        length = len(own) - math.ceil(threshold * len(own) - 1e-9) + 1 if len(own) else 0
        none = own[:0]
        if not len(self.frequent):
            return own[:length], none
        at = np.minimum(np.searchsorted(self.frequent, own), len(self.frequent) - 1)
        often = self.frequent[at] == own
        seldom = own[~often][:length]
        at = at[often]
        last = at[np.argsort(self.rank[at])][: length - len(seldom)]
        return np.concatenate([seldom, self.frequent[last[~self.hot[last]]]]), self.frequent[last[self.hot[last]]]


def sampled_order(docs: DataFrame, shingle: int, text_col: str = "text", sample: int = SAMPLE, most: int = FREQUENT) -> Order:
    """The order that a sample of texts, chosen by their hash, gives."""
    every = max(1, docs.count() // sample)
    some = docs.select(text_or_empty(text_col).alias("text")).filter(F.pmod(F.xxhash64("text"), F.lit(every)) == 0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in by_bytes(batches, "text"):
            own = [np.unique(shingle_hashes(t, shingle)).view(np.int64) for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.zeros(0, np.int64), *own]))], ["h"])

    counted = some.mapInArrow(run, "h long").groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter("n > 2")
    rows = counted.orderBy(F.desc("n"), "h").limit(most).collect()[::-1]
    return Order.of(np.array([r.h for r in rows], np.int64).view(np.uint64), np.array([r.n for r in rows]), max(8, HOT * sample))


def parities(own: np.ndarray) -> np.ndarray:
    """A bit for each shingle, rounded up to a power of two from 64 on: whether an odd number of them fell there."""
    bits = max(64, 1 << max(0, len(own) - 1).bit_length())
    odd = np.bincount((own >> np.uint64(20)).astype(np.int64) & (bits - 1), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.uint64)


def folded(words: np.ndarray, to: int) -> np.ndarray:
    """Parities over ``to`` words instead of more."""
    while len(words) > to:
        words = words[: len(words) // 2] ^ words[len(words) // 2 :]
    return words


def sketches(docs: DataFrame, shingle: int, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_key (MD5 of the text), fp, size (distinct shingles), digest (of their set), keys (48 bits of each), hot array<long>, bits."""
    order = sampled_order(docs, shingle, text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_worker()
        for batch in by_bytes(batches, "text"):
            fps, sizes, digests, keys, hot, bits = [], [], [], [], [], []
            for text in batch.column(2).to_pylist():
                hashes = shingle_hashes(text, shingle)
                fps.append(majority_bits(hashes))
                own = np.unique(hashes)
                sizes.append(len(own))
                digests.append(hashlib.blake2b(own.tobytes(), digest_size=16).digest())
                some, often = order.keys(own, threshold)
                keys.append(packed_keys(some))
                hot.append(often.view(np.int64))
                bits.append(parities(own).tobytes())
            offsets = np.concatenate([[0], np.cumsum([len(k) for k in hot])]).astype(np.int32)
            flat = np.concatenate([np.zeros(0, np.int64), *hot])
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0),
                    batch.column(1),
                    pa.array(np.array(fps, np.uint64).view(np.int64)),
                    pa.array(sizes, pa.int32()),
                    pa.array(digests, pa.binary()),
                    pa.array(keys, pa.binary()),
                    pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat)),
                    pa.array(bits, pa.binary()),
                ],
                ["doc_id", "text_key", "fp", "size", "digest", "keys", "hot", "bits"],
            )

    src = docs.select(F.col(id_col).alias("doc_id"), text_key(text_col).alias("text_key"), text_or_empty(text_col).alias("text"))
    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, text_key binary, fp long, size int, digest binary, keys binary, hot array<bigint>, bits binary")


def packed_keys(keys: np.ndarray) -> bytes:
    """The upper 48 bits of each."""
    return keys.astype("<u8", copy=False).view(np.uint8).reshape(-1, 8)[:, 2:].tobytes()


def unpacked_keys(packed: bytes | memoryview) -> np.ndarray:
    six = np.frombuffer(packed, np.uint8).reshape(-1, 6)
    out = np.zeros((len(six), 8), np.uint8)
    out[:, :6] = six
    return out.view("<u8")[:, 0]


def planes(nodes: np.ndarray) -> bytes:
    """Longs byte by byte, so that equal upper bytes stand together and compress."""
    return np.ascontiguousarray(nodes.astype("<i8", copy=False).view(np.uint8).reshape(-1, 8).T).tobytes()


def from_planes(held: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(held, np.uint8).reshape(8, -1).T).view("<i8")[:, 0]


def runs_of(keys: np.ndarray, nodes: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(key, ascending distinct nodes) of keys that several nodes have."""
    order = np.lexsort((nodes, keys))
    keys, nodes = keys[order], nodes[order]
    fresh = np.ones(len(keys), bool)
    fresh[1:] = (keys[1:] != keys[:-1]) | (nodes[1:] != nodes[:-1])
    keys, nodes = keys[fresh], nodes[fresh]
    starts = np.flatnonzero(np.concatenate([np.ones(min(1, len(keys)), bool), keys[1:] != keys[:-1]]))
    ends = np.append(starts[1:], len(keys))
    for a, b in zip(starts[ends - starts > 1].tolist(), ends[ends - starts > 1].tolist(), strict=True):
        yield int(keys[a]), nodes[a:b]


def meetings(nodes: DataFrame) -> DataFrame:
    """key, node: which nodes (node, keys, hot) share a key; of keys with the same nodes, one.

    A key of hot shingles may have any number of nodes, a third of all: its rows
    are never gathered. One of the others has no more than a small share of the
    sample and so, but for chance, of all nodes.
    """
    spark = nodes.sparkSession
    total = nodes.agg(F.sum(F.length("keys"))).first()[0] or 0
    buckets = max(partitions_of(spark), -(-total * 14 // 6 // BUCKET_BYTES))
    tasks = min(buckets, max(partitions_of(spark), MOST_TASKS))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_worker()
        held_keys, held_nodes, held = [], [], 0

        def done() -> pa.RecordBatch:
            keys, nodes = np.concatenate(held_keys), np.concatenate(held_nodes)
            bucket = (keys % np.uint64(buckets)).astype(np.int32)
            order = np.lexsort((keys, bucket))
            keys, nodes, bucket = keys[order], nodes[order], bucket[order]
            cuts = np.append(np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]])), len(bucket)).tolist()
            spans, starts = list(zip(cuts, cuts[1:], strict=False)), bucket[cuts[:-1]]
            return pa.RecordBatch.from_arrays(
                [
                    pa.array(starts % tasks),
                    pa.array(starts),
                    pa.array([keys[a:b].view(np.uint8).reshape(-1, 8)[:, :6].tobytes() for a, b in spans], pa.binary()),
                    pa.array([planes(nodes[a:b]) for a, b in spans], pa.binary()),
                ],
                ["task", "bucket", "keys", "nodes"],
            )

        for batch in batches:
            for node, packed in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if packed:
                    keys = unpacked_keys(packed)
                    held_keys.append(keys)
                    held_nodes.append(np.full(len(keys), node, np.int64))
                    held += len(keys)
                if held > PACK:
                    yield done()
                    held_keys, held_nodes, held = [], [], 0
        if held:
            yield done()

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = {"a": pa.int64(), "b": pa.int64(), "chunk": pa.int32(), "key": pa.int64(), "nodes": pa.binary()}

        def shared(keys: list[np.ndarray], nodes: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
            rows = []
            for key, run in runs_of(np.concatenate(keys), np.concatenate(nodes)):
                name = hashlib.blake2b(run.tobytes(), digest_size=16).digest()
                a, b = (int.from_bytes(half, "little", signed=True) for half in (name[:8], name[8:]))
                rows += [(a, b, i // CHUNK, key, run[i : i + CHUNK].tobytes()) for i in range(0, len(run), CHUNK)]
                if len(rows) >= 1 << 12:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds.values(), strict=True)], list(kinds))
                    rows = []
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds.values(), strict=True)], list(kinds))

        lean_worker()
        at, keys, nodes = None, [], []
        for batch in batches:
            for bucket, some, of in zip(*(batch.column(i) for i in (1, 2, 3)), strict=True):
                if bucket.as_py() != at and keys:
                    yield from shared(keys, nodes)
                    keys, nodes = [], []
                at = bucket.as_py()
                keys.append(unpacked_keys(some.as_buffer()))
                nodes.append(from_planes(of.as_buffer()))
        if keys:
            yield from shared(keys, nodes)

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = [np.frombuffer(x, np.int64) for x in batch.column(1).to_pylist()]
            keys = np.repeat(batch.column(0).to_numpy(), [len(x) for x in lists])
            yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(np.concatenate([np.zeros(0, np.int64), *lists]))], ["key", "node"])

    packed = nodes.select("node", "keys").mapInArrow(pack, "task int, bucket int, keys binary, nodes binary")
    dealt = packed.repartitionById(tasks, "task").sortWithinPartitions("bucket")
    runs = dealt.mapInArrow(meet, "a long, b long, chunk int, key long, nodes binary").groupBy("a", "b", "chunk").agg(F.min("key").alias("key"), F.first("nodes").alias("nodes"))
    hot = nodes.select(F.explode("hot").alias("key"), "node")
    return runs.select("key", "nodes").mapInArrow(spread, "key long, node long").unionByName(hot)


def text_key(text_col: str):
    return F.unhex(F.md5(text_or_empty(text_col).cast("binary")))


def spanning(cell: list[tuple], threshold: float, near) -> Iterator[tuple]:
    """Links of a forest over the rows (side, node, size, ...) of a cell, ascending by size.

    ``near(i, j, apart)`` gives those of the positions ``j`` that ``i`` is linked
    with; ``apart(x)`` tells whether a link with x would still join two trees.
    """
    side, sizes = np.array([r[0] for r in cell]), np.array([r[2] for r in cell])
    tree = np.arange(len(cell))
    for i in range(len(cell)):
        j = np.arange(i + 1, np.searchsorted(sizes, sizes[i] / threshold + 1e-9, side="right"))
        j = j[(side[j] != side[i]) | (side[i] == -1)]
        j = j[tree[j] != tree[i]]
        for x in near(i, j, lambda x, i=i: tree[x] != tree[i]) if len(j) else ():
            if tree[x] != tree[i]:
                yield cell[i][1], cell[x][1]
                tree[tree == tree[x]] = tree[i]


def candidates(cell: list[tuple], threshold: float) -> Iterator[tuple]:
    """Rows are (side, node, size, bits): pairs whose parities allow the threshold."""
    cell = sorted(cell, key=lambda r: r[2])
    sizes = np.array([r[2] for r in cell])
    words = [np.frombuffer(r[3], np.uint64) for r in cell]
    length = np.array([len(w) for w in words])
    # a partner is at most 1 / threshold as large; its parities are folded to this one's length
    stacks: dict[int, np.ndarray] = {}

    def near(i: int, j: np.ndarray, apart) -> np.ndarray:
        to = int(length[i])
        if to not in stacks:
            first = int(np.searchsorted(length, to))
            last = int(np.searchsorted(sizes, sizes[length == to].max() / threshold + 1e-9, side="right"))
            stacks.clear()
            stacks[to] = np.array([folded(w, to) for w in words[first:last]])
            stacks[-1] = np.array([first])
        rows = stacks[to][j - stacks[-1][0]]
        differ = np.bitwise_count(rows ^ words[i]).sum(1)
        return j[differ <= (1 - threshold) / (1 + threshold) * (sizes[i] + sizes[j]) + 1e-9]

    return spanning(cell, threshold, near)


def similarity(a: np.ndarray, b: np.ndarray) -> float:
    """Of two sets by their ascending hashes."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / max(1, len(a) + len(b) - both)


def verified(cell: list[tuple], threshold: float) -> Iterator[tuple]:
    """Rows are (side, node, size, set): pairs at the threshold."""
    cell = sorted(cell, key=lambda r: r[2])
    sets = [np.frombuffer(r[3], np.uint64) for r in cell]
    return spanning(cell, threshold, lambda i, j, apart: (x for x in j if apart(x) and similarity(sets[i], sets[x]) >= threshold))


def by_cell(rows: DataFrame, by: str, value: DataFrame, links, threshold: float, tile: int) -> DataFrame:
    """u, v: what ``links`` finds in the cells of ``rows`` (``by``, node, size), a table that can be read again, with ``value`` (node and one column)."""
    band = F.floor(F.log(F.col("size").cast("double")) / F.lit(-math.log(threshold))).cast("int")
    # sizes within the threshold lie in the same band or in one next to it; two, as logarithms are rounded
    kind = rows.schema["node"].dataType.simpleString()
    dealt = in_cells(rows.withColumn("band", band), [by], "band", 2, tile, "node", ["node", "size"], rows.count(), value)

    wide = next(c for c in value.columns if c != "node")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_worker()
        at, cell, id_type = None, [], None

        def done(found: list[tuple], id_type: pa.DataType) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], id_type) for k in (0, 1)], ["u", "v"])

        for batch in by_bytes(batches, wide):
            id_type, found = batch.schema.field("node").type, []
            for check, name, *row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (check, name) != at:
                    found += links(cell, threshold) if len(cell) > 1 else ()
                    at, cell = (check, name), []
                cell.append(tuple(row))
            yield done(found, id_type)
        if len(cell) > 1:
            yield done(list(links(cell, threshold)), id_type)

    return dealt.mapInArrow(run, f"u {kind}, v {kind}").distinct()


def set_links(nodes: DataFrame, sets_of, threshold: float = 0.8, tile: int = TILE) -> DataFrame:
    """u, v: links that connect whatever links at ``threshold`` and above connect.

    ``nodes`` (node, size, keys, hot, bits) can be read again; ``sets_of`` returns
    node and set (ascending hashes) for a table of nodes.
    """
    nodes = nodes.filter(F.col("size") > 0)
    sizes = nodes.select("node", "size")
    meets = checkpointed(meetings(nodes).join(sizes, "node"))
    maybe = by_cell(meets, "key", nodes.select("node", "bits"), candidates, threshold, tile)
    groups = checkpointed(star_components(maybe).withColumnRenamed("u", "node").join(sizes, "node"))
    return by_cell(groups, "root", sets_of(groups.select("node")), verified, threshold, tile)


def hashed_sets(texts: DataFrame, shingle: int) -> DataFrame:
    """node, set (ascending hashes of the distinct shingles) of ``texts`` (node, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_worker()
        for batch in by_bytes(batches, "text"):
            sets = [np.unique(shingle_hashes(t, shingle)).tobytes() for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.binary())], ["node", "set"])

    return texts.select("node", "text").mapInArrow(run, "node long, set binary")
