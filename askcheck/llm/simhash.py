"""SimHash near-duplicates by tiled exact comparison.

Fingerprints are compared by numpy exclusive-or and bit counts, tile against
tile, sorted by population count; a pair of tiles is skipped when its population
counts differ by more than the radius. All pairs of a corpus are too many for
that, so tiles are only formed of fingerprints that can be close at all: cut 64
bits into ``b`` blocks; two fingerprints that differ in at most ``r`` bits agree
in at least ``b - r`` whole blocks, so every choice of ``b - r`` blocks makes a
bucket for each value, and each close pair meets in some bucket. That loses no
pair; ``b`` only sets how many and how large the buckets are.

Equal fingerprints are one node, so copies never meet. A bucket with more than
``tile`` nodes is split by population count and then by hash; each pair of parts
within the radius is a cell of its own, so no task gets a whole hot bucket. A
cell returns a spanning forest of its links, never all pairs. Components are
found by alternating large and small stars, each round checkpointed.

Defined results: a null text counts as empty; texts without words have the
fingerprint zero and are linked as any other; rows with the same doc_id are all
returned; the component of rows without doc_id is the smallest doc_id in reach,
null if there is none; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, checkpointed, lean_worker, partitions_of, remove, scratch_path, text_or_empty

#: Fingerprints of a bucket or a part of one that are compared in one cell.
TILE = 1024
#: Rows and columns of one exclusive-or in a cell.
STEP = 256


def shingle_hashes(text: str, shingle: int, seed: int = 42) -> np.ndarray:
    """A hash for every run of ``shingle`` words, repeats included; of all words if there are fewer."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    k = min(shingle, len(words))
    starts = np.concatenate([[0], ends[:-1] + 1])[: len(words) - k + 1].tolist()
    parts = [joined[a:b] for a, b in zip(starts, ends[k - 1 :].tolist(), strict=True)]
    return np.fromiter(map(xxhash.xxh64_intdigest, parts, repeat(seed)), np.uint64, len(parts))


def majority_bits(hashes: np.ndarray) -> int:
    """A bit is 1 if it is set in over half of the hashes."""
    if not len(hashes):
        return 0
    counts = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 1 << 15):
        counts += np.unpackbits(hashes[i : i + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * counts > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprint(text: str, shingle: int = 4, seed: int = 42) -> int:
    return majority_bits(shingle_hashes(text, shingle, seed))


def fingerprints(docs: DataFrame, shingle: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fp: the 64 bits as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in by_bytes(batches, "text"):
            fps = np.array([fingerprint(t, shingle) for t in batch.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps)], ["doc_id", "fp"])

    src = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, fp long")


def block_masks(radius: int, blocks: int) -> list[int]:
    """For each choice of ``blocks - radius`` blocks the mask of their bits, signed."""
    edges = [64 * i // blocks for i in range(blocks + 1)]
    masks = [sum(1 << bit for bit in range(edges[i], edges[i + 1])) for i in range(blocks)]
    chosen = [sum(c) for c in combinations(masks, blocks - radius)]
    return [m - (1 << 64) if m >> 63 else m for m in chosen]


def blocks_for(n: int, radius: int, tile: int = TILE) -> int:
    """The fewest blocks for which evenly spread fingerprints fill buckets of at most a tile."""
    blocks = radius + 1
    while blocks < 2 * radius + 4 and n / 2 ** (64 * (blocks - radius) / blocks) > tile:
        blocks += 1
    return blocks


def linked(a: np.ndarray, b: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Positions of close pairs, tile by tile; both sides ascend by population count. ``a is b``: each pair once."""
    pops_a, pops_b = np.bitwise_count(a).astype(np.int16), np.bitwise_count(b).astype(np.int16)
    for i in range(0, len(a), STEP):
        part, low, high = a[i : i + STEP], pops_a[i], pops_a[min(i + STEP, len(a)) - 1]
        for j in range(i if a is b else 0, len(b), STEP):
            if pops_b[j] - high > radius:
                break
            if low - pops_b[min(j + STEP, len(b)) - 1] > radius:
                continue
            x, y = np.nonzero(np.bitwise_count(part[:, None] ^ b[None, j : j + STEP]) <= radius)
            x, y = x + i, y + j
            if a is b:
                keep = x < y
                x, y = x[keep], y[keep]
            if len(x):
                yield x, y


def forest(n: int, pairs: Iterator[tuple[np.ndarray, np.ndarray]]) -> list[tuple[int, int]]:
    """Of the pairs, those that join two trees: at most n - 1."""
    tree = np.arange(n)
    out = []
    for x, y in pairs:
        while True:
            apart = tree[x] != tree[y]
            if not apart.any():
                break
            x, y = x[apart], y[apart]
            out.append((int(x[0]), int(y[0])))
            tree[tree == tree[y[0]]] = tree[x[0]]
    return out


def cell_links(fps: np.ndarray, side: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links in one cell; side 0 and 1 are two tiles, -1 is one tile with itself."""
    fps = fps[np.argsort(np.bitwise_count(fps) + np.where(side == 1, 100, 0).astype(np.uint8), kind="stable")] if len(fps) > 1 else fps
    cut = int((side != 1).sum())
    if (side == -1).all():
        pairs = linked(fps, fps, radius)
    else:
        pairs = ((x, y + cut) for x, y in linked(fps[:cut], fps[cut:], radius))
    got = np.array(forest(len(fps), pairs), np.int64).reshape(-1, 2)
    return fps[got[:, 0]], fps[got[:, 1]]


def in_cells(keyed: DataFrame, by: list[str], band: str, reach: int, tile: int, node: str, values: list[str], n: int, wide: DataFrame | None = None) -> DataFrame:
    """check, cell, side and ``values`` of ``n`` rows, dealt by cell and sorted within partitions.

    A bucket (``by``) of at most ``tile`` rows is one cell, side -1. A larger one
    is split by ``band`` and a hash of ``node``; a row then goes to the cell of
    its own part with each part whose band is within ``reach`` of its own.
    ``wide`` (``node`` and further columns) is joined on once rows have their cells.
    """
    per_band = keyed.groupBy(*by, band).agg(F.count(F.lit(1)).alias("n"))
    hot = (
        per_band.groupBy(*by)
        .agg(F.sum("n").alias("total"), F.collect_list(F.struct(F.col(band).alias("band"), F.ceil(F.col("n") / tile).cast("int").alias("parts"))).alias("tiles"))
        .filter(F.col("total") > tile)
    )
    own = f"struct({band} as band, cast(pmod(xxhash64({node}), element_at(filter(tiles, t -> t.band = {band}), 1).parts) as int) as part)"
    others = f"flatten(transform(filter(tiles, t -> abs(t.band - {band}) <= {reach}), t -> transform(sequence(0, t.parts - 1), p -> struct(t.band as band, p as part))))"
    cells = (
        join_spread(keyed, hot, by, "total", n, ["tiles"])
        .withColumn("own", F.expr(f"case when tiles is null then null else {own} end"))
        .withColumn("other", F.explode_outer(F.expr(f"case when tiles is null then null else {others} end")))
        .select(*by, F.expr("least(own, other)").alias("lo"), F.expr("greatest(own, other)").alias("hi"), F.expr("case when own is null or own = other then -1 when own < other then 0 else 1 end").alias("side"), *values)
    )
    if wide is not None:
        cells, values = cells.join(wide, node), [*values, *(c for c in wide.columns if c != node)]
    place = [*by, "lo", "hi"]
    dealt = cells.withColumn("cell", F.xxhash64(*place)).repartition(partitions_of(keyed.sparkSession), "cell").sortWithinPartitions(*place)
    return dealt.select(F.hash(*place).alias("check"), "cell", "side", *values)


def join_spread(many: DataFrame, one: DataFrame, by: list[str], total: str, n: int, values: list[str]) -> DataFrame:
    """The ``n`` rows of ``many`` with ``values`` of ``one`` (null where it has no row for them), whose keys are its own.

    ``total`` tells how many rows of ``many`` a key has. Keys with more than a
    partition's share of the rows, fewer than there are partitions, are broadcast;
    the shuffle deals the others.
    """
    share = -(-n // partitions_of(many.sparkSession))
    side = one.select(*by, total, *values)
    few = side.filter(F.col(total) > share).withColumnRenamed(total, "_many")
    first = many.join(F.broadcast(few), by, "left")
    rest = first.filter("_many is null").drop("_many", *values).join(side.filter(F.col(total) <= share).drop(total), by, "left")
    return first.filter("_many is not null").drop("_many").unionByName(rest)


def close_links(nodes: DataFrame, radius: int = 4, tile: int = TILE) -> DataFrame:
    """u, v: links that connect whatever fingerprints within ``radius`` connect. ``nodes`` has distinct fp."""
    n = nodes.count()
    masks = block_masks(radius, blocks_for(n, radius, tile))
    keyed = nodes.select("fp", F.explode(F.array(*(F.struct(F.lit(i).alias("choice"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for i, m in enumerate(masks)))).alias("k")).select("fp", "k.choice", "k.key")
    keyed = keyed.withColumn("pop", F.bit_count("fp"))
    dealt = in_cells(keyed, ["choice", "key"], "pop", radius, tile, "fp", ["fp"], n * len(masks))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_worker()
        held = [np.zeros(0, t) for t in (np.int64, np.int64, np.int32, np.uint64)]

        def finished(cols: list[np.ndarray], last: bool) -> tuple[pa.RecordBatch, list[np.ndarray]]:
            cuts = np.flatnonzero((np.diff(cols[0]) != 0) | (np.diff(cols[1]) != 0)) + 1
            starts = np.concatenate([[0], cuts])
            ends = np.concatenate([cuts, [len(cols[0])]])
            keep = starts[-1] if not last else len(cols[0])
            left, right = [np.zeros(0, np.uint64)], [np.zeros(0, np.uint64)]
            for a, b in zip(starts.tolist(), ends.tolist(), strict=True):
                if a < keep and b - a > 1:
                    u, v = cell_links(cols[3][a:b], cols[2][a:b], radius)
                    left.append(u)
                    right.append(v)
            out = pa.RecordBatch.from_arrays([pa.array(np.concatenate(x).view(np.int64)) for x in (left, right)], ["u", "v"])
            return out, [c[keep:] for c in cols]

        for batch in batches:
            new = [batch.column(i).to_numpy() for i in range(4)]
            new[3] = new[3].view(np.uint64)
            held = [np.concatenate(x) for x in zip(held, new, strict=True)]
            if len(held[0]) > 1 << 16:
                out, held = finished(held, False)
                yield out
        if len(held[0]):
            yield finished(held, True)[0]

    return dealt.mapInArrow(run, "u long, v long").distinct()


def star_components(links: DataFrame) -> DataFrame:
    """u, root (the smallest node in reach) for every node with a link, by alternating large and small stars.

    Each round is two aggregates with map-side combination and two joins of
    links; a round's table is checkpointed. The rounds grow with the logarithm
    of the longest path.
    """
    edges = checkpointed(links.filter("u <> v").select("u", "v").distinct())
    before = None
    while True:
        state = edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first()
        if state == before or state[0] == 0:
            return edges.select("u", F.col("v").alias("root")).unionByName(edges.select(F.col("v").alias("u"), F.col("v").alias("root"))).distinct()
        before = state
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(least, "u")
        small = joined.filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
        edges = checkpointed(small.filter("u <> v").distinct())


def components(docs: DataFrame, shingle: int = 4, radius: int = 4, id_col: str = "doc_id", text_col: str = "text", tile: int = TILE) -> DataFrame:
    """doc_id, fp, fingerprint (16 hex digits), component_id."""
    found = component_ids(checkpointed(fingerprints(docs, shingle, id_col, text_col)), radius, tile)
    return found.select("doc_id", "fp", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def component_ids(of_docs: DataFrame, radius: int, tile: int = TILE) -> DataFrame:
    """doc_id, fp, component_id of ``of_docs`` (doc_id, fp), a table that can be read again."""
    nodes = checkpointed(of_docs.groupBy("fp").agg(F.min("doc_id").alias("first_id"), F.count(F.lit(1)).alias("copies")))
    roots = star_components(close_links(nodes.select("fp"), radius, tile))
    members = roots.join(nodes, roots["u"] == nodes["fp"]).select("fp", "root", "first_id")
    smallest = members.groupBy("root").agg(F.min("first_id").alias("component_id"))
    joined = members.join(smallest, "root").select("fp", "component_id")
    of_fp = nodes.join(joined, "fp", "left").select("fp", "copies", F.coalesce("component_id", "first_id").alias("component_id"))
    return join_spread(of_docs, of_fp, ["fp"], "copies", of_docs.count(), ["component_id"]).select("doc_id", "fp", "component_id")


#: Rows (an id and 16 bytes) that may be broadcast to find their texts; more are shuffled.
BROADCAST_ROWS = 500_000


def if_small(df: DataFrame) -> DataFrame:
    """A table that can be read again, to be broadcast if it has few rows."""
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


def keep_one(docs: DataFrame, shingle: int = 5, radius: int = 4, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text", tile: int = TILE) -> DataFrame:
    """The rows that stay: one of each group of near copies, that with the smallest doc_id.

    Texts are near copies if their fingerprints are within ``radius``, or, as
    short texts that differ in a word are further apart than that, if their sets
    of shingles have a similarity of at least ``threshold``. Both kinds of links
    make the groups together. Rows with equal sets are one node.

    Defined results: a null text counts as empty, and all texts without words are
    one group; rows that share doc_id and text leave one, rows that share the
    doc_id alone are judged by their texts; a null doc_id stays only where a group
    has no other; an empty table gives an empty result; columns of any name pass through.
    """
    from .near_sets import hashed_sets, set_links, sketches, text_key

    spark = docs.sparkSession
    path = scratch_path(spark, "sketches")
    sketches(docs, shingle, threshold, id_col, text_col).withColumn("row", F.monotonically_increasing_id()).write.option("compression", "zstd").parquet(path)
    sketched = spark.read.parquet(path)
    best = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_key")).alias("best")
    node_of = checkpointed(sketched.groupBy("digest").agg(F.min("row").alias("node"), F.first("fp").alias("fp"), best).drop("digest"))
    copies = checkpointed(sketched.select("row").join(node_of.select(F.col("node").alias("row")), "row", "left_anti"))
    first = sketched.join(if_small(copies), "row", "left_anti").withColumnRenamed("row", "node")

    def sets_of(nodes: DataFrame) -> DataFrame:
        """Made again from the texts of the nodes, as to store all sets takes more disk than the texts."""
        named = sketched.select(F.col("row").alias("node"), F.col("doc_id").alias("_id"), F.col("text_key").alias("_key"))
        wanted = checkpointed(named.join(nodes, "node", "left_semi"))
        found = docs.select(F.col(id_col).alias("_doc"), text_key(text_col).alias("_text"), text_or_empty(text_col).alias("text"))
        return hashed_sets(found.join(if_small(wanted), F.col("_doc").eqNullSafe(F.col("_id")) & (F.col("_text") == F.col("_key"))).select("node", "text"), shingle).dropDuplicates(["node"])

    # nodes of one fingerprint hang on the smallest of them
    of_fp = checkpointed(node_of.groupBy("fp").agg(F.min("node").alias("head")))
    equal = node_of.join(of_fp, "fp").select(F.col("node").alias("u"), F.col("head").alias("v"))
    close = close_links(of_fp.select("fp"), radius, tile)
    heads = [of_fp.select(F.col("fp").alias(k), F.col("head").alias(f"head_{k}")) for k in ("u", "v")]
    close = close.join(heads[0], "u").join(heads[1], "v").select(F.col("head_u").alias("u"), F.col("head_v").alias("v"))
    alike = set_links(first, sets_of, threshold, tile)
    roots = star_components(equal.unionByName(close).unionByName(alike)).select(F.col("u").alias("node"), "root")

    grouped = node_of.join(roots, "node", "left").groupBy(F.coalesce("root", "node").alias("root")).agg(F.min("best").alias("best"))
    stay = grouped.select(F.col("best.doc_id").alias("_keep"), F.col("best.text_key").alias("_keep_key"))
    # a null-safe pair of keys, as rows may lack a doc_id
    texts = sketched.groupBy(F.col("doc_id").alias("_gone"), F.col("text_key").alias("_gone_key")).agg(F.count(F.lit(1)).alias("_n"))
    match = F.col("_keep").eqNullSafe(F.col("_gone")) & (F.col("_keep_key") == F.col("_gone_key"))
    judged = checkpointed(texts.join(stay, match, "left").withColumn("_stays", F.col("_keep_key").isNotNull()).filter("_n > 1 or not _stays").select("_gone", "_gone_key", "_stays"))
    remove(spark, path)
    gone, again = judged.filter("not _stays"), judged.filter("_stays")
    # a struct of its own, so that no column of the table is taken for one of those named here
    named = docs.select(F.struct("*").alias("_row"), F.col(id_col).alias("_doc"), text_key(text_col).alias("_text"))
    match = F.col("_doc").eqNullSafe(F.col("_gone")) & (F.col("_text") == F.col("_gone_key"))
    left = named.join(if_small(gone), match, "left_anti")
    if again.isEmpty():
        return left.select("_row.*")
    repeated = left.join(if_small(again), match, "left_semi").dropDuplicates(["_doc", "_text"])
    return left.join(if_small(again), match, "left_anti").unionByName(repeated).select("_row.*")
