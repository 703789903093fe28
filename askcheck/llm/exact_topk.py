"""Exact top-k inner products by aggregation without random access.

Every dimension of a block of candidates is a list of contributions in sorted
order, read from the top for a positive query component and from the bottom for
a negative one. All lists are read sequentially and to equal depth. At a depth a
candidate's score lies between

* a lower bound: what was read, and the least of the list where it was not, and
* an upper bound: what was read, and the value last read where it was not.

Whether an entry was read follows from comparing it with the value last read
(``top`` and ``bottom``), so both bounds of a block of queries are products of
clipped matrices. Reading goes on until few candidates can still reach the k-th
lower bound; those outsiders' scores are then resolved exactly. A few queries of
the block read first and tell at which depth stopping is worth a test for all.
Components are integers and the products are exact in the floating type chosen,
so ties are exact too.

Queries and candidates meet block by block: a cell is a block of queries with a
block of candidates and returns k rows for each query. Nothing is broadcast. Rows
with equal id and equal vector are one candidate that counts several times, so
copies meet no block together.

Defined results: every row is a candidate but a query's own; repeated rows are
candidates and queries each, so their ids and their queries' ranks come
repeatedly; vectors that are null, empty, or hold null or non-finite components
take no part; a vector that is shorter than the longest counts as zero in the
missing dimensions; a null id is no query and comes last among ties, ids are of any
type that sorts; fewer than k candidates give them all; further columns of any
name don't matter; components of 2**63 / scale and more count as the largest long.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpointed

QUERY_BLOCK, CANDIDATE_BLOCK = 512, 4096
#: Queries of a block that read first.
PROBES = 8


def usable(vector: str) -> Column:
    c = F.col(vector)
    finite = F.forall(c, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(math.inf)))
    return F.coalesce(c.isNotNull() & (F.size(c) > 0) & finite, F.lit(False))


def integer_vector(vector: str, scale: int = 256) -> Column:
    return F.transform(F.col(vector), lambda x: F.floor(F.lit(float(scale)) * x.cast("double")).cast("double"))


def matrix(column: pa.Array, width: int) -> np.ndarray:
    values, ends = column.values.to_numpy(zero_copy_only=False), column.offsets.to_numpy()
    sizes = np.diff(ends)
    out = np.zeros((len(sizes), width))
    rows = np.repeat(np.arange(len(sizes)), sizes)
    out[rows, np.arange(len(rows)) - np.repeat(ends[:-1] - ends[0], sizes)] = values[ends[0] : ends[-1]]
    return out


def exact_dtype(a: np.ndarray, b: np.ndarray):
    largest = a.shape[1] * (np.abs(a).max(initial=0) + 1) * (np.abs(b).max(initial=0) + 1)
    return np.float32 if largest < 1 << 24 else np.float64 if largest < 1 << 53 else object


def bounds(queries: np.ndarray, block: np.ndarray, top: np.ndarray, bottom: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Lower and upper bounds (queries x candidates) when the lists were read down to ``top`` or up to ``bottom``."""
    up, down = np.maximum(queries, 0), np.minimum(queries, 0)
    upper = up @ np.maximum(block, top).T + down @ np.minimum(block, bottom).T
    lower = up @ np.where(block >= top, block, block.min(0)).T + down @ np.where(block <= bottom, block, block.max(0)).T
    return lower, upper


def undecided(queries: np.ndarray, block: np.ndarray, lists: np.ndarray, depth: int, own: np.ndarray, k: int) -> np.ndarray:
    """Candidates (queries x candidates) that may still be among the k best when lists are read to ``depth``."""
    n = len(block)
    if depth == n:
        lower = upper = queries @ block.T
    else:
        lower, upper = bounds(queries, block, lists[n - depth], lists[depth - 1])
    allowed = own[:, None] != np.arange(n)
    low = np.where(allowed, lower, -np.inf)
    at = max(0, n - k)
    return (upper >= np.partition(low, at, axis=1)[:, at, None]) & allowed


def block_top_k(queries: np.ndarray, own: np.ndarray, block: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query position, candidate position, score) of each query's k best in the block, ties to the smaller position.

    ``own``: the position that a query must not take, -1 if it may take all.
    """
    kind = exact_dtype(queries, block)
    queries, block = queries.astype(kind), block.astype(kind)
    n = len(block)
    lists = np.sort(block, axis=0)
    enough = max(4 * k, n // 8)
    depths = [n // 2, 3 * n // 4, 7 * n // 8] if n >= 64 and kind is not object else []
    while depths:
        some = undecided(queries[:PROBES], block, lists, depths[0], own[:PROBES], k)
        if 2 * np.count_nonzero(some.sum(1) <= enough) >= len(some):
            break
        del depths[0]
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    active = np.arange(len(queries))
    for depth in [*depths, n]:
        q = queries[active]
        may = undecided(q, block, lists, depth, own[active], k)
        few = (may.sum(1) <= enough) | (depth == n)
        rows, cols = np.nonzero(may & few[:, None])
        if len(rows):
            score = np.einsum("ij,ij->i", q[rows], block[cols]) if kind is not object else np.array([q[a] @ block[b] for a, b in zip(rows, cols, strict=True)], object)
            best = np.lexsort((cols, -score, rows))
            rows, cols, score = rows[best], cols[best], score[best]
            take = np.arange(len(rows)) - np.searchsorted(rows, rows) < k
            found.append((active[rows[take]], cols[take], score[take]))
        active = active[~few]
        if not len(active):
            break
    return tuple(np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, int),) * 3


def top_k(vectors: DataFrame, is_query: Column, k: int = 5, id_col: str = "vec_id", vector: str = "embedding", scale: int = 256, query_block: int = QUERY_BLOCK, candidate_block: int = CANDIDATE_BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score: each query row's k highest integer inner products with all other rows."""
    src = vectors.filter(usable(vector)).select(F.col(id_col).alias("id"), integer_vector(vector, scale).alias("v"), F.coalesce(is_query, F.lit(False)).alias("asks"))
    rows = src.groupBy("id", "v").agg(F.count(F.lit(1)).alias("times"), F.count_if("asks").alias("asked"))
    rows = checkpointed(rows.withColumn("row", F.monotonically_increasing_id()))
    n, asking = rows.agg(F.count(F.lit(1)), F.count_if(F.col("asked") > 0)).first()
    across, down = max(1, -(-n // candidate_block)), max(1, -(-asking // query_block))

    def dealt(df: DataFrame, own: str, blocks: int, other: str, copies: int, count: str) -> DataFrame:
        placed = df.withColumn(own, F.pmod(F.xxhash64("row"), F.lit(blocks)).cast("int")).withColumn(other, F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
        # columns of its own for each side, though both come from one table
        return placed.select(*(F.col(c).alias(c) for c in ("qb", "cb", "row", "id", "v", count)))

    queries = dealt(rows.filter("asked > 0"), "qb", down, "cb", across, "asked")
    candidates = dealt(rows, "cb", across, "qb", down, "times")
    kind = rows.schema["id"].dataType.simpleString()

    def cell(left: pa.Table, right: pa.Table) -> pa.Table:
        id_type = (left if left.num_rows else right).schema.field("id").type
        out = pa.schema([("query", pa.int64()), ("query_id", id_type), ("asked", pa.int64()), ("vec_id", id_type), ("score", pa.int64()), ("times", pa.int64())])
        if not left.num_rows or not right.num_rows:
            return out.empty_table()
        # one chunk each, as lists in several can't be taken from
        left, right = (pa.Table.from_batches([pa.RecordBatch.from_arrays([pa.concat_arrays(c.chunks) for c in t.columns], schema=t.schema)]) for t in (left, right))
        right = right.take(pc.sort_indices(right, sort_keys=[("id", "ascending")], null_placement="at_end"))
        a, b = left.column("v").combine_chunks(), right.column("v").combine_chunks()
        width = max(np.diff(x.offsets.to_numpy()).max() for x in (a, b))
        times = right.column("times").to_numpy()
        place = {row: i for i, row in enumerate(right.column("row").to_pylist()) if times[i] == 1}
        own = np.array([place.get(row, -1) for row in left.column("row").to_pylist()])
        q, c, score = block_top_k(matrix(a, width), own, matrix(b, width), k)
        asks, taken = (t.select(["row", "id", count]).take(pa.array(at, pa.int64())) for t, count, at in ((left, "asked", q), (right, "times", c)))
        # of several equal rows one is the query's own
        left_over = taken.column("times").to_numpy() - (asks.column("row").to_numpy() == taken.column("row").to_numpy())
        return pa.table([asks.column("row"), asks.column("id"), asks.column("asked"), taken.column("id"), pa.array([int(s) for s in score], pa.int64()), pa.array(left_over, pa.int64())], schema=out)

    near = queries.groupBy("qb", "cb").cogroup(candidates.groupBy("qb", "cb")).applyInArrow(cell, f"query long, query_id {kind}, asked long, vec_id {kind}, score long, times long")
    best = Window.partitionBy("query").orderBy(F.desc("score"), F.asc_nulls_last("vec_id"), "times")
    first = near.withColumn("place", F.row_number().over(best)).filter(F.col("place") <= k)
    last = F.sum("times").over(best.rowsBetween(Window.unboundedPreceding, 0))
    ranked = first.withColumn("last", last).filter(F.col("last") - F.col("times") < k)
    spread = ranked.withColumn("rank", F.explode(F.sequence(F.col("last") - F.col("times") + 1, F.least("last", F.lit(k).cast("long")))))
    return spread.withColumn("again", F.explode(F.sequence(F.lit(1), F.col("asked").cast("int")))).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
