"""Every row is a candidate but a query's own, whatever repeats."""

import numpy as np
from askcheck.llm import exact_topk
from pyspark.sql import functions as F


def brute(rows, asks, k=5):
    """rows: (id, integer vector)."""
    out = []
    for i, (qid, q) in enumerate(rows):
        if asks(qid):
            others = sorted((-int(np.dot(q, c)), cid is None, cid if cid is not None else 0) for j, (cid, c) in enumerate(rows) if j != i)
            out += [(qid, r + 1, None if none else cid, -s) for r, (s, none, cid) in enumerate(others[:k])]
    return sorted(map(str, out))


def found(spark, rows, asks, kind="long", **options):
    vectors = spark.createDataFrame([(i, [x / 256 for x in v]) for i, v in rows], f"vec_id {kind}, embedding array<double>")
    return sorted(str(tuple(r)) for r in exact_topk.top_k(vectors, asks, **options).collect())


def test_repeated_and_null_ids(spark):
    rng = np.random.default_rng(3)
    for n in (9, 200):
        rows = [(int(rng.integers(0, n // 3)) if i % 7 else None, rng.integers(-3, 4, 4).tolist()) for i in range(n)]
        rows += rows[: n // 2]
        for options in ({}, {"query_block": 3, "candidate_block": 16}):
            assert found(spark, rows, F.col("vec_id") % 3 == 0, **options) == brute(rows, lambda i: i is not None and i % 3 == 0)


def test_unlike_vectors_of_one_id_are_rows_each(spark):
    rows = [(0, [100, 0])] + [(1, [200 + i, 0]) for i in range(6)] + [(i, [i, 0]) for i in range(2, 8)]
    got = found(spark, rows, F.col("vec_id") == 0)
    assert got == brute(rows, lambda i: i == 0) and len(got) == 5


def test_large_and_text_ids(spark):
    rows = [((1 << 53) + i, [i, 1]) for i in range(8)]
    assert found(spark, rows, F.col("vec_id") == (1 << 53) + 7) == brute(rows, lambda i: i == (1 << 53) + 7)
    named = [(f"v{i}", [i % 3, 1]) for i in range(8)]
    vectors = spark.createDataFrame([(i, [x / 256 for x in v]) for i, v in named], "vec_id string, embedding array<double>")
    got = exact_topk.top_k(vectors, F.col("vec_id") == "v2", k=3).orderBy("rank").collect()
    assert [(r.vec_id, r.score) for r in got] == [("v5", 5), ("v1", 3), ("v4", 3)]


def test_far_outsiders_are_left_before_the_lists_end(monkeypatch):
    """Of a block with few large vectors, lists are not read to the end."""
    rng = np.random.default_rng(1)
    block = rng.integers(-2, 3, (400, 8)).astype(float)
    block[:6] *= 100
    depths = []
    real = exact_topk.undecided
    monkeypatch.setattr(exact_topk, "undecided", lambda q, b, lists, depth, own, k: depths.append(depth) or real(q, b, lists, depth, own, k))
    asks = rng.integers(-5, 6, (20, 8)).astype(float)
    q, c, s = exact_topk.block_top_k(asks, np.full(20, -1), block, 3)
    assert max(depths) < 400
    for i in range(20):
        want = sorted((-(asks[i] @ block[j]), j) for j in range(400))[:3]
        assert [(-v, j) for v, j in zip(s[q == i], c[q == i], strict=True)] == want
