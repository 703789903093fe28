"""Near copies: the threshold is exact, whatever the texts' length and repeats."""

import numpy as np
from askcheck.llm import near_sets, simhash
from pyspark.sql import functions as F


def kept(spark, texts, **options):
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return sorted(r.doc_id for r in simhash.keep_one(docs, **options).collect())


def test_long_texts_are_held_to_the_threshold_exactly(spark):
    # words stand alone as shingles: 888 of 1,000 in common is 0.7986, 889 is 0.8002
    texts = []
    for group in range(12):
        for common in ((1000, 0), (889, 1), (1000, 2), (888, 3)):
            texts.append(" ".join([f"g{group}x{common[1] // 2}w{i}" for i in range(common[0])] + [f"g{group}y{common[1]}w{i}" for i in range(1000 - common[0])]))
    assert kept(spark, texts, shingle=1, radius=0) == [i for i in range(48) if i % 4 != 1]


def test_repeats_in_one_copy_do_not_part_equal_sets(spark):
    words = [f"w{i}" for i in range(300)]
    texts = [" ".join(words), " ".join(words + words[:5] * 80)]
    a, b = (simhash.fingerprint(t, 1) for t in texts)
    assert (a ^ b).bit_count() > 20 and kept(spark, texts, shingle=1) == [0]


def test_no_pair_at_the_threshold_is_without_a_common_key():
    rng = np.random.default_rng(5)
    for n in (1, 4, 5, 9, 60, 400):
        for _ in range(200):
            own = np.unique(rng.integers(0, 2**63, n).astype(np.uint64))
            gone = len(own) - int(np.ceil(0.8 * len(own) - 1e-9))  # J is 0.8 or just above
            other = np.sort(rng.permutation(own)[gone:])
            frequent = rng.permutation(own)[: n // 2]
            for common in (frequent, frequent[:0]):
                order = near_sets.Order.of(common, np.arange(len(common)), n // 4)
                a, b = order.keys(own, 0.8), order.keys(other, 0.8)
                assert any(np.intersect1d(x, y).size for x, y in zip(a, b, strict=True))
                assert len(a[0]) + len(a[1]) == len(own) - int(np.ceil(0.8 * len(own) - 1e-9)) + 1
            short = min(len(near_sets.parities(own)), len(near_sets.parities(other)))
            apart = np.bitwise_count(near_sets.folded(near_sets.parities(own), short) ^ near_sets.folded(near_sets.parities(other), short)).sum()
            assert apart <= len(own) - len(other)


def test_pair_without_a_common_minimum_is_found(spark):
    # the words that hold the four smallest products under odd multipliers stand in one text only
    words = [f"w{i}" for i in range(200)]
    hashes = simhash.shingle_hashes(" ".join(words), 1)
    multipliers = [np.uint64((0x9E3779B97F4A7C15 * (2 * i + 1)) & (1 << 64) - 1 | 1) for i in range(4)]
    least = {int((hashes * m).argmin()) for m in multipliers}
    assert kept(spark, [" ".join(words), " ".join(w for i, w in enumerate(words) if i not in least)], shingle=1, radius=0) == [0]


def test_packing_of_keys_and_nodes():
    rng = np.random.default_rng(4)
    keys, nodes = rng.integers(0, 2**63, 500).astype(np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 2**62, 500)
    assert (near_sets.unpacked_keys(near_sets.packed_keys(keys)) == keys >> np.uint64(16)).all()
    assert (near_sets.from_planes(near_sets.planes(nodes)) == nodes).all()


def test_runs_against_a_dictionary():
    rng = np.random.default_rng(8)
    for n in (0, 1, 2, 500):
        keys, nodes = rng.integers(0, 60, n).astype(np.uint64), rng.integers(0, 40, n)
        want = {}
        for k, v in zip(keys.tolist(), nodes.tolist(), strict=True):
            want.setdefault(k, set()).add(v)
        got = {k: v.tolist() for k, v in near_sets.runs_of(keys, nodes)}
        assert got == {k: sorted(v) for k, v in want.items() if len(v) > 1}


def test_all_pairs_of_a_mixed_corpus(spark, monkeypatch):
    """Against all pairs: copies, near copies around the threshold, hot passages, chunks and tiles of every size."""
    monkeypatch.setattr(near_sets, "CHUNK", 3)
    rng = np.random.default_rng(11)
    passage, texts = [f"p{i}" for i in range(60)], []
    for g in range(12):
        base = [f"g{g}w{i}" for i in range(int(rng.integers(1, 120)))] + (passage[: int(rng.integers(0, 60))] if g % 2 else [])
        for _ in range(int(rng.integers(1, 9))):
            own = [f"x{rng.integers(10**9)}" if rng.random() < rng.choice([0, 0.02, 0.1, 0.3]) else w for w in base]
            texts.append(" ".join(own))
    texts += ["", "", " ".join(passage), " ".join(passage[:55]), "one", "one two"]
    sets = [set(simhash.shingle_hashes(t, 2).tolist()) for t in texts]
    fps = [simhash.fingerprint(t, 2) for t in texts]
    root = list(range(len(texts)))
    changed = True
    while changed:
        changed = False
        for i in range(len(texts)):
            for j in range(i):
                alike = sets[i] == sets[j] or fps[i] == fps[j] or len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])
                if alike and root[i] != root[j]:
                    root[i] = root[j] = min(root[i], root[j])
                    changed = True
    for hot, tile in ((0.005, 4096), (0.0005, 4096), (0.0005, 2)):
        monkeypatch.setattr(near_sets, "HOT", hot)
        assert kept(spark, texts, shingle=2, radius=0, tile=tile) == sorted(set(root))


def test_columns_of_any_name_pass(spark):
    docs = spark.createDataFrame([(1, "a b c d e f"), (2, "a b c d e f"), (3, None)], "doc_id long, text string")
    for name in ("_row", "_doc", "_text", "_gone", "_gone_key", "_stays", "row", "node", "key", "size", "digest"):
        docs = docs.withColumn(name, F.lit("clash"))
    got = simhash.keep_one(docs)
    assert got.columns == docs.columns and sorted(tuple(r)[:3] for r in got.collect()) == [(1, "a b c d e f", "clash"), (3, None, "clash")]


def test_both_kinds_of_links_make_one_group(spark):
    # 0 and 1 have near fingerprints only, 1 and 2 similar sets only: all three are one group
    rng, shared = np.random.default_rng(1), [f"w{i}" for i in range(100)]
    first = [" ".join([*shared, *shared[:50] * 30]), " ".join([*shared[50:], *[f"n{i}" for i in range(40)], *shared[:50] * 30])]
    alike = lambda a, b: len(set(a.split()) & set(b.split())) / len(set(a.split()) | set(b.split()))
    apart = lambda a, b: (simhash.fingerprint(a, 1) ^ simhash.fingerprint(b, 1)).bit_count()
    last = " ".join([*first[1].split()[:90], *[first[1].split()[i] for i in range(90, 140)], *[f"m{i}" for i in range(25)], *[f"n{i}" for i in rng.integers(0, 40, 900)]])
    texts = [*first, last]
    radius = apart(texts[0], texts[1])
    assert alike(texts[0], texts[1]) < 0.8 <= alike(texts[1], texts[2]) and alike(texts[0], texts[2]) < 0.8
    assert apart(texts[1], texts[2]) > radius and apart(texts[0], texts[2]) > radius
    assert kept(spark, texts, shingle=1, radius=radius) == [0]


def test_rows_that_share_id_and_text_leave_one(spark):
    docs = spark.createDataFrame([(1, "a b c"), (1, "a b c"), (1, "quite another text"), (None, "x y z"), (None, "x y z")], "doc_id long, text string")
    got = simhash.keep_one(docs.withColumn("more", F.lit(1)))
    assert got.columns == ["doc_id", "text", "more"]
    assert sorted(map(str, (tuple(r) for r in got.collect()))) == sorted(["(1, 'a b c', 1)", "(1, 'quite another text', 1)", "(None, 'x y z', 1)"])
