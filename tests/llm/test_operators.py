"""Every operator against a brute-force version, on ordinary and on awkward rows."""

import hashlib
import re
import time
import zlib
from collections import Counter
from functools import lru_cache

import duckdb
import numpy as np
import public_tokenizers as P
import pytest
import sentencepiece
import tiktoken
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from askcheck.llm import bpe, exact_topk, line_dedup, near_sets, packing, pii, quality_rules, queries, rule_ensemble, simhash, token_counts, token_files, units

PIECES = ["the ", "a", " ", "  ", "\n", "\t", "é", "'s", "'", "1", "23", "ß", "日本", " ", "\x1c", "\x85", ".", "!!", "ing", "😀", "A", "<|endoftext|>", "tion", "é"]
TEXTS = st.lists(st.sampled_from(PIECES), max_size=25).map("".join)
LONG_WORD, LONG_TEXT = "ab" * 60_000, "many words of a long text. " * 8_000
AWKWARD = [
    (1, "Plain words, in a line.\nAnd another line.", "en", "a"),
    (1, "Plain words, in a line.\nAnd another line.", "en", "a"),
    (2, None, None, None),
    (3, "", "en", "a"),
    (4, " \n\t ", "en", None),
    (5, LONG_WORD, "en", "b"),
    (6, LONG_TEXT, "en", "b"),
    (None, "no id here", "en", "a"),
    (7, "Plain words, in a line.\nAnd another line.", "en", "b"),
    (8, "<|endoftext|> é x  y \n z", "fr", "b"),
]


@pytest.fixture(scope="module")
def awkward(spark):
    docs = spark.createDataFrame(AWKWARD, "doc_id long, text string, lang string, source string").withColumn("n_chars", F.length("text").cast("long"))
    for name in ("n_tokens", "score", "kept", "above", "host", "fp", "spans", "ids", "start", "line", "_words", "n", "shard", "TOKENS"):
        docs = docs.withColumn(name, F.lit("clash"))
    return docs


@pytest.fixture(scope="module")
def empty(awkward):
    return awkward.limit(0)


@lru_cache
def library_of(path):
    return sentencepiece.SentencePieceProcessor(model_file=path) if path.endswith(".model") else Tokenizer.from_file(path)


def text_of(row):
    return row[1] or ""


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(queries.BYTE_JSON)


@pytest.fixture(scope="module")
def model():
    return bpe.worker_model(queries.BYTE_RANKS, P.PATTERN)


@pytest.fixture(scope="module")
def reference():
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.load_ranks(queries.BYTE_RANKS), special_tokens={})


class TestBpe:
    @settings(max_examples=300, deadline=None)
    @given(TEXTS)
    def test_ids_equal_the_library(self, model, reference, text):
        want = reference.encode_ordinary(text)
        assert model[0].encode(text) == want
        assert units.ids_array(model[1].encode([text])[0]).tolist() == want
        assert model[2].decode(np.array(want, np.int64)) == text.encode()

    @settings(max_examples=200, deadline=None)
    @given(TEXTS, st.integers(0, 60), st.integers(0, 20), TEXTS, TEXTS)
    def test_edits_and_appends(self, model, reference, text, at, removed, inserted, more):
        at = min(at, len(text))
        e = bpe.EditableEncoding(model[0], text)
        e.edit(at, removed, inserted)
        assert e.text == text[:at] + inserted + text[at + removed :]
        assert e.ids() == reference.encode_ordinary(e.text)
        e.append(more)
        assert e.ids() == reference.encode_ordinary(e.text)

    def test_an_edit_in_a_long_text_is_local(self, model):
        e = bpe.EditableEncoding(model[0], "some words here and " * 500)
        assert e.edit(5000, 1, "xy") < 12

    def test_every_token_is_reached_by_merges(self, model):
        assert all(model[0].reachable(i) for i in model[0].bytes_of)

    def test_documents(self, awkward, reference):
        got = bpe.round_trip_digests(awkward, queries.BYTE_RANKS, P.PATTERN).collect()
        want = []
        for row in AWKWARD:
            ids = reference.encode_ordinary(text_of(row))
            want.append((row[0], len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(text_of(row).encode()).hexdigest()))
        assert Counter(map(tuple, got)) == Counter(want)

    def test_decoding_of_encoded_rows(self, awkward):
        encoded = bpe.encode_documents(awkward, queries.BYTE_RANKS, P.PATTERN)
        got = bpe.decode_documents(encoded, queries.BYTE_RANKS, P.PATTERN).collect()
        assert Counter((r[0], bytes(r[1])) for r in got) == Counter((r[0], text_of(r).encode()) for r in AWKWARD)


class TestUnits:
    @settings(max_examples=300, deadline=None)
    @given(TEXTS)
    def test_ids_equal_the_library_with_special_strings(self, library, text):
        encoder = units.byte_level_encoder(queries.BYTE_JSON)
        assert units.ids_array(encoder.encode([text])[0]).tolist() == library.encode(text, add_special_tokens=False).ids

    def test_the_cache_is_bounded_and_right(self):
        asked = []
        cache = units.UnitCache(lambda us: asked.extend(us) or [len(u) for u in us], limit=10)
        for i in range(200):
            got = cache.resolve([f"w{i}", "often"])
            assert got["often"] == 5 and got[f"w{i}"] == len(f"w{i}")
        assert len(cache.young) <= 12 and len(cache.old) <= 12
        assert asked.count("often") == 1


def check_packing(rows, texts, library, capacity=2048):
    by_doc = {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
    for doc, pieces in by_doc.items():
        copies = [t for d, t in texts if d == doc]
        ids = library.encode(copies[0], add_special_tokens=False).ids + [1]
        covered = Counter()
        for p in pieces:
            assert p.length == len(p.ids) > 0 and p.ids == ids[p.start : p.start + p.length] and p.doc_tokens == len(ids)
            covered.update(range(p.start, p.start + p.length))
        assert covered == Counter({i: len(copies) for i in range(len(ids))})
    windows = {}
    for r in rows:
        windows.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in windows.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= capacity
    return sum(r.length for r in rows) / (capacity * len(windows))


class TestPacking:
    def test_the_tree_finds_the_tightest_room(self):
        rng = np.random.default_rng(1)
        tree, rooms = packing.RoomTree(100), []
        for _ in range(2000):
            need = int(rng.integers(1, 101))
            want = min((r for r in rooms if r >= need), default=None)
            assert tree.tightest(need) == want
            if want is not None and rng.random() < 0.6:
                rooms.remove(want)
                tree.add(want, -1)
            else:
                rooms.append(need)
                tree.add(need, 1)

    def test_best_fit_decreasing(self):
        packer = packing.Packer(10, min_fragment=3)
        pieces = [((i, i, n), 0, list(range(n))) for i, n in enumerate([7, 6, 5, 4, 3])]
        done = list(packer.place(pieces))
        assert sorted(sorted(len(p[2]) for p in w) for w in done) == [[3, 7], [4, 6]]
        assert [[len(p[2]) for p in w] for w in packer.settle()] == [[5]]

    def test_documents(self, awkward, library):
        rows = packing.pack_documents(awkward.coalesce(1), queries.BYTE_JSON).collect()
        assert check_packing(rows, [(r[0], text_of(r)) for r in AWKWARD], library) > 0.95

    def test_little_padding_on_the_table(self, spark, sf, library):
        docs = spark.read.parquet(f"{sf}/documents.parquet")
        rows = packing.pack_documents(docs.coalesce(1), queries.BYTE_JSON).collect()
        assert check_packing(rows, [(r.doc_id, r.text) for r in docs.collect()], library) > 0.97


def words(text):
    return [w for w in re.split(r"[ \t\n\x0b\f\r]+", text) if w]


def base(text):
    w = words(text)
    grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    n = Counter(grams)
    covered = {i + k for i, g in enumerate(grams) if n[g] > 1 for k in range(3)}
    lines = [x for x in text.split("\n") if words(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(covered)


class TestQualityRules:
    def test_base(self, awkward):
        got = quality_rules.judge(awkward).collect()
        want = Counter((r[0], *base(text_of(r))) for r in AWKWARD)
        assert Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in got) == want
        assert {r.base_failed for r in got if r.doc_id in (2, 3, 4, 5)} == {True}

    @settings(max_examples=25, deadline=None)
    @given(st.lists(st.lists(st.sampled_from("a b c d e \n".split(" ")), max_size=40).map(" ".join), min_size=1, max_size=12))
    def test_repeated_windows(self, spark, texts):
        docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
        got = {r.doc_id: r.n_repeat_words for r in quality_rules.base_counts(docs, "text").collect()}
        assert got == {i: base(t)[4] for i, t in enumerate(texts)}

    def test_frequent_lines_deplete(self, spark):
        own = " ".join(f"word{i}" for i in range(60))
        rows = [(i, f"Shared notice number {i}\n{own} {chr(97 + i // 26)}{chr(97 + i % 26)}" if i % 2 else "Shared notice number 7 " + " ".join(f"s{k}" for k in range(60)), "site") for i in range(40)]
        got = {r.doc_id: r.kept for r in quality_rules.judge(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
        assert [got[i] for i in range(40)] == [bool(i % 2) for i in range(40)]


def brute_components(texts, k=4, radius=4):
    fps = {}
    for doc, t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t))
        parts = [" ".join(w[i : i + k]) for i in range(len(w) - k + 1)] if len(w) >= k else [" ".join(w)] if w else []
        h = [xxhash.xxh64_intdigest(s.encode(), seed=42) for s in parts]
        fps[doc] = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0
    comp = {d: d for d in fps}
    changed = True
    while changed:
        changed = False
        for a in fps:
            for b in fps:
                if comp[a] > comp[b] and (fps[a] ^ fps[b]).bit_count() <= radius:
                    comp[a], changed = comp[b], True
    return fps, comp


class TestSimHash:
    def test_table(self, spark, sf):
        docs = spark.read.parquet(f"{sf}/documents.parquet")
        fps, comp = brute_components([(r.doc_id, r.text) for r in docs.collect()])
        for tile in (4096, 8):  # the second splits buckets into cells
            got = simhash.components(docs, tile=tile).collect()
            assert {r.doc_id: r.component_id for r in got} == comp
            assert {r.doc_id: r.fingerprint for r in got} == {d: f"{f:016x}" for d, f in fps.items()}

    def test_a_chain_of_links_is_one_component(self, spark):
        base_fp, rows = 0x123456789ABCDEF0, []
        for i in range(40):
            rows.append((base_fp,))
            base_fp ^= 0b1111 << (4 * (i % 15))
        nodes = spark.createDataFrame([(f - (1 << 64) if f >> 63 else f,) for (f,) in rows], "fp long").distinct()
        roots = simhash.star_components(simhash.close_links(nodes, 4, tile=4)).collect()
        assert len({r.root for r in roots}) == 1 and len(roots) == nodes.count()

    def test_tiles_against_all_pairs(self):
        rng = np.random.default_rng(2)
        fps = np.unique(np.concatenate([rng.integers(0, 2**63, 700, dtype=np.uint64), np.uint64(12345) ^ (np.uint64(1) << rng.integers(0, 40, 30).astype(np.uint64))]))
        fps = fps[np.argsort(np.bitwise_count(fps), kind="stable")]
        got = {(int(x), int(y)) for a, b in simhash.linked(fps, fps, 4) for x, y in zip(a, b, strict=True)}
        want = {(i, j) for i in range(len(fps)) for j in range(i + 1, len(fps)) if (int(fps[i]) ^ int(fps[j])).bit_count() <= 4}
        assert got == want
        assert len(simhash.forest(len(fps), simhash.linked(fps, fps, 4))) < len(fps)

    def test_blocks_lose_no_pair(self):
        for radius, blocks in ((4, 5), (4, 6), (2, 5)):
            masks = simhash.block_masks(radius, blocks)
            rng = np.random.default_rng(blocks)
            for _ in range(200):
                flip = sum(1 << int(b) for b in rng.choice(64, radius, replace=False))
                assert any(flip & (m & (1 << 64) - 1) == 0 for m in masks)

    def test_awkward(self, awkward):
        got = simhash.components(awkward).collect()
        assert len(got) == len(AWKWARD)
        by = {r.doc_id: r for r in got}
        assert by[2].fingerprint == by[3].fingerprint == by[4].fingerprint == "0" * 16
        assert by[2].component_id == by[3].component_id == by[4].component_id == 2
        assert by[1].component_id == by[7].component_id == 1
        kept = simhash.keep_one(awkward).collect()
        assert Counter(r.doc_id for r in kept)[7] == 0


class TestNearSets:
    def test_one_changed_word_in_a_short_text(self, spark):
        words_ = [f"w{i}" for i in range(60)]
        rows = [(1, " ".join(words_)), (2, " ".join([*words_[:30], "other", *words_[31:]])), (3, " ".join(w if i % 20 != 10 else "y" for i, w in enumerate(words_))), (4, " ".join(f"v{i}" for i in range(60)))]
        docs = spark.createDataFrame([*rows, (None, rows[0][1]), (9, None)], "doc_id long, text string")
        for tile in (4096, 1):
            kept = sorted(r.doc_id for r in simhash.keep_one(docs, tile=tile).collect())
            assert kept == [1, 3, 4, 9]

    def test_similarity(self):
        a, b = np.arange(100, dtype="<u8"), np.arange(20, 120, dtype="<u8")
        assert near_sets.similarity(a, b) == 80 / 120 and near_sets.similarity(a[:0], a[:0]) == 0

    def test_a_group_returns_a_forest(self, spark):
        base_words = [f"w{i}" for i in range(200)]
        rows = [(i, " ".join([*base_words[: 5 * i], f"new{i}", *base_words[5 * i + 1 :]])) for i in range(30)]
        docs = spark.createDataFrame(rows, "doc_id long, text string")
        nodes = near_sets.sketches(docs, 5).withColumnRenamed("doc_id", "node")
        links = near_sets.set_links(nodes, lambda wanted: near_sets.hashed_sets(docs.withColumnRenamed("doc_id", "node").join(wanted, "node", "left_semi"), 5))
        roots = simhash.star_components(links).collect()
        # one tree over all cells of a root; the links found are those of one cell here
        assert {r.root for r in roots} == {0} and len(roots) == 30 and links.count() == 29


class TestLineDedup:
    def test_ratio_by_host(self, spark):
        rows = [(i, f"Menu\nown line {i}\n\n Menu \nHome", "a") for i in range(20)] + [(100 + i, "Menu\nrest", "b") for i in range(4)] + [(200, None, "a"), (201, "", None)]
        got = {r.doc_id: r for r in line_dedup.drop_boilerplate(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
        assert got[3].text == "own line 3\n" and (got[3].n_lines, got[3].n_dropped) == (5, 3)
        assert got[100].text == "Menu\nrest" and got[100].n_dropped == 0
        assert got[200].text is None and got[201].text == ""

    def test_white_space_of_any_kind(self, spark):
        rows = [(i, f"own {i}\r\n\r\n\t\nmore {i}\r\n\tMenu \r" if i % 2 else f"own {i}\n\x0b\nMenu\f", "a") for i in range(20)]
        got = {r.doc_id: r for r in line_dedup.drop_boilerplate(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
        assert got[3].text == "own 3\r\n\r\n\t\nmore 3\r" and (got[3].n_lines, got[3].n_dropped) == (5, 1)
        assert got[4].text == "own 4\n\x0b" and got[4].n_dropped == 1

    def test_sql_on_white_space_and_repeats(self, spark):
        rows = [(i // 2, f"own {i}\r\n\r\nmore {i % 3}\r\n\tMenu 12 \r", "a" if i % 3 else None) for i in range(40)] + [(99, None, "a"), (None, "\r\n \t", "a")]
        docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
        con = duckdb.connect()
        con.register("documents", docs.toPandas().astype({"doc_id": "Int64"}))
        got = Counter(tuple(r) for r in line_dedup.drop_boilerplate(docs).select("doc_id", "text", "n_lines", "n_dropped").collect())
        assert got == Counter(con.execute(queries.oracle_sql()["op5_line_dedup"]).fetchall())
        judged = quality_rules.judge(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
        assert Counter(map(tuple, judged.collect())) == Counter(con.execute(queries.oracle_sql()["op3_quality_rules"]).fetchall())

    def test_awkward_rows_pass_unchanged(self, awkward):
        out = line_dedup.drop_boilerplate(awkward)
        assert out.columns == [*awkward.columns, "n_lines", "n_dropped"]
        assert Counter((r.doc_id, r.text) for r in out.collect()) == Counter((r[0], r[1]) for r in AWKWARD)

    def test_no_python_in_the_plan(self, spark, sf):
        docs = spark.read.parquet(f"{sf}/documents.parquet")
        for df in (line_dedup.drop_boilerplate(docs), quality_rules.judge(docs)):
            plan = df._jdf.queryExecution().executedPlan().toString()
            assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan and "Cartesian" not in plan


class TestRuleEnsemble:
    def test_held_out_accuracy(self, spark):
        sf = "/root/testdata/sf0.01"
        got = queries.op6_rule_ensemble(spark, sf).toPandas().set_index("doc_id")
        labels = duckdb.sql(f"select doc_id, quality from '{sf}/labels.parquet'").df().set_index("doc_id")
        both = got.join(labels, how="inner")
        assert all(got.loc[i].held_out == (zlib.crc32(str(i).encode()) % 3 == 1) for i in got.index)
        rest = both[both.held_out]
        assert len(rest) > 50 and (rest.predicted == rest.quality).mean() > 0.97

    def test_the_column_equals_the_numpy_score(self, spark, sf):
        docs = spark.read.parquet(f"{sf}/documents.parquet")
        found = rule_ensemble.train(docs, spark.read.parquet(f"{sf}/labels.parquet"))
        rows = rule_ensemble.statistics(docs).withColumn("score", found.column()).select("stats.*", "score").toPandas()
        assert np.allclose(found.score(rows[list(rule_ensemble.STATISTICS)].to_numpy(float)), rows["score"])
        assert all(len(r.terms) <= 3 for r, _ in found.rules)

    def test_columns_of_the_same_names_do_not_matter(self, spark, sf):
        docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
        found = rule_ensemble.train(docs, labels)
        plain = docs.select("doc_id", "text")
        named = plain
        for name in (*rule_ensemble.STATISTICS, "row", "stats", "words", "lines", "n", "id", "y", "most"):
            named = named.withColumn(name, F.lit("clash"))
        again = rule_ensemble.train(named, labels.withColumns({"id": F.lit(1), "y": F.lit(1)}))
        assert again == found
        assert sorted(rule_ensemble.score_documents(named, found).collect()) == sorted(rule_ensemble.score_documents(plain, found).collect())
        kept = rule_ensemble.keep_good(named, found)
        assert kept.columns == named.columns and kept.count() == rule_ensemble.keep_good(plain, found).count() > 0

    def test_ids_with_both_labels_teach_nothing(self, spark, sf):
        docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
        torn = labels.limit(5)
        more = labels.unionByName(torn.withColumn("quality", 1 - F.col("quality"))).unionByName(labels)
        assert rule_ensemble.train(docs, more) == rule_ensemble.train(docs, labels.join(torn, "doc_id", "left_anti"))

    def test_lasso_is_sparse(self):
        rng = np.random.default_rng(0)
        a = (rng.random((400, 30)) < 0.5).astype(float)
        y = (a[:, 0] + a[:, 1] > 1).astype(float)
        _, w = rule_ensemble.lasso_logistic(a, y, 0.02)
        assert {0, 1} <= set(np.flatnonzero(w)) and (w == 0).sum() > 15

    def test_awkward(self, spark, awkward):
        labels = spark.createDataFrame([(1, 1), (2, None)], "doc_id long, quality int")
        got = rule_ensemble.score_documents(awkward, rule_ensemble.train(awkward, labels)).collect()
        assert len(got) == len(AWKWARD) and all(0 <= r.score <= 1 for r in got)


class TestTopK:
    @settings(max_examples=40, deadline=None)
    @given(st.integers(1, 90), st.integers(1, 6), st.integers(1, 7), st.integers(0, 10**6))
    def test_block_against_brute_force(self, n, width, k, seed):
        rng = np.random.default_rng(seed)
        x = rng.integers(-3, 4, (n, width)).astype(float)
        own = np.arange(min(9, n))
        own[::3] = -1
        q, c, s = exact_topk.block_top_k(x[:9], own, x, k)
        for i in range(min(9, n)):
            want = sorted((-(x[i] @ x[j]), j) for j in range(n) if j != own[i])[:k]
            assert [(-v, j) for v, j in zip(s[q == i], c[q == i], strict=True)] == want

    def test_bounds_hold_at_every_depth(self):
        rng = np.random.default_rng(5)
        block, queries_ = rng.integers(-20, 20, (80, 7)).astype(float), rng.integers(-20, 20, (9, 7)).astype(float)
        lists, exact = np.sort(block, 0), queries_ @ block.T
        for depth in (1, 20, 60, 80):
            low, high = exact_topk.bounds(queries_, block, lists[80 - depth], lists[depth - 1])
            assert (low <= exact).all() and (exact <= high).all()

    def test_awkward_vectors(self, spark):
        rows = [(0, [0.5, 0.5]), (50, [0.25, None]), (1, [float("nan"), 1.0]), (2, [float("inf"), 1.0]), (3, None), (4, []), (5, [0.5, 0.25]), (6, [0.5, 0.25]), (7, [-0.001, 0.0]), (7, [-0.001, 0.0]), (100, [0.5])]
        vectors = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("score", F.lit(1))
        got = exact_topk.top_k(vectors, F.col("vec_id") % 50 == 0).orderBy("query_id", "rank").collect()
        assert [tuple(r) for r in got] == [(0, 1, 5, 24576), (0, 2, 6, 24576), (0, 3, 100, 16384), (0, 4, 7, -128), (0, 5, 7, -128), (100, 1, 0, 16384), (100, 2, 5, 16384), (100, 3, 6, 16384), (100, 4, 7, -128), (100, 5, 7, -128)]

    def test_blocks_don_t_change_the_result(self, spark, sf):
        e = spark.read.parquet(f"{sf}/embeddings.parquet")
        a = exact_topk.top_k(e, F.col("vec_id") % 50 == 0)
        b = exact_topk.top_k(e, F.col("vec_id") % 50 == 0, query_block=3, candidate_block=70)
        assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty() and a.count() == 50


PII_TEXT = st.lists(st.sampled_from(["a", "@", "a.b", "-", ".", "1", "23", "255", "4111 1111-1111 1111", "4111111111111111", " ", "+", "+1 (5)", "mail.com", "x@y.z", "_", "é", "0", "192.168.0.1", "token = \"", "0af93bc1", "iban: ", "https://"]), max_size=14).map("".join)


class TestPii:
    @settings(max_examples=800, deadline=None)
    @given(PII_TEXT)
    def test_base_spans_equal_the_patterns(self, text):
        want = {"email": [m.span() for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]}
        want["ip"] = [m.span() for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(x) <= 255 for x in m.group().split("."))]
        digits = lambda m: "".join(c for c in m.group() if c.isdigit())
        want["card"] = [m.span() for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text) if 16 <= len(digits(m)) <= 19 and pii.luhn(digits(m))]
        want["phone"] = [m.span() for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 8 <= len(digits(m)) <= 15]
        got = pii.find_spans(text)
        for k in pii.BASE:
            assert [(a, b) for kind, a, b in got if kind == k] == want[k]

    def test_added_kinds(self):
        text = 'see https://x.example.org/a?b=1. token = "24be64439e3e49cf" IBAN: GB82 WEST 1234 5698 7654 32, Account no: 12345678'
        found = {k: text[a:b] for k, a, b in pii.find_spans(text)}
        assert found["url"] == "https://x.example.org/a?b=1" and found["secret"] == "24be64439e3e49cf" and found["account"] in ("GB82 WEST 1234 5698 7654 32", "12345678")
        assert pii.bank_account("GB82 WEST 1234 5698 7654 32") and not pii.bank_account("GB83 WEST 1234 5698 7654 32")
        clean = pii.redact(text, pii.find_spans(text))
        assert "24be64439e3e49cf" not in clean and "<URL>" in clean and not pii.find_spans(clean)

    HOSTILE = ["1", "a@", "a.", "1.", "+1(", "http://", "https://a.", "mailto:", "mailto:a@", "token=", "token= ", "secret:password", "api_key=a1", "iban", "account no ", "4111-", "ftp://x.y/", "a@b.c@", "1 2-3", "password\":"]

    @pytest.mark.parametrize("unit", HOSTILE)
    def test_a_hostile_run_takes_linear_time(self, unit):
        def took(n):
            text = unit * n + " end"
            began = time.process_time()
            pii.find_spans(text)
            return time.process_time() - began

        took(100)
        assert min(took(32_000) for _ in range(2)) < 10 * min(took(8_000) for _ in range(2)) + 0.2

    @settings(max_examples=300, deadline=None)
    @given(st.lists(st.sampled_from(["token", "=", ":", " ", "secret", "api_key", "pass", "password", "abc", "x1y2", "99", "\"", ".", "abcdefgh", "=="]), max_size=14).map("".join))
    def test_secrets_equal_one_pattern(self, text):
        """Read by one pattern at every cue from left to right, past what was accepted."""
        whole = re.compile(r"(?:\"|')?[ \t]{0,8}[=:][ \t]{0,8}(?:\"|')?([A-Za-z0-9_+/.~=-]{8,})")
        cues = sorted({(m.start() + len(w), m.start()) for w in pii.SECRET_CUES for m in re.finditer(f"(?={re.escape(w)})", text.lower())})
        want, done = [], 0
        for end, at in cues:
            m = whole.match(text, end) if at >= done and not (at and text[at - 1].isalnum()) else None
            value = m.group(1).rstrip(".=") if m else ""
            if sum(c.isdigit() for c in value) >= 2:
                done = m.end(1)
                want.append((m.start(1), m.start(1) + len(value)))
        assert [(a, b) for k, a, b in pii.find_spans(text) if k == "secret"] == want

    def test_cues_in_any_case(self):
        for cue in ("Token", "TOKEN", "toKen", "Api_Key"):
            assert pii.find_spans(f"{cue}: ab12cd34") == [("secret", len(cue) + 2, len(cue) + 10)]
        assert pii.find_spans("İ token: ab12cd34 é") == [("secret", 9, 17)]

    def test_awkward(self, awkward):
        got = pii.digests(awkward).collect()
        assert len(got) == len(AWKWARD) and {r.base_sha256 for r in got} == {hashlib.sha256(b"").hexdigest()}
        assert Counter((r.doc_id, r.text) for r in pii.redact_documents(awkward).collect()) == Counter((r[0], r[1]) for r in AWKWARD)


class TestTokenCounts:
    @settings(max_examples=300, deadline=None)
    @given(TEXTS)
    def test_counts_equal_the_library(self, text):
        library = library_of(queries.WORD_JSON)
        assert token_counts.worker_counter(queries.WORD_JSON).counts([text]) == [len(library.encode(text, add_special_tokens=False).ids)]

    @settings(max_examples=100, deadline=None)
    @given(TEXTS)
    def test_other_files_equal_their_libraries(self, text):
        path = P.path("piece_bpe_32k.model")
        want = len(library_of(path).encode(text))
        assert token_counts.worker_counter(path).counts([text, ""]) == [want, 0]
        library = library_of(queries.BYTE_JSON)
        assert token_counts.worker_counter(queries.BYTE_JSON).counts([text]) == [len(library.encode(text, add_special_tokens=False).ids)]

    def test_only_the_word_vocabulary_is_counted_by_words(self):
        kinds = {p: type(token_counts.worker_counter(p)).__name__ for p in (queries.WORD_JSON, queries.BYTE_JSON)}
        assert kinds == {queries.WORD_JSON: "WordCounter", queries.BYTE_JSON: "TextCounter"}

    def test_batches_are_balanced_by_bytes(self):
        parts = list(token_counts.byte_balanced(["a" * n for n in (5, 5, 5, 40, 1, 1)], 11))
        assert [len("".join(p)) for p in parts] == [10, 5, 40, 2]

    def test_documents(self, awkward):
        library = Tokenizer.from_file(queries.WORD_JSON)
        want = Counter((r[0], len(text_of(r).encode()), n := len(library.encode(text_of(r), add_special_tokens=False).ids), n > 2048) for r in AWKWARD)
        assert Counter(map(tuple, token_counts.token_counts(awkward, queries.WORD_JSON).collect())) == want


class TestTokenFiles:
    @settings(max_examples=200, deadline=None)
    @given(st.lists(st.lists(st.one_of(st.integers(0, 300), st.integers(0, 2**32 - 1)), max_size=30), min_size=1, max_size=6))
    def test_coding_round_trip(self, docs):
        sizes = np.array([len(d) for d in docs])
        control, control_ends, data, data_ends = token_files.code_many(np.array(sum(docs, []), "<u4"), sizes)
        assert control_ends[-1] == len(control) and data_ends[-1] == len(data)
        got = token_files.decode(np.frombuffer(control, np.uint8), np.frombuffer(data, np.uint8), sizes)
        assert got.tolist() == sum(docs, [])
        one = token_files.code(np.array(docs[0], "<u4"))
        assert one == (control[: control_ends[0]], data[: data_ends[0]])

    def test_documents(self, spark, awkward, library):
        path = token_files.write_token_files(awkward, queries.BYTE_JSON, end_id=0, shards=3)
        got = sorted(token_files.read_digests(spark, path).collect(), key=lambda r: r.start)
        assert [r.doc_id for r in got] == sorted((r[0] for r in AWKWARD), key=lambda d: (d is not None, d))
        at, want = 0, {}
        for r in AWKWARD:
            ids = np.array([*library.encode(text_of(r), add_special_tokens=False).ids, 0], "<u4")
            want[r[0]] = (len(ids), zlib.crc32(ids.tobytes()))
        for r in got:
            assert r.start == at and (r.n_tokens, r.ids_crc32) == want[r.doc_id]
            at += r.n_tokens
        decoded = {r.doc_id: r.ids for r in token_files.decode_token_files(spark, path).collect()}
        assert decoded[3] == [0] and len(decoded[6]) == want[6][0]
        ranks = token_files.vocabulary(spark, path)
        assert len(set(ranks.tolist())) == len(ranks)

    def test_text_ids(self, spark, awkward):
        named = awkward.withColumn("doc_id", F.concat(F.lit("d"), F.col("doc_id").cast("string")))
        path = token_files.write_token_files(named, queries.BYTE_JSON, shards=2)
        got = sorted(token_files.read_digests(spark, path).collect(), key=lambda r: r.start)
        assert [r.doc_id for r in got][1:] == sorted(f"d{r[0]}" for r in AWKWARD if r[0] is not None)


def test_empty_tables(spark, empty):
    labels = spark.createDataFrame([], "doc_id long, quality int")
    vectors = spark.createDataFrame([], "vec_id long, embedding array<float>")
    frames = [
        bpe.round_trip_digests(empty, queries.BYTE_RANKS, P.PATTERN),
        packing.with_crc(packing.pack_documents(empty, queries.BYTE_JSON)),
        quality_rules.judge(empty),
        simhash.components(empty),
        simhash.keep_one(empty),
        line_dedup.drop_boilerplate(empty),
        rule_ensemble.score_documents(empty, rule_ensemble.train(empty, labels)),
        exact_topk.top_k(vectors, F.col("vec_id") % 50 == 0),
        pii.digests(empty),
        token_counts.token_counts(empty, queries.WORD_JSON),
        token_files.read_digests(spark, token_files.write_token_files(empty, queries.BYTE_JSON)),
    ]
    for f in frames:
        assert f.collect() == []
