"""The corpus pipeline: every stage and run() against plain Python."""

from collections import Counter, defaultdict

import corpus_pipeline
import public_tokenizers as P
import pytest
from askcheck.llm import pii, rule_ensemble, simhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

SPACE = " \t\n\x0b\f\r"


def brute_lines(rows, ratio=0.1, least=5):
    pages, on = Counter(r.source for r in rows), Counter()
    for r in rows:
        on.update({(r.source, x.strip(SPACE)) for x in (r.text or "").split("\n") if x.strip(SPACE)})
    bad = {k for k, n in on.items() if n >= least and n / pages[k[0]] > ratio}
    return {r.doc_id: None if r.text is None else "\n".join(x for x in r.text.split("\n") if (r.source, x.strip(SPACE)) not in bad) for r in rows}


def brute_groups(texts, shingle=5, radius=4, threshold=0.8):
    """The smallest id of each group of links by fingerprint or by the similarity of whole sets."""
    ids = sorted(texts)
    sets = {i: set(simhash.shingle_hashes(texts[i] or "", shingle).tolist()) for i in ids}
    fps = {i: simhash.fingerprint(texts[i] or "", shingle) for i in ids}
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for n, a in enumerate(ids):
        for b in ids[:n]:
            if (fps[a] ^ fps[b]).bit_count() <= radius or len(sets[a] & sets[b]) >= threshold * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {find(i) for i in ids}


@pytest.fixture(scope="module")
def brute(spark, sf):
    """The texts of each stage by plain Python, on the scores of the classifier."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = rule_ensemble.train(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    good = {r.doc_id for r in rule_ensemble.score_documents(docs, model).collect() if r.predicted}
    kept = [r for r in docs.collect() if r.doc_id in good]
    lines = brute_lines(kept)
    one = {d: lines[d] for d in brute_groups(lines)}
    return {"quality_classifier": {r.doc_id: r.text for r in kept}, "line_dedup": lines, "near_dedup": one, "personal_data": {d: pii.redact(t, pii.find_spans(t)) for d, t in one.items()}}


def test_stages_against_plain_python(spark, sf, brute):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [name for name, _ in corpus_pipeline.STAGES] == ["quality_classifier", "line_dedup", "near_dedup", "personal_data", "pack"]
    good = {r.doc_id for r in spark.read.parquet(f"{sf}/labels.parquet").filter("quality = 1").collect()}
    held = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        held = stage(spark, held, sf)
        rows = held.collect()
        held = spark.createDataFrame(rows, held.schema)
        assert held.schema.names == docs.schema.names and {r.doc_id: r.text for r in rows} == brute[name], name
        assert all(r.n_chars == len(r.text) for r in rows) or name == "quality_classifier"
    assert len(good - set(brute["quality_classifier"])) <= 0.02 * len(good)
    assert not any(pii.find_spans(t) for t in brute["personal_data"].values())


def test_run_holds_the_ids_of_what_stays(spark, sf, brute):
    pieces = defaultdict(dict)
    for r in corpus_pipeline.run(spark, sf).collect():
        pieces[r.doc_id][r.start] = r.ids
    library = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    want = {d: library.encode(t, add_special_tokens=False).ids + [1] for d, t in brute["personal_data"].items()}
    assert {d: sum((p[s] for s in sorted(p)), []) for d, p in pieces.items()} == want


def test_awkward_documents(spark, sf):
    long = "many words stand here in one line " * 2000
    rows = [(1, None, "en", "a", None), (2, "", None, None, 0), (3, "x", "en", "a", 1), (3, "x", "en", "a", 1), (3, "y", "en", "a", 1), (4, long, "en", "a", 5), (None, long + "end", "en", None, 5), (None, "z a@b.cd", None, None, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumn("score", F.lit("clash"))
    stages = dict(corpus_pipeline.STAGES)
    for name in ("quality_classifier", "line_dedup", "personal_data"):
        got = stages[name](spark, docs, sf)
        assert got.columns == docs.columns[:5] and (name == "quality_classifier" or got.count() == len(rows))
    stay = Counter((r.doc_id, (r.text or "")[:3]) for r in stages["near_dedup"](spark, docs, sf).collect())
    # texts without words are one group, so are the long ones; equal rows leave one
    assert stay == Counter([(1, ""), (3, "x"), (3, "y"), (4, "man"), (None, "z a")])
    clean = {r.text for r in stages["personal_data"](spark, docs, sf).collect()}
    assert "z <EMAIL>" in clean and None in clean
    packed = stages["pack"](spark, docs, sf).collect()
    assert Counter(r.doc_id for r in packed if r.start == 0) == Counter(r[0] for r in rows)
    empty = docs.limit(0)
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, sf).collect() == [], name
