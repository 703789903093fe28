from pyspark.sql import functions as F

from askcheck.functions.taxonomy import SUBCATEGORIES, TAXONOMY, TYPE_OF
from askcheck.plans import generation, grammar
from askcheck.sources import tables, transcripts


def test_thirteen_labels():
    assert len(SUBCATEGORIES) == len(set(SUBCATEGORIES)) == 13
    kinds = [t[0] for t in TAXONOMY]
    assert (kinds.count("ambiguous"), kinds.count("unanswerable"), kinds.count("answerable")) == (7, 4, 2)
    assert len({t[1] for t in TAXONOMY if t[0] != "answerable"}) == 8


def test_column_words():
    assert tables.column_tokens("l_extendedprice") == ["extended", "price"]
    assert tables.column_tokens("o_orderstatus") == ["order", "status"]
    assert tables.column_tokens("doc_id") == ["doc", "id"]


def test_grammar_is_read_back():
    for db, names in tables.DATABASES.items():
        for sub in SUBCATEGORIES:
            for t in names:
                for variant in range(3):
                    filled = grammar.fill(sub, db, t, variant)
                    if filled is None:
                        continue
                    for style in ("formal", "colloquial", "interrogative"):
                        nl = grammar.restyle(filled.nl, style)
                        seen = grammar.understand(nl, db)
                        assert seen is not None and seen.subcategory == sub, (nl, seen)
                        assert seen.readings == filled.readings and grammar.style_of(nl) == style
                    assert (len(filled.readings) == 2) == (TYPE_OF[sub] == "ambiguous")
                    assert bool(filled.feedback) == (TYPE_OF[sub] == "unanswerable")


def test_unlinked_tables():
    assert grammar.unlinked_pairs("eval_items") == [("benchmark", "documents")]
    assert grammar.unlinked_pairs("retail_full") == []


def test_schema_context_and_links(spark, sf):
    context = tables.schema_context(spark, sf, "geo").collect()
    assert len(context) == 4 and all(len(r.samples) == 5 for r in context)
    q = spark.createDataFrame([("q1", "geo", "What is the number of nations per region?")], "obj_id string, db_id string, nl string")
    found = {(r.table_name, r.col_name) for r in generation.link_schema(q, tables.schema_catalog(spark, sf)).collect()}
    assert ("nation", "n_nationkey") in found and ("region", "r_name") not in found


def test_difficulty_and_types(spark):
    rows = [("SELECT 1",), ("SELECT a, count(*) FROM t JOIN u ON a = b GROUP BY a",), ("WITH x AS (SELECT 1) SELECT a, sum(b) OVER (PARTITION BY c) FROM t JOIN u ON a = b WHERE a IN (SELECT b FROM c)",), (None,)]
    got = [r[0] for r in spark.createDataFrame(rows, "sql string").select(generation.sqlmask.difficulty("sql")).collect()]
    assert got == ["simple", "moderate", "highly_complex", None]


def test_transcripts_and_formats(spark, tmp_path):
    (tmp_path / "in").mkdir()
    (tmp_path / "in" / "a.jsonl").write_text('{"conv_id": "c1", "turns": [{"role": "system", "kind": "sql", "text": "SELECT 1"}, {"role": "user", "kind": "reply", "text": "ok", "relevancy": "relevant", "forced": true}]}\n')
    spark.dataSource.register(transcripts.TranscriptSource)
    by_source = spark.read.format("transcripts").load(str(tmp_path / "in")).orderBy("turn").collect()
    assert [tuple(r) for r in by_source] == [tuple(r) for r in transcripts.read_transcripts(spark, str(tmp_path / "in")).orderBy("turn").collect()]
    df = spark.range(4).select(F.col("id"), F.lit("geo").alias("db_id"))
    transcripts.write_questions(df, str(tmp_path / "q"))
    assert spark.read.parquet(str(tmp_path / "q")).filter("db_id = 'geo'").count() == 4
    transcripts.export_benchmark(df, str(tmp_path / "j"))
    (tmp_path / "j" / "bad.json").write_text("not json\n")
    got = transcripts.read_benchmark(spark, str(tmp_path / "j"), "id long, db_id string").cache()
    assert got.count() == 5 and got.filter("_corrupt is not null").count() == 1
    transcripts.write_report(df, str(tmp_path / "r"))
    assert transcripts.read_any(spark, str(tmp_path / "r"), "csv", header=True).count() == 4
    df.write.orc(str(tmp_path / "o"))
    assert transcripts.read_any(spark, str(tmp_path / "o"), "orc").count() == 4
