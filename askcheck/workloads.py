"""The experiment workloads over the given tables, and the stand-in benchmark end to end."""

from __future__ import annotations

import uuid
from collections import Counter
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import sqlmask
from .functions.taxonomy import DIFFICULTIES, STYLES, SUBCATEGORIES, TAXONOMY, taxonomy
from .plans import agents as A
from .plans import generation, measures, published, simulation, validation
from .plans.council import Briefing, majority, plurality
from .plans.equivalence import ResultCache, equivalent, strict_equal, union_all
from .plans.execsql import probe
from .plans.members import council
from .registry import Registry
from .sources.tables import DATABASES, FOREIGN_KEYS, TABLES, column_tokens, register_views, schema_catalog, schema_texts, table
from .streaming.measures import shared_dir

ops = Registry()
T = table


def values(rows, names: str) -> str:
    """A VALUES list for another engine."""
    show = lambda v: "NULL" if v is None else "'" + str(v).replace("'", "''") + "'" if isinstance(v, str) else str(v)
    return "(VALUES " + ", ".join("(" + ", ".join(show(v) for v in r) + ")" for r in rows) + f") AS v({names})"


def stored(spark: SparkSession) -> Callable[[DataFrame, str], DataFrame]:
    """Materialise a table in the shared folder and read it back: a restart point without lineage."""
    base = f"{shared_dir(spark)}/run-{uuid.uuid4().hex}"

    def store(df: DataFrame, name: str) -> DataFrame:
        df.write.mode("overwrite").parquet(f"{base}/{name}")
        return spark.read.schema(df.schema).parquet(f"{base}/{name}")

    return store


# ---- generation and schema


_GENERATORS = ("gen_a", "gen_b", "gen_c")


@ops.add("SELECT * FROM (VALUES ('ambiguous', 5, 7), ('unanswerable', 3, 4), ('answerable', 1, 2)) AS v(qtype, categories, subcategories)")
def w_taxonomy(spark, sf):
    """Categories and subcategories of each type: eight problem categories in all, 13 subcategories."""
    return taxonomy(spark).groupBy("qtype").agg(F.countDistinct("category").cast("int").alias("categories"), F.countDistinct("subcategory").cast("int").alias("subcategories"))


_SAMPLED = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id"}
#: Keys as text, for both engines; lines and turns have keys of several columns.
_SAMPLE_KEYS = {t: f"CAST({c} AS {{s}})" for t, c in _SAMPLED.items()} | {
    "lineitem": "concat(CAST(l_orderkey AS {s}), '|', CAST(l_linenumber AS {s}), '|', CAST(l_partkey AS {s}), '|', CAST(l_suppkey AS {s}))",
    "conversations": "concat(CAST(conv_id AS {s}), '|', CAST(turn AS {s}))",
}


@ops.add(" UNION ALL ".join(f"SELECT '{t}' AS table_name, k FROM (SELECT {c.format(s='VARCHAR')} AS k FROM {t} ORDER BY md5(concat('7:', k)), k LIMIT 5)" for t, c in _SAMPLE_KEYS.items()))
def w_schema_context(spark, sf):
    """Five sample rows of each table, by the order of a hash of the key: a top-k in each task and a merge."""
    one = lambda t, c: T(spark, sf, t).select(F.expr(c.format(s="STRING")).alias("k")).orderBy(F.md5(F.concat(F.lit("7:"), "k")), "k").limit(5).select(F.lit(t).alias("table_name"), "k")
    return union_all([one(t, c) for t, c in _SAMPLE_KEYS.items()])


_SEED_KEYS = {t: f"CAST({c} AS {{s}})" for t, c in _SAMPLED.items()} | {t: " || '|' || ".join(f"CAST({c} AS {{s}})" for c in cs) for t, cs in (("lineitem", ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")), ("conversations", ("conv_id", "turn")))}
_SAMPLES = 3
_SEED_DUCK = " UNION ALL ".join(f"(SELECT '{t}' AS t, k FROM (SELECT {c.format(s='VARCHAR')} AS k FROM {t}) WHERE k IS NOT NULL ORDER BY md5(concat('7:{t}:', k)), k LIMIT {_SAMPLES})" for t, c in _SEED_KEYS.items())


@ops.add(f"""SELECT g AS generator, s AS subcategory, y AS style, d AS difficulty_asked, b AS db_id, n::INTEGER AS sample_no, seed_row FROM (SELECT unnest({list(_GENERATORS)}) AS g), (SELECT unnest({list(SUBCATEGORIES)}) AS s),
 (SELECT unnest({list(STYLES)}) AS y), (SELECT unnest({list(DIFFICULTIES)}) AS d), (SELECT db_id AS b, concat(t, ':', k) AS seed_row, row_number() OVER (PARTITION BY db_id ORDER BY md5(concat('7:', t, ':', k)), t, k) AS n
 FROM {values([(d, t) for d, ts in DATABASES.items() for t in ts], 'db_id, t')} JOIN ({_SEED_DUCK}) USING (t)) WHERE n <= {_SAMPLES}""")
def w_grid(spark, sf):
    """The grid with the row that each sample of a database starts from: its rows of smallest hash, over all its tables. A database without rows has nothing to ask about."""
    drawn = F.md5(F.concat(F.lit("7:"), "t", F.lit(":"), "k"))
    one = lambda t, c: T(spark, sf, t).select(F.lit(t).alias("t"), F.expr(c.format(s="STRING")).alias("k")).filter("k is not null").orderBy(drawn, "k").limit(_SAMPLES)
    held = spark.createDataFrame([(d, t) for d, ts in DATABASES.items() for t in ts], "db_id string, t string")
    # the first rows of a database are among the first rows of its tables
    ranked = held.join(union_all([one(t, c) for t, c in _SEED_KEYS.items()]), "t").withColumn("sample_no", F.row_number().over(Window.partitionBy("db_id").orderBy(drawn, "t", "k")))
    seeds = ranked.select("db_id", "sample_no", F.concat("t", F.lit(":"), "k").alias("seed_row"))
    grid = generation.generation_grid(spark, list(_GENERATORS), samples=_SAMPLES)
    return grid.join(F.broadcast(seeds), ["db_id", "sample_no"]).select(*grid.columns, "seed_row")


_COLUMN_WORDS = [
    ("region", ("r_regionkey", "r_name")), ("nation", ("n_nationkey", "n_name", "n_regionkey")), ("customer", ("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment")),
    ("supplier", ("s_suppkey", "s_name", "s_nationkey", "s_acctbal")), ("part", ("p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice")),
    ("orders", ("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")),
    ("lineitem", ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")),
    ("events", ("event_id", "ts", "user_id", "event_type", "value", "props")), ("documents", ("doc_id", "text", "lang", "source", "n_chars")), ("embeddings", ("vec_id", "embedding", "label")),
    ("pages", ("page_id", "url", "html")), ("benchmark", ("item_id", "text")), ("labels", ("doc_id", "quality", "toxic")), ("conversations", ("conv_id", "turn", "role", "text")),
]
_WORDS = values([(t, c, w) for t, cs in _COLUMN_WORDS for c in cs for w in sorted(set(column_tokens(c)))], "t, c, w")
_KEYS = ("key", "id")
#: A word of a column's name and how many values the column holds.
_HELD_WORDS = f"""(SELECT t, c, w, n FROM {_WORDS} JOIN ({' UNION ALL '.join(f"SELECT '{t}' AS t, '{c}' AS c, count({c}) AS n FROM {t}" for t, cs in _COLUMN_WORDS for c in cs)}) USING (t, c) WHERE n > 0 AND w NOT IN ('key', 'id'))"""


def _held_words(spark, sf) -> DataFrame:
    """table_name, col_name, token, n_values: the words of columns' names with the number of values in each column; a column without any gives no reading.

    One pass over each table, and only over columns that share a word with another.
    """
    frames = {t: T(spark, sf, t) for t in TABLES}
    words = {(t, c): set(column_tokens(c)) - set(_KEYS) for t, df in frames.items() for c in df.columns}
    seen = Counter(w for ws in words.values() for w in ws)
    parts = []
    for t, df in frames.items():
        cells = [(c, sorted(w for w in ws if seen[w] > 1)) for (x, c), ws in words.items() if x == t]
        rows = F.array(*(F.struct(F.lit(c).alias("col_name"), F.lit(w).alias("token"), F.count(c).alias("n_values")) for c, ws in cells for w in ws))
        if any(ws for _, ws in cells):
            parts.append(df.agg(rows.alias("r")).select(F.lit(t).alias("table_name"), F.explode("r").alias("r")).select("table_name", "r.*"))
    return union_all(parts).filter("n_values > 0")


@ops.add(f"""SELECT a.t AS table_a, a.c AS col_a, b.t AS table_b, b.c AS col_b, a.w AS token, a.n AS values_a, b.n AS values_b FROM {_HELD_WORDS} a JOIN {_HELD_WORDS} b ON a.w = b.w AND (a.t, a.c) < (b.t, b.c)""")
def w_lexical_overlap_pairs(spark, sf):
    """Columns whose names share a word and that hold values: candidates for two readings of it, with the number of values behind each."""
    words = _held_words(spark, sf)
    side = lambda s: words.select(F.col("table_name").alias(f"table_{s}"), F.col("col_name").alias(f"col_{s}"), "token", F.col("n_values").alias(f"values_{s}"))
    return side("a").join(side("b"), "token").filter(F.struct("table_a", "col_a") < F.struct("table_b", "col_b")).select("table_a", "col_a", "table_b", "col_b", "token", "values_a", "values_b")


_HELD_TABLES = f"(SELECT t, w, sum(n)::BIGINT AS n FROM {_HELD_WORDS} GROUP BY t, w)"


@ops.add(f"SELECT a.t AS table_a, b.t AS table_b, a.w AS token, a.n AS values_a, b.n AS values_b FROM {_HELD_TABLES} a JOIN {_HELD_TABLES} b ON a.w = b.w AND a.t < b.t")
def w_entity_pairs(spark, sf):
    """Tables that carry an attribute with the same word, with the number of values behind it."""
    words = _held_words(spark, sf).groupBy("table_name", "token").agg(F.sum("n_values").alias("n"))
    side = lambda s: words.select(F.col("table_name").alias(f"table_{s}"), "token", F.col("n").alias(f"values_{s}"))
    return side("a").join(side("b"), "token").filter("table_a < table_b").select("table_a", "table_b", "token", "values_a", "values_b")


#: The declared keys along which at least one row finds the row it points to, both ways.
_EDGES = "(" + " UNION ALL ".join(f"SELECT '{x}' AS a, '{y}' AS b WHERE EXISTS (SELECT 1 FROM {t} WHERE {c} IN (SELECT {fc} FROM {f}))" for t, c, f, fc in FOREIGN_KEYS for x, y in ((t, f), (f, t))) + ")"
_ALL = values([(t,) for t in TABLES], "t")


@ops.add(f"""WITH RECURSIVE e AS (SELECT * FROM {_EDGES}), reach AS (SELECT t AS a, t AS b FROM {_ALL} UNION SELECT reach.a, e.b FROM reach JOIN e ON reach.b = e.a)
 SELECT x.t AS table_a, y.t AS table_b FROM {_ALL.replace(' AS v(t)', ' AS x(t)')} , {_ALL.replace(' AS v(t)', ' AS y(t)')} WHERE x.t < y.t AND NOT EXISTS (SELECT 1 FROM reach WHERE a = x.t AND b = y.t)""")
def w_missing_join_paths(spark, sf):
    """Pairs of tables without a path of keys along which rows meet: closure by doubling of a catalog-sized relation, at most log2 of its tables rounds.

    A declared key counts if any row finds the row it points to; where none does, a join along it is empty.
    """
    met = lambda t, c, f, fc: T(spark, sf, t).join(T(spark, sf, f).select(F.col(fc).alias("_k")), F.col(c) == F.col("_k"), "left_semi").agg(F.count(F.lit(1)).alias("n")).select(F.lit(t).alias("x"), F.lit(f).alias("f"), "n")
    edges = [(r.x, r.f) for r in union_all([met(*key) for key in FOREIGN_KEYS]).filter("n > 0").collect()]  # one row for each declared key
    t = spark.createDataFrame([(x,) for x in TABLES], "a string")
    reach = spark.createDataFrame([p for x, f in edges for p in ((x, f), (f, x))], "a string, b string").union(t.select("a", "a")).distinct()
    for _ in range(len(TABLES).bit_length()):
        reach = reach.join(reach.select(F.col("a").alias("b"), F.col("b").alias("c")), "b").select("a", F.col("c").alias("b")).distinct()
    pairs = t.select(F.col("a").alias("table_a")).crossJoin(F.broadcast(t.select(F.col("a").alias("table_b")))).filter("table_a < table_b")
    return pairs.join(reach, (F.col("table_a") == F.col("a")) & (F.col("table_b") == F.col("b")), "left_anti")


@ops.add(f"""SELECT db_id, count(*)::BIGINT AS n FROM {values([(d, t) for d, ts in DATABASES.items() for t in ts], 'db_id, t')} JOIN information_schema.columns c ON c.table_name = v.t GROUP BY db_id""")
def w_schema_catalog(spark, sf):
    return schema_catalog(spark, sf).groupBy("db_id").agg(F.count(F.lit(1)).alias("n"))


# ---- readings


@ops.add("SELECT threshold, (SELECT count(*) FROM orders WHERE o_totalprice > threshold) AS n FROM (VALUES (100000), (200000), (300000)) AS t(threshold)")
def w_vagueness_readings(spark, sf):
    """One scan for all cut-offs."""
    cuts = (100000, 200000, 300000)
    row = T(spark, sf, "orders").agg(*(F.count_if(F.col("o_totalprice") > c).alias(str(c)) for c in cuts))
    return row.select(F.explode(F.array(*(F.struct(F.lit(c).alias("threshold"), F.col(f"`{c}`").alias("n")) for c in cuts))).alias("r")).select("r.threshold", "r.n")


_CENTS = "CAST(round(o_totalprice*100) AS BIGINT)"


@ops.add(f"SELECT 'collective' AS reading, NULL AS grp, sum({_CENTS})::BIGINT AS total FROM orders UNION ALL SELECT 'distributive', o_orderpriority, sum({_CENTS})::BIGINT FROM orders GROUP BY o_orderpriority")
def w_scope_readings(spark, sf):
    """Both readings in one pass by grouping sets."""
    g = T(spark, sf, "orders").rollup("o_orderpriority").agg(F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("total"), F.grouping("o_orderpriority").alias("whole"))
    return g.select(F.when(F.col("whole") == 1, "collective").otherwise("distributive").alias("reading"), F.col("o_orderpriority").alias("grp"), "total")


@ops.add("""SELECT 'both' AS reading, 'customer' AS kind, c_custkey AS key FROM customer WHERE c_nationkey = 7 UNION ALL SELECT 'both', 'supplier', s_suppkey FROM supplier WHERE s_nationkey = 7
 UNION ALL SELECT 'last', 'customer', c_custkey FROM customer WHERE c_nationkey = 7 UNION ALL SELECT 'last', 'supplier', s_suppkey FROM supplier""")
def w_attachment_readings(spark, sf):
    c = T(spark, sf, "customer").filter("c_nationkey = 7").select(F.lit("customer").alias("kind"), F.col("c_custkey").alias("key"))
    s = T(spark, sf, "supplier").select(F.lit("supplier").alias("kind"), F.col("s_suppkey").alias("key"), "s_nationkey")
    one = c.withColumn("reading", F.explode(F.array(F.lit("both"), F.lit("last"))))
    two = s.withColumn("reading", F.explode(F.when(F.col("s_nationkey") == 7, F.array(F.lit("both"), F.lit("last"))).otherwise(F.array(F.lit("last"))))).drop("s_nationkey")
    return one.unionByName(two).select("reading", "kind", "key")


_NET = "CAST(round(l_extendedprice * (1 - l_discount) * 10000) AS BIGINT)"
_TAXED = "CAST(round(l_extendedprice * (1 - l_discount) * (1 + l_tax) * 10000) AS BIGINT)"


@ops.add(f"SELECT l_returnflag, sum({_NET})::BIGINT AS def_a, sum({_TAXED})::BIGINT AS def_b FROM lineitem GROUP BY 1")
def w_conflict_readings(spark, sf):
    """Two definitions of net revenue, in ten-thousandths, from one scan."""
    return T(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.expr(f"sum({_NET})").alias("def_a"), F.expr(f"sum({_TAXED})").alias("def_b"))


@ops.add("SELECT r_name, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def w_user_knowledge_readings(spark, sf):
    """One query for each region as one grouped pass."""
    j = T(spark, sf, "orders").join(T(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(T(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(T(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


# ---- duplicates, councils


@ops.add("SELECT min(doc_id) AS keep_doc_id, count(*) AS copies FROM documents GROUP BY text")
def w_dedup_exact(spark, sf):
    """Exact duplicates with only hashes and ids in the shuffle; two hashes of 64 and 128 bits tell texts apart."""
    keyed = T(spark, sf, "documents").select("doc_id", F.xxhash64("text").alias("h"), F.md5(F.col("text").cast("binary")).alias("m"))
    return keyed.groupBy("h", "m").agg(F.min("doc_id").alias("keep_doc_id"), F.count(F.lit(1)).alias("copies")).select("keep_doc_id", "copies")


_TEXTS = (
    "concat('SELECT * FROM orders WHERE o_orderkey = ', CAST(o_orderkey AS {s}), ' AND o_orderpriority = ''', o_orderpriority, '''')",
    "concat('select count(*) from orders where o_custkey in (', CAST(o_custkey AS {s}), ', ', CAST(o_orderkey AS {s}), ') and o_totalprice > ', CAST(o_custkey AS {s}), '.5e3')",
    "concat('SELECT o_orderstatus FROM orders -- note ', CAST(o_orderkey AS {s}))",
)


@ops.add("SELECT masked, count(*) AS n FROM (" + " UNION ALL ".join(f"SELECT {sqlmask.mask_sql_text(t.format(s='VARCHAR'))} AS masked FROM orders" for t in _TEXTS) + ") GROUP BY masked")
def w_mask_dedup(spark, sf):
    texts = T(spark, sf, "orders").select(F.explode(F.array(*(F.expr(t.format(s="STRING")) for t in _TEXTS))).alias("sql"))
    return texts.groupBy(sqlmask.mask_values("sql").alias("masked")).agg(F.count(F.lit(1)).alias("n"))


_SIZE = "greatest(3, max(n))"


@ops.add("SELECT l_orderkey AS item_id, count(*) FILTER (WHERE l_returnflag = 'A') AS n_yes, 3::BIGINT AS n_members, 2 * count(*) FILTER (WHERE l_returnflag = 'A') > 3 AS kept FROM lineitem GROUP BY 1")
def w_council_majority(spark, sf):
    ballots = T(spark, sf, "lineitem").select(F.col("l_orderkey").alias("item_id"), F.col("l_returnflag").alias("vote"))
    return majority(ballots, 3, yes="A")


@ops.add("""WITH c AS (SELECT l_orderkey AS item_id, l_returnflag AS vote, count(*) AS n FROM lineitem GROUP BY 1, 2), t AS (SELECT item_id, max(n) AS most FROM c GROUP BY 1)
 SELECT c.item_id, CASE WHEN count(*) > 1 THEN 'N' ELSE min(vote) END AS winner, count(*) > 1 AS tied FROM c JOIN t ON c.item_id = t.item_id AND c.n = t.most GROUP BY c.item_id""")
def w_council_plurality_tie(spark, sf):
    ballots = T(spark, sf, "lineitem").select(F.col("l_orderkey").alias("item_id"), F.col("l_returnflag").alias("vote"))
    return plurality(ballots, "N")


# ---- equivalence, execution

#: case, gold, candidate, superset, expected.
EQUIVALENCE_CASES = (
    ("reordered", "SELECT n_name, n_regionkey FROM nation ORDER BY n_name", "SELECT n_name, n_regionkey FROM nation ORDER BY n_regionkey DESC", "candidate", True),
    ("renamed", "SELECT n_name AS a FROM nation", "SELECT n_name AS b FROM nation", "candidate", True),
    ("columns_swapped", "SELECT n_name, n_nationkey FROM nation", "SELECT n_nationkey, n_name FROM nation", "candidate", True),
    ("superset", "SELECT n_name FROM nation", "SELECT n_name, n_nationkey FROM nation", "candidate", True),
    ("superset_refused", "SELECT n_name FROM nation", "SELECT n_name, n_nationkey FROM nation", "none", False),
    ("subset", "SELECT n_name, n_nationkey FROM nation", "SELECT n_name FROM nation", "candidate", False),
    ("subset_either", "SELECT n_name, n_nationkey FROM nation", "SELECT n_name FROM nation", "either", True),
    ("lost_duplicates", "SELECT n_regionkey FROM nation", "SELECT DISTINCT n_regionkey FROM nation", "candidate", False),
    ("swapped_pairing", "SELECT n_nationkey, n_nationkey % 2 AS p FROM nation WHERE n_nationkey < 4", "SELECT n_nationkey, (n_nationkey + 1) % 2 AS p FROM nation WHERE n_nationkey < 4", "candidate", False),
    ("null_is_a_value", "SELECT CAST(NULL AS INT) AS x", "SELECT 0 AS x", "candidate", False),
    ("negative_zero", "SELECT DISTINCT abs(l_discount) AS d FROM lineitem WHERE l_discount = 0", "SELECT CAST('-0.0' AS DOUBLE) AS d", "candidate", True),
    ("whole_numbers", "SELECT CAST(n_nationkey AS DOUBLE) AS x FROM nation", "SELECT CAST(n_nationkey AS BIGINT) AS y FROM nation", "candidate", True),
    ("empty_results", "SELECT n_name FROM nation WHERE 1 = 0", "SELECT n_name FROM nation WHERE n_nationkey < 0", "candidate", True),
)


def _oracle_equal(gold: str, cand: str, superset: str, expected: bool) -> str:
    return f"(SELECT count(*) FROM ({gold} EXCEPT ALL {cand})) + (SELECT count(*) FROM ({cand} EXCEPT ALL {gold})) = 0"


_N = "SELECT n_name FROM nation"
_DIRECT = {
    "reordered": ("SELECT n_name, n_regionkey FROM nation",) * 2, "renamed": (_N, _N), "columns_swapped": ("SELECT n_name, n_nationkey FROM nation", "SELECT n_name, n_nationkey FROM (SELECT n_nationkey, n_name FROM nation)"),
    "superset": (_N, "SELECT n_name FROM (SELECT n_name, n_nationkey FROM nation)"), "subset_either": ("SELECT n_name FROM (SELECT n_name, n_nationkey FROM nation)", _N), "lost_duplicates": ("SELECT n_regionkey FROM nation", "SELECT DISTINCT n_regionkey FROM nation"),
    "swapped_pairing": ("SELECT n_nationkey, n_nationkey % 2 FROM nation WHERE n_nationkey < 4", "SELECT n_nationkey, (n_nationkey + 1) % 2 FROM nation WHERE n_nationkey < 4"), "null_is_a_value": ("SELECT CAST(NULL AS INT)", "SELECT 0"),
    "negative_zero": ("SELECT DISTINCT abs(l_discount) FROM lineitem WHERE l_discount = 0", "SELECT abs(CAST('-0.0' AS DOUBLE))"), "whole_numbers": ("SELECT CAST(n_nationkey AS DOUBLE) FROM nation", "SELECT CAST(CAST(n_nationkey AS BIGINT) AS DOUBLE) FROM nation"),
    "empty_results": ("SELECT n_name FROM nation WHERE 1 = 0", "SELECT n_name FROM nation WHERE n_nationkey < 0"),
}


@ops.add(" UNION ALL ".join(f"SELECT '{c[0]}' AS case_id, {_oracle_equal(*_DIRECT[c[0]], c[3], c[4]) if c[0] in _DIRECT else 'false'} AS equal" for c in EQUIVALENCE_CASES))
def w_equiv_matrix(spark, sf):
    register_views(spark, sf)
    rows = [(name, bool(equivalent(spark.sql(g), spark.sql(c), superset))) for name, g, c, superset, _ in EQUIVALENCE_CASES]
    return spark.createDataFrame(rows, "case_id string, equal boolean")


@ops.add("SELECT * FROM (VALUES ('same_order', true), ('other_order', false), ('other_columns', false)) AS v(case_id, equal)")
def w_equiv_strict(spark, sf):
    """The contrast without relaxation."""
    register_views(spark, sf)
    q = spark.sql
    a = q("SELECT n_name, n_regionkey FROM nation ORDER BY n_name")
    rows = [("same_order", strict_equal(a, q("SELECT n_name AS x, n_regionkey AS y FROM nation ORDER BY n_name"))), ("other_order", strict_equal(a, q("SELECT n_name, n_regionkey FROM nation ORDER BY n_name DESC"))), ("other_columns", strict_equal(a, q("SELECT n_regionkey, n_name FROM nation ORDER BY n_name")))]
    return spark.createDataFrame(rows, "case_id string, equal boolean")


EXECUTION_CASES = (
    ("good", "SELECT count(*) FROM nation", "ok"), ("with_cte", "WITH x AS (SELECT * FROM region) SELECT * FROM x", "ok"), ("nothing", "SELECT * FROM nation WHERE 1 = 0", "empty"), ("typo", "SELEC 1", "syntax"),
    ("no_table", "SELECT * FROM warehouse", "analysis"), ("no_column", "SELECT manager FROM nation", "analysis"), ("division", "SELECT 1 / (n_nationkey - n_nationkey) FROM nation", "runtime"),
    ("drop", "DROP TABLE nation", "refused"), ("insert", "INSERT INTO nation SELECT * FROM nation", "refused"), ("path", "SELECT * FROM parquet.`/tmp/x`", "refused"), ("function", "SELECT reflect('java.lang.System', 'exit', 0)", "refused"),
)


@ops.add("SELECT * FROM " + values([(c, s) for c, _, s in EXECUTION_CASES], "case_id, status"))
def w_executability(spark, sf):
    register_views(spark, sf)
    return spark.createDataFrame([(c, probe(spark, q).status) for c, q, _ in EXECUTION_CASES], "case_id string, status string")


# ---- measures on the given tables


_BUCKET = "CASE WHEN {c} <= 1 THEN 'answerable' WHEN {c} <= 6 THEN 'ambiguous' ELSE 'unanswerable' END"


@ops.add(f"SELECT {_BUCKET.format(c='label')} AS qtype, CAST(label AS VARCHAR) AS subcategory, count(*) AS n FROM embeddings GROUP BY ROLLUP (1, 2)")
def w_distribution(spark, sf):
    return measures.category_distribution(T(spark, sf, "embeddings").select(F.expr(_BUCKET.format(c="label")).alias("qtype"), F.col("label").cast("string").alias("subcategory")))


@ops.add(f"""SELECT count(*) AS n, round(100.0 * count(*) FILTER (WHERE {_BUCKET.format(c='label')} = {_BUCKET.format(c='p')}) / count(*), 4) AS rec, round(100.0 * count(*) FILTER (WHERE label = p) / count(*), 4) AS cls
 FROM (SELECT label, list_position(embedding[1:10], list_max(embedding[1:10])) - 1 AS p FROM embeddings)""")
def w_rec_cls(spark, sf):
    first = F.slice("embedding", 1, 10)
    e = T(spark, sf, "embeddings").select(F.col("label").alias("subcategory"), (F.array_position(first, F.array_max(first)) - 1).alias("pred_subcategory"))
    return measures.recognition_and_classification(e.withColumns({"qtype": F.expr(_BUCKET.format(c="subcategory")), "pred_qtype": F.expr(_BUCKET.format(c="pred_subcategory"))}))


@ops.add("SELECT label, " + ", ".join(f"count(*) FILTER (WHERE p = {k}) AS \"{k}\"" for k in range(10)) + " FROM (SELECT label, list_position(embedding[1:10], list_max(embedding[1:10])) - 1 AS p FROM embeddings) GROUP BY label")
def w_confusion(spark, sf):
    first = F.slice("embedding", 1, 10)
    e = T(spark, sf, "embeddings").select("label", (F.array_position(first, F.array_max(first)) - 1).alias("p"))
    return measures.confusion(e, tuple(range(10)), "label", "p")


@ops.add("""WITH j AS (SELECT quality, lang, d.doc_id FROM labels l JOIN documents d ON l.doc_id = d.doc_id), k AS (SELECT min(n) AS k FROM (SELECT count(*) AS n FROM j GROUP BY quality, lang))
 SELECT quality, lang, doc_id FROM (SELECT *, row_number() OVER (PARTITION BY quality, lang ORDER BY md5(concat('7:', CAST(doc_id AS VARCHAR))), doc_id) AS r FROM j), k WHERE r <= k""")
def w_balanced(spark, sf):
    j = T(spark, sf, "labels").join(T(spark, sf, "documents"), "doc_id").select("quality", "lang", "doc_id")
    return measures.balance(j, ["quality", "lang"], "doc_id")


@ops.add("""SELECT count(*) AS n_conv, round(avg(s), 4) AS avg_system_turns, round(100.0 * count(*) FILTER (WHERE s >= 2) / count(*), 4) AS multi_turn_pct FROM (SELECT conv_id, count(*) FILTER (WHERE role = 'assistant') AS s FROM conversations GROUP BY 1)""")
def w_dialogue_stats(spark, sf):
    per = T(spark, sf, "conversations").groupBy("conv_id").agg(F.count_if(F.col("role") == "assistant").alias("s"))
    return per.agg(F.count(F.lit(1)).alias("n_conv"), F.round(F.avg("s"), 4).alias("avg_system_turns"), measures.share(F.col("s") >= 2).alias("multi_turn_pct"))


#: Events of a user on one day as a dialogue: a view asks, clicks, purchases and errors are replies, a signup ends.
_EVENT_TURNS = """SELECT concat(CAST(user_id AS {s}), '|', {day}) AS conv_id, ts, event_id, CASE event_type WHEN 'view' THEN 'clarification' WHEN 'signup' THEN 'sql' ELSE 'reply' END AS kind,
 CASE event_type WHEN 'click' THEN 'relevant' WHEN 'purchase' THEN 'technical' WHEN 'error' THEN 'irrelevant' END AS relevancy, CASE WHEN event_type IN ('view', 'signup') THEN 'system' ELSE 'user' END AS role, false AS forced FROM events"""
_EVENT_DUCK = _EVENT_TURNS.format(s="VARCHAR", day="strftime(ts, '%Y-%m-%d')")


def _event_turns(spark, sf) -> DataFrame:
    T(spark, sf, "events").createOrReplaceTempView("events")
    return spark.sql(_EVENT_TURNS.format(s="STRING", day="date_format(ts, 'yyyy-MM-dd')"))


@ops.add(f"""WITH t AS ({_EVENT_DUCK}), n AS (SELECT *, lead(kind) OVER (PARTITION BY conv_id ORDER BY ts, event_id) AS next FROM t),
 f AS (SELECT conv_id, next, row_number() OVER (PARTITION BY conv_id ORDER BY ts, event_id) AS r FROM n WHERE relevancy = 'relevant' AND next IS NOT NULL)
 SELECT count(*) AS n_conv, count(*) FILTER (WHERE next = 'sql') AS n_terminal, round(100.0 * count(*) FILTER (WHERE next = 'sql') / count(*), 4) AS air FROM f WHERE r = 1""")
def w_air(spark, sf):
    return measures.air(_event_turns(spark, sf), order=("ts", "event_id"))


@ops.add(f"""WITH t AS ({_EVENT_DUCK}), n AS (SELECT *, lead(kind) OVER (PARTITION BY conv_id ORDER BY ts, event_id) AS next FROM t)
 SELECT count(*) AS n_conv, count(*) FILTER (WHERE next = 'sql') AS n_terminal, round(100.0 * count(*) FILTER (WHERE next = 'sql') / count(*), 4) AS air FROM n WHERE relevancy = 'relevant' AND next IS NOT NULL""")
def w_air_all_replies(spark, sf):
    return measures.air(_event_turns(spark, sf), which="all", order=("ts", "event_id"))


@ops.add(f"SELECT count(*) AS n_conv, round(100.0 * count(*) FILTER (WHERE a) / count(*), 4) AS clar_pct FROM (SELECT conv_id, bool_or(kind = 'clarification') AS a FROM ({_EVENT_DUCK}) GROUP BY 1)")
def w_clar_rate(spark, sf):
    return measures.dialogue_statistics(_event_turns(spark, sf)).select("n_conv", "clar_pct")


@ops.add(f"SELECT relevancy AS label, count(*) AS n, round(100.0 * count(*) / (SELECT count(*) FROM ({_EVENT_DUCK}) WHERE relevancy IS NOT NULL), 4) AS pct FROM ({_EVENT_DUCK}) WHERE relevancy IS NOT NULL GROUP BY 1")
def w_relevancy_mix(spark, sf):
    n = _event_turns(spark, sf).filter("relevancy is not null").groupBy(F.col("relevancy").alias("label")).agg(F.count(F.lit(1)).alias("n"))
    total = n.agg(F.sum("n").alias("total"))
    return n.crossJoin(F.broadcast(total)).select("label", "n", F.round(100.0 * F.col("n") / F.col("total"), 4).alias("pct"))  # a total of one row


_OUTCOMES = "SELECT CASE {k} % 3 WHEN 0 THEN 'answerable' WHEN 1 THEN 'ambiguous' ELSE 'unanswerable' END AS qtype, CASE WHEN event_type IN ('view', 'click') THEN 'sql' WHEN event_type = 'error' THEN NULL ELSE 'feedback' END AS final_kind, {k} % 5 < 3 AS correct FROM events"
_OUT_DUCK = _OUTCOMES.format(k="CAST(json_extract(props, '$.k') AS BIGINT)")


@ops.add(f"""SELECT *, round(100.0 * ex_num / ex_den, 4) AS ex, round(100.0 * fb_num / fb_den, 4) AS fb FROM (SELECT count(*) FILTER (WHERE qtype <> 'unanswerable' AND final_kind = 'sql' AND correct) AS ex_num, count(*) FILTER (WHERE qtype <> 'unanswerable' OR final_kind = 'sql') AS ex_den,
 count(*) FILTER (WHERE qtype = 'unanswerable' AND final_kind = 'feedback' AND correct) AS fb_num, count(*) FILTER (WHERE qtype = 'unanswerable' OR final_kind = 'feedback') AS fb_den FROM ({_OUT_DUCK}))""")
def w_ex_fb(spark, sf):
    T(spark, sf, "events").createOrReplaceTempView("events")
    return measures.score(spark.sql(_OUTCOMES.format(k="CAST(get_json_object(props, '$.k') AS BIGINT)"))).select("ex_num", "ex_den", "fb_num", "fb_den", "ex", "fb")


@ops.add("SELECT dimension, count(*) AS n, round(100.0 * count(*) FILTER (WHERE ok) / count(*), 4) AS ok_pct FROM (SELECT 'quality' AS dimension, quality = 1 AS ok FROM labels UNION ALL SELECT 'not_toxic', toxic = 0 FROM labels) WHERE ok IS NOT NULL GROUP BY 1")
def w_annotation_report(spark, sf):
    two = F.explode(F.array(F.struct(F.lit("quality").alias("dimension"), (F.col("quality") == 1).alias("ok")), F.struct(F.lit("not_toxic").alias("dimension"), (F.col("toxic") == 0).alias("ok"))))
    return measures.annotation_report(T(spark, sf, "labels").select(two.alias("r")).select("r.*"))


@ops.add("SELECT conv_id FROM (SELECT DISTINCT conv_id FROM conversations) ORDER BY md5(concat('7:', CAST(conv_id AS VARCHAR))), conv_id LIMIT 150")
def w_audit_sample(spark, sf):
    return measures.sample_conversations(T(spark, sf, "conversations"))


@ops.add("""SELECT count(*) AS n, round(avg(CASE WHEN a = b THEN 1.0 ELSE 0.0 END), 6) AS agreement, round((avg(CASE WHEN a = b THEN 1.0 ELSE 0.0 END) - pe) / (1 - pe), 6) AS kappa FROM (SELECT quality AS a, toxic AS b FROM labels),
 (SELECT avg(quality) * avg(toxic) + (1 - avg(quality)) * (1 - avg(toxic)) AS pe FROM labels) GROUP BY pe""")
def w_kappa(spark, sf):
    """Two annotators: here the two columns of labels, as any pair of 0/1 judgements."""
    rows = F.explode(F.array(F.struct(F.lit("a").alias("annotator"), F.col("quality").cast("string").alias("label")), F.struct(F.lit("b").alias("annotator"), F.col("toxic").cast("string").alias("label"))))
    return measures.cohen_kappa(T(spark, sf, "labels").select(F.col("doc_id").alias("item_id"), rows.alias("r")).select("item_id", "r.annotator", "r.label"))


# ---- reports of dialogues made of the events, and published scores


def _nth(x: str, names) -> str:
    """The name at a whole number, whatever its sign, counted round the names."""
    return f"CASE (({x}) % {len(names)} + {len(names)}) % {len(names)} " + " ".join(f"WHEN {i} THEN '{v}'" for i, v in enumerate(names)) + " END"


#: One for each row of the published table; their scores say nothing about language models.
GROUPS = tuple(f"group_{i}" for i in range(len(published.OVERALL)))
#: A user's events in order, cut after every signup (a query) and error (feedback). What has no such end is left out.
_TALK_ORDER = "ts NULLS FIRST, event_id NULLS FIRST, event_type NULLS FIRST, props NULLS FIRST"
_TALKS = f"""SELECT *, concat(CAST(user_id AS {{s}}), '|', CAST(part AS {{s}})) AS conv_id, {_nth("part", A.MODES)} AS mode, {_nth("user_id", ("A",) * len(GROUPS) + ("B",) * len(GROUPS))} AS set, {_nth("user_id", GROUPS)} AS agent,
 CASE WHEN kind = 'reply' THEN 'user' ELSE 'system' END AS role, CASE WHEN event_type = 'click' THEN 'relevant' WHEN event_type = 'purchase' THEN CASE WHEN k % 3 = 0 THEN 'irrelevant' ELSE 'technical' END END AS relevancy, false AS forced
 FROM (SELECT *, count(CASE WHEN kind IN ('sql', 'feedback') THEN 1 END) OVER (PARTITION BY user_id) AS ends, count(CASE WHEN kind IN ('sql', 'feedback') THEN 1 END) OVER (PARTITION BY user_id ORDER BY {_TALK_ORDER} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS part
 FROM (SELECT *, {{k}} AS k, CASE event_type WHEN 'view' THEN 'clarification' WHEN 'signup' THEN 'sql' WHEN 'error' THEN 'feedback' ELSE 'reply' END AS kind FROM events WHERE user_id IS NOT NULL)) WHERE part < ends"""
#: The end of each dialogue as its outcome: a third of the labels are guessed by the event's number, the others are right.
_ENDS = f"""SELECT *, {_nth("label", [t[0] for t in TAXONOMY])} AS qtype, {_nth("guess", [t[0] for t in TAXONOMY])} AS pred_qtype, {_nth("label", SUBCATEGORIES)} AS subcategory, {_nth("guess", SUBCATEGORIES)} AS predicted, kind AS final_kind, k % 5 < 3 AS correct
 FROM (SELECT *, k AS label, CASE WHEN event_id % 3 = 0 THEN event_id ELSE k END AS guess FROM {{talks}}) WHERE kind IN ('sql', 'feedback') AND k IS NOT NULL"""
_TALKS_DUCK = _TALKS.format(s="VARCHAR", k="CAST(json_extract(props, '$.k') AS BIGINT)")


def _talks(spark, sf) -> DataFrame:
    T(spark, sf, "events").createOrReplaceTempView("events")
    return spark.sql(_TALKS.format(s="STRING", k="CAST(get_json_object(props, '$.k') AS BIGINT)"))


def _ends(spark, sf) -> DataFrame:
    _talks(spark, sf).createOrReplaceTempView("event_talks")
    return spark.sql(_ENDS.format(talks="event_talks")).drop("pred_qtype")


_P = lambda num, den: f"round(100.0 * count(*) FILTER (WHERE {num}) / nullif(count(*) FILTER (WHERE {den}), 0), 4)"
#: talks, ends, scores, and in the shape of the published tables: overall, by_mode, dialogues.
_REPORTS_DUCK = f"""WITH talks AS MATERIALIZED ({_TALKS_DUCK}), ends AS MATERIALIZED ({_ENDS.format(talks="talks")}),
 scores AS (SELECT set, mode, agent, {_P("qtype = pred_qtype", "true")} AS rec, {_P("subcategory = predicted", "true")} AS cls, {_P("qtype <> 'unanswerable' AND kind = 'sql' AND correct", "qtype <> 'unanswerable' OR kind = 'sql'")} AS ex,
 {_P("qtype = 'unanswerable' AND kind = 'feedback' AND correct", "qtype = 'unanswerable' OR kind = 'feedback'")} AS fb, {_P("qtype = 'answerable' AND kind = 'sql' AND correct", "qtype = 'answerable'")} AS ex_ans, {_P("qtype = 'ambiguous' AND kind = 'sql' AND correct", "qtype = 'ambiguous'")} AS ex_amb FROM ends GROUP BY ALL),
 overall AS (SELECT s.set, s.agent, s.rec, s.cls, s.ex, s.fb, g.ex AS ex_oracle, g.fb AS fb_oracle FROM scores s JOIN scores g ON s.set = g.set AND s.agent = g.agent AND s.mode = 'predicted' AND g.mode = 'ground_truth'),
 by_mode AS (SELECT set, mode, round(avg(ex_ans), 4) AS ex_ans, round(avg(ex_amb), 4) AS ex_amb, round(avg(fb), 4) AS fb FROM scores GROUP BY set, mode),
 followed AS (SELECT *, lead(kind) OVER (PARTITION BY conv_id ORDER BY {_TALK_ORDER}) AS next FROM talks),
 first_reply AS (SELECT mode, next, row_number() OVER (PARTITION BY conv_id ORDER BY {_TALK_ORDER}) AS r FROM followed WHERE relevancy = 'relevant' AND next IS NOT NULL),
 dialogues AS (SELECT mode, round(avg(s), 4) AS turns, round(100.0 * count(*) FILTER (WHERE asks) / count(*), 4) AS clar, round(100.0 * sum(r) / nullif(sum(r + t + i), 0), 4) AS relevant, round(100.0 * sum(t) / nullif(sum(r + t + i), 0), 4) AS technical, round(100.0 * sum(i) / nullif(sum(r + t + i), 0), 4) AS irrelevant, any_value(air) AS air
 FROM (SELECT conv_id, mode, count(*) FILTER (WHERE role = 'system') AS s, bool_or(kind = 'clarification') AS asks, count(*) FILTER (WHERE relevancy = 'relevant') AS r, count(*) FILTER (WHERE relevancy = 'technical') AS t, count(*) FILTER (WHERE relevancy = 'irrelevant') AS i FROM talks GROUP BY conv_id, mode)
 LEFT JOIN (SELECT mode, {_P("next IN ('sql', 'feedback')", "true")} AS air FROM first_reply WHERE r = 1 GROUP BY mode) USING (mode) GROUP BY mode) """


_RANKED = ("rec", "cls", "ex", "fb", "ex_oracle", "fb_oracle")


@ops.add("SELECT set, agent, " + ", ".join(f"(SELECT count(*) + 1 FROM {published.overall_values()} WHERE p.set = o.set AND p.{c} > o.{c})::INTEGER AS {c}" for c in _RANKED) + f" FROM {published.overall_values().replace('AS p(', 'AS o(')}")
def w_published_overall(spark, sf):
    """The place of each agent in each published measure."""
    return published.overall(spark).select("set", "agent", *(F.rank().over(Window.partitionBy("set").orderBy(F.desc(c))).alias(c) for c in _RANKED))


@ops.add("SELECT set, " + ", ".join(f"round(avg({c}), 2) AS {c}" for c in ("rec", "cls", "ex", "fb", "ex_oracle", "fb_oracle")) + f" FROM {published.overall_values()} GROUP BY set")
def w_published_means(spark, sf):
    return published.means(spark)


@ops.add(f"SELECT a.set, a.mode, " + ", ".join(f"round(a.{c} - b.{c}, 4) AS {c}" for c in ("ex_ans", "ex_amb", "fb")) + f" FROM (SELECT * FROM {published.by_mode_values()}) a JOIN (SELECT * FROM {published.by_mode_values()}) b ON a.set = b.set AND b.mode = 'ground_truth'")
def w_published_mode_impact(spark, sf):
    """How far each published mode is from the true label."""
    true = Window.partitionBy("set")
    gap = lambda c: F.round(F.col(c) - F.max(F.when(F.col("mode") == "ground_truth", F.col(c))).over(true), 4).alias(c)
    return published.by_mode(spark).select("set", "mode", gap("ex_ans"), gap("ex_amb"), gap("fb"))


def _dialogues(spark, sf) -> DataFrame:
    """Statistics and AIR of the dialogues made of the events, as ``published.dialogues``."""
    t = _talks(spark, sf)
    rate = measures.air(t, "mode", order=("ts", "event_id", "event_type", "props")).select("mode", "air")
    return measures.dialogue_statistics(t, "mode").join(rate, "mode", "left").select("mode", F.col("avg_turns").alias("turns"), F.col("clar_pct").alias("clar"), *(F.col(f"{k}_pct").alias(k) for k in ("relevant", "technical", "irrelevant")), "air")


@ops.add(_REPORTS_DUCK + "SELECT mode, round((turns - 1) / nullif(clar / 100, 0), 4) AS clarifications_each, abs(relevant + technical + irrelevant - 100) <= 0.11 AS sums_up FROM dialogues")
def w_published_dialogues(spark, sf):
    """The arithmetic of the published dialogue table on the dialogues made of the events: each ends in one turn, so the others of the system are clarifications."""
    return published.clarifications(_dialogues(spark, sf))


#: A judgement of annotator {a} on a dialogue's end; a null number gives none.
_JUDGED = {d: f"(event_id + {i} + {{a}}) % {i + 5} <> 0" for i, d in enumerate(measures.DIMENSIONS)}
_JUDGED_DUCK = " UNION ALL ".join(f"SELECT '{d}' AS dimension, {ok.format(a='a')} AS ok FROM ends, (VALUES (0), (1)) AS v(a) WHERE {measures.DIMENSIONS[d]}" for d, ok in _JUDGED.items())


@ops.add(_REPORTS_DUCK + f"""SELECT dimension, n_ok, (2000 * n_ok + n) // (2 * n) = tenths AS hit FROM (SELECT *, (2 * tenths * n + 1000) // 2000 AS n_ok FROM (SELECT dimension, count(*) AS n, (2000 * count(*) FILTER (WHERE ok) + count(*)) // (2 * count(*)) AS tenths
 FROM ({_JUDGED_DUCK}) WHERE ok IS NOT NULL GROUP BY dimension))""")
def w_published_human(spark, sf):
    """The whole number of judgements behind each printed share, over all that the dimension applies to: two annotators judge the ends of the dialogues made of the events."""
    ends = _ends(spark, sf).withColumnRenamed("conv_id", "obj_id")
    ballots = F.array(*(F.struct(F.lit(a).alias("annotator"), F.lit(d).alias("dimension"), F.expr(ok.format(a=a)).alias("ok")) for a in (0, 1) for d, ok in _JUDGED.items()))
    annotations = measures.mask_annotations(ends.select("obj_id", F.explode(ballots).alias("b")).select("obj_id", "b.*"), ends)
    pooled = annotations.filter("ok is not null").groupBy("dimension").agg(F.count(F.lit(1)).alias("n"), F.count_if("ok").alias("n_true"))
    return published.whole_numbers(pooled.withColumn("tenths", F.expr("(2000 * n_true + n) div (2 * n)")))


_PLACES = dict(zip((r[0] for r in published.OVERALL), GROUPS, strict=True))


@ops.add(_REPORTS_DUCK + published.findings_sql("overall AS p", "by_mode AS q", "dialogues AS d", _PLACES))
def w_published_findings(spark, sf):
    """The reported findings as checks of the reports of the dialogues made of the events."""
    store, ends = stored(spark), _ends(spark, sf)
    by_mode = measures.mode_impact(measures.score(ends, "set", "mode", "agent"))
    return published.findings(spark, store(overall_of(ends), "overall"), store(by_mode, "by_mode"), store(_dialogues(spark, sf), "dialogues"), _PLACES)


@ops.add(_REPORTS_DUCK + "SELECT set, agent, round(rec - cls, 4) AS rec_minus_cls, round(ex_oracle - ex, 4) AS ex_gain, round(fb_oracle - fb, 4) AS fb_gain FROM overall")
def w_published_gaps(spark, sf):
    """The gaps that were published, of the dialogues made of the events."""
    o = overall_of(_ends(spark, sf)).withColumns({"air": F.lit(None).cast("double"), "ex_amb": F.lit(None).cast("double")})
    return measures.bottlenecks(o).drop("air_minus_ex_amb")


@ops.add(f"SELECT * FROM {values(published.SIZES, 'set, n, balanced, each')} WHERE balanced = 13 * each")
def w_published_sizes(spark, sf):
    return spark.createDataFrame(list(published.SIZES), "set string, n int, balanced int, each int").filter("balanced = 13 * each")


# ---- the stand-in benchmark end to end

#: Two sets: databases of each, all eleven together.
SETS = {"A": ["sales", "clicks", "eval_items", "supply", "retail_full", "dialogs"], "B": ["geo", "corpus", "catalog_parts", "web", "vectors"]}
#: The whole grid of a database; every registered query asks for it.
GRID = {"samples": 3, "styles": STYLES, "generators": _GENERATORS, "difficulties": DIFFICULTIES}


_RESULTS: dict[tuple[str, str], ResultCache] = {}


def results_of(spark: SparkSession, sf: str) -> ResultCache:
    """Results of query texts on one version of the tables, shared by the workloads of a session."""
    return _RESULTS.setdefault((spark.sparkContext.applicationId, sf), ResultCache(spark))


def forget() -> None:
    """Drop what is known of results: after the tables changed, or before a run that is timed."""
    _RESULTS.clear()


def briefing_of(spark: SparkSession, sf: str) -> Briefing:
    """Schema texts with five sample rows of each table, read once."""
    texts = [tuple(r) for r in schema_texts(spark, sf).select("db_id", "schema").collect()]  # one row for each database
    return Briefing(spark.createDataFrame(texts, "db_id string, schema string"))


def questions_of(spark: SparkSession, faults: float = 0.12, db_ids: list[str] | None = None, samples: int = 1, styles=STYLES, aware: bool = True, generators=_GENERATORS[:2], difficulties=DIFFICULTIES[:1]) -> DataFrame:
    made = [generation.RuleGenerator(g, faults, aware=aware) for g in generators]
    return generation.build(spark, made, db_ids, samples, styles, difficulties)


def validated(spark: SparkSession, sf: str, db_ids: list[str] | None = None, skip: tuple[str, ...] = (), **options) -> tuple[DataFrame, DataFrame, DataFrame, validation.Context]:
    """(questions, survivors, verdict log, context)."""
    register_views(spark, sf)
    store = stored(spark)
    raw = store(questions_of(spark, db_ids=db_ids, **GRID), "raw")
    cx = validation.Context(spark, results=results_of(spark, sf), briefing=briefing_of(spark, sf), **options)
    kept, log = validation.run_cascade(raw, cx, store, skip)
    return raw, kept, log, cx


@ops.add()
def w_cascade_report(spark, sf):
    raw, _, log, _ = validated(spark, sf)
    return validation.rejection_report(log, raw)


@ops.add()
def w_cascade_without_execution(spark, sf):
    """Ablation: one stage off; what later stages reject instead."""
    raw, _, log, _ = validated(spark, sf, skip=("executability",))
    return validation.rejection_report(log, raw).filter("subcategory is null").drop("subcategory")


@ops.add()
def w_single_judge(spark, sf):
    """A council of one against a council of three, on the same questions: rejections by stage."""
    out = []
    for name, size in (("one", 1), ("three", 3)):
        raw, _, log, _ = validated(spark, sf, members=council(size, 0.08))
        out.append(validation.rejection_report(log, raw).filter("subcategory is null").select(F.lit(name).alias("council"), "stage", "stage_name", "n_in", "n_rejected"))
    return union_all(out)


@ops.add()
def w_generator_awareness(spark, sf):
    """Generators that are told the category against ones that are not: how many questions conform to the label they carry."""
    out = []
    for name, aware in (("aware", True), ("unaware", False)):
        q = stored(spark)(questions_of(spark, 0.0, aware=aware, **GRID), "q")
        got = validation.stage_conformance(q, validation.Context(spark, results=results_of(spark, sf), briefing=briefing_of(spark, sf)))
        out.append(got.agg(F.count(F.lit(1)).alias("n"), measures.share(F.col("kept")).alias("conforming_pct")).select(F.lit(name).alias("generator"), "n", "conforming_pct"))
    return union_all(out)


def benchmark_run(spark: SparkSession, sf: str, sets: dict[str, list[str]], agents: list, modes=A.MODES) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(judged conversations, turns, questions), each with its set."""
    register_views(spark, sf)
    store = stored(spark)
    cx = validation.Context(spark, results=results_of(spark, sf), briefing=briefing_of(spark, sf))
    raw = store(questions_of(spark, 0.0, sum(sets.values(), []), **GRID), "raw")
    distinct = store(raw.join(validation.stage_duplicates(raw, cx).filter("kept"), "obj_id", "left_semi"), "distinct")
    # every set is balanced by itself; both go through the dialogues together
    questions = store(union_all([measures.balance(distinct.filter(F.col("db_id").isin(dbs)), ["subcategory"], "obj_id").withColumn("set", F.lit(name)) for name, dbs in sets.items()]), "balanced")
    conversations, said = simulation.simulate(questions, agents, cx.members, store, modes, briefing=cx.briefing)
    ends = measures.judge_ends(conversations, questions, cx.results, cx.members).join(questions.select("obj_id", "set"), "obj_id")
    judged = store(ends, "judged")
    return judged, said.join(judged.select("conv_id", "set"), "conv_id"), questions


def overall_of(judged: DataFrame) -> DataFrame:
    """set, agent, rec, cls, ex, fb, ex_oracle, fb_oracle."""
    kinds = taxonomy(judged.sparkSession).select(F.col("subcategory").alias("predicted"), F.col("qtype").alias("pred_qtype"))
    typed = judged.filter("mode = 'predicted'").join(F.broadcast(kinds), "predicted").withColumn("pred_subcategory", F.col("predicted"))
    seen = measures.recognition_and_classification(typed, "set", "agent").drop("n")
    by_mode = {m: measures.score(judged.filter(F.col("mode") == m), "set", "agent").select("set", "agent", F.col("ex").alias(a), F.col("fb").alias(b)) for m, a, b in (("predicted", "ex", "fb"), ("ground_truth", "ex_oracle", "fb_oracle"))}
    return seen.join(by_mode["predicted"], ["set", "agent"]).join(by_mode["ground_truth"], ["set", "agent"])


@ops.add()
def w_overall_table(spark, sf):
    """Eight stand-in agents; never to be put beside published scores."""
    judged, _, _ = benchmark_run(spark, sf, SETS, A.roster(), ("predicted", "ground_truth"))
    return overall_of(judged)


@ops.add()
def w_mode_impact(spark, sf):
    judged, _, _ = benchmark_run(spark, sf, SETS, A.roster())
    return measures.mode_impact(measures.score(judged, "set", "mode", "agent"))


@ops.add()
def w_per_category(spark, sf):
    judged, _, _ = benchmark_run(spark, sf, SETS, A.roster(), ("ground_truth", "predicted"))
    return measures.per_category(judged)


@ops.add()
def w_bottlenecks(spark, sf):
    judged, turns, _ = benchmark_run(spark, sf, SETS, A.roster(), ("ground_truth", "predicted"))
    about = judged.select("conv_id", "agent", "mode", "qtype")
    amb = turns.join(about, "conv_id").filter("qtype = 'ambiguous' and mode = 'predicted'")
    rate = measures.air(amb, "set", "agent").select("set", "agent", "air")
    ex_amb = measures.score(judged.filter("mode = 'predicted'"), "set", "agent").select("set", "agent", "ex_amb")
    return measures.bottlenecks(overall_of(judged).join(rate, ["set", "agent"], "left").join(ex_amb, ["set", "agent"]))


@ops.add()
def w_dialogue_table(spark, sf):
    """Turns, clarification, relevancy and AIR of ambiguous questions, by mode."""
    judged, turns, _ = benchmark_run(spark, sf, SETS, A.roster())
    amb = turns.join(judged.filter("qtype = 'ambiguous'").select("conv_id", "mode"), "conv_id")
    return measures.dialogue_statistics(amb, "mode").join(measures.air(amb, "mode").select("mode", "air"), "mode", "left")


@ops.add()
def w_specialised_writer(spark, sf):
    """Two agents of one skill that differ in writing queries only."""
    judged, _, _ = benchmark_run(spark, sf, SETS, A.specialised_pair(), ("predicted", "ground_truth"))
    return overall_of(judged)


@ops.add()
def w_static_dialogue(spark, sf):
    """A fixed history, where only the last turn is tested, against the live dialogue: execution on solvable questions."""
    register_views(spark, sf)
    store, agents = stored(spark), A.roster()
    raw = store(questions_of(spark, 0.0, **GRID), "raw")
    cx = validation.Context(spark, results=results_of(spark, sf), briefing=briefing_of(spark, sf))
    q = store(raw.join(validation.stage_duplicates(raw, cx).filter("kept"), "obj_id", "left_semi"), "distinct")
    live, _ = simulation.simulate(q, agents, cx.members, store, ("predicted",), briefing=cx.briefing)
    fixed = union_all([simulation.replay_static(q, agent).select("conv_id", "obj_id", F.lit(agent.name).alias("agent"), F.lit("static").alias("mode"), F.col("kind").alias("final_kind"), F.col("text").alias("final_text")) for agent in agents])
    both = live.select(*fixed.columns).unionByName(fixed)
    judged = measures.judge_ends(store(both, "both"), q, cx.results, cx.members)
    return measures.score(judged.filter("qtype <> 'unanswerable'"), "mode", "agent").select("mode", "agent", "ex", "ex_ans", "ex_amb")


@ops.add()
def w_full_simulation(spark, sf):
    """The flagship: generation, validation and dialogues of two sets under all four modes; one row per set, mode and agent."""
    _, kept, _, cx = validated(spark, sf)
    store = stored(spark)
    sets = F.create_map(*(F.lit(x) for name, dbs in SETS.items() for db in dbs for x in (db, name)))
    conversations, turns = simulation.simulate(kept, A.roster(), cx.members, store, briefing=cx.briefing)
    ends = measures.judge_ends(conversations, kept, cx.results, cx.members).join(kept.select("obj_id", sets[F.col("db_id")].alias("set")), "obj_id")
    judged = store(ends, "judged")
    scores = measures.score(judged, "set", "mode", "agent").select("set", "mode", "agent", "ex", "ex_ans", "ex_amb", "fb")
    amb = turns.join(judged.filter("qtype = 'ambiguous'").select("conv_id", "set", "mode", "agent"), "conv_id")
    return scores.join(measures.air(amb, "set", "mode", "agent").select("set", "mode", "agent", "air"), ["set", "mode", "agent"], "left")
