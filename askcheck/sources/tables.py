"""The given tables and the eleven logical databases over them.

Keys are declared here and never inferred: values of unrelated columns overlap.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

DATABASES: dict[str, tuple[str, ...]] = {
    "sales": ("customer", "orders", "lineitem"),
    "supply": ("part", "supplier", "lineitem"),
    "geo": ("region", "nation", "customer", "supplier"),
    "retail_full": ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"),
    "catalog_parts": ("part",),
    "clicks": ("events",),
    "corpus": ("documents", "labels"),
    "eval_items": ("benchmark", "documents"),
    "web": ("pages",),
    "dialogs": ("conversations",),
    "vectors": ("embeddings",),
}

PRIMARY_KEYS = {
    "region": ("r_regionkey",),
    "nation": ("n_nationkey",),
    "customer": ("c_custkey",),
    "supplier": ("s_suppkey",),
    "part": ("p_partkey",),
    "orders": ("o_orderkey",),
    "events": ("event_id",),
    "documents": ("doc_id",),
    "embeddings": ("vec_id",),
    "pages": ("page_id",),
    "benchmark": ("item_id",),
    "conversations": ("conv_id", "turn"),
}

FOREIGN_KEYS = (
    ("nation", "n_regionkey", "region", "r_regionkey"),
    ("customer", "c_nationkey", "nation", "n_nationkey"),
    ("supplier", "s_nationkey", "nation", "n_nationkey"),
    ("orders", "o_custkey", "customer", "c_custkey"),
    ("lineitem", "l_orderkey", "orders", "o_orderkey"),
    ("lineitem", "l_partkey", "part", "p_partkey"),
    ("lineitem", "l_suppkey", "supplier", "s_suppkey"),
    ("labels", "doc_id", "documents", "doc_id"),
)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, prefix: str = "") -> None:
    """A temporary view for each table, so that candidate SQL can name it."""
    for name in TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(prefix + name)


def foreign_keys(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(FOREIGN_KEYS), "table_name string, col_name string, fk_table string, fk_col string")


def schema_catalog(spark: SparkSession, sf_dir: str) -> DataFrame:
    """db_id, table_name, col_name, data_type, ordinal, is_pk, fk_table, fk_col, tokens.

    Read from the tables' schemas (file footers), never from their rows.
    """
    links = {(t, c): (ft, fc) for t, c, ft, fc in FOREIGN_KEYS}
    rows = []
    schemas = {t: table(spark, sf_dir, t).schema for t in TABLES}
    for db, names in DATABASES.items():
        for t in names:
            for i, field in enumerate(schemas[t]):
                fk = links.get((t, field.name), (None, None))
                inside = fk if fk[0] in names else (None, None)
                rows.append((db, t, field.name, field.dataType.simpleString(), i, field.name in PRIMARY_KEYS.get(t, ()), *inside, column_tokens(field.name)))
    return spark.createDataFrame(rows, "db_id string, table_name string, col_name string, data_type string, ordinal int, is_pk boolean, fk_table string, fk_col string, tokens array<string>")


#: Parts that compound column names are made of.
NAME_PARTS = ("key", "cust", "supp", "part", "nation", "region", "order", "line", "total", "retail", "extended", "ship", "return", "mkt", "acct", "price", "status", "flag", "date", "segment", "name", "bal", "number", "priority", "size", "type", "brand", "quantity", "discount", "tax")


def column_tokens(name: str) -> list[str]:
    """Words of a column's name: its prefix letter off, compounds cut at known parts."""
    bare = name.split("_", 1)[1] if name[1:2] == "_" else name
    out = []
    for piece in bare.split("_"):
        while piece:
            part = max((p for p in NAME_PARTS if piece.startswith(p)), key=len, default=None)
            if part is None:
                out.append(piece)
                break
            out.append(part)
            piece = piece[len(part) :]
    return out


def sample_rows(df: DataFrame, n: int = 5, seed: int = 7, exact: bool = True) -> DataFrame:
    """``n`` rows as JSON; by the order of a hash of seed and row, or just any where a table is huge."""
    rows = df.select(F.to_json(F.struct(*(F.col(c).cast("string").alias(c) if t.startswith("timestamp") else F.col(c) for c, t in df.dtypes))).alias("row_json"))
    if not exact:
        return rows.limit(n)
    return rows.orderBy(F.md5(F.concat(F.lit(str(seed)), F.col("row_json"))), "row_json").limit(n)


def schema_context(spark: SparkSession, sf_dir: str, db_id: str, n: int = 5, seed: int = 7, exact: bool = True) -> DataFrame:
    """db_id, table_name, columns, samples: what a generator or an agent sees of a database."""
    out = None
    for t in DATABASES[db_id]:
        df = table(spark, sf_dir, t)
        about = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in df.schema)
        one = sample_rows(df, n, seed, exact).agg(F.sort_array(F.collect_list("row_json")).alias("samples")).select(F.lit(db_id).alias("db_id"), F.lit(t).alias("table_name"), F.lit(about).alias("columns"), "samples")
        out = one if out is None else out.unionByName(one)
    return out


def schema_texts(spark: SparkSession, sf_dir: str, n: int = 5, seed: int = 7, exact: bool = True, widest: int = 60, db_ids: list[str] | None = None) -> DataFrame:
    """db_id, schema: one text for each database with its tables, columns, keys and ``n`` sample rows, cells cut to ``widest`` characters.

    Sample rows are chosen once for each table, whatever databases hold it.
    """
    parts = None
    for t in TABLES:
        df = table(spark, sf_dir, t)
        links = {c: f"{ft}.{fc}" for x, c, ft, fc in FOREIGN_KEYS if x == t}
        about = ", ".join(f"{f.name} {f.dataType.simpleString()}" + (f" -> {links[f.name]}" if f.name in links else "") for f in df.schema)
        cut = df.select(*(F.substring(F.col(f.name).cast("string"), 1, widest).alias(f.name) for f in df.schema))
        one = sample_rows(cut, n, seed, exact).agg(F.concat_ws("\n", F.lit(f"{t}({about})"), F.sort_array(F.collect_list("row_json"))).alias("part")).select(F.lit(t).alias("table_name"), "part")
        parts = one if parts is None else parts.unionByName(one)
    held = spark.createDataFrame([(d, t) for d, names in DATABASES.items() if not db_ids or d in db_ids for t in names], "db_id string, table_name string")
    return held.join(parts, "table_name").groupBy("db_id").agg(F.concat_ws("\n", F.sort_array(F.collect_list("part"))).alias("schema"))
