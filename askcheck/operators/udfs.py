"""The user-function surface: a scalar and a grouped pandas function, a table function, a batch adapter, SQL names."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, StringType, StructField, StructType

from ..functions import sqlmask
from ..registry import Registry
from ..sources.tables import table

ops = Registry()

_ORDER_SQL = "concat('SELECT * FROM orders WHERE o_orderkey = ', CAST({key} AS {text}), ' AND o_orderpriority = ''', o_orderpriority, '''')"


@ops.add(f"SELECT {sqlmask.mask_sql_text(_ORDER_SQL.format(key='o_orderkey', text='VARCHAR'))} AS masked, count(*) AS n FROM orders GROUP BY 1")
def op_udf_scalar(spark, sf):
    """The tokenizer as a pandas function, brought to the spacing of the expression chain."""
    q = table(spark, sf, "orders").select(sqlmask.mask_values_exact(F.expr(_ORDER_SQL.format(key="o_orderkey", text="STRING"))).alias("masked"))
    return q.groupBy("masked").agg(F.count(F.lit(1)).alias("n"))


@F.pandas_udf(DoubleType())
def middle_half_mean(v: pd.Series) -> float:
    """The mean of values between the quartiles."""
    s = v.sort_values().to_numpy()
    return float(s[len(s) // 4 : len(s) - len(s) // 4].mean())


@ops.add("""SELECT c_mktsegment, round(avg(c_acctbal) FILTER (WHERE r > n // 4 AND r <= n - n // 4), 4) AS trimmed FROM (SELECT *, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal) AS r, count(*) OVER (PARTITION BY c_mktsegment) AS n FROM customer) GROUP BY 1""")
def op_udaf(spark, sf):
    return table(spark, sf, "customer").groupBy("c_mktsegment").agg(F.round(middle_half_mean("c_acctbal"), 4).alias("trimmed"))


@F.udtf(returnType=StructType([StructField("node_id", IntegerType()), StructField("clause", StringType()), StructField("text", StringType())]))
class SqlFragments:
    """The parts of a query as rows."""

    def eval(self, sql: str):
        from ..plans.simulation import sql_fragments

        for i, f in enumerate(sql_fragments(sql)):
            clause, _, text = f.partition(": ")
            yield i, clause, text


_PARTS = (("select", "'o_orderkey'"), ("select", "'o_totalprice'"), ("from", "'orders'"), ("where", "concat('o_orderpriority = ', chr(39), o_orderpriority, chr(39))"), ("where", "'o_custkey BETWEEN 1 AND 9'"), ("limit", "CAST(o_orderkey % 5 AS VARCHAR)"))


@ops.add("SELECT clause, text, count(*) AS n FROM (" + " UNION ALL ".join(f"SELECT '{c}' AS clause, {t} AS text FROM orders" for c, t in _PARTS) + ") GROUP BY 1, 2")
def op_udtf(spark, sf):
    """The fragments of a query text for each order, counted."""
    spark.udtf.register("sql_fragments", SqlFragments)
    table(spark, sf, "orders").createOrReplaceTempView("orders")
    text = "concat('SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderpriority = ', chr(39), o_orderpriority, chr(39), ' AND o_custkey BETWEEN 1 AND 9 LIMIT ', o_orderkey % 5)"
    return spark.sql(f"SELECT clause, text, count(*) AS n FROM (SELECT {text} AS sql FROM orders), LATERAL sql_fragments(sql) GROUP BY clause, text")


@ops.add("SELECT conv_id, turn, length(text) AS size FROM conversations")
def op_map_in_pandas(spark, sf):
    """The adapter members use: frames in, frames out."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield pd.DataFrame({"conv_id": f["conv_id"], "turn": f["turn"], "size": f["text"].str.len()})

    return table(spark, sf, "conversations").select("conv_id", "turn", "text").mapInPandas(run, "conv_id long, turn long, size long")


def register_functions(spark: SparkSession) -> None:
    """Names for SQL: mask_values_exact, sql_fragments."""
    spark.udf.register("mask_values_exact", sqlmask.mask_values_exact)
    spark.udtf.register("sql_fragments", SqlFragments)


@ops.add(f"SELECT count(DISTINCT {sqlmask.mask_sql_text(_ORDER_SQL.format(key='o_orderkey', text='VARCHAR'))}) AS n FROM orders")
def op_sql_surface(spark, sf):
    register_functions(spark)
    table(spark, sf, "orders").createOrReplaceTempView("orders")
    return spark.sql(f"SELECT count(DISTINCT mask_values_exact({_ORDER_SQL.format(key='o_orderkey', text='STRING')})) AS n FROM orders")
