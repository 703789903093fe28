"""Streaming operators over the events and conversations tables, run to the end of the input."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..registry import Registry
from ..sources.tables import table
from ..streaming import measures as M

ops = Registry()
_SHOW = "yyyy-MM-dd HH:mm:ss"


@ops.add("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def op_st_tumbling(spark, sf):
    got = M.run_to_end(M.tumbling(M.events(spark, sf), "1 day"), "complete")
    return got.select(F.date_format("start", _SHOW).alias("start"), "event_type", "n")


@ops.add("""SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 12 HOUR]) AS s FROM events) GROUP BY 1""")
def op_st_sliding(spark, sf):
    got = M.run_to_end(M.sliding(M.events(spark, sf), "1 day", "12 hours"), "complete")
    return got.select(F.date_format("start", _SHOW).alias("start"), "n")


@ops.add("""SELECT user_id, strftime(date_trunc('second', min(ts)), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM
 (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s""")
def op_st_session(spark, sf):
    got = M.run_to_end(M.sessions(M.events(spark, sf), "30 minutes"), "complete")
    return got.select("user_id", F.date_format("start", _SHOW).alias("start"), "n")


@ops.add("SELECT DISTINCT event_id FROM events")
def op_st_dedup(spark, sf):
    twice = M.events(spark, sf).select("event_id", "ts")
    return M.run_to_end(M.without_repeats(twice.unionByName(M.events(spark, sf).select("event_id", "ts")), "event_id", "400 days")).select("event_id")


@ops.add("SELECT user_id, c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1, 2")
def op_st_join_static(spark, sf):
    joined = M.events(spark, sf).join(table(spark, sf, "customer"), F.col("user_id") == F.col("c_custkey")).groupBy("user_id", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
    return M.run_to_end(joined, "complete")


def _turns(df):
    """Conversations as turns: an assistant's turn that is followed by nothing ends as SQL, the others ask; a user's reply is relevant by its length."""
    kind = F.when(F.col("role") == "assistant", F.when(F.length("text") % 2 == 0, "sql").otherwise("clarification")).otherwise("reply")
    return df.select("conv_id", "turn", kind.alias("kind"), F.when((F.col("role") == "user") & (F.length("text") % 3 > 0), "relevant").alias("relevancy"), F.lit(False).alias("forced"))


@ops.add()
def op_st_stateful(spark, sf):
    """AIR of conversations by arbitrary state, against the batch measure on the same rows."""
    stream = _turns(M.file_stream(spark, f"{sf}/conversations.parquet")).select("conv_id", "turn", "kind", "relevancy")
    got = M.run_to_end(M.stream_air(stream))
    return got.agg(F.count(F.lit(1)).alias("n_conv"), F.count_if("terminal").alias("n_terminal"))


@ops.add("""WITH t AS (SELECT conv_id, turn, CASE WHEN role = 'assistant' THEN CASE WHEN length(text) % 2 = 0 THEN 'sql' ELSE 'clarification' END ELSE 'reply' END AS kind, role = 'user' AND length(text) % 3 > 0 AS rel FROM conversations),
 n AS (SELECT *, lead(kind) OVER (PARTITION BY conv_id ORDER BY turn) AS next FROM t), f AS (SELECT conv_id, arg_min(next, turn) AS next FROM n WHERE rel AND next IS NOT NULL GROUP BY conv_id)
 SELECT count(*) AS n_conv, count(*) FILTER (WHERE next IN ('sql', 'feedback')) AS n_terminal FROM f""")
def op_st_air_batch(spark, sf):
    from ..plans.measures import air

    return air(_turns(table(spark, sf, "conversations"))).select("n_conv", "n_terminal")


_PARTS = 4


@ops.add(f"""WITH b AS (SELECT ts, user_id % {_PARTS} AS b FROM events), t AS (SELECT b, max(ts) AS top FROM b GROUP BY b)
 SELECT count(*) AS n_late FROM b WHERE ts < (SELECT max(top) FROM t WHERE t.b < b.b) - INTERVAL 10 DAY""")
def op_st_late(spark, sf):
    """Events that arrive in four parts by their user: those over ten days behind what came in the parts before."""
    base = f"{M.shared_dir(spark)}/late-{uuid.uuid4().hex}"
    given = table(spark, sf, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))

    def sink(batch, number):
        batch.write.mode("overwrite").parquet(f"{base}/out/b={number}")

    for i in range(_PARTS):
        given.filter(F.col("user_id") % _PARTS == i).write.mode("append").parquet(f"{base}/in")
        arriving = spark.readStream.schema(given.schema).parquet(f"{base}/in")
        arriving.writeStream.foreachBatch(M.late_rows(base, "10 DAYS", sink)).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(given.schema).parquet(f"{base}/out").agg(F.count(F.lit(1)).alias("n_late"))


@ops.add("""SELECT day, count(*) AS n_conv, round(100.0 * count(*) FILTER (WHERE a) / count(*), 4) AS clar_pct FROM (SELECT strftime(ts, '%Y-%m-%d') AS day, user_id, bool_or(event_type = 'view') AS a FROM events GROUP BY 1, 2) GROUP BY 1""")
def op_st_clar_rate(spark, sf):
    """The share of conversations (a user's day) that hold a clarification (a view), by day."""
    turns = M.events(spark, sf).select("ts", F.col("user_id").alias("conv_id"), F.when(F.col("event_type") == "view", "clarification").otherwise("reply").alias("kind"))
    got = M.run_to_end(M.stream_clar_rate(turns, "1 day"), "update", ["start", "conv_id"])
    return got.groupBy(F.date_format("start", "yyyy-MM-dd").alias("day")).agg(F.count(F.lit(1)).alias("n_conv"), F.round(100.0 * F.count_if("asks") / F.count(F.lit(1)), 4).alias("clar_pct"))


@ops.add("SELECT l_orderkey AS item_id, count(*) FILTER (WHERE l_returnflag = 'A') AS n_yes, count(*) AS n_members, 2 * count(*) FILTER (WHERE l_returnflag = 'A') > count(*) AS kept FROM lineitem GROUP BY 1")
def op_st_votes(spark, sf):
    ballots = M.file_stream(spark, f"{sf}/lineitem.parquet").select(F.col("l_orderkey").alias("item_id"), F.col("l_returnflag").alias("vote"))
    return M.run_to_end(M.stream_votes(ballots, "A"), "update", ["item_id"])
