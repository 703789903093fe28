"""Relational operators that candidate queries and measures are made of."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..registry import Registry
from ..sources.tables import table

ops = Registry()
T = table


def cents(c: str):
    """A double of two decimals as whole cents, so that sums don't depend on their order."""
    return F.round(F.col(c) * 100).cast("bigint")


# ---- scan, projection, filter


@ops.add("SELECT o_orderkey, o_custkey, o_orderpriority FROM orders")
def op_scan_project(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderpriority")


@ops.add("""SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20
 AND l_returnflag IN ('A','R') AND regexp_matches(l_linestatus, '^[OF]$')""")
def op_filter_pred(spark, sf):
    li = T(spark, sf, "lineitem")
    return li.filter(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & F.col("l_linestatus").rlike("^[OF]$")).select("l_orderkey", "l_linenumber", "l_quantity")


@ops.add("""SELECT d.doc_id, (l.quality IS NOT DISTINCT FROM NULL) AS unlabelled FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id""")
def op_null_safe(spark, sf):
    d, lab = T(spark, sf, "documents").select("doc_id"), T(spark, sf, "labels").select("doc_id", "quality")
    return d.join(lab, "doc_id", "left").select("doc_id", F.col("quality").eqNullSafe(F.lit(None)).alias("unlabelled"))


@ops.add("""SELECT CASE WHEN p_size <= 10 THEN 'small' WHEN p_size <= 30 THEN 'medium' ELSE 'large' END AS bucket, count(*) AS n FROM part GROUP BY 1""")
def op_case_bucket(spark, sf):
    size = F.col("p_size")
    return T(spark, sf, "part").groupBy(F.when(size <= 10, "small").when(size <= 30, "medium").otherwise("large").alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


# ---- joins


@ops.add("""SELECT n_name, count(*) AS lines, sum(CAST(round(l_extendedprice*100) AS BIGINT))::BIGINT AS cents FROM lineitem
 JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name""")
def op_join_inner(spark, sf):
    li, o = T(spark, sf, "lineitem"), T(spark, sf, "orders")
    c, n = T(spark, sf, "customer"), T(spark, sf, "nation")
    # both large sides carry only what the aggregate needs; the small ones are left to the planner
    j = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey)
    return j.groupBy("n_name").agg(F.count(F.lit(1)).alias("lines"), F.sum(cents("l_extendedprice")).alias("cents"))


def _outer(kind: str):
    def run(spark, sf):
        d, lab = T(spark, sf, "documents").select("doc_id", "lang"), T(spark, sf, "labels").filter("quality = 1").select(F.col("doc_id").alias("l_doc"), "toxic")
        return d.filter("lang <> 'en'").join(lab, d.doc_id == lab.l_doc, kind).select("doc_id", "lang", "l_doc", "toxic")

    return run


for _kind in ("left", "right", "full"):
    ops.add(f"""SELECT d.doc_id, d.lang, l.doc_id AS l_doc, l.toxic FROM (SELECT * FROM documents WHERE lang <> 'en') d {_kind.upper()} JOIN (SELECT * FROM labels WHERE quality = 1) l ON d.doc_id = l.doc_id""", f"op_join_{_kind}")(_outer(_kind))


@ops.add("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def op_join_semi(spark, sf):
    return T(spark, sf, "customer").join(T(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@ops.add("SELECT c_custkey FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)")
def op_join_anti(spark, sf):
    return T(spark, sf, "customer").join(T(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@ops.add("SELECT a.r_name AS left_name, b.r_name AS right_name FROM region a CROSS JOIN region b")
def op_join_cross(spark, sf):
    r = T(spark, sf, "region").select("r_name")  # five rows by definition of the table
    return r.select(F.col("r_name").alias("left_name")).crossJoin(r.select(F.col("r_name").alias("right_name")))


_HINTED = """SELECT p_brand, count(*) AS n, sum(CAST(l_quantity AS BIGINT))::BIGINT AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand"""


def _hinted(hint: str):
    def run(spark, sf):
        li, p = T(spark, sf, "lineitem"), T(spark, sf, "part").select("p_partkey", "p_brand")
        return li.join(p.hint(hint), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("quantity"))

    return run


for _name, _hint in (("broadcast", "broadcast"), ("merge", "merge"), ("shash", "shuffle_hash")):
    ops.add(_HINTED, f"op_join_{_name}")(_hinted(_hint))


@ops.add("""SELECT n_name, count(*) AS n FROM customer JOIN supplier ON c_nationkey = s_nationkey AND c_acctbal > s_acctbal JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name""")
def op_join_theta(spark, sf):
    # Within a nation, customers above each supplier: balances of both sides in one order, suppliers counted on the way.
    c = T(spark, sf, "customer").select(F.col("c_nationkey").alias("k"), F.col("c_acctbal").alias("bal"), F.lit(1).alias("asks"))
    s = T(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"), F.col("s_acctbal").alias("bal"), F.lit(0).alias("asks"))
    below = Window.partitionBy("k").orderBy("bal").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    same = Window.partitionBy("k", "bal")
    counted = c.unionByName(s).withColumn("n", F.sum(1 - F.col("asks")).over(below) - F.sum(1 - F.col("asks")).over(same))
    per = counted.filter("asks = 1").groupBy("k").agg(F.sum("n").alias("n")).filter("n > 0")
    return per.join(T(spark, sf, "nation"), F.col("k") == F.col("n_nationkey")).select("n_name", "n")


_CUTS = "(VALUES (0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 300000.0), (3, 300000.0, 1e12)) AS t(band, lo, hi)"


@ops.add(f"SELECT band, count(*) AS n FROM orders JOIN {_CUTS} ON o_totalprice >= lo AND o_totalprice < hi GROUP BY band")
def op_join_range(spark, sf):
    cuts = spark.createDataFrame([(0, 0.0, 5e4), (1, 5e4, 1.5e5), (2, 1.5e5, 3e5), (3, 3e5, 1e12)], "band int, lo double, hi double")
    o = T(spark, sf, "orders").select("o_totalprice")
    return o.join(F.broadcast(cuts), (F.col("o_totalprice") >= F.col("lo")) & (F.col("o_totalprice") < F.col("hi"))).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


@ops.add("""SELECT event_id, view_id FROM (SELECT event_id, event_type, max(CASE WHEN event_type = 'view' THEN struct_pack(ts := ts, id := event_id) END)
 OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING).id AS view_id FROM events) WHERE event_type = 'signup'""")
def op_join_asof(spark, sf):
    """The last view before each signup: one shuffle on the user, no pairs."""
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = T(spark, sf, "events").filter(F.col("event_type").isin("view", "signup")).select("event_id", "user_id", "ts", "event_type")
    return e.withColumn("view_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before)).filter("event_type = 'signup'").select("event_id", "view_id")


@ops.add("""SELECT s.event_id AS signup_id, count(e.event_id) AS errors FROM events s LEFT JOIN events e ON e.event_type = 'error' AND e.user_id = s.user_id
 AND e.ts >= s.ts - INTERVAL 1 HOUR AND e.ts <= s.ts WHERE s.event_type = 'signup' GROUP BY s.event_id""")
def op_join_interval(spark, sf):
    e = T(spark, sf, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, Window.currentRow)
    counted = e.filter(F.col("event_type").isin("signup", "error")).withColumn("errors", F.count_if(F.col("event_type") == "error").over(hour))
    return counted.filter("event_type = 'signup'").select(F.col("event_id").alias("signup_id"), "errors")


# ---- subqueries


@ops.add("SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer)")
def op_sub_scalar(spark, sf):
    c = T(spark, sf, "customer")
    return c.filter(F.col("c_acctbal") > c.select(F.avg("c_acctbal")).scalar()).select("c_custkey")


@ops.add("SELECT o_orderkey FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_returnflag = 'R')")
def op_sub_exists(spark, sf):
    returned = T(spark, sf, "lineitem").filter("l_returnflag = 'R'")
    o = T(spark, sf, "orders")
    return o.filter(returned.filter(F.col("l_orderkey") == F.col("o_orderkey").outer()).exists()).select("o_orderkey")


@ops.add("SELECT s_suppkey FROM supplier WHERE s_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)")
def op_sub_in(spark, sf):
    return T(spark, sf, "supplier").join(T(spark, sf, "nation").filter("n_regionkey = 1"), F.col("s_nationkey") == F.col("n_nationkey"), "left_semi").select("s_suppkey")


@ops.add("""SELECT c_custkey, o_orderkey FROM (SELECT o_custkey AS c_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2 AND c_custkey IN (SELECT c_custkey FROM customer)""")
def op_lateral_top(spark, sf):
    """Two orders of each customer: a ranking window stops early in every group, where a lateral join would pair first."""
    best = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    top = T(spark, sf, "orders").withColumn("r", F.row_number().over(best)).filter("r <= 2")
    return top.join(T(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey")).select("c_custkey", "o_orderkey")


# ---- aggregates


@ops.add("""SELECT l_returnflag, l_linestatus, count(*) AS n, sum(CAST(round(l_extendedprice*100) AS BIGINT))::BIGINT AS cents FROM lineitem GROUP BY 1, 2""")
def op_agg_hash(spark, sf):
    return T(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(cents("l_extendedprice")).alias("cents"))


@ops.add("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def op_agg_distinct(spark, sf):
    return T(spark, sf, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@ops.add("""SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS finished, count(*) FILTER (WHERE o_totalprice > 200000) AS large FROM orders GROUP BY 1""")
def op_agg_filtered(spark, sf):
    return T(spark, sf, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("finished"), F.count_if(F.col("o_totalprice") > 200000).alias("large"))


@ops.add("""SELECT l_linestatus, round(stddev_samp(l_quantity), 4) AS spread, quantile_cont(l_quantity, 0.5) AS middle, quantile_cont(l_quantity, 0.9) AS high FROM lineitem GROUP BY 1""")
def op_agg_stats(spark, sf):
    return T(spark, sf, "lineitem").groupBy("l_linestatus").agg(F.round(F.stddev_samp("l_quantity"), 4).alias("spread"), F.percentile("l_quantity", 0.5).alias("middle"), F.percentile("l_quantity", 0.9).alias("high"))


@ops.add("SELECT o_custkey, max(o_totalprice) AS best, arg_max(o_orderkey, struct_pack(p := o_totalprice, k := o_orderkey)) AS best_order FROM orders GROUP BY 1")
def op_agg_maxby(spark, sf):
    return T(spark, sf, "orders").groupBy("o_custkey").agg(F.max("o_totalprice").alias("best"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("best_order"))


@ops.add("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def op_agg_collect(spark, sf):
    return T(spark, sf, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("names"))


@ops.add()
def op_agg_approx(spark, sf):
    """An estimate and whether it lies within three standard errors of the exact count."""
    got = T(spark, sf, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("estimate"), F.countDistinct("user_id").alias("exact"))
    return got.withColumn("within", F.abs(F.col("estimate") - F.col("exact")) <= 0.06 * F.col("exact"))


# ---- several levels


_SETS = "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY {}"


@ops.add(_SETS.format("GROUPING SETS ((o_orderstatus), (o_orderpriority), ())"))
def op_grouping_sets(spark, sf):
    a, b = F.col("o_orderstatus"), F.col("o_orderpriority")
    return T(spark, sf, "orders").groupingSets([[a], [b], []], a, b).agg(F.count(F.lit(1)).alias("n"))


@ops.add(_SETS.format("ROLLUP (o_orderstatus, o_orderpriority)"))
def op_rollup(spark, sf):
    return T(spark, sf, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@ops.add(_SETS.format("CUBE (o_orderstatus, o_orderpriority)"))
def op_cube(spark, sf):
    return T(spark, sf, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


_TYPES = ("click", "error", "purchase", "signup", "view")


@ops.add("SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{t}') AS {t}" for t in _TYPES) + " FROM events GROUP BY user_id")
def op_pivot(spark, sf):
    return T(spark, sf, "events").groupBy("user_id").pivot("event_type", list(_TYPES)).agg(F.count(F.lit(1))).na.fill(0)


@ops.add("""SELECT l_returnflag, 'discount' AS measure, round(avg(l_discount), 6) AS value FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 'tax', round(avg(l_tax), 6) FROM lineitem GROUP BY 1""")
def op_unpivot(spark, sf):
    wide = T(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.round(F.avg("l_discount"), 6).alias("discount"), F.round(F.avg("l_tax"), 6).alias("tax"))
    return wide.unpivot("l_returnflag", ["discount", "tax"], "measure", "value")


# ---- windows


@ops.add("""SELECT s_suppkey, row_number() OVER w AS r, rank() OVER (PARTITION BY s_nationkey ORDER BY round(s_acctbal/1000)) AS rk, dense_rank() OVER (PARTITION BY s_nationkey ORDER BY round(s_acctbal/1000)) AS dr
 FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)""")
def op_rank_all(spark, sf):
    by, coarse = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey"), Window.partitionBy("s_nationkey").orderBy(F.round(F.col("s_acctbal") / 1000))
    return T(spark, sf, "supplier").select("s_suppkey", F.row_number().over(by).alias("r"), F.rank().over(coarse).alias("rk"), F.dense_rank().over(coarse).alias("dr"))


@ops.add("SELECT c_custkey, ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey) AS quarter FROM customer")
def op_ntile(spark, sf):
    return T(spark, sf, "customer").select("c_custkey", F.ntile(4).over(Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")).alias("quarter"))


@ops.add("SELECT conv_id, turn, lag(role) OVER w AS before, lead(role) OVER w AS after FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn, role, text)")
def op_lag_lead(spark, sf):
    w = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    return T(spark, sf, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"))


@ops.add("""SELECT DISTINCT user_id, first_value(event_type) OVER w AS opened, last_value(event_type) OVER w AS closed FROM events
 WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def op_first_last(spark, sf):
    """Ends of each user's events by two ordered aggregates: no sort of whole histories."""
    at = F.struct("ts", "event_id")
    return T(spark, sf, "events").groupBy("user_id").agg(F.min_by("event_type", at).alias("opened"), F.max_by("event_type", at).alias("closed"))


@ops.add("""SELECT o_orderkey, sum(CAST(round(o_totalprice*100) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING)::BIGINT AS so_far FROM orders""")
def op_running_rows(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return T(spark, sf, "orders").select("o_orderkey", F.sum(cents("o_totalprice")).over(w).alias("so_far"))


@ops.add("""SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS last_day FROM events""")
def op_sliding_range(spark, sf):
    e = T(spark, sf, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)).alias("last_day"))


@ops.add("""SELECT user_id, count(*) AS sessions FROM (SELECT user_id, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS gap FROM events) WHERE gap IS NULL OR gap > INTERVAL 30 MINUTE GROUP BY user_id""")
def op_gaps_islands(spark, sf):
    e = T(spark, sf, "events").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    gap = F.col("us") - F.lag("us").over(Window.partitionBy("user_id").orderBy("us"))
    return e.withColumn("gap", gap).filter("gap is null or gap > 1800000000").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"))


# ---- order, top k, sets


@ops.add("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def op_topk(spark, sf):
    return T(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@ops.add("SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
def op_topk_group(spark, sf):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return T(spark, sf, "part").withColumn("r", F.row_number().over(w)).filter("r <= 3").select("p_brand", "p_partkey")


@ops.add("SELECT c_custkey FROM customer ORDER BY c_acctbal, c_custkey LIMIT 10 OFFSET 5")
def op_limit_offset(spark, sf):
    return T(spark, sf, "customer").orderBy("c_acctbal", "c_custkey").offset(5).limit(10).select("c_custkey")


_C, _S = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"


def _both(spark, sf):
    return T(spark, sf, "customer").select(F.col("c_nationkey").alias("k")), T(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"))


for _key, _word, _how in (
    ("union_all", "UNION ALL", lambda a, b: a.unionByName(b)),
    ("union", "UNION", lambda a, b: a.unionByName(b).distinct()),
    ("intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    ops.add(f"{_C} {_word} {_S}", f"op_{_key}")(lambda spark, sf, f=_how: f(*_both(spark, sf)))


# ---- scalars


@ops.add("""SELECT c_custkey, upper(c_mktsegment) AS segment, length(c_name) AS chars, substr(c_name, 1, 4) AS head, trim(concat(' ', c_mktsegment, ' ')) AS bare, concat_ws('-', c_name, c_mktsegment) AS joined, replace(c_name, '#', '_') AS safe FROM customer""")
def op_str(spark, sf):
    return T(spark, sf, "customer").select(
        "c_custkey", F.upper("c_mktsegment").alias("segment"), F.length("c_name").alias("chars"), F.substring("c_name", 1, 4).alias("head"), F.trim(F.concat(F.lit(" "), "c_mktsegment", F.lit(" "))).alias("bare"), F.concat_ws("-", "c_name", "c_mktsegment").alias("joined"), F.replace("c_name", F.lit("#"), F.lit("_")).alias("safe")
    )


@ops.add("SELECT conv_id, turn, regexp_replace(text, '[aeiou]', '*', 'g') AS masked, len(regexp_extract_all(text, '[.]')) AS stops FROM conversations")
def op_regex(spark, sf):
    return T(spark, sf, "conversations").select("conv_id", "turn", F.regexp_replace("text", "[aeiou]", "*").alias("masked"), F.regexp_count("text", F.lit("[.]")).cast("bigint").alias("stops"))


@ops.add("""SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, count(*) AS n, min(date_diff('day', TIMESTAMP '1992-01-01', o_orderdate)) AS first_day FROM orders GROUP BY 1""")
def op_date(spark, sf):
    return T(spark, sf, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.min(F.datediff("o_orderdate", F.lit("1992-01-01"))).cast("bigint").alias("first_day"))


@ops.add("""SELECT p_partkey, greatest(p_size, 10) AS at_least, least(p_size, 40) AS at_most, abs(p_size - 25) AS off, CASE WHEN p_size = 7 THEN NULL ELSE round(p_retailprice / (p_size - 7), 4) END AS per_size FROM part""")
def op_math(spark, sf):
    return T(spark, sf, "part").select("p_partkey", F.greatest("p_size", F.lit(10)).alias("at_least"), F.least("p_size", F.lit(40)).alias("at_most"), F.abs(F.col("p_size") - 25).alias("off"), F.round(F.try_divide("p_retailprice", F.col("p_size") - 7), 4).alias("per_size"))


@ops.add("SELECT vec_id, len([x FOR x IN embedding IF x > 0]) AS positive, list_sum([CAST(floor(CAST(x AS DOUBLE)*1000) AS BIGINT) FOR x IN embedding])::BIGINT AS total FROM embeddings")
def op_array(spark, sf):
    mills = F.transform("embedding", lambda x: F.floor(x.cast("double") * 1000))
    return T(spark, sf, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("positive"), F.aggregate(mills, F.lit(0).cast("bigint"), lambda a, x: a + x).alias("total"))


@ops.add("SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")
def op_map(spark, sf):
    counts = T(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("view")), F.lit(0)).alias("views"), F.size("m").cast("bigint").alias("kinds"))


@ops.add("SELECT event_type, sum(CAST(json_extract(props, '$.k') AS BIGINT))::BIGINT AS k FROM events GROUP BY event_type")
def op_json(spark, sf):
    return T(spark, sf, "events").groupBy("event_type").agg(F.sum(F.from_json("props", "k bigint")["k"]).alias("k"))


@ops.add("SELECT a.n_name AS left_name, b.n_name AS right_name, levenshtein(a.n_name, b.n_name) AS distance FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_name < b.n_name")
def op_levenshtein(spark, sf):
    n = T(spark, sf, "nation")
    a, b = n.select("n_regionkey", F.col("n_name").alias("left_name")), n.select("n_regionkey", F.col("n_name").alias("right_name"))
    return a.join(b, "n_regionkey").filter("left_name < right_name").select("left_name", "right_name", F.levenshtein("left_name", "right_name").cast("bigint").alias("distance"))


@ops.add("SELECT doc_id, md5(text) AS digest FROM documents")
def op_hash_md5(spark, sf):
    return T(spark, sf, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("digest"))


@ops.add("""WITH x AS (SELECT vec_id, label, unnest(embedding) AS v, generate_subscripts(embedding, 1) AS i FROM embeddings), w AS (SELECT vec_id, label, i, round(v::DOUBLE * 4096)::BIGINT AS v FROM x),
 s AS (SELECT label, i, sum(v) AS total FROM w GROUP BY label, i) SELECT w.vec_id, w.label, sum(w.v * s.total)::BIGINT AS dot FROM w JOIN s ON w.label = s.label AND w.i = s.i GROUP BY w.vec_id, w.label""")
def op_vector_dot(spark, sf):
    """Inner product of every vector with the sum of its label's vectors, components as whole 4096ths so that no order of adding matters."""
    e = T(spark, sf, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("i", "x")).select("vec_id", "label", "i", F.round(F.col("x").cast("double") * 4096).cast("bigint").alias("v"))
    total = e.groupBy("label", "i").agg(F.sum("v").alias("total"))
    return e.join(total, ["label", "i"]).groupBy("vec_id", "label").agg(F.sum(F.col("v") * F.col("total")).alias("dot"))
