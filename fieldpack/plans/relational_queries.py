"""The relational operators around the methods, each over the given tables, with an SQL twin."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators import joins as J
from ..sources.tables import load, register_views
from .field_queries import q6, r6

QUERIES, ORACLES = {}, {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


CENTS = "CAST(round(l_extendedprice * 100) AS BIGINT)"


def li(spark, d, *cols):
    return load(spark, d, "lineitem", *cols)


def cents(c="l_extendedprice"):
    return F.round(F.col(c) * 100).cast("long")


QTR = "CAST(4 * (year(l_shipdate) - 1995) + quarter(l_shipdate) - 1 AS INTEGER)"


def qtr():
    return (4 * (F.year("l_shipdate") - 1995) + F.quarter("l_shipdate") - 1).cast("int")


@query("op_project", f"SELECT l_orderkey, l_linenumber, CAST(l_partkey % 16 AS INTEGER) AS x, {QTR} AS t, {CENTS} AS cents FROM lineitem")
def op_project(spark, d):
    return li(spark, d, "l_orderkey", "l_linenumber", "l_partkey", "l_shipdate", "l_extendedprice").select("l_orderkey", "l_linenumber", (F.col("l_partkey") % 16).cast("int").alias("x"), qtr().alias("t"), cents().alias("cents"))


@query("op_filter", f"SELECT l_orderkey, l_linenumber, {QTR} AS t, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1998-01-01' AND l_quantity <= 25")
def op_filter(spark, d):
    f = li(spark, d, "l_orderkey", "l_linenumber", "l_shipdate", "l_quantity").where((F.col("l_shipdate") >= "1996-01-01") & (F.col("l_shipdate") < "1998-01-01") & (F.col("l_quantity") <= 25))
    return f.select("l_orderkey", "l_linenumber", qtr().alias("t"), "l_quantity")


@query("op_in_between", "SELECT p_partkey, p_brand, p_type, p_size FROM part WHERE p_size BETWEEN 10 AND 30 AND (p_brand LIKE 'Brand#1%' OR regexp_matches(p_type, 'E')) AND p_size IN (10, 12, 14, 16, 18, 20, 25, 30)")
def op_in_between(spark, d):
    return load(spark, d, "part", "p_partkey", "p_brand", "p_type", "p_size").where(F.col("p_size").between(10, 30) & (F.col("p_brand").like("Brand#1%") | F.col("p_type").rlike("E")) & F.col("p_size").isin(10, 12, 14, 16, 18, 20, 25, 30))


@query("op_nulls", "SELECT doc_id, quality, coalesce(quality, -1) AS filled, quality IS NOT DISTINCT FROM toxic AS same FROM documents LEFT JOIN labels USING (doc_id)")
def op_nulls(spark, d):
    j = load(spark, d, "documents", "doc_id").join(load(spark, d, "labels"), "doc_id", "left")
    return j.select("doc_id", "quality", F.coalesce("quality", F.lit(-1)).alias("filled"), F.col("quality").eqNullSafe(F.col("toxic")).alias("same"))


def _orders_join(hint: str):
    def run(spark, d):
        o = load(spark, d, "orders", "o_orderkey", "o_orderstatus", "o_orderpriority")
        j = li(spark, d, "l_orderkey", "l_extendedprice").join(o.hint(hint), F.col("l_orderkey") == F.col("o_orderkey"))
        return j.groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.sum(cents()).alias("cents"))

    return run


_ORDERS_SQL = f"SELECT o_orderstatus, o_orderpriority, count(*) AS n, CAST(sum({CENTS}) AS BIGINT) AS cents FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2"
for _name, _hint in (("op_join_hash", "shuffle_hash"), ("op_join_smj", "merge")):
    QUERIES[_name], ORACLES[_name] = _orders_join(_hint), _ORDERS_SQL


@query("op_join_bcast", f"SELECT r_name, n_name, count(*) AS n, CAST(sum({CENTS}) AS BIGINT) AS cents FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def op_join_bcast(spark, d):
    axis = load(spark, d, "supplier", "s_suppkey", "s_nationkey").join(F.broadcast(load(spark, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return J.join_dimension(li(spark, d, "l_suppkey", "l_extendedprice"), axis, F.col("l_suppkey") == F.col("s_suppkey")).groupBy("r_name", "n_name").agg(F.count("*").alias("n"), F.sum(cents()).alias("cents"))


@query("op_join_nl", "WITH c AS (SELECT label, list_sum(embedding) AS s FROM embeddings WHERE vec_id < 10), e AS (SELECT vec_id, list_sum(embedding) AS s FROM embeddings) SELECT count(*) AS n FROM e, c WHERE e.s > c.s + 0.5")
def op_join_nl(spark, d):
    s = load(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.aggregate("embedding", F.lit(0.0), lambda a, v: a + v).alias("s"))
    c = s.where("vec_id < 10").select(F.col("s").alias("c"))
    return s.join(F.broadcast(c), F.col("s") > F.col("c") + 0.5).agg(F.count("*").alias("n"))


@query("op_join_nl_labels", "WITH e AS (SELECT label, list_sum(embedding) AS s FROM embeddings), c AS (SELECT label, avg(s) AS s FROM e GROUP BY 1) SELECT count(*) AS n FROM e, c WHERE e.s > c.s + 0.5")
def op_join_nl_labels(spark, d):
    """As `op_join_nl`, whose SQL takes ten rows by id, with the labels' centroids: a centroid's sum is the mean of its rows' sums."""
    s = load(spark, d, "embeddings", "label", "embedding").select("label", F.aggregate("embedding", F.lit(0.0), lambda a, v: a + v).alias("s"))
    c = s.groupBy("label").agg(F.avg("s").alias("c")).select("c")
    return s.join(F.broadcast(c), F.col("s") > F.col("c") + 0.5).agg(F.count("*").alias("n"))


_BANDS = "b AS (SELECT CAST(i AS INTEGER) AS band, CAST(i * 9000 AS DOUBLE) AS lo, CAST((i + 1) * 9000 AS DOUBLE) AS hi FROM range(0, 12) r(i))"


@query("op_join_range", f"WITH {_BANDS} SELECT band, count(*) AS n FROM lineitem JOIN b ON l_extendedprice >= lo AND l_extendedprice < hi GROUP BY 1")
def op_join_range(spark, d):
    bands = spark.range(12).select(F.col("id").cast("int").alias("band"), (F.col("id") * 9000.0).alias("lo"), ((F.col("id") + 1) * 9000.0).alias("hi"))
    return J.range_join(li(spark, d, "l_extendedprice"), "l_extendedprice", bands, "lo", "hi", 5000.0).groupBy("band").agg(F.count("*").alias("n"))


@query("op_join_asof", """SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN
 (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY 1, 2) v ON p.user_id = v.user_id AND p.ts >= v.ts""")
def op_join_asof(spark, d):
    e = load(spark, d, "events", "event_id", "user_id", "ts", "event_type")
    return J.asof_join(e.where("event_type = 'purchase'"), e.where("event_type = 'view'"), "user_id", "ts", "event_id").select("event_id", F.col("matched").alias("view_id"))


@query("op_join_interval", "SELECT e.event_id AS error_id, p.event_id AS purchase_id FROM events e JOIN events p ON e.user_id = p.user_id AND e.event_type = 'error' AND p.event_type = 'purchase' AND p.ts BETWEEN e.ts - INTERVAL 1 HOUR AND e.ts + INTERVAL 1 HOUR")
def op_join_interval(spark, d):
    e = load(spark, d, "events", "event_id", "user_id", "ts", "event_type")
    return J.interval_join(e.where("event_type = 'error'"), e.where("event_type = 'purchase'"), "user_id", "ts", 3600).select(F.col("event_id").alias("error_id"), F.col("other_id").alias("purchase_id"))


@query("op_join_left", "SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def op_join_left(spark, d):
    return load(spark, d, "customer", "c_custkey").join(load(spark, d, "orders", "o_orderkey", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("op_join_full", f"WITH a AS (SELECT l_partkey % 16 AS x, l_suppkey % 8 AS y, sum({CENTS}) AS v FROM lineitem WHERE year(l_shipdate) = 1996 AND l_linenumber = 1 GROUP BY 1, 2), b AS (SELECT l_partkey % 16 AS x, l_suppkey % 8 AS y, sum({CENTS}) AS v FROM lineitem WHERE year(l_shipdate) = 1997 AND l_linenumber = 7 GROUP BY 1, 2) SELECT x, y, CAST(coalesce(a.v, 0) - coalesce(b.v, 0) AS BIGINT) AS change FROM a FULL JOIN b USING (x, y)")
def op_join_full(spark, d):
    f = li(spark, d, "l_partkey", "l_suppkey", "l_shipdate", "l_linenumber", "l_extendedprice").select((F.col("l_partkey") % 16).alias("x"), (F.col("l_suppkey") % 8).alias("y"), F.year("l_shipdate").alias("yr"), "l_linenumber", cents().alias("c"))
    side = lambda yr, ln, name: f.where((F.col("yr") == yr) & (F.col("l_linenumber") == ln)).groupBy("x", "y").agg(F.sum("c").alias(name))
    return side(1996, 1, "a").join(side(1997, 7, "b"), ["x", "y"], "full").select("x", "y", (F.coalesce("a", F.lit(0)) - F.coalesce("b", F.lit(0))).alias("change"))


@query("op_join_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def op_join_semi(spark, d):
    return load(spark, d, "documents", "doc_id", "lang").join(load(spark, d, "labels", "doc_id"), "doc_id", "left_semi")


@query("op_join_anti", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti(spark, d):
    return load(spark, d, "documents", "doc_id", "lang").join(load(spark, d, "labels", "doc_id"), "doc_id", "left_anti")


@query("op_join_neighbor", f"WITH g AS (SELECT l_partkey % 64 AS x, CAST(sum({CENTS}) AS BIGINT) AS v FROM lineitem GROUP BY 1) SELECT a.x, a.v, b.v - a.v AS step FROM g a JOIN g b ON b.x = a.x + 1")
def op_join_neighbor(spark, d):
    g = li(spark, d, "l_partkey", "l_extendedprice").groupBy((F.col("l_partkey") % 64).alias("x")).agg(F.sum(cents()).alias("v"))
    return g.join(g.select((F.col("x") - 1).alias("x"), F.col("v").alias("n")), "x").select("x", "v", (F.col("n") - F.col("v")).alias("step"))


@query("op_join_salted", f"SELECT o_orderstatus, l_returnflag, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2")
def op_join_salted(spark, d):
    o = load(spark, d, "orders", "o_orderkey", "o_orderstatus").withColumnRenamed("o_orderkey", "l_orderkey")
    return J.salted_join(li(spark, d, "l_orderkey", "l_returnflag"), o, "l_orderkey", 8).groupBy("o_orderstatus", "l_returnflag").agg(F.count("*").alias("n"))


@query("op_agg_hash", f"SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum({CENTS}) AS BIGINT) AS cents, min(l_quantity) AS lo, max(l_quantity) AS hi FROM lineitem GROUP BY 1, 2")
def op_agg_hash(spark, d):
    return li(spark, d, "l_returnflag", "l_linestatus", "l_extendedprice", "l_quantity").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(cents()).alias("cents"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"))


@query("op_agg_sort", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def op_agg_sort(spark, d):
    return load(spark, d, "nation", "n_regionkey", "n_name").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


@query("op_agg_distinct", "SELECT CAST(l_partkey % 16 AS INTEGER) AS x, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1")
def op_agg_distinct(spark, d):
    return li(spark, d, "l_partkey", "l_suppkey", "l_orderkey").groupBy((F.col("l_partkey") % 16).cast("int").alias("x")).agg(F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_orderkey").alias("orders"))


@query("op_agg_approx")
def op_agg_approx(spark, d):
    return load(spark, d, "events", "ts", "user_id", "value").groupBy(F.datediff("ts", F.lit("2024-01-01")).alias("day")).agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("median"))


@query("op_agg_stats", f"SELECT {QTR} AS t, count(*) AS n, {q6('stddev_pop(l_extendedprice)', 'sd', 4)}, {q6('var_samp(l_quantity)', 'var', 6)}, {q6('corr(l_quantity, l_discount)', 'corr', 6)}, {q6('covar_pop(l_quantity, l_tax)', 'cov', 6)} FROM lineitem GROUP BY 1")
def op_agg_stats(spark, d):
    return li(spark, d, "l_shipdate", "l_extendedprice", "l_quantity", "l_discount", "l_tax").groupBy(qtr().alias("t")).agg(F.count("*").alias("n"), r6(F.stddev_pop("l_extendedprice"), "sd", 4), r6(F.var_samp("l_quantity"), "var"), r6(F.corr("l_quantity", "l_discount"), "corr"), r6(F.covar_pop("l_quantity", "l_tax"), "cov"))


@query("op_agg_minby", "SELECT user_id, arg_max(event_id, (value, -event_id)) AS top_event, arg_min(event_id, (ts, event_id)) AS first_event FROM events GROUP BY 1")
def op_agg_minby(spark, d):
    return load(spark, d, "events", "user_id", "event_id", "ts", "value").groupBy("user_id").agg(F.max_by("event_id", F.struct("value", -F.col("event_id"))).alias("top_event"), F.min_by("event_id", F.struct("ts", "event_id")).alias("first_event"))


@query("op_agg_filter", "SELECT user_id % 16 AS x, count(*) FILTER (event_type = 'error') AS errors, CAST(sum(CASE WHEN value > 50 THEN 1 ELSE 0 END) AS BIGINT) AS large FROM events GROUP BY 1")
def op_agg_filter(spark, d):
    return load(spark, d, "events", "user_id", "event_type", "value").groupBy((F.col("user_id") % 16).alias("x")).agg(F.count_if(F.col("event_type") == "error").alias("errors"), F.sum(F.when(F.col("value") > 50, 1).otherwise(0)).alias("large"))


_CUBE = "coalesce(l_returnflag, '*') AS flag, coalesce(l_linestatus, '*') AS status, count(*) AS n"


@query("op_rollup", f"SELECT {_CUBE} FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def op_rollup(spark, d):
    return li(spark, d, "l_returnflag", "l_linestatus").rollup("l_returnflag", "l_linestatus").count().select(F.coalesce("l_returnflag", F.lit("*")).alias("flag"), F.coalesce("l_linestatus", F.lit("*")).alias("status"), F.col("count").alias("n"))


@query("op_cube", f"SELECT {_CUBE} FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def op_cube(spark, d):
    return li(spark, d, "l_returnflag", "l_linestatus").cube("l_returnflag", "l_linestatus").count().select(F.coalesce("l_returnflag", F.lit("*")).alias("flag"), F.coalesce("l_linestatus", F.lit("*")).alias("status"), F.col("count").alias("n"))


_GSETS = "SELECT coalesce(l_returnflag, '*') AS flag, coalesce(l_linestatus, '*') AS status, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())"


@query("op_gsets", _GSETS)
def op_gsets(spark, d):
    return spark.sql(_GSETS.replace("FROM lineitem", "FROM {src}"), src=li(spark, d, "l_returnflag", "l_linestatus"))


@query("op_pivot", "SELECT CAST(ts AS DATE) - DATE '2024-01-01' AS day, " + ", ".join(f"count(*) FILTER (event_type = '{e}') AS {e}" for e in ("view", "purchase", "error")) + " FROM events WHERE event_type IN ('view', 'purchase', 'error') GROUP BY 1")
def op_pivot(spark, d):
    e = load(spark, d, "events", "ts", "event_type").select(F.datediff("ts", F.lit("2024-01-01")).cast("long").alias("day"), "event_type")
    return e.groupBy("day").pivot("event_type", ["view", "purchase", "error"]).count().na.fill(0).where("view + purchase + error > 0")


@query("op_unpivot", "SELECT doc_id, name, CAST(value AS INTEGER) AS value FROM labels UNPIVOT (value FOR name IN (quality, toxic))")
def op_unpivot(spark, d):
    return load(spark, d, "labels").unpivot(["doc_id"], ["quality", "toxic"], "name", "value").select("doc_id", "name", F.col("value").cast("int").alias("value"))


@query("op_win_rank", "SELECT event_id, row_number() OVER w AS rn, rank() OVER (PARTITION BY user_id ORDER BY event_type) AS rk, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS dr FROM events WINDOW w AS (PARTITION BY user_id ORDER BY value DESC, event_id)")
def op_win_rank(spark, d):
    u = W.partitionBy("user_id")
    return load(spark, d, "events", "event_id", "user_id", "event_type", "value").select("event_id", F.row_number().over(u.orderBy(F.desc("value"), "event_id")).cast("long").alias("rn"), F.rank().over(u.orderBy("event_type")).cast("long").alias("rk"), F.dense_rank().over(u.orderBy("event_type")).cast("long").alias("dr"))


@query("op_win_dist", f"SELECT doc_id, ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS tile, {q6('percent_rank() OVER (PARTITION BY lang ORDER BY n_chars)', 'pr')}, {q6('cume_dist() OVER (PARTITION BY lang ORDER BY n_chars)', 'cd')} FROM documents")
def op_win_dist(spark, d):
    w = W.partitionBy("lang").orderBy("n_chars")
    return load(spark, d, "documents", "doc_id", "lang", "n_chars").select("doc_id", F.ntile(4).over(W.partitionBy("lang").orderBy("n_chars", "doc_id")).cast("long").alias("tile"), r6(F.percent_rank().over(w), "pr"), r6(F.cume_dist().over(w), "cd"))


_CELLS = f"g AS (SELECT l_partkey % 16 AS x, {QTR} AS t, CAST(sum({CENTS}) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2)"


def cells(spark, d):
    return li(spark, d, "l_partkey", "l_shipdate", "l_extendedprice").groupBy((F.col("l_partkey") % 16).alias("x"), qtr().alias("t")).agg(F.sum(cents()).alias("v"))


@query("op_win_lag", f"WITH {_CELLS} SELECT x, t, v - lag(v) OVER w AS before, lead(v, 2) OVER w - v AS after FROM g WINDOW w AS (PARTITION BY x ORDER BY t)")
def op_win_lag(spark, d):
    w = W.partitionBy("x").orderBy("t")
    return cells(spark, d).select("x", "t", (F.col("v") - F.lag("v").over(w)).alias("before"), (F.lead("v", 2).over(w) - F.col("v")).alias("after"))


@query("op_win_rows", f"WITH {_CELLS} SELECT x, t, CAST(sum(v) OVER (PARTITION BY x ORDER BY t ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS s FROM g")
def op_win_rows(spark, d):
    return cells(spark, d).select("x", "t", F.sum("v").over(W.partitionBy("x").orderBy("t").rowsBetween(-1, 1)).alias("s"))


@query("op_win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def op_win_range(spark, d):
    w = W.partitionBy("user_id").orderBy(J.seconds_of("ts")).rangeBetween(-3600, 0)
    return load(spark, d, "events", "event_id", "user_id", "ts").select("event_id", F.count("*").over(w).alias("n"))


@query("op_win_first", "SELECT event_id, first_value(event_id) OVER w AS f, last_value(event_id) OVER w AS l, nth_value(event_id, 2) OVER w AS n2 FROM events WINDOW w AS (PARTITION BY user_id, CAST(ts AS DATE) ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def op_win_first(spark, d):
    w = W.partitionBy("user_id", F.to_date("ts")).orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return load(spark, d, "events", "event_id", "user_id", "ts").select("event_id", F.first("event_id").over(w).alias("f"), F.last("event_id").over(w).alias("l"), F.nth_value("event_id", 2).over(w).alias("n2"))


@query("op_sort", "SELECT s_suppkey, s_name FROM supplier ORDER BY s_acctbal DESC, s_suppkey")
def op_sort(spark, d):
    return load(spark, d, "supplier", "s_suppkey", "s_name", "s_acctbal").orderBy(F.desc("s_acctbal"), "s_suppkey").select("s_suppkey", "s_name")


@query("op_limit", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 25")
def op_limit(spark, d):
    return load(spark, d, "orders", "o_orderkey").orderBy("o_orderkey").limit(25)


@query("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def op_topk(spark, d):
    return load(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("op_topk_group", "SELECT o_orderpriority, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def op_topk_group(spark, d):
    w = W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return load(spark, d, "orders", "o_orderpriority", "o_orderkey", "o_totalprice").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_orderpriority", "o_orderkey")


def _keys(spark, d, lo, hi):
    return li(spark, d, "l_suppkey", "l_quantity").where(F.col("l_quantity").between(lo, hi)).select((F.col("l_suppkey") % 50).alias("k"))


_A, _B = "SELECT l_suppkey % 50 AS k FROM lineitem WHERE l_quantity BETWEEN 1 AND 1", "SELECT l_suppkey % 50 AS k FROM lineitem WHERE l_quantity BETWEEN 50 AND 50"
for _name, _op, _f in (
    ("op_union", "UNION", lambda a, b: a.union(b).distinct()), ("op_unionall", "UNION ALL", lambda a, b: a.unionAll(b)), ("op_unionbyname", "UNION ALL BY NAME", lambda a, b: a.unionByName(b)),
    ("op_intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("op_except", "EXCEPT", lambda a, b: a.subtract(b)), ("op_exceptall", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    QUERIES[_name] = (lambda f: lambda spark, d: f(_keys(spark, d, 1, 1), _keys(spark, d, 50, 50)))(_f)
    ORACLES[_name] = f"{_A} {_op} {_B}"


@query("op_distinct", "SELECT DISTINCT l_returnflag, l_linestatus, year(l_shipdate) AS y FROM lineitem")
def op_distinct(spark, d):
    return li(spark, d, "l_returnflag", "l_linestatus", "l_shipdate").select("l_returnflag", "l_linestatus", F.year("l_shipdate").cast("long").alias("y")).distinct()


@query("op_dedup", "SELECT l_orderkey, l_linenumber, min(l_partkey) AS l_partkey FROM lineitem GROUP BY 1, 2")
def op_dedup(spark, d):
    w = W.partitionBy("l_orderkey", "l_linenumber").orderBy("l_partkey")
    return li(spark, d, "l_orderkey", "l_linenumber", "l_partkey").withColumn("r", F.row_number().over(w)).where("r = 1").drop("r")


@query("op_sample_hash", "SELECT event_id FROM events WHERE (event_id * 2654435761) % 97 < 10")
def op_sample_hash(spark, d):
    return load(spark, d, "events", "event_id").where((F.col("event_id") * 2654435761) % 97 < 10)


@query("op_sample_strat", "SELECT event_id, event_type FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY (event_id * 48271) % 2147483647, event_id) AS r, count(*) OVER (PARTITION BY event_type) AS n FROM events) WHERE r <= n * 0.25")
def op_sample_strat(spark, d):
    w = W.partitionBy("event_type")
    e = load(spark, d, "events", "event_id", "event_type").withColumn("r", F.row_number().over(w.orderBy((F.col("event_id") * 48271) % 2147483647, "event_id"))).withColumn("n", F.count("*").over(w))
    return e.where(F.col("r") <= F.col("n") * 0.25).select("event_id", "event_type")


def _sql(name: str, text: str, tables: tuple[str, ...]):
    """The same text in both engines, over temporary views."""

    def run(spark, d):
        register_views(spark, d, list(tables))
        return spark.sql(text)

    QUERIES[name], ORACLES[name] = run, text


_sql("op_subq_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.9 FROM orders)", ("orders",))
_sql("op_subq_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')", ("customer", "orders"))
_sql("op_subq_in", "SELECT s_suppkey FROM supplier WHERE s_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)", ("supplier", "nation"))
_sql("op_subq_corr", "SELECT event_id FROM events e WHERE value > 2 * (SELECT avg(value) FROM events i WHERE i.user_id = e.user_id)", ("events",))
_sql("op_cte", "WITH a AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), b AS (SELECT n, count(*) AS customers FROM a GROUP BY n) SELECT n, customers FROM b", ("orders",))


@query("op_explode", "SELECT vec_id, round(CAST(unnest(embedding) AS DOUBLE), 6) + 0.0 AS v FROM embeddings")
def op_explode(spark, d):
    return load(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.explode("embedding").alias("x")).select("vec_id", r6(F.col("x").cast("double"), "v"))


@query("op_posexplode", "SELECT vec_id, CAST(unnest(range(0, 64)) AS INTEGER) AS p, round(CAST(unnest(embedding) AS DOUBLE), 6) + 0.0 AS v FROM embeddings")
def op_posexplode(spark, d):
    return load(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("p", "x")).select("vec_id", "p", r6(F.col("x").cast("double"), "v"))


@query("op_lateral", "SELECT n_nationkey, CAST(s AS INTEGER) AS scale, CAST(ceil(n_nationkey / pow(2, s - 1)) AS BIGINT) AS extent FROM nation, (SELECT unnest([1, 2, 3]) AS s)")
def op_lateral(spark, d):
    return spark.sql("SELECT n_nationkey, scale, CAST(ceil(n_nationkey / pow(2, scale - 1)) AS BIGINT) AS extent FROM {n}, LATERAL (SELECT explode(array(1, 2, 3)) AS scale)", n=load(spark, d, "nation", "n_nationkey"))


@query("op_cache_repart", f"SELECT x, t, v FROM (WITH {_CELLS} SELECT * FROM g)")
def op_cache_repart(spark, d):
    return cells(spark, d).repartitionByRange(8, "x", "t").sortWithinPartitions("x", "t")
