"""Operators around the methods, on the given tables; each has the same question in SQL for DuckDB."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def op(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            SQL[name or f.__name__] = sql
        return f

    return add


def t(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


# scans, filters, projections


@op("SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1998-01-01'")
def op_scan_pruned(spark, sf):
    return t(spark, sf, "lineitem").where(F.col("l_shipdate") >= F.to_timestamp_ntz(F.lit("1998-01-01 00:00:00"))).select("l_orderkey", "l_quantity")


BOX = "l_quantity >= 10 AND l_quantity < 30 AND l_discount >= 0.02 AND l_discount < 0.07"


@op(f"SELECT l_orderkey, l_linenumber, l_quantity, l_discount FROM lineitem WHERE {BOX}")
def op_box_filter(spark, sf):
    return t(spark, sf, "lineitem").where(BOX).select("l_orderkey", "l_linenumber", "l_quantity", "l_discount")


HOLE = "l_quantity >= 15 AND l_quantity < 20 AND l_discount >= 0.03 AND l_discount < 0.05"


@op(f"SELECT l_orderkey, l_linenumber, l_quantity, l_discount FROM lineitem WHERE {BOX} AND NOT ({HOLE})")
def op_hole_filter(spark, sf):
    return t(spark, sf, "lineitem").where(f"{BOX} AND NOT ({HOLE})").select("l_orderkey", "l_linenumber", "l_quantity", "l_discount")


BALL = "(l_quantity - 25) * (l_quantity - 25) + (100 * l_discount - 5) * (100 * l_discount - 5) <= 16"


@op(f"SELECT l_orderkey, l_linenumber, l_quantity, l_discount FROM lineitem WHERE {BALL}")
def op_ball_filter(spark, sf):
    return t(spark, sf, "lineitem").where(BALL).select("l_orderkey", "l_linenumber", "l_quantity", "l_discount")


@op("""SELECT p_partkey, p_brand, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS size_class FROM part
 WHERE p_brand IN ('Brand#11', 'Brand#12', 'Brand#23') OR p_name LIKE '%1%' AND p_size BETWEEN 5 AND 40 AND p_type IS NOT NULL AND regexp_matches(p_brand, '#[1-3]')""")
def op_predicates(spark, sf):
    size = F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large")
    like = F.col("p_name").like("%1%") & F.col("p_size").between(5, 40) & F.col("p_type").isNotNull() & F.col("p_brand").rlike("#[1-3]")
    return t(spark, sf, "part").where(F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#23") | like).select("p_partkey", "p_brand", size.alias("size_class"))


@op("SELECT o_orderkey, o_totalprice / 1000.0 AS price_k, CAST(o_custkey AS VARCHAR) AS cust FROM orders")
def op_project_scale(spark, sf):
    return t(spark, sf, "orders").select("o_orderkey", (F.col("o_totalprice") / 1000.0).alias("price_k"), F.col("o_custkey").cast("string").alias("cust"))


@op("SELECT o_orderkey, CASE WHEN o_orderstatus = 'F' THEN 1.0 ELSE 0.0 END AS is_f, CASE WHEN o_orderstatus = 'O' THEN 1.0 ELSE 0.0 END AS is_o, CASE WHEN o_orderstatus = 'P' THEN 1.0 ELSE 0.0 END AS is_p FROM orders")
def op_one_hot(spark, sf):
    return t(spark, sf, "orders").select("o_orderkey", *[F.when(F.col("o_orderstatus") == v, 1.0).otherwise(0.0).alias(f"is_{v.lower()}") for v in "FOP"])


@op("SELECT l_quantity, l_discount, count(*) AS w FROM lineitem GROUP BY ALL")
def op_bag_project(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_quantity", "l_discount").agg(F.count("*").alias("w"))


@op("SELECT DISTINCT l_quantity, l_discount FROM lineitem")
def op_set_project(spark, sf):
    return t(spark, sf, "lineitem").select("l_quantity", "l_discount").distinct()


# joins


def _hinted(hint: str):
    def run(spark, sf):
        c, o = t(spark, sf, "customer"), t(spark, sf, "orders")
        return o.join(c.hint(hint), o["o_custkey"] == c["c_custkey"]).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))

    return run


for _h, _n in (("broadcast", "op_join_broadcast"), ("shuffle_hash", "op_join_shuffle_hash"), ("merge", "op_join_sort_merge")):
    op("SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1", _n)(_hinted(_h))


def _outer(how: str):
    def run(spark, sf):
        o, l = t(spark, sf, "orders"), t(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("items"))
        return o.join(l, o["o_orderkey"] == l["l_orderkey"], how).select("o_orderkey", "l_orderkey", "items")

    return run


for _h in ("left", "right", "full"):
    op(f"SELECT o_orderkey, l_orderkey, items FROM orders {_h.upper()} JOIN (SELECT l_orderkey, count(*) AS items FROM lineitem GROUP BY 1) l ON o_orderkey = l_orderkey", f"op_join_{_h}")(_outer(_h))


@op("SELECT o_orderkey FROM orders SEMI JOIN lineitem ON o_orderkey = l_orderkey")
def op_join_semi(spark, sf):
    return t(spark, sf, "orders").join(t(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey")


@op("SELECT o_orderkey FROM orders ANTI JOIN lineitem ON o_orderkey = l_orderkey")
def op_join_anti(spark, sf):
    return t(spark, sf, "orders").join(t(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@op("SELECT c_custkey, s_suppkey FROM customer JOIN supplier ON c_nationkey = s_nationkey AND c_acctbal < s_acctbal")
def op_join_theta(spark, sf):
    return t(spark, sf, "customer").join(t(spark, sf, "supplier"), (F.col("c_nationkey") == F.col("s_nationkey")) & (F.col("c_acctbal") < F.col("s_acctbal"))).select("c_custkey", "s_suppkey")


@op("SELECT i AS box_id, count(*) AS n FROM lineitem, range(16) b(i) WHERE l_quantity >= 3 * i AND l_quantity < 3 * i + 10 AND l_discount * 100 >= i / 2.0 AND l_discount * 100 < i / 2.0 + 3 GROUP BY 1")
def op_join_range_boxes(spark, sf):
    boxes = spark.range(16).select(F.col("id").alias("box_id"))
    i = F.col("box_id")
    test = (F.col("l_quantity") >= 3 * i) & (F.col("l_quantity") < 3 * i + 10) & (F.col("l_discount") * 100 >= i / 2.0) & (F.col("l_discount") * 100 < i / 2.0 + 3)
    rows = t(spark, sf, "lineitem").groupBy("l_quantity", "l_discount").agg(F.count("*").alias("w"))
    return rows.join(F.broadcast(boxes), test).groupBy("box_id").agg(F.sum("w").alias("n"))


@op("SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def op_join_interval(spark, sf):
    e = t(spark, sf, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = 3_600_000_000
    a = e.select(F.col("event_id").alias("first"), "user_id", F.col("us").alias("ua"), F.floor(F.col("us") / hour).alias("slot"))
    b = e.select(F.col("event_id").alias("second"), "user_id", F.col("us").alias("ub"), F.explode(F.array(F.floor(F.col("us") / hour), F.floor(F.col("us") / hour) - 1)).alias("slot"))
    return a.join(b, ["user_id", "slot"]).where((F.col("ub") > F.col("ua")) & (F.col("ub") <= F.col("ua") + hour)).select("first", "second")


@op("""SELECT c.event_id, p.event_id AS purchase_id FROM (SELECT * FROM events WHERE event_type = 'click') c
 ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) p ON c.user_id = p.user_id AND c.ts >= p.ts""")
def op_join_asof(spark, sf):
    e = t(spark, sf, "events").where(F.col("event_type").isin("click", "purchase"))
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    buy = F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))
    return e.withColumn("p", F.max(buy).over(w)).where("event_type = 'click'").select("event_id", F.col("p.event_id").alias("purchase_id"))


@op("SELECT a.r_name AS x, b.r_name AS y FROM region a CROSS JOIN region b")
def op_join_cross(spark, sf):
    r = t(spark, sf, "region")
    return r.select(F.col("r_name").alias("x")).crossJoin(r.select(F.col("r_name").alias("y")))


@op("SELECT a.l_orderkey, count(*) AS pairs FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey GROUP BY 1")
def op_join_self_pairs(spark, sf):
    n = t(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("c"))
    return n.select("l_orderkey", (F.col("c") * F.col("c")).alias("pairs"))


@op("SELECT c_custkey, s_suppkey, l_orderkey, l_linenumber, l_quantity FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey JOIN supplier ON l_suppkey = s_suppkey AND s_nationkey = c_nationkey")
def op_join_cycle(spark, sf):
    left = t(spark, sf, "orders").join(t(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).select("o_custkey", "l_suppkey", "l_orderkey", "l_linenumber", "l_quantity")
    right = t(spark, sf, "customer").join(t(spark, sf, "supplier"), F.col("c_nationkey") == F.col("s_nationkey")).select("c_custkey", "s_suppkey")
    return left.join(right, (F.col("o_custkey") == F.col("c_custkey")) & (F.col("l_suppkey") == F.col("s_suppkey"))).select("c_custkey", "s_suppkey", "l_orderkey", "l_linenumber", "l_quantity")


@op("SELECT DISTINCT c_custkey, s_suppkey FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey JOIN supplier ON l_suppkey = s_suppkey AND s_nationkey = c_nationkey")
def op_join_triangle(spark, sf):
    pairs = t(spark, sf, "orders").join(t(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).select("o_custkey", "l_suppkey").distinct()
    near = pairs.join(t(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return near.join(t(spark, sf, "supplier"), (F.col("l_suppkey") == F.col("s_suppkey")) & (F.col("c_nationkey") == F.col("s_nationkey"))).select("c_custkey", "s_suppkey")


@op("SELECT n_name, c_custkey, c_acctbal FROM (SELECT n_name, c_custkey, c_acctbal, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn FROM nation JOIN customer ON c_nationkey = n_nationkey) WHERE rn <= 3")
def op_join_lateral_topk(spark, sf):
    spark_n, c = t(spark, sf, "nation"), t(spark, sf, "customer")
    top = c.groupBy("c_nationkey").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("c_acctbal")).alias("b"), "c_custkey"))), 1, 3).alias("best"))
    return spark_n.join(top, F.col("n_nationkey") == F.col("c_nationkey")).select("n_name", F.explode("best").alias("x")).select("n_name", F.col("x.c_custkey").alias("c_custkey"), (-F.col("x.b")).alias("c_acctbal"))


# aggregation


@op("SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS qty, round(avg(l_extendedprice), 4) AS avg_price, min(l_discount) AS lo, max(l_discount) AS hi FROM lineitem GROUP BY 1, 2")
def op_agg_basic(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("avg_price"), F.min("l_discount").alias("lo"), F.max("l_discount").alias("hi"))


@op("SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS vp, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_samp(l_quantity, l_discount), 6) AS cv FROM lineitem GROUP BY 1")
def op_agg_stats(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_quantity"), 6).alias("vp"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.covar_samp("l_quantity", "l_discount"), 6).alias("cv"))


@op("SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS f, count(*) FILTER (WHERE o_totalprice > 250000) AS big FROM orders GROUP BY 1")
def op_agg_filter_clause(spark, sf):
    return t(spark, sf, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("f"), F.count_if(F.col("o_totalprice") > 250000).alias("big"))


@op("SELECT c_nationkey, arg_min(c_custkey, (c_acctbal, c_custkey)) AS poorest, arg_max(c_custkey, (c_acctbal, c_custkey)) AS richest FROM customer GROUP BY 1")
def op_agg_min_by(spark, sf):
    return t(spark, sf, "customer").groupBy("c_nationkey").agg(F.min_by("c_custkey", F.struct("c_acctbal", "c_custkey")).alias("poorest"), F.max_by("c_custkey", F.struct("c_acctbal", "c_custkey")).alias("richest"))


@op("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY 1")
def op_agg_distinct(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps"))


@op("SELECT count(DISTINCT user_id) AS users, TRUE AS near FROM events")
def op_agg_approx_distinct(spark, sf):
    return t(spark, sf, "events").agg(F.countDistinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("a")).select("users", (F.abs(F.col("a") - F.col("users")) <= 0.1 * F.col("users")).alias("near"))


@op("SELECT o_orderstatus, round(quantile_cont(o_totalprice, 0.5), 4) AS median, round(quantile_cont(o_totalprice, 0.9), 4) AS p90 FROM orders GROUP BY 1")
def op_agg_percentile(spark, sf):
    return t(spark, sf, "orders").groupBy("o_orderstatus").agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("median"), F.round(F.percentile("o_totalprice", 0.9), 4).alias("p90"))


@op("SELECT count(*) AS n, TRUE AS near FROM orders")
def op_agg_approx_percentile(spark, sf):
    r = t(spark, sf, "orders").agg(F.count("*").alias("n"), F.percentile_approx("o_totalprice", 0.5, 10000).alias("a"), F.percentile("o_totalprice", 0.49).alias("lo"), F.percentile("o_totalprice", 0.51).alias("hi"))
    return r.select("n", F.col("a").between(F.col("lo"), F.col("hi")).alias("near"))


@op("SELECT CAST(floor(o_totalprice / 50000) AS BIGINT) AS bin, count(*) AS n FROM orders GROUP BY 1")
def op_histogram(spark, sf):
    return t(spark, sf, "orders").groupBy(F.floor(F.col("o_totalprice") / 50000).alias("bin")).agg(F.count("*").alias("n"))


def _oc(spark, sf):
    return t(spark, sf, "orders").join(t(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey"))


_AGG = "count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey"


def _sums():
    return [F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total")]


@op(f"SELECT o_orderstatus, c_mktsegment, {_AGG} GROUP BY ROLLUP (o_orderstatus, c_mktsegment)")
def op_rollup(spark, sf):
    return _oc(spark, sf).rollup("o_orderstatus", "c_mktsegment").agg(*_sums())


@op(f"SELECT o_orderstatus, c_mktsegment, {_AGG} GROUP BY CUBE (o_orderstatus, c_mktsegment)")
def op_cube(spark, sf):
    return _oc(spark, sf).cube("o_orderstatus", "c_mktsegment").agg(*_sums())


@op(f"SELECT o_orderstatus, c_mktsegment, CAST(grouping_id(o_orderstatus, c_mktsegment) AS BIGINT) AS gid, {_AGG} GROUP BY GROUPING SETS ((o_orderstatus), (c_mktsegment))")
def op_grouping_sets(spark, sf):
    return _oc(spark, sf).groupingSets([[F.col("o_orderstatus")], [F.col("c_mktsegment")]], F.col("o_orderstatus"), F.col("c_mktsegment")).agg(F.grouping_id().cast("long").alias("gid"), *_sums())


@op("SELECT c_mktsegment, count(*) FILTER (WHERE o_orderstatus = 'F') AS F, count(*) FILTER (WHERE o_orderstatus = 'O') AS O, count(*) FILTER (WHERE o_orderstatus = 'P') AS P FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def op_pivot(spark, sf):
    return _oc(spark, sf).groupBy("c_mktsegment").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0)


# windows

_OW = "OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)"


def _by_price():
    return Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")


def _window(name: str, expression: Callable, sql: str):
    @op(f"SELECT o_orderkey, {sql} AS v FROM orders", name)
    def run(spark, sf):
        return t(spark, sf, "orders").select("o_orderkey", expression().alias("v"))


_window("op_win_row_number", lambda: F.row_number().over(_by_price()).cast("long"), f"row_number() {_OW}")
_window("op_win_rank", lambda: F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).cast("long"), "rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)")
_window("op_win_dense", lambda: F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).cast("long"), "dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)")
_window("op_win_pct", lambda: F.round(F.percent_rank().over(_by_price()), 6), f"round(percent_rank() {_OW}, 6)")
_window("op_win_cume", lambda: F.round(F.cume_dist().over(_by_price()), 6), f"round(cume_dist() {_OW}, 6)")
_window("op_win_ntile", lambda: F.ntile(4).over(_by_price()).cast("long"), f"ntile(4) {_OW}")
_window("op_win_nth", lambda: F.nth_value("o_orderkey", 2).over(_by_price()), f"nth_value(o_orderkey, 2) {_OW}")
_window("op_win_first_last", lambda: F.last("o_orderkey").over(_by_price().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)) - F.first("o_orderkey").over(_by_price()), "last_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) - first_value(o_orderkey) " + _OW)
_window("op_win_rows_cum", lambda: F.round(F.sum("o_totalprice").over(_by_price().rowsBetween(Window.unboundedPreceding, 0)), 2), "round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey ROWS UNBOUNDED PRECEDING), 2)")
_window("op_win_rows_sliding", lambda: F.round(F.avg("o_totalprice").over(_by_price().rowsBetween(-2, 0)), 4), "round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey ROWS 2 PRECEDING), 4)")


@op("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_win_lag_lead(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(spark, sf, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"))


@op("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 90 DAY PRECEDING AND CURRENT ROW) AS n FROM orders")
def op_win_range_days(spark, sf):
    o = t(spark, sf, "orders").withColumn("us", F.unix_micros(F.col("o_orderdate").cast("timestamp")))
    w = Window.partitionBy("o_custkey").orderBy("us").rangeBetween(-90 * 86_400_000_000, 0)
    return o.select("o_orderkey", F.count("*").over(w).alias("n"))


# order, limits, sets


@op("SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 50")
def op_topk_global(spark, sf):
    return t(spark, sf, "lineitem").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey").select("l_orderkey", "l_linenumber", "l_extendedprice").limit(50)


@op("SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 2")
def op_topk_per_group(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t(spark, sf, "orders").withColumn("rn", F.row_number().over(w)).where("rn <= 2").select("o_custkey", "o_orderkey")


@op("SELECT p_partkey FROM part ORDER BY p_retailprice, p_partkey LIMIT 20 OFFSET 10")
def op_offset(spark, sf):
    return t(spark, sf, "part").orderBy("p_retailprice", "p_partkey").offset(10).limit(20).select("p_partkey")


@op("SELECT o_orderkey, l_orderkey FROM orders LEFT JOIN (SELECT DISTINCT l_orderkey FROM lineitem) ON o_orderkey = l_orderkey ORDER BY l_orderkey NULLS FIRST, o_orderkey LIMIT 30")
def op_sort_nulls(spark, sf):
    l = t(spark, sf, "lineitem").select("l_orderkey").distinct()
    return t(spark, sf, "orders").join(l, F.col("o_orderkey") == F.col("l_orderkey"), "left").orderBy(F.asc_nulls_first("l_orderkey"), "o_orderkey").select("o_orderkey", "l_orderkey").limit(30)


_SETS = {"op_union_all": ("UNION ALL", "unionByName"), "op_union": ("UNION", None), "op_intersect": ("INTERSECT", "intersect"), "op_intersect_all": ("INTERSECT ALL", "intersectAll"), "op_except": ("EXCEPT", "subtract"), "op_except_all": ("EXCEPT ALL", "exceptAll")}
for _n, (_s, _m) in _SETS.items():

    def _run(spark, sf, m=_m):
        a = t(spark, sf, "customer").select(F.col("c_nationkey").alias("nk"))
        b = t(spark, sf, "supplier").select(F.col("s_nationkey").alias("nk"))
        return getattr(a, m)(b) if m else a.union(b).distinct()

    op(f"SELECT c_nationkey AS nk FROM customer {_s} SELECT s_nationkey AS nk FROM supplier", _n)(_run)


# functions


@op("SELECT p_partkey, upper(p_brand) AS u, trim(substring(p_name, 1, 8)) AS s, p_brand || '|' || p_type AS c, CAST(levenshtein(p_brand, 'Brand#11') AS BIGINT) AS d, CAST(length(p_name) AS BIGINT) AS n FROM part")
def op_string(spark, sf):
    return t(spark, sf, "part").select("p_partkey", F.upper("p_brand").alias("u"), F.trim(F.substring("p_name", 1, 8)).alias("s"), F.concat_ws("|", "p_brand", "p_type").alias("c"), F.levenshtein("p_brand", F.lit("Brand#11")).cast("long").alias("d"), F.length("p_name").cast("long").alias("n"))


@op("SELECT p_partkey, CAST(regexp_extract(p_brand, '#([0-9]+)', 1) AS BIGINT) AS no, regexp_replace(p_type, '[AEIOU]', '', 'g') AS short FROM part")
def op_regex(spark, sf):
    return t(spark, sf, "part").select("p_partkey", F.regexp_extract("p_brand", "#([0-9]+)", 1).cast("long").alias("no"), F.regexp_replace("p_type", "[AEIOU]", "").alias("short"))


@op("SELECT doc_id FROM documents ORDER BY md5('s' || CAST(doc_id AS VARCHAR)), doc_id LIMIT 40")
def op_md5_sample(spark, sf):
    return t(spark, sf, "documents").orderBy(F.md5(F.concat(F.lit("s"), F.col("doc_id").cast("string"))), "doc_id").select("doc_id").limit(40)


@op("SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) AS days, strftime(o_orderdate + INTERVAL 10 DAY, '%Y-%m-%d') AS due FROM orders")
def op_date(spark, sf):
    d = F.col("o_orderdate")
    return t(spark, sf, "orders").select("o_orderkey", F.year(d).cast("long").alias("y"), F.month(d).cast("long").alias("m"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("first"), F.datediff(d.cast("date"), F.lit("1995-01-01").cast("date")).cast("long").alias("days"), F.date_format(F.date_add(d.cast("date"), 10), "yyyy-MM-dd").alias("due"))


@op("SELECT event_id, epoch_us(ts) AS us FROM events")
def op_timestamp_coord(spark, sf):
    return t(spark, sf, "events").select("event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))


@op("SELECT l_orderkey, l_linenumber, l_partkey, round(sqrt(l_extendedprice), 4) AS s, round(power(l_discount, 2), 6) AS p, round(log2(l_quantity), 6) AS l, abs(l_quantity - 25) AS a, greatest(l_quantity, 30) AS g, CAST(floor(l_tax * 100 + 0.5) AS BIGINT) AS f FROM lineitem")
def op_math(spark, sf):
    q = F.col("l_quantity")
    return t(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.sqrt("l_extendedprice"), 4).alias("s"), F.round(F.pow("l_discount", F.lit(2)), 6).alias("p"), F.round(F.log2(q), 6).alias("l"), F.abs(q - 25).alias("a"), F.greatest(q, F.lit(30.0)).alias("g"), F.floor(F.col("l_tax") * 100 + 0.5).alias("f"))


@op("SELECT l_orderkey, l_linenumber, l_partkey, round(abs(l_quantity - 25) + abs(100 * l_discount - 5), 6) AS l1, round(sqrt((l_quantity - 25) * (l_quantity - 25) + (100 * l_discount - 5) * (100 * l_discount - 5)), 6) AS l2, round(greatest(abs(l_quantity - 25), abs(100 * l_discount - 5)), 6) AS linf FROM lineitem")
def op_dist_l1_l2_linf(spark, sf):
    a, b = F.col("l_quantity") - 25, 100 * F.col("l_discount") - 5
    return t(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.abs(a) + F.abs(b), 6).alias("l1"), F.round(F.sqrt(a * a + b * b), 6).alias("l2"), F.round(F.greatest(F.abs(a), F.abs(b)), 6).alias("linf"))


@op("SELECT vec_id, round(list_sum(list_transform(embedding[1:8], lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 5) AS sq, CAST(len(embedding) AS BIGINT) AS n, round(CAST(list_max(embedding) AS DOUBLE), 5) AS top FROM embeddings")
def op_array(spark, sf):
    x = F.transform(F.slice("embedding", 1, 8), lambda v: v.cast("double") * v.cast("double"))
    return t(spark, sf, "embeddings").select("vec_id", F.round(F.aggregate(x, F.lit(0.0), lambda s, v: s + v), 5).alias("sq"), F.size("embedding").cast("long").alias("n"), F.round(F.array_max("embedding").cast("double"), 5).alias("top"))


@op("SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def op_map(spark, sf):
    counts = t(spark, sf, "events").groupBy("event_type").agg(F.count("*").alias("n"))
    packed = counts.groupBy().agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return packed.select(F.explode("m").alias("event_type", "n"))


@op("SELECT c_nationkey, min(c_acctbal) AS least FROM customer GROUP BY 1")
def op_struct_min(spark, sf):
    return t(spark, sf, "customer").groupBy("c_nationkey").agg(F.min(F.struct("c_acctbal", "c_custkey")).alias("m")).select("c_nationkey", F.col("m.c_acctbal").alias("least"))


@op("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def op_json(spark, sf):
    return t(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


# subqueries

_TEXT = {
    "op_subquery_scalar": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)",
    "op_subquery_exists": "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)",
    "op_subquery_not_exists": "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)",
    "op_subquery_in": "SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity = 50)",
    "op_subquery_cte": "WITH big AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT n, count(*) AS customers FROM big GROUP BY n",
    "op_subquery_correlated": "SELECT o_orderkey FROM orders o WHERE o_totalprice = (SELECT max(i.o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)",
    "op_value_weights_sql": "WITH l AS (SELECT l_orderkey, count(*) AS w FROM lineitem GROUP BY 1) SELECT o_orderpriority AS value, CAST(sum(w) AS BIGINT) AS w FROM orders JOIN l ON o_orderkey = l_orderkey GROUP BY 1",
    "op_factorised_count": "WITH o AS (SELECT o_custkey, count(*) AS w FROM orders GROUP BY 1), c AS (SELECT c_nationkey, sum(w) AS w FROM customer JOIN o ON c_custkey = o_custkey GROUP BY 1), l AS (SELECT l_suppkey, count(*) AS w FROM lineitem GROUP BY 1), s AS (SELECT s_nationkey, sum(w) AS w FROM supplier JOIN l ON s_suppkey = l_suppkey GROUP BY 1) SELECT CAST(sum(c.w * s.w) AS BIGINT) AS n FROM c JOIN s ON c_nationkey = s_nationkey",
}
for _n, _s in _TEXT.items():

    def _sql(spark, sf, text=_s):
        import re

        return spark.sql(re.sub(r"\b(FROM|JOIN)\s+(orders|customer|part|lineitem|supplier)\b", lambda m: f"{m[1]} parquet.`{sf}/{m[2]}.parquet` AS {m[2]}" if not re.match(r"\s+[oi]\b", text[m.end():]) else f"{m[1]} parquet.`{sf}/{m[2]}.parquet`", text))

    op(_s, _n)(_sql)

# samples

_U = "CAST(('0x' || substr(md5('b' || CAST(l_orderkey AS VARCHAR) || ':' || CAST(l_linenumber AS VARCHAR) || ':' || CAST(l_partkey AS VARCHAR)), 1, 8)) AS BIGINT) / 4294967296.0"


def _u():
    key = F.concat(F.lit("b"), F.col("l_orderkey").cast("string"), F.lit(":"), F.col("l_linenumber").cast("string"), F.lit(":"), F.col("l_partkey").cast("string"))
    return F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


@op(f"SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE {_U} < 0.05")
def op_sample_bernoulli_hash(spark, sf):
    return t(spark, sf, "lineitem").where(_u() < 0.05).select("l_orderkey", "l_linenumber", "l_partkey")


@op(f"SELECT l_returnflag, count(*) AS n FROM lineitem WHERE {_U} < CASE l_returnflag WHEN 'A' THEN 0.1 WHEN 'N' THEN 0.02 ELSE 0.05 END GROUP BY 1")
def op_sample_stratified(spark, sf):
    share = F.when(F.col("l_returnflag") == "A", 0.1).when(F.col("l_returnflag") == "N", 0.02).otherwise(0.05)
    return t(spark, sf, "lineitem").where(_u() < share).groupBy("l_returnflag").agg(F.count("*").alias("n"))
