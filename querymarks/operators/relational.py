"""Relational operators around the grading methods, one query each, with the SQL that they answer to."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.catalog import read_tables

Tables = dict[str, DataFrame]
_ALL: dict[str, tuple[Callable[[Tables], DataFrame], str]] = {}


def _op(name: str, sql: str) -> Callable:
    def add(fn: Callable[[Tables], DataFrame]) -> Callable:
        _ALL[f"op_{name}"] = (fn, sql)
        return fn

    return add


def money(c: str):
    """Exact sums of two decimals, as a double at the end."""
    return F.sum(F.col(c).cast("decimal(18,2)")).cast("double")


def _micros(c: str):
    return F.unix_micros(F.col(c).cast("timestamp"))


def range_join(points: DataFrame, ranges: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Rows with low <= value < high, by an equi-join on bins of ``width``: a range goes to each bin that it meets,
    a point to its own."""
    p = points.withColumn("__bin", F.floor(F.col(value) / width))
    r = ranges.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return p.join(r, "__bin").where((F.col(low) <= F.col(value)) & (F.col(value) < F.col(high))).drop("__bin")


def interval_join(a: DataFrame, b: DataFrame, key: str, at: str, other: str, seconds: int) -> DataFrame:
    """Rows of equal ``key`` with b.other in [a.at, a.at + seconds], by bins of that length: two bins for each row of a."""
    x = a.withColumn("__bin", F.explode(F.array(*(F.floor(_micros(at) / (seconds * 1_000_000)) + k for k in (0, 1)))))
    y = b.withColumn("__bin", F.floor(_micros(other) / (seconds * 1_000_000)))
    return x.join(y, [key, "__bin"]).where((F.col(other) >= F.col(at)) & (_micros(other) <= _micros(at) + seconds * 1_000_000)).drop("__bin")


def as_of_join(left: DataFrame, right: DataFrame, key: str, left_at: str, right_at: str, value: str) -> DataFrame:
    """left with the value of the last row of right at or before it (null: none), by one union and a running last():
    one shuffle by key, and no pairs."""
    u = left.select("*", F.col(left_at).alias("__at"), F.lit(1).alias("__side"), F.lit(None).cast(dict(right.dtypes)[value]).alias("__v"))
    v = right.select(F.col(key), F.col(right_at).alias("__at"), F.lit(0).alias("__side"), F.col(value).alias("__v"))
    w = Window.partitionBy(key).orderBy("__at", "__side", F.col("__v")).rowsBetween(Window.unboundedPreceding, 0)
    both = u.unionByName(v, allowMissingColumns=True).withColumn("as_of", F.last("__v", ignorenulls=True).over(w))
    return both.where("__side = 1").drop("__at", "__side", "__v")


# -- scans, projections, filters
_op("scan_pruned", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderstatus = 'F' AND o_orderkey < 500")(lambda t: t["orders"].where("o_orderstatus = 'F' AND o_orderkey < 500").select("o_orderkey", "o_totalprice"))
_op("computed", "SELECT l_orderkey, l_linenumber, CAST(CAST(l_extendedprice AS DECIMAL(12,2)) * (1 - CAST(l_discount AS DECIMAL(4,2))) AS DOUBLE) AS net FROM lineitem WHERE l_orderkey < 200")(lambda t: t["lineitem"].where("l_orderkey < 200").select("l_orderkey", "l_linenumber", (F.col("l_extendedprice").cast("decimal(12,2)") * (1 - F.col("l_discount").cast("decimal(4,2)"))).cast("double").alias("net")))
_op("in_list", "SELECT n_nationkey, n_name FROM nation WHERE n_regionkey IN (1, 3)")(lambda t: t["nation"].where(F.col("n_regionkey").isin(1, 3)).select("n_nationkey", "n_name"))
_op("like", "SELECT p_partkey FROM part WHERE p_type LIKE '%S%' AND p_brand NOT LIKE 'Brand#1%'")(lambda t: t["part"].where(F.col("p_type").like("%S%") & ~F.col("p_brand").like("Brand#1%")).select("p_partkey"))
_op("between", "SELECT p_partkey, p_size FROM part WHERE p_size BETWEEN 10 AND 12")(lambda t: t["part"].where(F.col("p_size").between(10, 12)).select("p_partkey", "p_size"))
_op("case", "SELECT CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band, count(*) AS n FROM orders GROUP BY 1")(lambda t: t["orders"].groupBy(F.when(F.col("o_totalprice") > 200000, "high").when(F.col("o_totalprice") > 100000, "mid").otherwise("low").alias("band")).agg(F.count("*").alias("n")))
_op("null_tests", "SELECT d.doc_id, quality IS NULL AS unlabelled FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")(lambda t: t["documents"].select("doc_id").join(t["labels"], "doc_id", "left").select("doc_id", F.col("quality").isNull().alias("unlabelled")))
_op("null_safe", "SELECT count(*) AS n FROM (SELECT quality AS q FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) x WHERE q IS NOT DISTINCT FROM NULL")(lambda t: t["documents"].select("doc_id").join(t["labels"], "doc_id", "left").where(F.col("quality").eqNullSafe(F.lit(None))).agg(F.count("*").alias("n")))
# -- joins
_op("join_inner", "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_orderstatus = 'P'")(lambda t: t["orders"].where("o_orderstatus = 'P'").join(t["customer"], F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name"))
_op("join_merge", "SELECT l_orderkey, l_linenumber, o_orderstatus FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_quantity > 45")(lambda t: t["lineitem"].where("l_quantity > 45").join(t["orders"].hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).select("l_orderkey", "l_linenumber", "o_orderstatus"))
_op("join_broadcast", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")(lambda t: t["customer"].join(F.broadcast(t["nation"]), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name"))
_op("join_shuffle_hash", "SELECT s_name, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY s_name")(lambda t: t["lineitem"].join(t["supplier"].hint("shuffle_hash"), F.col("l_suppkey") == F.col("s_suppkey")).groupBy("s_name").agg(F.count("*").alias("n")))
_op("join_theta", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey")(lambda t: t["nation"].alias("a").join(t["nation"].alias("b"), F.col("a.n_regionkey") < F.col("b.n_regionkey")).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b")))
_op("join_cross", "SELECT r_name, n_name FROM region, nation")(lambda t: t["region"].crossJoin(t["nation"]).select("r_name", "n_name"))
_op("join_left", "SELECT c_custkey, count(event_id) AS n FROM customer LEFT JOIN events ON c_custkey = user_id GROUP BY c_custkey")(lambda t: t["customer"].join(t["events"], F.col("c_custkey") == F.col("user_id"), "left").groupBy("c_custkey").agg(F.count("event_id").alias("n")))
_op("join_right", "SELECT o_orderkey, l_linenumber FROM lineitem RIGHT JOIN orders ON l_orderkey = o_orderkey AND l_quantity = 50")(lambda t: t["lineitem"].where("l_quantity = 50").join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey"), "right").select("o_orderkey", "l_linenumber"))
_op("join_full", "SELECT coalesce(a.s_nationkey, b.c_nationkey) AS nation, a.n AS sellers, b.n AS buyers FROM (SELECT s_nationkey, count(*) AS n FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) a FULL JOIN (SELECT c_nationkey, count(*) AS n FROM customer WHERE c_acctbal > 9000 GROUP BY 1) b ON a.s_nationkey = b.c_nationkey")(
    lambda t: t["supplier"].where("s_acctbal > 5000").groupBy("s_nationkey").agg(F.count("*").alias("sellers")).join(t["customer"].where("c_acctbal > 9000").groupBy("c_nationkey").agg(F.count("*").alias("buyers")), F.col("s_nationkey") == F.col("c_nationkey"), "full").select(F.coalesce("s_nationkey", "c_nationkey").alias("nation"), "sellers", "buyers")
)
_op("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")(lambda t: t["customer"].join(t["orders"].where("o_orderpriority = '1-URGENT'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"))
_op("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")(lambda t: t["customer"].join(t["orders"].where("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"))
_op("join_self", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")(lambda t: t["nation"].alias("a").join(t["nation"].alias("b"), (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b")))
_op("join_using", "SELECT doc_id, lang, quality FROM documents JOIN labels USING (doc_id)")(lambda t: t["documents"].join(t["labels"], "doc_id").select("doc_id", "lang", "quality"))
_op("join_range", "SELECT event_id, band FROM events JOIN (VALUES (0.0, 25.0, 'a'), (25.0, 60.0, 'b'), (50.0, 90.0, 'c')) v(lo, hi, band) ON lo <= value AND value < hi")(
    lambda t: range_join(t["events"].select("event_id", "value"), t["events"].sparkSession.createDataFrame([(0.0, 25.0, "a"), (25.0, 60.0, "b"), (50.0, 90.0, "c")], "lo double, hi double, band string"), "value", "lo", "hi", 10.0).select("event_id", "band")
)
_op("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR AND a.event_id <> b.event_id")(
    lambda t: interval_join(t["events"].select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("at")), t["events"].select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("other")), "user_id", "at", "other", 3600).where("a <> b").select("a", "b")
)
_op("join_as_of", "SELECT e.event_id, (SELECT arg_max(p.event_id, (p.ts, p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts) AS previous FROM events e WHERE e.event_type <> 'purchase'")(
    lambda t: as_of_join(t["events"].where("event_type <> 'purchase'").select("event_id", "user_id", "ts"), t["events"].where("event_type = 'purchase'").select("user_id", F.col("ts").alias("pts"), F.col("event_id").alias("pid")), "user_id", "ts", "pts", "pid").select("event_id", F.col("as_of").alias("previous"))
)
# -- aggregation
_op("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS qty, min(l_discount) AS low, max(l_discount) AS high FROM lineitem GROUP BY 1, 2")(lambda t: t["lineitem"].groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), money("l_quantity").alias("qty"), F.min("l_discount").alias("low"), F.max("l_discount").alias("high")))
_op("agg_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS buyers, count(DISTINCT o_orderpriority) AS priorities FROM orders GROUP BY 1")(lambda t: t["orders"].groupBy("o_orderstatus").agg(F.countDistinct("o_custkey").alias("buyers"), F.countDistinct("o_orderpriority").alias("priorities")))
_op("agg_filtered", "SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F') AS finished, count(*) AS n FROM orders GROUP BY 1")(lambda t: t["orders"].groupBy("o_custkey").agg(F.count_if(F.col("o_orderstatus") == "F").alias("finished"), F.count("*").alias("n")))
_op("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 15")(lambda t: t["orders"].groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 15"))
_op("agg_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")(lambda t: t["lineitem"].rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")))
_op("agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n, CAST(grouping_id(o_orderstatus, o_orderpriority) AS BIGINT) AS gid FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")(lambda t: t["orders"].cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().alias("gid")))
_op("agg_grouping_sets", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")(lambda t: _sql(t, "customer", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM {customer} GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())"))
_op("agg_max_by", "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest FROM orders GROUP BY 1")(lambda t: t["orders"].groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest")))
_op("agg_collect_set", "SELECT c_nationkey, string_agg(DISTINCT c_mktsegment, ',' ORDER BY c_mktsegment) AS segments FROM customer GROUP BY 1")(lambda t: t["customer"].groupBy("c_nationkey").agg(F.array_join(F.array_sort(F.collect_set("c_mktsegment")), ",").alias("segments")))
_op("agg_pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY 1")(lambda t: t["orders"].groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0).select("o_orderpriority", F.col("F").alias("f"), F.col("O").alias("o"), F.col("P").alias("p")))
_op("agg_percentile", "SELECT p_brand, quantile_cont(p_size, 0.5) AS middle FROM part GROUP BY 1")(lambda t: t["part"].groupBy("p_brand").agg(F.percentile("p_size", 0.5).alias("middle")))
_op("agg_global", "SELECT count(*) AS n, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE) AS worth FROM orders")(lambda t: t["orders"].agg(F.count("*").alias("n"), money("o_totalprice").alias("worth")))
_op("agg_two_step", "SELECT o_orderpriority, max(n) AS most FROM (SELECT o_orderpriority, o_custkey, count(*) AS n FROM orders GROUP BY 1, 2) x GROUP BY 1")(lambda t: t["orders"].groupBy("o_orderpriority", "o_custkey").agg(F.count("*").alias("n")).groupBy("o_orderpriority").agg(F.max("n").alias("most")))
_op("agg_salted", "SELECT event_type, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18,2))) AS DOUBLE) AS total FROM events GROUP BY 1")(lambda t: t["events"].groupBy("event_type", (F.col("event_id") % 16).alias("salt")).agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(18,2)")).alias("v")).groupBy("event_type").agg(F.sum("n").alias("n"), F.sum("v").cast("double").alias("total")))
_op("agg_approx_distinct", "")(lambda t: t["lineitem"].agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts")))
# -- windows
_W = "PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey"
_w = lambda: Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
_op("win_row_number", f"SELECT o_orderkey, row_number() OVER ({_W}) AS k FROM orders")(lambda t: t["orders"].select("o_orderkey", F.row_number().over(_w()).cast("long").alias("k")))
_op("win_rank", "SELECT p_partkey, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS r, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS d FROM part")(lambda t: t["part"].select("p_partkey", F.rank().over(Window.partitionBy("p_brand").orderBy("p_size")).cast("long").alias("r"), F.dense_rank().over(Window.partitionBy("p_brand").orderBy("p_size")).cast("long").alias("d")))
_op("win_lag", f"SELECT o_orderkey, lag(o_orderkey) OVER ({_W}) AS before, lead(o_orderkey, 2) OVER ({_W}) AS after FROM orders")(lambda t: t["orders"].select("o_orderkey", F.lag("o_orderkey").over(_w()).alias("before"), F.lead("o_orderkey", 2).over(_w()).alias("after")))
_op("win_running_max", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS best FROM events")(lambda t: t["events"].select("event_id", F.max("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)).alias("best")))
_op("win_rows_frame", "SELECT event_id, CAST(sum(CAST(value AS DECIMAL(18,2))) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS DOUBLE) AS last3 FROM events")(lambda t: t["events"].select("event_id", F.sum(F.col("value").cast("decimal(18,2)")).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)).cast("double").alias("last3")))
_op("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day FROM events")(lambda t: t["events"].select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.floor(_micros("ts") / 1_000_000)).rangeBetween(-86400, 0)).alias("day")))
_op("win_ntile", "SELECT c_custkey, ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey) AS q FROM customer")(lambda t: t["customer"].select("c_custkey", F.ntile(4).over(Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")).cast("long").alias("q")))
_op("win_percent_rank", "SELECT s_suppkey, round(percent_rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal), 9) AS p FROM supplier")(lambda t: t["supplier"].select("s_suppkey", F.round(F.percent_rank().over(Window.partitionBy("s_nationkey").orderBy("s_acctbal")), 9).alias("p")))
_op("win_first_last", f"SELECT o_orderkey, first_value(o_orderkey) OVER ({_W}) AS first, last_value(o_orderkey) OVER ({_W} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM orders")(lambda t: t["orders"].select("o_orderkey", F.first("o_orderkey").over(_w()).alias("first"), F.last("o_orderkey").over(_w().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("last")))
_op("win_share", "SELECT n_nationkey, round(count(*) OVER (PARTITION BY n_regionkey) / 25.0, 9) AS share FROM nation")(lambda t: t["nation"].select("n_nationkey", F.round(F.count("*").over(Window.partitionBy("n_regionkey")) / 25.0, 9).alias("share")))
# -- order and limit
def _ranked(ordered: DataFrame) -> DataFrame:
    """o_orderkey and its place in a total order: range partitions are numbered within, and by the sizes of those before."""
    placed = ordered.select("o_orderkey", F.monotonically_increasing_id().alias("at")).withColumn("part", F.shiftright("at", 33))
    sizes = placed.groupBy("part").agg(F.count("*").alias("n"))  # one row for each partition
    before = sizes.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    within = F.col("at").bitwiseAND(F.lit((1 << 33) - 1)) + 1
    return placed.join(F.broadcast(before), "part").select("o_orderkey", (within + F.col("before")).alias("k"))


_op("sort_top", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")(lambda t: t["orders"].select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10))
_op("sort_top_group", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) x WHERE k <= 2")(lambda t: t["orders"].withColumn("k", F.row_number().over(_w())).where("k <= 2").select("o_custkey", "o_orderkey"))
_op("sort_offset", "SELECT p_partkey FROM part ORDER BY p_partkey LIMIT 20 OFFSET 30")(lambda t: t["part"].select("p_partkey").orderBy("p_partkey").offset(30).limit(20))
_op("sort_nulls", "SELECT doc_id, row_number() OVER (ORDER BY quality ASC NULLS LAST, doc_id) AS k FROM (SELECT d.doc_id, quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) x ORDER BY k LIMIT 50")(lambda t: t["documents"].select("doc_id").join(t["labels"], "doc_id", "left").orderBy(F.asc_nulls_last("quality"), "doc_id").limit(50).select("doc_id", F.row_number().over(Window.orderBy(F.asc_nulls_last("quality"), "doc_id")).cast("long").alias("k")))
# -- set operations
_N = "SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 8000"
_S = "SELECT s_nationkey AS k FROM supplier"
_a = lambda t: t["customer"].where("c_acctbal > 8000").select(F.col("c_nationkey").alias("k"))
_b = lambda t: t["supplier"].select(F.col("s_nationkey").alias("k"))
_op("set_union_all", f"{_N} UNION ALL {_S}")(lambda t: _a(t).union(_b(t)))
_op("set_union", f"{_N} UNION {_S}")(lambda t: _a(t).union(_b(t)).distinct())
_op("set_intersect", f"{_N} INTERSECT {_S}")(lambda t: _a(t).intersect(_b(t)))
_op("set_intersect_all", f"{_N} INTERSECT ALL {_S}")(lambda t: _a(t).intersectAll(_b(t)))
_op("set_except", f"SELECT n_nationkey AS k FROM nation EXCEPT ({_S} WHERE s_acctbal > 8000)")(lambda t: t["nation"].select(F.col("n_nationkey").alias("k")).subtract(_b({"supplier": t["supplier"].where("s_acctbal > 8000")})))
_op("sort_total", "SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders ORDER BY k")(lambda t: _ranked(t["orders"].select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey")))
_op("set_except_all", f"{_N} EXCEPT ALL {_S}")(lambda t: _a(t).exceptAll(_b(t)))
_op("set_by_name", "SELECT r_name AS name, r_regionkey AS k FROM region UNION ALL SELECT n_name, n_nationkey FROM nation")(lambda t: t["region"].select(F.col("r_name").alias("name"), F.col("r_regionkey").alias("k")).unionByName(t["nation"].select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("name"))))
# -- scalars
_scalars = {
    "upper": ("upper(p_name)", lambda: F.upper("p_name")), "trim": ("trim('  ' || p_brand || ' ')", lambda: F.trim(F.concat(F.lit("  "), "p_brand", F.lit(" ")))), "substr": ("substr(p_type, 2, 3)", lambda: F.substring("p_type", 2, 3)),
    "concat": ("p_brand || ':' || p_type", lambda: F.concat("p_brand", F.lit(":"), "p_type")), "replace_pattern": ("regexp_replace(p_brand, '[0-9]+', 'x', 'g')", lambda: F.regexp_replace("p_brand", "[0-9]+", "x")), "split": ("split_part(p_brand, '#', 2)", lambda: F.element_at(F.split("p_brand", "#"), 2)),
    "levenshtein": ("CAST(levenshtein(p_brand, p_type) AS BIGINT)", lambda: F.levenshtein("p_brand", "p_type").cast("long")), "length": ("CAST(length(p_name) AS BIGINT)", lambda: F.length("p_name").cast("long")), "abs": ("abs(p_size - 25)", lambda: F.abs(F.col("p_size") - 25)),
    "round": ("round(p_retailprice / 7, 3)", lambda: F.round(F.col("p_retailprice") / 7, 3)), "floor": ("CAST(floor(p_retailprice) AS BIGINT)", lambda: F.floor("p_retailprice")), "pmod": ("p_size % 7", lambda: F.pmod("p_size", F.lit(7))), "shift": ("p_partkey >> 2", lambda: F.shiftright("p_partkey", 2)),
    "bit_count": ("CAST(bit_count(p_partkey) AS BIGINT)", lambda: F.bit_count("p_partkey").cast("long")), "coalesce": ("coalesce(nullif(p_size, 25), -1)", lambda: F.coalesce(F.nullif("p_size", F.lit(25)), F.lit(-1))), "greatest": ("greatest(p_size, 10)", lambda: F.greatest("p_size", F.lit(10))), "hex": ("lower(to_hex(p_partkey))", lambda: F.lower(F.hex("p_partkey"))),
}
for _k, (_sql_text, _col) in _scalars.items():
    _op(f"fn_{_k}", f"SELECT p_partkey, {_sql_text} AS v FROM part")(lambda t, c=_col: t["part"].select("p_partkey", c().alias("v")))
_op("fn_dates", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")(lambda t: t["orders"].select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("first"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01")).cast("long").alias("days")))
_op("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS INT) AS k FROM events")(lambda t: t["events"].select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k")))
_op("fn_from_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS INT) * 2 AS twice FROM events")(lambda t: t["events"].select("event_id", (F.from_json("props", "k int")["k"] * 2).alias("twice")))
_op("fn_arrays", "SELECT vec_id, round(coalesce(list_sum(list_transform(list_filter(embedding[1:8], lambda x: x > 0), lambda x: CAST(x AS DOUBLE))), 0), 4) AS up FROM embeddings")(lambda t: t["embeddings"].select("vec_id", F.round(F.aggregate(F.filter(F.slice("embedding", 1, 8), lambda x: x > 0), F.lit(0.0), lambda a, x: a + x.cast("double")), 4).alias("up")))
_op("fn_explode", "SELECT doc_id, unnest(string_split(lang || '-' || source, '-')) AS part FROM documents")(lambda t: t["documents"].select("doc_id", F.explode(F.split(F.concat("lang", F.lit("-"), "source"), "-")).alias("part")))
_op("fn_array_sets", "SELECT c_custkey, len(list_filter(string_split(c_name, '0'), lambda x: x <> '')) AS n FROM customer")(lambda t: t["customer"].select("c_custkey", F.size(F.array_remove(F.split("c_name", "0"), "")).cast("long").alias("n")))
_op("fn_maps", "SELECT n_nationkey, n_regionkey * 2.0 + 1.0 AS cost FROM nation")(lambda t: t["nation"].select("n_nationkey", F.aggregate(F.map_values(F.map_zip_with(F.create_map(F.lit("a"), F.col("n_regionkey").cast("double"), F.lit("b"), F.lit(1.0)), F.create_map(F.lit("a"), F.lit(2.0), F.lit("b"), F.lit(1.0)), lambda k, x, y: x * y)), F.lit(0.0), lambda a, x: a + x).alias("cost")))
_op("fn_to_json", "SELECT n_nationkey, '{\"n\":' || n_nationkey || ',\"r\":' || n_regionkey || '}' AS j FROM nation")(lambda t: t["nation"].select("n_nationkey", F.to_json(F.struct(F.col("n_nationkey").alias("n"), F.col("n_regionkey").alias("r"))).alias("j")))
# -- subqueries, by SQL text
_sub = {
    "scalar": "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT max(s_acctbal) - 100 FROM supplier)",
    "correlated": "SELECT p_partkey FROM part p WHERE p_size = (SELECT max(p_size) FROM part q WHERE q.p_brand = p.p_brand)",
    "in": "SELECT s_suppkey FROM supplier WHERE s_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)",
    "exists": "SELECT n_nationkey FROM nation WHERE NOT EXISTS (SELECT 1 FROM supplier WHERE s_nationkey = n_nationkey AND s_acctbal > 5000)",
    "nested": "SELECT r_name FROM region WHERE r_regionkey IN (SELECT n_regionkey FROM nation WHERE n_nationkey IN (SELECT c_nationkey FROM customer WHERE c_acctbal > 9900))",
    "in_select": "SELECT n_nationkey, (SELECT count(*) FROM supplier WHERE s_nationkey = n_nationkey) AS sellers FROM nation",
    "not_in": "SELECT n_nationkey FROM nation WHERE n_nationkey NOT IN (SELECT s_nationkey FROM supplier WHERE s_acctbal > 3000)",
    "from": "SELECT band, count(*) AS n FROM (SELECT CAST(floor(o_totalprice / 50000) AS BIGINT) AS band FROM orders) x GROUP BY band",
}
for _k, _text in _sub.items():
    _op(f"sub_{_k}", _text)(lambda t, s=_text: _sql(t, None, s))
_op("join_lateral", "SELECT c_custkey, k FROM customer, LATERAL (SELECT max(o_orderkey) AS k FROM orders WHERE o_custkey = c_custkey) x")(lambda t: _sql(t, None, "SELECT c_custkey, k FROM customer, LATERAL (SELECT max(o_orderkey) AS k FROM orders WHERE o_custkey = c_custkey) x"))
_op("join_null_aware_anti", "SELECT d.doc_id FROM documents d WHERE d.n_chars NOT IN (SELECT quality FROM labels)")(lambda t: _sql(t, None, "SELECT d.doc_id FROM documents d WHERE d.n_chars NOT IN (SELECT quality FROM labels)"))
# -- sources and sinks
_op("source_values", "SELECT * FROM (VALUES (1, 'a'), (2, 'b')) v(k, s)")(lambda t: t["region"].sparkSession.createDataFrame([(1, "a"), (2, "b")], "k int, s string"))


def _sql(tables: Tables, only: str | None, text: str) -> DataFrame:
    spark = next(iter(tables.values())).sparkSession
    if only:
        return spark.sql(text, **{only: tables[only]})
    for n, df in tables.items():
        df.createOrReplaceTempView(n)
    return spark.sql(text)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: (lambda spark, sf_dir, fn=fn: fn(read_tables(spark, sf_dir))) for k, (fn, _) in _ALL.items()}


def oracle_sql() -> dict[str, str]:
    return {k: sql for k, (_, sql) in _ALL.items() if sql}
