"""Scans, joins, aggregates, windows, set operations and functions that discovery inputs are built with."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..oracle import CALENDAR
from ..sources import relations as R
from .rewriting import _JOIN

QUERIES, SQL = {}, {}


def query(sql=None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def _t(spark, d, n):
    return R.table(spark, d, n)


def _money(c):
    return F.col(c).cast("decimal(18,2)") if isinstance(c, str) else c.cast("decimal(18,2)")


def _sum(c):
    return F.sum(_money(c)).cast("decimal(18,2)")


_M = "CAST(sum(CAST({} AS DECIMAL(18,2))) AS DECIMAL(18,2))"


@query("SELECT o_orderkey, o_orderstatus, o_totalprice FROM orders")
def q_scan_project(spark, d):
    return _t(spark, d, "orders").select("o_orderkey", "o_orderstatus", "o_totalprice")


@query("SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_discount >= 0.05")
def q_scan_filter(spark, d):
    return _t(spark, d, "lineitem").where(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & (F.col("l_discount") >= 0.05)).select("l_orderkey", "l_linenumber", "l_quantity")


@query(CALENDAR)
def q_project_calendar(spark, d):
    return R.calendar(spark, d)


@query("SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size BETWEEN 10 AND 30 THEN 'mid' ELSE 'large' END AS band, coalesce(nullif(p_brand, 'Brand#11'), 'none') AS brand FROM part WHERE p_name LIKE '%1%' AND regexp_matches(p_type, '[A-Z]') AND p_size IN (1, 5, 9, 14, 23, 36, 45, 49)")
def q_filter_predicates(spark, d):
    p = _t(spark, d, "part")
    band = F.when(F.col("p_size") < 10, "small").when(F.col("p_size").between(10, 30), "mid").otherwise("large")
    p = p.where(F.col("p_name").like("%1%") & F.col("p_type").rlike("[A-Z]") & F.col("p_size").isin(1, 5, 9, 14, 23, 36, 45, 49))
    return p.select("p_partkey", band.alias("band"), F.coalesce(F.nullif("p_brand", F.lit("Brand#11")), F.lit("none")).alias("brand"))


@query(f"SELECT c_mktsegment, {_M.format('l_extendedprice')} AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def q_join_inner(spark, d):
    i, o, c = (_t(spark, d, n) for n in ("lineitem", "orders", "customer"))
    return i.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(_sum("l_extendedprice").alias("revenue"))


@query("SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def q_join_broadcast(spark, d):
    """Nations and regions are fixed tables of 25 and 5 rows."""
    c, n, r = (_t(spark, d, x) for x in ("customer", "nation", "region"))
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", "n_name", "r_name")


@query("SELECT n_nationkey, count(s_suppkey) AS n FROM nation LEFT JOIN supplier ON s_nationkey = n_nationkey GROUP BY n_nationkey")
def q_join_outer(spark, d):
    n, s = _t(spark, d, "nation"), _t(spark, d, "supplier")
    return n.join(s, F.col("s_nationkey") == F.col("n_nationkey"), "left").groupBy("n_nationkey").agg(F.count("s_suppkey").alias("n"))


@query("SELECT n_nationkey, s_suppkey FROM (SELECT * FROM nation WHERE n_regionkey < 3) FULL JOIN (SELECT * FROM supplier WHERE s_suppkey % 2 = 0) ON s_nationkey = n_nationkey")
def q_join_full(spark, d):
    n, s = _t(spark, d, "nation").where("n_regionkey < 3"), _t(spark, d, "supplier").where("s_suppkey % 2 = 0")
    return n.join(s, F.col("s_nationkey") == F.col("n_nationkey"), "full").select("n_nationkey", "s_suppkey")


@query("SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def q_join_semi(spark, d):
    return _t(spark, d, "orders").join(_t(spark, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").select("o_orderkey")


@query("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def q_join_anti(spark, d):
    return _t(spark, d, "orders").join(_t(spark, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").select("o_orderkey")


@query("SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def q_join_theta(spark, d):
    n = _t(spark, d, "nation")
    a, b = n.alias("a"), n.alias("b")
    return a.join(b, (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b"))


_BANDS = [(0, 1000, "low"), (1000, 100000, "mid"), (100000, 300000, "high"), (300000, 10**9, "top")]


@query(f"SELECT band, count(*) AS n FROM orders JOIN (VALUES {', '.join(map(str, _BANDS))}) b(lo, hi, band) ON o_totalprice >= lo AND o_totalprice < hi GROUP BY band")
def q_join_range(spark, d):
    """A literal table of bands; the range is the join condition."""
    bands = spark.createDataFrame(_BANDS, "lo long, hi long, band string")
    return _t(spark, d, "orders").join(F.broadcast(bands), (F.col("o_totalprice") >= F.col("lo")) & (F.col("o_totalprice") < F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


@query("SELECT event_id, (SELECT max(b.event_id) FROM events b WHERE b.user_id = a.user_id AND b.ts < a.ts AND b.ts = (SELECT max(c.ts) FROM events c WHERE c.user_id = a.user_id AND c.ts < a.ts)) AS before FROM events a WHERE event_type = 'error'")
def q_join_asof(spark, d):
    """Each error with the latest earlier event of its user: one window, no join."""
    e = _t(spark, d, "events")
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy(at).rangeBetween(Window.unboundedPreceding, -1)
    last = F.max(F.struct("ts", "event_id")).over(w)
    return e.withColumn("before", last["event_id"]).where("event_type = 'error'").select("event_id", "before")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def q_join_interval(spark, d):
    """Pairs of a user within half an hour: time buckets make the range an equality on two buckets."""
    e = _t(spark, d, "events").select("event_id", "user_id", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_800_000_000).alias("k"))
    a = e.select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("ta"), F.explode(F.array(F.col("k"), F.col("k") + 1)).alias("k"))
    b = e.select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("tb"), F.col("k").alias("k2"))
    hit = (F.col("u") == F.col("v")) & (F.col("k") == F.col("k2")) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("INTERVAL 30 MINUTES"))
    return a.join(b, hit).where("a <> b").select("a", "b")


@query("SELECT r_name, kind FROM region, (VALUES ('constancy'), ('compat')) k(kind)")
def q_join_cross(spark, d):
    kinds = spark.createDataFrame([("constancy",), ("compat",)], "kind string")
    return _t(spark, d, "region").crossJoin(F.broadcast(kinds)).select("r_name", "kind")


@query(f"SELECT l_returnflag, l_linestatus, {_M.format('l_quantity')} AS qty, {_M.format('l_extendedprice')} AS price, round(avg(l_discount), 6) AS disc, count(*) AS n FROM lineitem GROUP BY ALL")
def q_agg_basic(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(_sum("l_quantity").alias("qty"), _sum("l_extendedprice").alias("price"), F.round(F.avg("l_discount"), 6).alias("disc"), F.count("*").alias("n"))


@query("SELECT p_brand, count(DISTINCT l_suppkey) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def q_agg_distinct(spark, d):
    return _t(spark, d, "lineitem").join(_t(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count_distinct("l_suppkey").alias("n"))


@query("SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 15")
def q_agg_having(spark, d):
    return _t(spark, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 15")


@query(f"SELECT d_year, d_quarter, CAST(grouping_id(d_year, d_quarter) AS BIGINT) AS g, count(*) AS n {_JOIN} GROUP BY GROUPING SETS ((d_year, d_quarter), (d_quarter), ())")
def q_grouping_sets(spark, d):
    f = R.orders_sk(spark, d).join(R.calendar(spark, d), F.col("o_date_sk") == F.col("d_date_sk"))
    y, q = F.col("d_year"), F.col("d_quarter")
    return f.groupingSets([[y, q], [q], []], y, q).agg(F.grouping_id().alias("g"), F.count("*").alias("n"))


@query(f"SELECT d_year, d_quarter, d_month, count(*) AS n {_JOIN} GROUP BY ROLLUP (d_year, d_quarter, d_month)")
def q_rollup_calendar(spark, d):
    f = R.orders_sk(spark, d).join(R.calendar(spark, d), F.col("o_date_sk") == F.col("d_date_sk"))
    return f.rollup("d_year", "d_quarter", "d_month").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def q_cube_flags(spark, d):
    return _t(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("SELECT o_custkey, arg_max(o_orderkey, {'p': o_totalprice, 'k': o_orderkey}) AS o_orderkey FROM orders GROUP BY o_custkey")
def q_agg_minmaxby(spark, d):
    return _t(spark, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("o_orderkey"))


@query("SELECT c_nationkey, bool_and(c_acctbal > 0) AS every, bool_or(c_acctbal < 0) AS some_debt FROM customer GROUP BY c_nationkey")
def q_agg_boolean(spark, d):
    return _t(spark, d, "customer").groupBy("c_nationkey").agg(F.bool_and(F.col("c_acctbal") > 0).alias("every"), F.bool_or(F.col("c_acctbal") < 0).alias("some_debt"))


@query("SELECT o_orderpriority, string_agg(DISTINCT o_orderstatus, ',' ORDER BY o_orderstatus) AS statuses FROM orders GROUP BY o_orderpriority")
def q_agg_collect_set(spark, d):
    return _t(spark, d, "orders").groupBy("o_orderpriority").agg(F.array_join(F.array_sort(F.collect_set("o_orderstatus")), ",").alias("statuses"))


@query("SELECT year(o_orderdate) AS yr, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY yr")
def q_pivot(spark, d):
    g = _t(spark, d, "orders").groupBy(F.year("o_orderdate").alias("yr")).pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey"))
    return g.select("yr", *[F.coalesce(x, F.lit(0)).alias(x.lower()) for x in "FOP"])


@query()
def q_agg_approx(spark, d):
    """Sketched beside exact counts; sketches only order work, never decide."""
    return _t(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("approx"), F.count_distinct("l_partkey").alias("exact"))


@query("SELECT o_orderkey, CAST(rank() OVER w AS INT) AS rank, CAST(dense_rank() OVER w AS INT) AS dense, CAST(row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey) AS INT) AS n, CAST(ntile(4) OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey) AS INT) AS tile, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_totalprice)")
def q_win_rank(spark, d):
    w = Window.partitionBy("o_orderpriority").orderBy("o_totalprice")
    u = Window.partitionBy("o_orderpriority").orderBy("o_totalprice", "o_orderkey")
    return _t(spark, d, "orders").select("o_orderkey", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.row_number().over(u).alias("n"), F.ntile(4).over(u).alias("tile"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@query("SELECT event_id, (epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id)) // 1000000 AS gap_s FROM events")
def q_win_lag(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    return _t(spark, d, "events").select("event_id", F.floor((at - F.lag(at).over(w)) / 1_000_000).alias("gap_s"))


@query("SELECT DISTINCT user_id, first_value(event_type) OVER w AS first_type, last_value(event_type) OVER w AS last_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def q_win_first_last(spark, d):
    """First and last by one aggregate instead of a window."""
    e = _t(spark, d, "events")
    return e.groupBy("user_id").agg(F.min_by("event_type", F.struct("ts", "event_id")).alias("first_type"), F.max_by("event_type", F.struct("ts", "event_id")).alias("last_type"))


@query("SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderstatus ORDER BY CAST(o_orderdate AS DATE) RANGE BETWEEN INTERVAL 6 DAY PRECEDING AND CURRENT ROW) AS n FROM orders")
def q_win_range(spark, d):
    w = Window.partitionBy("o_orderstatus").orderBy(F.unix_date(F.to_date("o_orderdate"))).rangeBetween(-6, 0)
    return _t(spark, d, "orders").select("o_orderkey", F.count("*").over(w).alias("n"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def q_topk(spark, d):
    return _t(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


@query("SELECT n_name, o_orderkey FROM (SELECT n_name, o_orderkey, row_number() OVER (PARTITION BY n_name ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey) WHERE r <= 3")
def q_group_topk(spark, d):
    o, c, n = (_t(spark, d, x) for x in ("orders", "customer", "nation"))
    j = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    w = Window.partitionBy("n_name").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return j.withColumn("r", F.row_number().over(w)).where("r <= 3").select("n_name", "o_orderkey")


_NATIONS = ("SELECT c_nationkey AS k FROM customer WHERE c_custkey <= 60", "SELECT s_nationkey AS k FROM supplier WHERE s_suppkey <= 40")


def _nations(spark, d):
    return _t(spark, d, "customer").where("c_custkey <= 60").select(F.col("c_nationkey").alias("k")), _t(spark, d, "supplier").where("s_suppkey <= 40").select(F.col("s_nationkey").alias("k"))


@query(f"{_NATIONS[0]} UNION {_NATIONS[1]}")
def q_set_union(spark, d):
    a, b = _nations(spark, d)
    return a.union(b).distinct()


@query(f"{_NATIONS[0]} UNION ALL {_NATIONS[1]}")
def q_set_union_all(spark, d):
    a, b = _nations(spark, d)
    return a.unionByName(b)


@query(f"{_NATIONS[0]} INTERSECT {_NATIONS[1]}")
def q_set_intersect(spark, d):
    a, b = _nations(spark, d)
    return a.intersect(b)


@query(f"{_NATIONS[0]} EXCEPT ALL {_NATIONS[1]}")
def q_set_except(spark, d):
    a, b = _nations(spark, d)
    return a.exceptAll(b)


@query("SELECT p_partkey, length(p_name) AS n, substring(p_name, 1, 4) AS head, string_split(p_name, ' ')[1] AS word, concat_ws('-', p_brand, p_type) AS joined, regexp_extract(p_brand, '([0-9]+)', 1) AS digits, lower(p_type) AS low, upper(p_name) AS up, lpad(CAST(p_size AS VARCHAR), 4, '0') AS padded FROM part")
def q_fn_string(spark, d):
    return _t(spark, d, "part").select("p_partkey", F.length("p_name").cast("long").alias("n"), F.substring("p_name", 1, 4).alias("head"), F.split("p_name", " ")[0].alias("word"), F.concat_ws("-", "p_brand", "p_type").alias("joined"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"), F.lower("p_type").alias("low"), F.upper("p_name").alias("up"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"))


@query("SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(quarter(o_orderdate) AS INT) AS q, CAST(month(o_orderdate) AS INT) AS m, CAST(day(o_orderdate) AS INT) AS dom, CAST(dayofweek(o_orderdate) + 1 AS INT) AS dow, CAST(weekofyear(o_orderdate) AS INT) AS iso, CAST(ceil(dayofyear(o_orderdate) / 7.0) AS INT) AS wk, CAST(date_trunc('month', o_orderdate) AS DATE) AS first, CAST(CAST(o_orderdate AS DATE) + 10 AS DATE) AS later, CAST(CAST(o_orderdate AS DATE) - DATE '1995-01-01' AS INT) AS age FROM orders")
def q_fn_date(spark, d):
    c = F.to_date("o_orderdate")
    return _t(spark, d, "orders").select("o_orderkey", F.year(c).alias("y"), F.quarter(c).alias("q"), F.month(c).alias("m"), F.dayofmonth(c).alias("dom"), F.dayofweek(c).alias("dow"), F.weekofyear(c).alias("iso"), F.ceil(F.dayofyear(c) / 7).cast("int").alias("wk"), F.to_date(F.date_trunc("month", c)).alias("first"), F.date_add(c, 10).alias("later"), F.datediff(c, F.lit("1995-01-01").cast("date")).alias("age"))


@query("SELECT c_custkey, CAST(floor(c_acctbal) AS BIGINT) AS f, abs(c_acctbal) AS a, CAST(sign(c_acctbal) AS DOUBLE) AS s, CAST(c_custkey % 7 AS BIGINT) AS r, greatest(c_acctbal, 0.0) AS g, least(c_acctbal, 0.0) AS l, CAST(c_acctbal AS DECIMAL(12,2)) AS dec FROM customer")
def q_fn_math(spark, d):
    b = F.col("c_acctbal")
    return _t(spark, d, "customer").select("c_custkey", F.floor(b).alias("f"), F.abs(b).alias("a"), F.signum(b).alias("s"), F.pmod("c_custkey", F.lit(7)).cast("long").alias("r"), F.greatest(b, F.lit(0.0)).alias("g"), F.least(b, F.lit(0.0)).alias("l"), b.cast("decimal(12,2)").alias("dec"))


@query("SELECT o_custkey, count(*) AS n, max(o_orderkey) AS last, sum(CASE WHEN o_orderkey % 2 = 0 THEN 1 ELSE 0 END) AS even, min(o_orderkey) * 2 AS doubled FROM orders GROUP BY o_custkey")
def q_fn_array(spark, d):
    a = _t(spark, d, "orders").groupBy("o_custkey").agg(F.array_sort(F.collect_list("o_orderkey")).alias("k"))
    return a.select("o_custkey", F.size("k").cast("long").alias("n"), F.element_at("k", -1).alias("last"), F.aggregate("k", F.lit(0).cast("decimal(38,0)"), lambda s, x: (s + F.when(x % 2 == 0, 1).otherwise(0)).cast("decimal(38,0)")).cast("int").alias("even"), F.transform("k", lambda x: x * 2)[0].alias("doubled"))


SQL["q_fn_array"] = "SELECT o_custkey, count(*) AS n, max(o_orderkey) AS last, CAST(sum(CASE WHEN o_orderkey % 2 = 0 THEN 1 ELSE 0 END) AS INT) AS even, min(o_orderkey) * 2 AS doubled FROM orders GROUP BY o_custkey"


@query("SELECT o_orderpriority, CAST(p AS INT) AS place, m FROM (SELECT o_orderpriority, list_sort(list_distinct(list(month(o_orderdate)))) AS ms FROM orders GROUP BY o_orderpriority), LATERAL (SELECT unnest(range(0, len(ms))) AS p), LATERAL (SELECT CAST(ms[p + 1] AS INT) AS m)")
def q_fn_posexplode(spark, d):
    g = _t(spark, d, "orders").groupBy("o_orderpriority").agg(F.array_sort(F.collect_set(F.month("o_orderdate"))).alias("ms"))
    return g.select("o_orderpriority", F.posexplode("ms").alias("place", "m"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
def q_fn_json(spark, d):
    return _t(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
def q_fn_from_json(spark, d):
    return _t(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))
