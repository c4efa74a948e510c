"""Definitions, checks, violations, partitions, discovery and baselines on the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import oracle
from ..discovery.discover import discover
from ..discovery.exhaustive import candidate_counts, enumerate_all
from ..discovery.fd_only import fd_discover
from ..discovery.lattice import lattice_size
from ..discovery.list_lattice import compare_results, list_lattice_discover
from ..functions import table_functions
from ..inference import count_expanded, minimal_cover
from ..model import Canonical, Compat, Constancy, od_frame
from ..operators import partitions as P
from ..operators import segscan
from ..operators import validate as V
from ..operators import violations as W
from ..operators.encode import rank_encode
from ..sources import relations as R

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    """Registers a function under its own name."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def t(name: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: R.table(spark, d, name)


@query("SELECT a.n_nationkey AS s, b.n_nationkey AS t, (a.n_regionkey, a.n_name) <= (b.n_regionkey, b.n_name) AS le, (a.n_regionkey, a.n_name) < (b.n_regionkey, b.n_name) AS lt FROM nation a, nation b")
def q_lex_pairs(spark, d):
    """Lexicographic comparison of all pairs of nations."""
    n = R.table(spark, d, "nation")
    a, b = n.alias("a"), n.alias("b")
    left, right = ([F.col(f"{x}.n_regionkey"), F.col(f"{x}.n_name")] for x in "ab")
    return a.join(F.broadcast(b), F.lit(True)).select(F.col("a.n_nationkey").alias("s"), F.col("b.n_nationkey").alias("t"), V.lex_le(left, right).alias("le"), V.lex_lt(left, right).alias("lt"))


_LISTS = [(["d_date"], ["d_year", "d_month"]), (["d_date"], ["d_month", "d_year"]), (["d_month"], ["d_quarter"]), (["d_year", "d_month"], ["d_year", "d_quarter"]), (["d_date_sk"], ["d_date"]), (["d_quarter"], ["d_month"])]


@query(oracle.list_checks(oracle.CALENDAR, _LISTS))
def q_list_od_checks(spark, d):
    """List dependencies on the calendar, with counts of splitting and swapping groups."""
    cal = R.calendar(spark, d)
    rows = [(",".join(x), ",".join(y), c.holds, c.n_split_groups, c.n_swap_groups) for x, y in _LISTS for c in [V.check_list_od(cal, x, y)]]
    return spark.createDataFrame(rows, "lhs string, rhs string, holds boolean, n_split_groups long, n_swap_groups long")


_EQUIV = [(["d_date_sk"], ["d_date"]), (["d_year", "d_quarter", "d_month"], ["d_year", "d_month"]), (["d_month"], ["d_quarter"])]


@query(f"WITH c AS ({oracle.list_checks(oracle.CALENDAR, _EQUIV + [(y, x) for x, y in _EQUIV])}) SELECT a.lhs AS x, a.rhs AS y, a.holds AND b.holds AS equivalent FROM c a JOIN c b ON a.lhs = b.rhs AND a.rhs = b.lhs WHERE (a.lhs, a.rhs) IN ({', '.join(f'''('{','.join(x)}', '{','.join(y)}')''' for x, y in _EQUIV)})")
def q_order_equiv(spark, d):
    cal = R.calendar(spark, d)
    return spark.createDataFrame([(",".join(x), ",".join(y), V.check_order_equiv(cal, x, y)) for x, y in _EQUIV], "x string, y string, equivalent boolean")


@query(f"WITH c AS ({oracle.list_checks(oracle.CALENDAR, [(['d_month', 'd_week'], ['d_week', 'd_month']), (['d_week', 'd_month'], ['d_month', 'd_week'])])}) SELECT bool_and(holds) AS compatible FROM c")
def q_month_week_compat(spark, d):
    """Month and week never disagree, though neither determines the other."""
    return spark.createDataFrame([(V.check_list_compat(R.calendar(spark, d), ["d_month"], ["d_week"]),)], "compatible boolean")


_CUSTOMER = ["c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"]
_CONSTANT = [Constancy(frozenset(["c_custkey"]), "c_name"), Constancy(frozenset(["c_name"]), "c_custkey"), Constancy(frozenset(["c_nationkey"]), "c_mktsegment"), Constancy(frozenset(), "c_nationkey"), Constancy(frozenset(["c_acctbal", "c_mktsegment"]), "c_custkey")]
_PAIRS = [Compat.of([], "c_custkey", "c_name"), Compat.of(["c_nationkey"], "c_custkey", "c_acctbal"), Compat.of(["c_acctbal"], "c_nationkey", "c_mktsegment"), Compat.of([], "c_nationkey", "c_mktsegment"), Compat.of(["c_mktsegment"], "c_custkey", "c_name")]


def _tasks(ods: list[Canonical], columns: list[str]) -> list[tuple]:
    place = {c: k for k, c in enumerate(columns)}
    mask = lambda o: sum(1 << place[c] for c in o.context)
    return [(str(o), mask(o), place[o.attribute], None) if isinstance(o, Constancy) else (str(o), mask(o), *sorted(place[c] for c in o.pair)) for o in ods]


def _checked(spark, df, ods) -> DataFrame:
    return spark.createDataFrame([(str(o), V.check(df, o)) for o in ods], "od string, holds boolean")


@query(oracle.checks("SELECT * FROM customer", _CUSTOMER, _tasks(_CONSTANT, _CUSTOMER)))
def q_constancy_checks(spark, d):
    return _checked(spark, R.table(spark, d, "customer"), _CONSTANT)


@query(oracle.checks("SELECT * FROM customer", _CUSTOMER, _tasks(_PAIRS, _CUSTOMER)))
def q_compat_checks(spark, d):
    return _checked(spark, R.table(spark, d, "customer"), _PAIRS)


@query("SELECT 'n_nationkey' AS lhs, 'n_name,n_regionkey' AS rhs, count(*) = 0 AS holds FROM (SELECT 1 FROM nation GROUP BY n_nationkey HAVING min(n_name) <> max(n_name) OR min(n_regionkey) <> max(n_regionkey)) UNION ALL SELECT 'n_regionkey', 'n_name', count(*) = 0 FROM (SELECT 1 FROM nation GROUP BY n_regionkey HAVING min(n_name) <> max(n_name))")
def q_fd_checks(spark, d):
    n = R.table(spark, d, "nation")
    return spark.createDataFrame([(",".join(x), ",".join(y), V.check_fd(n, x, y)) for x, y in ((["n_nationkey"], ["n_name", "n_regionkey"]), (["n_regionkey"], ["n_name"]))], "lhs string, rhs string, holds boolean")


@query(oracle.checks("SELECT * FROM customer", _CUSTOMER, _tasks(_CONSTANT + _PAIRS, _CUSTOMER)))
def q_check_many(spark, d):
    """All of them from few shared plans."""
    ods = _CONSTANT + _PAIRS
    got = V.check_many(R.table(spark, d, "customer"), ods)
    labels = spark.createDataFrame([(str(o), *V.od_row(o, _CUSTOMER)[:4]) for o in ods], "od string, kind string, context string, `left` string, `right` string")
    return got.join(labels, (got.kind == labels.kind) & (got.context == labels.context) & got["left"].eqNullSafe(labels["left"]) & (got["right"] == labels["right"])).select("od", "holds")


@query("""WITH l AS (SELECT min(p_partkey) AS od, [p_brand, p_type] AS x, list_concat([p_type], string_split(p_name, ' ')) AS y FROM part GROUP BY p_brand, p_type, p_name),
f AS (SELECT od, list_sort(list_distinct(x)) AS c, CAST(NULL AS VARCHAR) AS a, unnest(y) AS b FROM l),
p AS (SELECT od, list_sort(list_distinct(list_concat(list_slice(x, 1, i - 1), list_slice(y, 1, j - 1)))) AS c, x[i] AS a, y[j] AS b
      FROM (SELECT od, x, y, i, unnest(range(1, len(y) + 1)) AS j FROM (SELECT od, x, y, unnest(range(1, len(x) + 1)) AS i FROM l)))
SELECT DISTINCT od, 'constancy' AS kind, array_to_string(c, ',') AS context, a AS "left", b AS "right" FROM f WHERE NOT list_contains(c, b)
UNION ALL SELECT DISTINCT od, 'compat', array_to_string(c, ','), least(a, b), greatest(a, b) FROM p WHERE a <> b AND NOT list_contains(c, a) AND NOT list_contains(c, b)""")
def q_map_list_od(spark, d):
    """Canonical members of list dependencies by the SQL table function: a part's brand and type, taken as attributes, order
    its type and the words of its name.  Each different pair of lists is mapped once, under its first part."""
    table_functions.register(spark)
    lists = R.table(spark, d, "part").groupBy("p_brand", "p_type", "p_name").agg(F.min("p_partkey").alias("od"))
    lists.select("od", F.array("p_brand", "p_type").alias("x"), F.concat(F.array("p_type"), F.split("p_name", " ")).alias("y")).createOrReplaceTempView("od_lists")
    return spark.sql("SELECT l.od, c.kind, c.context, c.`left`, c.`right` FROM od_lists l, LATERAL od_canonical(l.x, l.y) c")


_GROUPS = "SELECT o_orderpriority AS p, CAST(epoch_us(o_orderdate) // 86400000000 AS BIGINT) AS day, min(CAST(round(o_totalprice * 100) AS BIGINT)) AS lo, max(CAST(round(o_totalprice * 100) AS BIGINT)) AS hi FROM orders GROUP BY ALL"


def _price_groups(spark, d):
    o = R.table(spark, d, "orders")
    cents = F.round(F.col("o_totalprice") * 100).cast("long")
    return o.groupBy(F.col("o_orderpriority").alias("p"), F.unix_date(F.to_date("o_orderdate")).cast("long").alias("day")).agg(F.min(cents).alias("lo"), F.max(cents).alias("hi"))


@query(f"SELECT p, day, lo, hi, coalesce(max(hi) OVER (PARTITION BY p ORDER BY day ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) > lo, false) AS exceeds FROM ({_GROUPS})")
def q_win_prefix_max(spark, d):
    """Groups below the greatest price of an earlier day, in buckets of 100 days with a carry."""
    return segscan.prefix_exceeds(_price_groups(spark, d), ["p"], "day", "lo", "hi", width=100)


@query(f"SELECT p, count(*) FILTER (prev > lo) AS n_bad FROM (SELECT p, lo, lag(hi) OVER (PARTITION BY p ORDER BY day) AS prev FROM ({_GROUPS})) GROUP BY p")
def q_swap_adjacent(spark, d):
    from pyspark.sql import Window

    g = _price_groups(spark, d).withColumn("prev", F.lag("hi").over(Window.partitionBy("p").orderBy("day")))
    return g.groupBy("p").agg(F.count_if(F.col("prev") > F.col("lo")).alias("n_bad"))


@query("SELECT a.n_nationkey AS s, b.n_nationkey AS t FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey AND a.n_name <> b.n_name")
def q_split_pairs(spark, d):
    return W.split_pairs(R.table(spark, d, "nation"), "n_nationkey", ["n_regionkey"], ["n_name"])


@query("SELECT a.n_nationkey AS s, b.n_nationkey AS t FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_name > b.n_name")
def q_swap_pairs(spark, d):
    return W.swap_pairs(R.table(spark, d, "nation"), "n_nationkey", ["n_nationkey"], ["n_name"])


@query("SELECT a.c_custkey AS s, b.c_custkey AS t FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_custkey < b.c_custkey AND a.c_acctbal > b.c_acctbal")
def q_swap_pairs_context(spark, d):
    return W.swap_pairs(R.table(spark, d, "customer"), "c_custkey", ["c_custkey"], ["c_acctbal"], ["c_nationkey"])


@query("SELECT o_custkey, count(*) AS n_rows, count(DISTINCT o_orderstatus) AS n_values FROM orders GROUP BY o_custkey HAVING count(DISTINCT o_orderstatus) > 1")
def q_violation_summary(spark, d):
    return W.violation_summary(R.table(spark, d, "orders"), Constancy(frozenset(["o_custkey"]), "o_orderstatus"))


@query("SELECT c_nationkey, count(*) AS n_groups, count(*) FILTER (top > c_custkey) AS n_swapped FROM (SELECT c_nationkey, c_custkey, max(hi) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM (SELECT c_nationkey, c_acctbal, min(c_custkey) AS c_custkey, max(c_custkey) AS hi FROM customer GROUP BY ALL)) GROUP BY c_nationkey HAVING n_swapped > 0")
def q_violation_swaps(spark, d):
    return W.violation_summary(R.table(spark, d, "customer"), Compat.of(["c_nationkey"], "c_acctbal", "c_custkey"))


@query("SELECT least(lo.i, hi.i) AS s, greatest(lo.i, hi.i) AS t FROM (SELECT min({'v': n_name, 'i': n_nationkey}) AS lo, max({'v': n_name, 'i': n_nationkey}) AS hi FROM nation GROUP BY n_regionkey) WHERE lo.v <> hi.v ORDER BY 1, 2 LIMIT 1")
def q_witness(spark, d):
    return W.witness(R.table(spark, d, "nation"), Constancy(frozenset(["n_regionkey"]), "n_name"), "n_nationkey")


@query("SELECT count(*) AS n_pairs FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey < b.o_orderkey AND a.o_orderstatus <> b.o_orderstatus")
def q_split_counts(spark, d):
    return W.split_count(R.table(spark, d, "orders"), ["o_custkey"], "o_orderstatus")


@query("SELECT count(*) AS n_pairs FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_custkey < b.c_custkey AND a.c_acctbal > b.c_acctbal")
def q_swap_counts(spark, d):
    return W.swap_count(R.table(spark, d, "customer"), Compat.of(["c_nationkey"], "c_custkey", "c_acctbal"))


@query("SELECT c_nationkey, count(*) AS n_swaps FROM (SELECT a.c_nationkey FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_custkey < b.c_custkey AND a.c_acctbal > b.c_acctbal) GROUP BY c_nationkey")
def q_udaf_inversions(spark, d):
    """The same per class by the vectorised aggregate."""
    return R.table(spark, d, "customer").groupBy("c_nationkey").agg(table_functions.inversions("c_custkey", "c_acctbal").alias("n_swaps")).where("n_swaps > 0")


@query("SELECT dense_rank() OVER (ORDER BY c_custkey) AS row_id, dense_rank() OVER (ORDER BY c_mktsegment NULLS FIRST) AS c_mktsegment, dense_rank() OVER (ORDER BY c_acctbal NULLS FIRST) AS c_acctbal, dense_rank() OVER (ORDER BY c_name NULLS FIRST) AS c_name FROM customer")
def q_rank_encode(spark, d):
    c = R.table(spark, d, "customer")
    got = rank_encode(c, ["c_custkey", "c_mktsegment", "c_acctbal", "c_name"])
    return got.withColumnRenamed("c_custkey", "row_id")


@query("SELECT c_custkey AS row_id, min(c_custkey) OVER (PARTITION BY c_nationkey) AS class_id FROM customer")
def q_partition(spark, d):
    return P.partition_of(R.table(spark, d, "customer"), "c_custkey", ["c_nationkey"])


@query("SELECT c_custkey AS row_id, min(c_custkey) OVER (PARTITION BY c_nationkey, c_mktsegment) AS class_id FROM customer")
def q_partition_product(spark, d):
    c = R.table(spark, d, "customer")
    return P.product(P.partition_of(c, "c_custkey", ["c_nationkey"]), P.partition_of(c, "c_custkey", ["c_mktsegment"]))


@query("SELECT row_id, class_id FROM (SELECT c_custkey AS row_id, min(c_custkey) OVER w AS class_id, count(*) OVER w AS n FROM customer WINDOW w AS (PARTITION BY c_nationkey, c_mktsegment)) WHERE n > 1")
def q_stripped_partition(spark, d):
    c = R.table(spark, d, "customer")
    return P.product(P.strip(P.partition_of(c, "c_custkey", ["c_nationkey"])), P.strip(P.partition_of(c, "c_custkey", ["c_mktsegment"])), stripped=True)


@query("SELECT CAST(dense_rank() OVER (ORDER BY n_regionkey) AS INT) AS rank, rows FROM (SELECT n_regionkey, string_agg(n_nationkey, ',' ORDER BY n_nationkey) AS rows FROM nation GROUP BY n_regionkey)")
def q_sorted_partition(spark, d):
    return P.sorted_partition(R.table(spark, d, "nation"), "n_nationkey", "n_regionkey").select("rank", F.array_join(F.transform("rows", lambda x: x.cast("string")), ",").alias("rows"))


@query("SELECT c_nationkey, CAST(dense_rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS INT) AS rank, rows FROM (SELECT c_nationkey, c_mktsegment, string_agg(c_custkey, ',' ORDER BY c_custkey) AS rows FROM customer GROUP BY ALL)")
def q_tau_in_context(spark, d):
    return P.sorted_in_context(R.table(spark, d, "customer"), "c_custkey", ["c_nationkey"], "c_mktsegment").select("c_nationkey", "rank", F.array_join(F.transform("rows", lambda x: x.cast("string")), ",").alias("rows"))


def _key_sql(table: str, columns: list[str]) -> str:
    from itertools import combinations

    sets = [c for k in (1, 2, 3) for c in combinations(range(len(columns)), k)]
    rows = " UNION ALL ".join(f"SELECT {sum(1 << k for k in c)} AS m, '{','.join(columns[k] for k in c)}' AS key, count(*) = 0 AS ok FROM (SELECT 1 FROM {table} GROUP BY {', '.join(columns[k] for k in c)} HAVING count(*) > 1)" for c in sets)
    return f"SELECT '{table}' AS tab, key FROM ({rows}) x WHERE ok AND NOT EXISTS (SELECT 1 FROM ({rows}) y WHERE y.ok AND y.m <> x.m AND y.m & x.m = y.m)"


_KEYED = {"nation": ["n_nationkey", "n_name", "n_regionkey"], "supplier": ["s_suppkey", "s_name", "s_nationkey", "s_acctbal"], "conversations": ["conv_id", "turn", "role"]}


@query(" UNION ALL ".join(_key_sql(k, v) for k, v in _KEYED.items()))
def q_keys(spark, d):
    rows = [(k, ",".join(c for c in v if c in key)) for k, v in _KEYED.items() for key in P.keys(R.table(spark, d, k), v)]
    return spark.createDataFrame(rows, "tab string, key string")


@query("SELECT a.n AS classes, b.n AS classes_with, a.n = b.n AS holds FROM (SELECT count(*) AS n FROM (SELECT DISTINCT n_nationkey FROM nation)) a, (SELECT count(*) AS n FROM (SELECT DISTINCT n_nationkey, n_name FROM nation)) b")
def q_fd_by_counts(spark, d):
    a, b = P.class_counts(R.table(spark, d, "nation"), [["n_nationkey"], ["n_nationkey", "n_name"]])
    return spark.createDataFrame([(a, b, P.fd_by_counts(a, b))], "classes long, classes_with long, holds boolean")


#: name -> (relation, columns, SQL of the relation)
DISCOVERED: dict[str, tuple] = {
    "region": (t("region"), ["r_regionkey", "r_name"], "SELECT * FROM region"),
    "nation": (t("nation"), ["n_nationkey", "n_name", "n_regionkey"], "SELECT * FROM nation"),
    "supplier": (t("supplier"), ["s_suppkey", "s_name", "s_nationkey", "s_acctbal"], "SELECT * FROM supplier"),
    "customer": (t("customer"), _CUSTOMER, "SELECT * FROM customer"),
    "customer_geo": (lambda s, d: R.table(s, d, "customer").join(R.table(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(R.table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")), ["c_custkey", "c_nationkey", "n_name", "n_regionkey", "r_name"], oracle.CUSTOMER_GEO),
    "part": (t("part"), ["p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"], "SELECT * FROM part"),
    "orders": (t("orders"), ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"], "SELECT * FROM orders"),
    "events": (t("events"), ["event_id", "ts", "user_id", "event_type", "value", "props"], "SELECT * FROM events"),
    "labels": (t("labels"), ["doc_id", "quality", "toxic"], "SELECT * FROM labels"),
    "documents": (t("documents"), ["doc_id", "lang", "source", "n_chars"], "SELECT * FROM documents"),
    "conversations": (lambda s, d: R.table(s, d, "conversations").withColumn("size", F.length("text")), ["conv_id", "turn", "role", "size"], "SELECT *, length(text) AS size FROM conversations"),
    "calendar": (R.calendar, ["d_date", "d_year", "d_quarter", "d_month", "d_week"], oracle.CALENDAR),
    "orders_cal": (R.orders_cal, ["d_date", "d_year", "d_quarter", "d_month", "d_ym", "o_orderstatus", "o_orderpriority"], oracle.ORDERS_CAL),
    "lineitem": (t("lineitem"), ["l_orderkey", "l_linenumber", "l_quantity", "l_returnflag", "l_linestatus", "l_tax"], "SELECT * FROM lineitem"),
}


def _discovery(name: str, relation, columns: list[str]) -> None:
    def found(spark, d):
        return discover(relation(spark, d), columns).to_df(spark)

    found.__doc__ = f"All minimal dependencies of {name}."
    QUERIES[f"q_discover_{name}"] = found
    SQL[f"q_discover_{name}"] = oracle.discovery(DISCOVERED[name][2], columns)


for _name, (_relation, _columns, _) in DISCOVERED.items():
    _discovery(_name, _relation, _columns)


@query(oracle.discovery(oracle.CALENDAR, DISCOVERED["calendar"][1]))
def q_discover_distributed(spark, d):
    """The calendar again, every verdict by Spark plans behind a falsifying sample."""
    return discover(R.calendar(spark, d), DISCOVERED["calendar"][1], validator="spark").to_df(spark)


def _distributed(name: str) -> None:
    relation, columns, sql = DISCOVERED[name]

    def found(spark, d):
        return discover(relation(spark, d), columns, validator="spark").to_df(spark)

    found.__doc__ = f"All minimal dependencies of {name}, every verdict by Spark plans behind a falsifying sample."
    QUERIES[f"q_discover_{name}_distributed"] = found
    SQL[f"q_discover_{name}_distributed"] = oracle.discovery(sql, columns)


for _name in ("orders", "lineitem", "events"):
    _distributed(_name)


@query(oracle.discovery("SELECT * FROM customer", _CUSTOMER, pairs=False))
def q_fd_only_customer(spark, d):
    """The baseline for functional dependencies alone."""
    return fd_discover(R.table(spark, d, "customer"), _CUSTOMER).to_df(spark)


@query(oracle.valid_counts("SELECT * FROM customer", _CUSTOMER))
def q_exhaustive_counts(spark, d):
    """All valid dependencies, minimal or not, without pruning."""
    ods = enumerate_all(R.table(spark, d, "customer"), _CUSTOMER)
    n = sum(isinstance(o, Constancy) for o in ods)
    return spark.createDataFrame([(n, len(ods) - n)], "n_fd long, n_ocd long")


@query(oracle.valid_counts(oracle.CALENDAR, DISCOVERED["calendar"][1]))
def q_expanded_counts(spark, d):
    """The same numbers inferred from the minimal ones alone."""
    columns = DISCOVERED["calendar"][1]
    return spark.createDataFrame([count_expanded(discover(R.calendar(spark, d), columns).ods, columns)], "n_fd long, n_ocd long")


@query(oracle.discovery(oracle.CALENDAR, ["d_year", "d_quarter", "d_month"]))
def q_minimal_cover(spark, d):
    """All valid dependencies of three columns, cut down to a cover by inference."""
    columns = ["d_year", "d_quarter", "d_month"]
    return od_frame(spark, minimal_cover(enumerate_all(R.calendar(spark, d), columns)), columns)


@query()
def q_discover_flightlike(spark, d):
    """All rows, 10 columns of the flight stand-in."""
    return discover(R.flightlike_10(spark, d), R.FLIGHTLIKE_10).to_df(spark)


@query()
def q_discover_flightlike_levels(spark, d):
    """Nodes, checks and results per level of the same search."""
    return discover(R.flightlike_10(spark, d), R.FLIGHTLIKE_10).levels_df(spark).drop("ms")


_NARROW = ["yr", "qtr", "mon", "l_returnflag", "l_linestatus"]
_FLIGHT_SQL = "SELECT year(l_shipdate) AS yr, quarter(l_shipdate) AS qtr, month(l_shipdate) AS mon, l_returnflag, l_linestatus FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01'"


@query(oracle.discovery(_FLIGHT_SQL, _NARROW))
def q_discover_flight_year(spark, d):
    """All line items shipped in a year, five columns, the year a constant."""
    return discover(R.flightlike(spark, d), _NARROW).to_df(spark)


@query("SELECT 'yr' AS attribute FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01' HAVING count(DISTINCT year(l_shipdate)) = 1")
def q_constants(spark, d):
    """Columns with one value in the flight stand-in."""
    found = discover(R.flightlike(spark, d), R.FLIGHTLIKE_10, max_level=1)
    return spark.createDataFrame([(o.attribute,) for o in found.fds if not o.context], "attribute string")


@query("SELECT lhs, rhs FROM (" + oracle.list_checks(oracle.CALENDAR, [([a], [b]) for a in ("d_date", "d_year", "d_quarter", "d_month") for b in ("d_date", "d_year", "d_quarter", "d_month") if a != b]) + ") WHERE holds")
def q_list_lattice(spark, d):
    """The list baseline on four calendar columns, single columns on both sides."""
    got = list_lattice_discover(R.calendar(spark, d), ["d_date", "d_year", "d_quarter", "d_month"], max_length=2).ods
    return spark.createDataFrame([(",".join(o.lhs), ",".join(o.rhs)) for o in got], "lhs string, rhs string")


@query()
def q_list_lattice_compared(spark, d):
    """The list baseline beside the full search: sizes, redundancy and misses on the calendar."""
    columns = DISCOVERED["calendar"][1]
    cal = R.calendar(spark, d)
    full, lists = discover(cal, columns), list_lattice_discover(cal, columns)
    c = compare_results(lists.ods, full.ods)
    return spark.createDataFrame([(c.n_list, c.n_fd, c.n_ocd, c.n_redundant, len(c.missed), len(full.fds), len(full.ocds))], "n_list long, mapped_fd long, mapped_ocd long, n_redundant long, n_missed long, n_fd long, n_ocd long")


def _width_sql(table: str, keys: list[str], columns: list[str]) -> str:
    several = " + ".join(f"CAST(count(DISTINCT {c}) + CAST(count(*) > count({c}) AS INT) > 1 AS INT)" for c in columns)
    return f"SELECT m, count(*) AS n_groups FROM (SELECT {several} AS m FROM {table} GROUP BY {', '.join(keys)}) GROUP BY m"


def _widths(df: DataFrame, keys: list[str], columns: list[str]) -> DataFrame:
    """(m, n_groups): how many groups have m columns of several values, which are those that a search in the group keeps."""
    several = [(F.min(V.ordered(df, c)) != F.max(V.ordered(df, c))).cast("int").alias(c) for c in columns]
    return df.groupBy(*keys).agg(*several).groupBy(sum((F.col(c) for c in columns[1:]), F.col(columns[0])).alias("m")).agg(F.count("*").alias("n_groups"))


_PART_GROUP, _PART_REST = ["p_brand", "p_size"], ["p_partkey", "p_name", "p_type", "p_retailprice"]


@query(f"SELECT CAST(m AS INT) AS n_columns, n_groups, CAST(power(2, m) AS BIGINT) AS set_nodes, CAST((SELECT sum(x) FROM (SELECT factorial(CAST(m AS INT)) / factorial(CAST(k AS INT)) AS x FROM range(0, m + 1) q(k))) AS BIGINT) AS list_nodes FROM ({_width_sql('part', _PART_GROUP, _PART_REST)}) p")
def q_lattice_sizes(spark, d):
    """Nodes of both lattices over the columns that vary among the parts of a brand and size."""
    found = _widths(R.table(spark, d, "part"), _PART_GROUP, _PART_REST).collect()  # one row a width
    return spark.createDataFrame([(r["m"], r["n_groups"], *lattice_size(r["m"])) for r in found], "n_columns int, n_groups long, set_nodes long, list_nodes long")


_CUSTOMER_GROUP, _CUSTOMER_REST = ["c_nationkey", "c_mktsegment"], ["c_custkey", "c_name", "c_acctbal"]


@query(f"SELECT CAST(m AS INT) AS n_columns, n_groups, CAST(m * power(2, m - 1) AS BIGINT) AS n_fd, CAST(m * (m - 1) / 2 * power(2, m - 2) AS BIGINT) AS n_ocd FROM ({_width_sql('customer', _CUSTOMER_GROUP, _CUSTOMER_REST)}) p")
def q_candidate_counts(spark, d):
    """Candidates over the columns that vary among the customers of a nation and segment."""
    found = _widths(R.table(spark, d, "customer"), _CUSTOMER_GROUP, _CUSTOMER_REST).collect()  # one row a width
    return spark.createDataFrame([(r["m"], r["n_groups"], *candidate_counts(r["m"])) for r in found], "n_columns int, n_groups long, n_fd long, n_ocd long")
