"""Measures, extensions, formats and the SQL entry as queries."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from .. import oracle, sql
from ..discovery import measures as M
from ..discovery.discover import discover
from ..discovery.list_lattice import list_lattice_discover
from ..mapping import to_canonical
from ..model import Compat, Constancy
from ..operators import extensions as X
from ..sources import formats
from ..sources import relations as R
from ..storage import shared_dir

QUERIES, SQL = {}, {}
_CAL = ["d_date", "d_year", "d_quarter", "d_month", "d_week"]


def query(text=None):
    def add(f):
        QUERIES[f.__name__] = f
        if text:
            SQL[f.__name__] = text
        return f

    return add


@query(f"SELECT count(*) FILTER (kind = 'constancy') AS n_fd, count(*) FILTER (kind = 'compat') AS n_ocd, CAST(max(context_size) AS INT) AS largest_context FROM ({oracle.discovery(oracle.CALENDAR, _CAL)})")
def q_measure_counts(spark, d):
    return M.summarise(discover(R.calendar(spark, d), _CAL).to_df(spark))


@query()
def q_measure_quality(spark, d):
    """Recall, soundness and conciseness of the list baseline against the full result on the calendar."""
    cal = R.calendar(spark, d)
    full, lists = discover(cal, _CAL).ods, list_lattice_discover(cal, _CAL).ods
    q = M.quality(set().union(*(to_canonical(o) for o in lists)), full)
    return spark.createDataFrame([(q.recall, q.soundness, q.conciseness)], "recall double, soundness double, conciseness double")


@query("SELECT round(regr_slope(ln(y), ln(x)), 6) AS power, round(regr_r2(ln(y), ln(x)), 6) AS power_r2, round(regr_slope(ln(y), x), 6) AS rate, round(regr_r2(ln(y), x), 6) AS rate_r2 FROM (SELECT CAST(l_quantity AS DOUBLE) AS x, avg(l_extendedprice) AS y FROM lineitem GROUP BY l_quantity)")
def q_measure_growth(spark, d):
    """The fits used for time series, here of the mean price by quantity."""
    s = R.table(spark, d, "lineitem").groupBy(F.col("l_quantity").alias("x")).agg(F.avg("l_extendedprice").alias("y"))
    return M.growth_fit(s, "x", "y").select(*[F.round(c, 6).alias(c) for c in ("power", "power_r2", "rate", "rate_r2")])


@query("SELECT CAST(sum(n) AS BIGINT) AS n_rows, CAST(sum(most) AS BIGINT) AS n_kept, round(1 - sum(most) / sum(n), 9) AS error FROM (SELECT sum(c) AS n, max(c) AS most FROM (SELECT c_nationkey, c_mktsegment, count(*) AS c FROM customer GROUP BY ALL) GROUP BY c_nationkey)")
def q_approximate_constancy(spark, d):
    """How many customers have to go so that a nation has one segment."""
    e = X.constancy_error(R.table(spark, d, "customer"), ["c_nationkey"], "c_mktsegment")
    return e.select("n_rows", "n_kept", F.round("error", 9).alias("error"))


@query("SELECT o_orderstatus, bool_and(ok) AS holds FROM (SELECT o_orderstatus, o_custkey, count(DISTINCT o_orderpriority) = 1 AS ok FROM orders GROUP BY ALL) GROUP BY o_orderstatus")
def q_conditional_constancy(spark, d):
    return X.constancy_by_condition(R.table(spark, d, "orders"), "o_orderstatus", ["o_custkey"], "o_orderpriority")


@query(f"SELECT d_year, NOT coalesce(bool_or(bad), false) AS holds FROM (SELECT d_year, lag(d_date) OVER (PARTITION BY d_year ORDER BY d_month, d_date) > d_date AS bad FROM ({oracle.CALENDAR})) GROUP BY d_year")
def q_conditional_compat(spark, d):
    """In which years date and month agree on order."""
    return X.compat_by_condition(R.calendar(spark, d), "d_year", "d_date", "d_month")


@query("SELECT * FROM (VALUES ('same', false), ('reversed', true)) v(column_b, opposite)")
def q_bidirectional(spark, d):
    """A column against itself and against its negative."""
    c = R.table(spark, d, "customer").select("c_acctbal", (-F.col("c_acctbal")).alias("neg"), F.col("c_acctbal").alias("again"))
    return spark.createDataFrame([("same", X.check_opposite(c, [], "c_acctbal", "again")), ("reversed", X.check_opposite(c, [], "c_acctbal", "neg"))], "column_b string, opposite boolean")


@query("SELECT n_nationkey, n_name, n_regionkey, kind FROM nation, (VALUES ('csv'), ('json'), ('orc'), ('parquet')) v(kind)")
def q_formats(spark, d):
    """A table written and read back in four formats."""
    n = R.table(spark, d, "nation")
    out = None
    for kind in formats.FORMATS:
        formats.write(n, path := f"{shared_dir(spark)}/nation-{uuid.uuid4().hex}", kind)
        got = formats.read(spark, path, kind, n.schema).withColumn("kind", F.lit(kind))
        out = got if out is None else out.unionByName(got)
    return out


@query("SELECT * FROM (VALUES ('{c_nationkey}: [] -> c_mktsegment', true), ('{}: c_custkey ~ c_name', false)) v(rule, broken)")
def q_sql_views(spark, d):
    """The catalog and its broken rules as views."""
    rules = [Constancy(frozenset(["c_nationkey"]), "c_mktsegment"), Compat.of([], "c_custkey", "c_name")]
    sql.register(spark, rules, R.table(spark, d, "customer"))
    return spark.sql("SELECT concat('{', c.context, '}: ', if(c.kind = 'constancy', concat('[] -> ', c.right), concat(c.left, ' ~ ', c.right))) AS rule, v.kind IS NOT NULL AS broken FROM od_catalog c LEFT JOIN od_violations v ON c.kind = v.kind AND c.context = v.context AND c.right = v.right")
