"""Relations of the experiments: literal fixtures and derived tables over the given Parquet tables."""

from __future__ import annotations

import functools
import random

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..storage import shuffles_dropped, stored


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: The employee tax table of the worked examples.
SALARY_TAX = [
    ("t1", 10, 16, "secr", 1, 5.0, 20, 1.0, "A", "III"),
    ("t2", 11, 16, "mngr", 2, 8.0, 25, 2.0, "C", "II"),
    ("t3", 12, 16, "direct", 3, 10.0, 30, 3.0, "D", "I"),
    ("t4", 10, 15, "secr", 1, 4.5, 20, 0.9, "A", "III"),
    ("t5", 11, 15, "mngr", 2, 6.0, 25, 1.5, "C", "I"),
    ("t6", 12, 15, "direct", 3, 8.0, 25, 2.0, "C", "II"),
]
SALARY_TAX_SCHEMA = "tid string, id int, yr int, posit string, bin int, sal double, perc int, tax double, grp string, subg string"
SALARY_TAX_COLUMNS = ["id", "yr", "posit", "bin", "sal", "perc", "tax", "grp", "subg"]
#: Eight rows with the classes and ranks of the sorted-partition example.
TAU_DEMO = [("t1", 1, 2), ("t2", 2, 5), ("t3", 3, 1), ("t4", 3, 3), ("t5", 3, 1), ("t6", 4, 2), ("t7", 4, 4), ("t8", 5, 1)]


def salary_tax(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(SALARY_TAX, SALARY_TAX_SCHEMA)


def tau_demo(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(TAU_DEMO, "tid string, x int, a int")


def calendar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per order date; the surrogate key counts dates in their order.  A date dimension has few rows for ever,
    so its rank is one window."""
    days = table(spark, sf_dir, "orders").select(F.to_date("o_orderdate").alias("d_date")).distinct()
    return days.select(
        (F.row_number().over(Window.orderBy("d_date")) - 1).cast("long").alias("d_date_sk"), "d_date",
        F.year("d_date").alias("d_year"), F.quarter("d_date").alias("d_quarter"), F.month("d_date").alias("d_month"),
        F.ceil(F.dayofyear("d_date") / 7).cast("int").alias("d_week"),
    )


def orders_sk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders with the surrogate key of their date."""
    days = calendar(spark, sf_dir).select("d_date_sk", "d_date")
    o = table(spark, sf_dir, "orders")
    return o.join(F.broadcast(days), F.to_date("o_orderdate") == F.col("d_date")).drop("d_date").withColumnRenamed("d_date_sk", "o_date_sk")


def _parts(c, prefix: str = "") -> list:
    return [F.year(c).alias(f"{prefix}yr"), F.quarter(c).alias(f"{prefix}qtr"), F.month(c).alias(f"{prefix}mon"), F.dayofmonth(c).alias(f"{prefix}dom"), F.dayofweek(c).alias(f"{prefix}dow")]


FLIGHTLIKE_10 = ["yr", "qtr", "mon", "dom", "dow", "l_suppkey", "l_returnflag", "l_linestatus", "l_linenumber", "l_quantity"]
FLIGHTLIKE_ORDER = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity"]


def flightlike_10(spark: SparkSession, sf_dir: str, year: int = 1996) -> DataFrame:
    """The different rows of ``flightlike`` in ``FLIGHTLIKE_10``: all come from line items, the other tables only say which of these count.

    One job over the keys tells whether every key has its partner; then no row is moved.  Else semi-joins leave rows out.
    """
    t = lambda n: table(spark, sf_dir, n)
    own = [c for c in FLIGHTLIKE_10 if c in t("lineitem").columns]
    items = _shipped(t("lineitem"), year).select("l_shipdate", *dict.fromkeys(["l_orderkey", "l_partkey", "l_suppkey", *own]))
    with shuffles_dropped(spark):
        items = stored(items, "shipped")  # one year of many, read often
        links = [(t("nation"), "n_regionkey", t("region"), "r_regionkey"), (t("customer"), "c_nationkey", t("nation"), "n_nationkey"), (t("orders"), "o_custkey", t("customer"), "c_custkey"), (items, "l_orderkey", t("orders"), "o_orderkey"), (items, "l_partkey", t("part"), "p_partkey"), (items, "l_suppkey", t("supplier"), "s_suppkey")]
        lone = [rows.select(key).distinct().join(others.select(F.col(other_key).alias(key)), key, "left_anti").select(F.lit(key)) for rows, key, others, other_key in links]
        every = functools.reduce(DataFrame.union, lone).isEmpty()
    if not every:
        semi = lambda rows, key, others, other_key: rows.join(others.select(F.col(other_key).alias(key)), key, "left_semi")
        nations = semi(t("nation"), "n_regionkey", t("region"), "r_regionkey")
        orders = semi(t("orders"), "o_custkey", semi(t("customer"), "c_nationkey", nations, "n_nationkey"), "c_custkey")
        items = semi(semi(semi(items, "l_orderkey", orders, "o_orderkey"), "l_partkey", t("part"), "p_partkey"), "l_suppkey", t("supplier"), "s_suppkey")
    return items.select(*_parts(F.col("l_shipdate")), *own).select(*FLIGHTLIKE_10)


def _shipped(items: DataFrame, year: int) -> DataFrame:
    return items.where((F.col("l_shipdate") >= F.lit(f"{year}-01-01").cast("timestamp")) & (F.col("l_shipdate") < F.lit(f"{year + 1}-01-01").cast("timestamp")))


def flightlike(spark: SparkSession, sf_dir: str, year: int = 1996) -> DataFrame:
    """40 columns: line items shipped in one year with their order, customer, part and supplier."""
    t = lambda n: table(spark, sf_dir, n)
    items = _shipped(t("lineitem"), year)
    wide = items.join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey")).join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    d = F.col("l_shipdate")
    return wide.select(
        *_parts(d), F.to_date(d).alias("ship_date"), F.ceil(F.dayofyear(d) / 7).cast("int").alias("wk"), (F.year(d) * 100 + F.month(d)).alias("ym"),
        *[c for c in t("lineitem").columns if c != "l_shipdate"],
        "o_custkey", "o_orderstatus", "o_totalprice", F.to_date("o_orderdate").alias("o_date"), F.year("o_orderdate").alias("o_yr"), F.month("o_orderdate").alias("o_mon"), "o_orderpriority",
        "c_name", "c_nationkey", "c_acctbal", "c_mktsegment", "n_name", "n_regionkey", "r_name",
        "p_name", "p_brand", "p_type", "p_size", "p_retailprice", "s_name", "s_nationkey", "s_acctbal",
    )


def voterlike(spark: SparkSession, sf_dir: str) -> DataFrame:
    """20 columns of personal records: customers with their nation, derived parts and a summary of their orders."""
    t = lambda n: table(spark, sf_dir, n)
    sums = t("orders").groupBy("o_custkey").agg(F.count("*").alias("n_ord"), F.min(F.to_date("o_orderdate")).alias("first_d"), F.max(F.to_date("o_orderdate")).alias("last_d"), F.max("o_totalprice").alias("max_p"), F.min("o_orderpriority").alias("top_pri"), F.count_distinct(F.year("o_orderdate")).alias("n_yrs"))
    wide = t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).join(sums, F.col("c_custkey") == F.col("o_custkey"), "left")
    return wide.select(
        "c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment", "n_name", "n_regionkey", "r_name",
        F.regexp_extract("c_name", "([0-9]+)", 1).cast("int").alias("name_no"), F.substring("c_name", -2, 2).alias("name_tail"),
        F.floor(F.col("c_acctbal") / 1000).cast("int").alias("bal_band"), (F.col("c_acctbal") < 0).alias("in_debt"), F.substring("c_mktsegment", 1, 1).alias("seg1"),
        F.coalesce("n_ord", F.lit(0)).alias("n_ord"), "first_d", "last_d", "max_p", "top_pri", F.coalesce("n_yrs", F.lit(0)).alias("n_yrs"), F.lit(False).alias("inactive"),
    )


def clinical_like(spark: SparkSession, sf_dir: str, rows: int = 155) -> DataFrame:
    """20 narrow columns of the first customers; no column names a row."""
    t = lambda n: table(spark, sf_dir, n)
    first = t("customer").orderBy("c_custkey").limit(rows)
    n_if = lambda c: F.count_if(c).cast("int")
    o = t("orders").groupBy("o_custkey").agg(
        F.count("*").cast("int").alias("n"), F.min("o_orderpriority").alias("top_pri"), F.max("o_orderpriority").alias("low_pri"),
        n_if(F.col("o_orderstatus") == "F").alias("n_f"), n_if(F.col("o_orderstatus") == "O").alias("n_o"), n_if(F.col("o_orderstatus") == "P").alias("n_p"),
        F.count_distinct(F.year("o_orderdate")).cast("int").alias("n_yrs"), F.min(F.year("o_orderdate")).alias("y0"), F.max(F.year("o_orderdate")).alias("y1"),
    )
    wide = first.join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).join(o, F.col("c_custkey") == F.col("o_custkey"), "left")
    zero = lambda c: F.coalesce(c, F.lit(0))
    return wide.select(
        "c_nationkey", "n_regionkey", "r_name", "c_mktsegment", F.floor(F.col("c_acctbal") / 1000).cast("int").alias("bal_band"), (F.col("c_acctbal") < 0).alias("in_debt"),
        F.pmod("c_custkey", F.lit(2)).cast("int").alias("par2"), F.pmod("c_custkey", F.lit(3)).cast("int").alias("par3"), F.floor(F.col("c_custkey") / 16).cast("int").alias("age_band"),
        (zero(F.col("n")) > 10).alias("busy"), F.least(zero(F.col("n")), F.lit(9)).alias("n_ord9"), "top_pri", "low_pri",
        zero(F.col("n_f")).alias("n_f"), zero(F.col("n_o")).alias("n_o"), zero(F.col("n_p")).alias("n_p"), zero(F.col("n_yrs")).alias("n_yrs"), "y0", "y1", (zero(F.col("n_f")) * 2 > zero(F.col("n"))).alias("mostly_f"),
    )


def synth_like(spark: SparkSession, sf_dir: str) -> DataFrame:
    """30 columns: line items with part, supplier, nation and region."""
    t = lambda n: table(spark, sf_dir, n)
    wide = t("lineitem").join(t("part"), F.col("l_partkey") == F.col("p_partkey")).join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    price, off = F.col("l_extendedprice"), F.col("l_discount")
    return wide.select(
        *t("lineitem").columns, "p_name", "p_brand", "p_type", "p_size", "p_retailprice", "s_name", "s_nationkey", "s_acctbal", "n_name", "n_regionkey", "r_name",
        *_parts(F.col("l_shipdate")), F.round(price * (1 - off), 2).alias("net"), F.round(price / F.col("l_quantity"), 2).alias("unit"), F.ceil(F.col("l_quantity") / 10).cast("int").alias("qty_band"),
    )


def orders_cal(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.to_date("o_orderdate")
    return table(spark, sf_dir, "orders").select(d.alias("d_date"), F.year(d).alias("d_year"), F.quarter(d).alias("d_quarter"), F.month(d).alias("d_month"), (F.year(d) * 100 + F.month(d)).alias("d_ym"), "o_orderstatus", "o_orderpriority")


RELATIONS = {"flightlike": flightlike, "voterlike": voterlike, "clinical_like": clinical_like, "synth_like": synth_like}


def some_columns(df: DataFrame, count: int, seed: int) -> DataFrame:
    """A random projection that the seed repeats."""
    columns = df.columns
    chosen = set(random.Random(seed).sample(columns, min(count, len(columns))))
    return df.select(*[c for c in columns if c in chosen])


def share_of_rows(df: DataFrame, percent: int) -> DataFrame:
    """A sample by hash of the whole row, the same on every run."""
    return df.where(F.pmod(F.xxhash64(*df.columns), F.lit(100)) < percent)


def first_rows(df: DataFrame, rows: int, order: list[str] | None = None) -> DataFrame:
    return df.orderBy(*(order or df.columns)).limit(rows)
