"""Where a dependency breaks: bad classes, counts, witnesses and row pairs."""

from __future__ import annotations

from collections.abc import Iterable, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import Canonical, Compat, Constancy
from . import segscan
from .encode import canonical, with_code
from .validate import compat_groups, constancy_bad, listed, ordered


def _capped(pairs: DataFrame, limit: int | None, keys: list[str]) -> DataFrame:
    if limit is None:
        return pairs
    w = Window.partitionBy(*keys).orderBy("s", "t") if keys else Window.orderBy("s", "t")
    return pairs.withColumn("__n", F.row_number().over(w)).where(F.col("__n") <= limit).drop("__n")


def split_pairs(df: DataFrame, row_id: str, lhs: Sequence[str], rhs: Sequence[str], limit: int | None = None) -> DataFrame:
    """(s, t), s < t: rows equal on lhs and different on rhs.  Only bad classes enter the join; ``limit`` caps a class."""
    base = df.select(F.col(row_id).alias("__id"), listed(df, lhs).alias("__x"), listed(df, rhs).alias("__y"))
    bad = base.groupBy("__x").agg(F.min("__y").alias("__lo"), F.max("__y").alias("__hi")).where("__lo <> __hi").select("__x")
    rows = base.join(bad, "__x", "left_semi")
    s, t = rows.select(F.col("__id").alias("s"), "__x", F.col("__y").alias("__ys")), rows.select(F.col("__id").alias("t"), "__x", F.col("__y").alias("__yt"))
    pairs = s.join(t, "__x").where((F.col("s") < F.col("t")) & (F.col("__ys") != F.col("__yt")))
    return _capped(pairs, limit, ["__x"]).select("s", "t")


def swap_pairs(df: DataFrame, row_id: str, x: Sequence[str], y: Sequence[str], context: Iterable[str] = (), limit: int | None = None) -> DataFrame:
    """(s, t): s before t on x and after t on y, both in one class of the context."""
    base = df.select(F.col(row_id).alias("__id"), listed(df, sorted(context)).alias("__c"), listed(df, x).alias("__x"), listed(df, y).alias("__y"))
    groups = base.groupBy("__c", "__x").agg(F.min("__y").alias("__lo"), F.max("__y").alias("__hi"))
    bad = segscan.prefix_exceeds(with_code(groups, "__x", "__k"), ["__c"], "__k", "__lo", "__hi").where("exceeds").select("__c").distinct()
    rows = base.join(bad, "__c", "left_semi")
    s = rows.select(F.col("__id").alias("s"), "__c", F.col("__x").alias("__xs"), F.col("__y").alias("__ys"))
    t = rows.select(F.col("__id").alias("t"), "__c", F.col("__x").alias("__xt"), F.col("__y").alias("__yt"))
    pairs = s.join(t, "__c").where((F.col("__xs") < F.col("__xt")) & (F.col("__ys") > F.col("__yt")))
    return _capped(pairs, limit, ["__c"]).select("s", "t")


def _by_value(df: DataFrame, context: list[str], a: str, *aggregates: Column) -> DataFrame:
    """(context, a as ``__a``, its code ``__k``, aggregates): a row for each value of a in a class, fit for bucketed scans."""
    groups = df.groupBy(*context, canonical(F.col(a), df.schema[a].dataType).alias("__a")).agg(*aggregates)
    return with_code(groups, "__a", "__k")


def violation_summary(df: DataFrame, od: Canonical) -> DataFrame:
    """Bad classes only: their context values with n_rows and n_values (constancy), or n_groups and n_swapped (compat)."""
    context = sorted(od.context)
    if isinstance(od, Constancy):
        v = ordered(df, od.attribute)
        g = df.groupBy(*context).agg(F.count("*").alias("n_rows"), F.count_distinct(v).alias("n_values"))
        return g.where("n_values > 1")
    a, b = sorted(od.pair)
    groups = _by_value(df, context, a, F.min(ordered(df, b)).alias("__lo"), F.max(ordered(df, b)).alias("__hi"))
    flags = segscan.prefix_exceeds(groups, context, "__k", "__lo", "__hi")
    return flags.groupBy(*context).agg(F.count("*").alias("n_groups"), F.count_if("exceeds").alias("n_swapped")).where("n_swapped > 0")


def witness(df: DataFrame, od: Canonical, row_id: str) -> DataFrame:
    """At most one row (s, t) for a broken dependency; ties go to the smallest ids."""
    context = sorted(od.context)
    if isinstance(od, Constancy):
        v = ordered(df, od.attribute)
        g = df.groupBy(*context).agg(F.min(F.struct(v.alias("v"), F.col(row_id).alias("i"))).alias("lo"), F.max(F.struct(v.alias("v"), F.col(row_id).alias("i"))).alias("hi"))
        return g.where("lo.v <> hi.v").select(F.least("lo.i", "hi.i").alias("s"), F.greatest("lo.i", "hi.i").alias("t")).orderBy("s", "t").limit(1)
    a, b = sorted(od.pair)
    value = F.struct(ordered(df, b).alias("v"), F.col(row_id).alias("i"))
    groups = _by_value(df, context, a, F.min(value).alias("__lo"), F.max(value).alias("__hi"))
    g = segscan.prefix_top(groups, context, "__k", "__hi").where("__top.v > __lo.v")
    return g.select(F.col("__top.i").alias("s"), F.col("__lo.i").alias("t")).orderBy("s", "t").limit(1)


def split_count(df: DataFrame, context: Iterable[str], attribute: str) -> DataFrame:
    """One row: n_pairs, the number of row pairs equal on the context and different on the attribute, without listing them."""
    context = sorted(context)
    cells = df.groupBy(*context, ordered(df, attribute).alias("__v")).agg(F.count("*").alias("__c"))
    per = cells.groupBy(*context).agg(F.sum("__c").alias("__n"), F.sum(F.col("__c") * F.col("__c")).alias("__q"))
    return per.agg(F.coalesce(F.sum((F.col("__n") * F.col("__n") - F.col("__q")) / 2), F.lit(0)).cast("long").alias("n_pairs"))


def swap_count(df: DataFrame, od: Compat) -> DataFrame:
    """One row: n_pairs in swap, without listing them.

    Two rows with different codes of the first attribute part at exactly one binary digit of them, the smaller on the
    0 side.  For each digit and each common front of the codes, a window over the other attribute counts how many of
    the 0 side lie above each of the 1 side.
    """
    from .encode import rank_encode

    context = sorted(od.context)
    a, b = sorted(od.pair)
    codes = rank_encode(df.select(*context, a, b), [*context, a, b])
    cells = codes.groupBy(*context, F.col(a).alias("__x"), F.col(b).alias("__y")).agg(F.count("*").alias("__n"))
    digits = int(codes.agg(F.max(a).alias("m")).first()["m"] or 0).bit_length()
    if not digits:
        return cells.agg(F.lit(0).cast("long").alias("n_pairs"))
    node = cells.withColumn("__d", F.explode(F.sequence(F.lit(0), F.lit(digits - 1))))
    node = node.withColumns({"__front": F.expr("shiftright(__x, __d + 1)"), "__one": F.expr("shiftright(__x, __d) & 1") == 1})
    w = Window.partitionBy(*context, "__d", "__front").orderBy(F.col("__y").desc()).rangeBetween(Window.unboundedPreceding, -1)
    above = F.coalesce(F.sum(F.when(~F.col("__one"), F.col("__n")).otherwise(0)).over(w), F.lit(0))
    per = node.withColumn("__above", above).where("__one")
    return per.agg(F.coalesce(F.sum(F.col("__above") * F.col("__n")), F.lit(0)).cast("long").alias("n_pairs"))


def constancy_witnesses(df: DataFrame, context: Iterable[str], attribute: str) -> DataFrame:
    return constancy_bad(df, context, attribute)


def swapped_groups(df: DataFrame, od: Compat) -> DataFrame:
    """Every group of the first attribute (as code) with the flag ``exceeds``, bucketed for classes of many groups."""
    a, b = sorted(od.pair)
    return segscan.prefix_exceeds(compat_groups(df, od.context, a, b), sorted(od.context), "__a", "__lo", "__hi")
