"""Order checks along a sequence inside segments, without a task for each segment.

Rows are reduced groups (segment, order key, lowest, highest).  A segment is in order if the highest of each group is
not above the lowest of the next; since lowest <= highest, neighbours are enough.  The order key is cut into buckets
that keep its order, so a segment with many groups is spread over tasks: neighbours inside buckets and neighbouring
buckets are two independent tests.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Groups of a segment that one window partition holds, if codes are dense.
WIDTH = 100_000


def _bucket(order: str, width: int) -> Column:
    return F.floor(F.col(order) / width).alias("__bucket")


def _between(order: str, cuts: Sequence[int]) -> Column:
    """How many of the ascending cuts are not above the code, by halving."""

    def number(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(F.col(order) < F.lit(cuts[mid]), number(lo, mid)).otherwise(number(mid + 1, hi))

    return number(0, len(cuts)).cast("long").alias("__bucket")


def breaks(df: DataFrame, seg: list[str], order: str, lo: str, hi: str, width: int = WIDTH, cuts: Sequence[int] | None = None) -> DataFrame:
    """One row: bad (boolean), whether some segment is out of order.  ``order`` is an integer code; buckets lie between
    the cuts if they are given, as codes that are not dense need."""
    keyed = df.withColumn("__bucket", _bucket(order, width) if cuts is None else _between(order, cuts))
    inside = Window.partitionBy(*seg, "__bucket").orderBy(order)
    near = keyed.select((F.lag(hi).over(inside) > F.col(lo)).alias("bad"))
    buckets = keyed.groupBy(*seg, "__bucket").agg(F.min(lo).alias("__lo"), F.max(hi).alias("__hi"))
    # one row for each bucket of a segment, so this window holds some WIDTH times fewer rows than the segment has groups
    along = Window.partitionBy(*seg).orderBy("__bucket")
    far = buckets.select((F.lag("__hi").over(along) > F.col("__lo")).alias("bad"))
    return near.unionByName(far).agg(F.coalesce(F.max("bad"), F.lit(False)).alias("bad"))


def is_monotone(df: DataFrame, seg: list[str], order: str, lo: str, hi: str, width: int = WIDTH) -> bool:
    return not breaks(df, seg, order, lo, hi, width).first()["bad"]


def prefix_top(df: DataFrame, seg: list[str], order: str, hi: str, width: int = WIDTH) -> DataFrame:
    """df with ``__top``: the greatest ``hi`` among the groups of a strictly smaller key in the segment, null for the first."""
    keyed = df.withColumn("__bucket", _bucket(order, width))
    buckets = keyed.groupBy(*seg, "__bucket").agg(F.max(hi).alias("__hi"))
    earlier = Window.partitionBy(*seg).orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    carried = buckets.select(*[F.col(c).alias(f"__s{k}") for k, c in enumerate(seg)], F.col("__bucket").alias("__b"), F.max("__hi").over(earlier).alias("__carry"))
    same = F.col("__bucket").eqNullSafe(F.col("__b"))
    for k, c in enumerate(seg):
        same = same & F.col(c).eqNullSafe(F.col(f"__s{k}"))
    inside = Window.partitionBy(*seg, "__bucket").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    joined = keyed.withColumn("__local", F.max(hi).over(inside)).join(carried, same)
    return joined.withColumn("__top", F.greatest("__local", "__carry")).select(*df.columns, "__top")


def prefix_exceeds(df: DataFrame, seg: list[str], order: str, lo: str, hi: str, width: int = WIDTH) -> DataFrame:
    """df with ``exceeds``: some group of a strictly smaller key in the segment has a highest above this lowest."""
    return prefix_top(df, seg, order, hi, width).withColumn("exceeds", F.coalesce(F.col("__top") > F.col(lo), F.lit(False))).drop("__top")
