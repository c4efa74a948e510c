"""Beyond exact ascending dependencies: approximate, conditional and bidirectional ones."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import segscan
from .encode import canonical, rank_encode, with_code
from .validate import ordered


def constancy_error(df: DataFrame, context: Iterable[str], attribute: str) -> DataFrame:
    """One row: n_rows, n_kept (most rows that can stay so that the constancy holds) and the share that has to go."""
    context = sorted(context)
    cells = df.groupBy(*context, ordered(df, attribute).alias("__v")).agg(F.count("*").alias("__c"))
    per = cells.groupBy(*context).agg(F.sum("__c").alias("__n"), F.max("__c").alias("__most"))
    total = per.agg(F.coalesce(F.sum("__n"), F.lit(0)).alias("n_rows"), F.coalesce(F.sum("__most"), F.lit(0)).alias("n_kept"))
    return total.withColumn("error", F.when(F.col("n_rows") > 0, 1 - F.col("n_kept") / F.col("n_rows")).otherwise(0.0))


def holds_approximately(df: DataFrame, context: Iterable[str], attribute: str, threshold: float) -> bool:
    return constancy_error(df, context, attribute).first()["error"] <= threshold


def constancy_by_condition(df: DataFrame, condition: str, context: Iterable[str], attribute: str) -> DataFrame:
    """(condition, holds): for which values of a column the constancy holds within its rows, in one aggregate."""
    v = ordered(df, attribute)
    g = df.groupBy(condition, *sorted(set(context) - {condition})).agg((F.min(v) != F.max(v)).alias("__bad"))
    return g.groupBy(condition).agg((~F.max("__bad")).alias("holds"))


def compat_by_condition(df: DataFrame, condition: str, a: str, b: str) -> DataFrame:
    """(condition, holds) for a compatibility."""
    g = df.groupBy(condition, canonical(F.col(a), df.schema[a].dataType).alias("__a")).agg(F.min(ordered(df, b)).alias("__lo"), F.max(ordered(df, b)).alias("__hi"))
    g = segscan.prefix_exceeds(with_code(g, "__a", "__k"), [condition], "__k", "__lo", "__hi")
    return g.groupBy(condition).agg((~F.max("exceeds")).alias("holds"))


def check_opposite(df: DataFrame, context: Iterable[str], a: str, b: str) -> bool:
    """Whether b never rises while a rises inside a class: the compatibility of a with the reversed codes of b."""
    context = sorted(context)
    codes = rank_encode(df.select(*context, a, b), [*context, a, b])
    groups = codes.groupBy(*context, F.col(a).alias("__a")).agg(F.min(-F.col(b)).alias("__lo"), F.max(-F.col(b)).alias("__hi"))
    return segscan.is_monotone(groups, context, "__a", "__lo", "__hi")
