"""Partitions as tables (row_id, class_id); a class is named by its smallest row id."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from itertools import combinations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .validate import ordered


def partition_of(df: DataFrame, row_id: str, context: Iterable[str]) -> DataFrame:
    context = sorted(context)
    base = df.select(F.col(row_id).alias("row_id"), F.struct(*[ordered(df, c).alias(f"f{k}") for k, c in enumerate(context)]).alias("__k") if context else F.lit(0).alias("__k"))
    names = base.groupBy("__k").agg(F.min("row_id").alias("class_id"))
    return base.join(names, "__k").select("row_id", "class_id")


def product(p: DataFrame, q: DataFrame, stripped: bool = False) -> DataFrame:
    """Rows of one class in both; for stripped inputs, rows alone in either have left already."""
    both = p.withColumnRenamed("class_id", "__p").join(q.withColumnRenamed("class_id", "__q"), "row_id")
    names = both.groupBy("__p", "__q").agg(F.min("row_id").alias("class_id"), F.count("*").alias("__n"))
    out = both.join(names.where("__n > 1") if stripped else names, ["__p", "__q"])
    return out.select("row_id", "class_id")


def strip(p: DataFrame) -> DataFrame:
    """Without the rows that are alone in their class."""
    return p.join(p.groupBy("class_id").agg(F.count("*").alias("__n")).where("__n > 1").select("class_id"), "class_id", "left_semi").select("row_id", "class_id")


def sorted_partition(df: DataFrame, row_id: str, attribute: str) -> DataFrame:
    """(rank, rows): the classes of one attribute in its order."""
    g = df.groupBy(ordered(df, attribute).alias("__v")).agg(F.array_sort(F.collect_list(row_id)).alias("rows"))
    return g.select(F.dense_rank().over(Window.orderBy("__v")).alias("rank"), "rows")


def sorted_in_context(df: DataFrame, row_id: str, context: Iterable[str], attribute: str) -> DataFrame:
    """(context, rank, rows): the same inside each class of the context."""
    context = sorted(context)
    g = df.groupBy(*context, ordered(df, attribute).alias("__v")).agg(F.array_sort(F.collect_list(row_id)).alias("rows"))
    return g.select(*context, F.dense_rank().over(Window.partitionBy(*context).orderBy("__v")).alias("rank"), "rows")


def is_superkey(df: DataFrame, context: Sequence[str]) -> bool:
    if not context:
        return df.limit(2).count() < 2
    return df.groupBy(*context).count().where("count > 1").limit(1).count() == 0


def keys(df: DataFrame, columns: Sequence[str], most: int = 3) -> list[frozenset[str]]:
    """Minimal keys of at most ``most`` columns."""
    found: list[frozenset[str]] = []
    for size in range(0, most + 1):
        for c in map(frozenset, combinations(columns, size)):
            if not any(k <= c for k in found) and is_superkey(df, sorted(c)):
                found.append(c)
    return found


def class_counts(df: DataFrame, sets: Sequence[Sequence[str]]) -> list[int]:
    """Exact number of classes of each set."""
    return [df.select(*s).distinct().count() if s else int(not df.isEmpty()) for s in sets]


def fd_by_counts(classes: int, classes_with: int) -> bool:
    """A set determines an attribute where adding it makes no more classes."""
    return classes == classes_with
