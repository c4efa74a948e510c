"""Rule catalogs as JSON lines on any store Spark writes."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession

from ..model import OD_SCHEMA, Canonical, Compat, Constancy, od_frame


def save_catalog(spark: SparkSession, ods: Iterable[Canonical], columns: list[str], path: str) -> None:
    od_frame(spark, ods, columns).coalesce(1).write.mode("overwrite").json(path)


def load_catalog(spark: SparkSession, path: str) -> set[Canonical]:
    return from_rows(spark.read.schema(OD_SCHEMA).json(path))


def from_rows(rows: DataFrame) -> set[Canonical]:
    """A catalog is metadata: as many rows as rules."""
    out: set[Canonical] = set()
    for r in rows.collect():
        context = [c for c in (r["context"] or "").split(",") if c]
        out.add(Constancy(frozenset(context), r["right"]) if r["kind"] == "constancy" else Compat.of(context, r["left"], r["right"]))
    return out
