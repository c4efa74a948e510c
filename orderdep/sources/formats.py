"""Reading and writing tables in the common formats."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

FORMATS = ("parquet", "orc", "json", "csv")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: StructType | str | None = None) -> DataFrame:
    """Text formats need their schema: nothing is inferred by reading data twice."""
    if kind not in FORMATS:
        raise ValueError(f"{kind} is none of {FORMATS}")
    if kind in ("json", "csv") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    r = spark.read.format(kind)
    if kind == "csv":
        r = r.option("header", True)
    return (r.schema(schema) if schema is not None else r).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", by: Sequence[str] = (), mode: str = "errorifexists") -> None:
    if kind not in FORMATS:
        raise ValueError(f"{kind} is none of {FORMATS}")
    w = df.write.format(kind).mode(mode)
    if kind == "csv":
        w = w.option("header", True)
    (w.partitionBy(*by) if by else w).save(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, keys: Sequence[str], order: Sequence[str] = (), mode: str = "overwrite") -> DataFrame:
    """A table whose buckets join and group by the keys without a shuffle, sorted inside."""
    w = df.write.mode(mode).bucketBy(buckets, *keys)
    (w.sortBy(*order) if order else w).saveAsTable(table)
    return df.sparkSession.table(table)


def run_only(df: DataFrame) -> None:
    """Runs the plan and keeps nothing, for timings."""
    df.write.format("noop").mode("overwrite").save()
