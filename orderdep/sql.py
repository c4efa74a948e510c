"""SQL entry: table functions and views over a rule catalog."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import table_functions
from .model import OD_SCHEMA, Canonical, od_frame
from .operators.validate import check_many


def register(spark: SparkSession, ods: Iterable[Canonical] = (), df: DataFrame | None = None) -> None:
    """od_canonical(), od_closure(), inversions(); view od_catalog with the rules; with a relation also od_violations,
    the rules that it breaks."""
    table_functions.register(spark)
    ods = list(ods)
    columns = df.columns if df is not None else sorted(set().union(*(o.context | (o.pair if hasattr(o, "pair") else {o.attribute}) for o in ods))) if ods else []
    od_frame(spark, ods, columns).createOrReplaceTempView("od_catalog")
    broken = check_many(df, ods).where(~F.col("holds")).drop("holds") if df is not None and ods else spark.createDataFrame([], OD_SCHEMA)
    broken.createOrReplaceTempView("od_violations")
