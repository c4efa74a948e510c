"""Columns as order- and equality-preserving integers: null first, NaN last and equal to itself, -0.0 equal to 0.0."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..storage import stored

_NUMBERED = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)
_ORDERED = (*_NUMBERED, T.FloatType, T.DoubleType, T.DecimalType, T.StringType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType, T.DayTimeIntervalType)
#: Different values up to which a dictionary is ranked by one window.
SMALL = 1_000_000
#: Different values up to which a dictionary goes to every task, so that the rows stay where they are.
BROADCAST = 100_000
#: Estimated different values of a string or double up to which its code is a place in a literal list.
FEW_VALUES = 64
_LOWEST = -(1 << 63)


def orderable(df: DataFrame) -> list[str]:
    """The columns that have an order here; arrays, maps and structs are left out."""
    return [f.name for f in df.schema.fields if isinstance(f.dataType, _ORDERED)]


def canonical(c: Column, kind: T.DataType) -> Column:
    """-0.0 becomes 0.0; Spark already takes NaN as equal to itself and largest."""
    return F.when(c == 0, F.lit(0).cast(kind)).otherwise(c) if isinstance(kind, (T.FloatType, T.DoubleType)) else c


def identity_code(c: Column, kind: T.DataType) -> Column | None:
    """A code that needs no dictionary, or None.  Nulls go below every value: integers move up by one."""
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType)):
        n = c.cast("long")
    elif isinstance(kind, T.DateType):
        n = F.unix_date(c).cast("long")
    elif isinstance(kind, T.TimestampType):
        n = F.unix_micros(c)
    elif isinstance(kind, T.BooleanType):
        n = c.cast("long")
    else:
        return None
    return F.coalesce(n, F.lit(_LOWEST))


def dictionary(df: DataFrame, column: str) -> DataFrame:
    """(value, code): dense ranks from 1 for small dictionaries; for large ones ascending ids from a global sort.

    Ids of a sort are not the same when recomputed, so such a dictionary is written down.
    """
    kind = df.schema[column].dataType
    values = df.select(canonical(F.col(column), kind).alias("value")).distinct()
    if values.count() <= SMALL:
        return values.withColumn("code", F.dense_rank().over(Window.orderBy(F.col("value").asc_nulls_first())).cast("long"))
    ordered = values.orderBy(F.col("value").asc_nulls_first()).withColumn("code", F.monotonically_increasing_id() + 1)
    return stored(ordered, "dictionary")


def with_code(df: DataFrame, column: str, name: str) -> DataFrame:
    """df with ``name``, an order-preserving bigint of the column: integers, dates and booleans themselves, else ranks."""
    kind = df.schema[column].dataType
    direct = None if isinstance(kind, T.TimestampType) else identity_code(F.col(column), kind)
    if direct is not None:
        return df.withColumn(name, direct)
    codes = dictionary(df, column).select(F.col("value").alias("__value"), F.col("code").alias(name))
    return df.join(codes, canonical(F.col(column), kind).eqNullSafe(F.col("__value"))).drop("__value")


def rank_encode(df: DataFrame, columns: list[str] | None = None, *, dense: bool = True) -> DataFrame:
    """The columns as bigint codes, in the same row multiset.

    ``dense=False`` keeps integers, dates and timestamps as they are and ranks only the others.
    """
    columns = columns or orderable(df)
    out = df.select(*columns)
    for c in columns:
        kind = df.schema[c].dataType
        direct = None if dense else identity_code(F.col(c), kind)
        if direct is not None:
            out = out.withColumn(c, direct)
            continue
        d = dictionary(df, c).withColumnRenamed("value", "__value").withColumnRenamed("code", "__code")
        out = out.withColumn(c, canonical(F.col(c), kind)).join(d, F.col(c).eqNullSafe(F.col("__value"))).drop(c, "__value").withColumnRenamed("__code", c)
    return out.select(*columns)


def _micros(c: Column) -> Column:
    """Microseconds since 1970 of a time without zone, whatever the session's zone."""
    minutes = (F.unix_date(F.to_date(c)).cast("long") * 24 + F.hour(c)) * 60 + F.minute(c)
    return minutes * 60_000_000 + (F.extract(F.lit("SECOND"), c) * 1_000_000).cast("long")


def _real_codes(df: DataFrame, columns: list[str]) -> DataFrame:
    """Doubles as the integers that their bits, in order, stand for; nulls lowest, NaN highest."""

    def run(batches):
        for b in batches:
            cols = list(b.columns)
            for k, name in enumerate(b.schema.names):
                if name in columns:
                    null = pc.is_null(cols[k]).to_numpy(zero_copy_only=False)
                    v = cols[k].fill_null(0.0).to_numpy(zero_copy_only=False) + 0.0  # -0.0 becomes 0.0
                    code = np.where(np.isnan(v), np.nan, v).view(np.int64)
                    code = np.where(code < 0, code ^ np.int64((1 << 63) - 1), code)
                    cols[k] = pa.array(np.where(null, np.int64(_LOWEST), code), pa.int64())
            yield pa.RecordBatch.from_arrays(cols, names=b.schema.names)

    kinds = T.StructType([T.StructField(f.name, T.LongType() if f.name in columns else f.dataType) for f in df.schema.fields])
    return df.withColumns({c: F.col(c).cast("double") for c in columns}).mapInArrow(run, kinds)


def order_codes(df: DataFrame) -> tuple[DataFrame, int, list[int]]:
    """(codes, rows, estimated different values of each column): all columns as order- and equality-preserving bigints.

    Unlike ``rank_encode`` no row is moved for a number or a time, whose code need not be dense, and none for a column of
    few different values: the place in a list of up to some ``FEW_VALUES`` values, else a broadcast dictionary.  A relation that needs dictionaries is written down first, so that its joins run once.
    """
    kinds = {f.name: f.dataType for f in df.schema.fields}
    longs = [c for c, k in kinds.items() if isinstance(k, T.LongType)]
    ends = [f for c in longs for f in (F.count(c).alias(f"n_{c}"), F.min(c).alias(f"lo_{c}"))]
    about = df.agg(F.count("*").alias("rows"), *[F.approx_count_distinct(c).alias(f"d_{c}") for c in kinds], *ends).first()
    few = [c for c, k in kinds.items() if isinstance(k, (T.FloatType, T.DoubleType)) or k == T.StringType() if about[f"d_{c}"] <= min(FEW_VALUES, BROADCAST // 2)]
    listed = df.agg(*[F.array_sort(F.collect_set(canonical(F.col(c), kinds[c]))).alias(c) for c in few]).first() if few else None
    out, reals = df, []
    for c, kind in kinds.items():
        direct = identity_code(F.col(c), kind)
        if isinstance(kind, T.LongType) and (about[f"n_{c}"] == about["rows"] or (about[f"lo_{c}"] or 0) > _LOWEST):
            direct = F.coalesce(F.col(c), F.lit(_LOWEST))
        elif isinstance(kind, T.TimestampNTZType):
            direct = F.coalesce(_micros(F.col(c)), F.lit(_LOWEST))
        elif c in few:
            values = F.array(*[F.lit(v).cast(kind) for v in listed[c]]) if listed[c] else F.array().cast(T.ArrayType(kind))
            direct = F.coalesce(F.array_position(values, canonical(F.col(c), kind)).cast("long"), F.lit(0).cast("long"))
        if direct is not None:
            out = out.withColumn(c, direct)
        elif isinstance(kind, (T.FloatType, T.DoubleType)) and about[f"d_{c}"] > BROADCAST // 2:
            reals.append(c)
        else:
            values = dictionary(df, c).withColumnRenamed("value", "__value").withColumnRenamed("code", "__code")
            values = F.broadcast(values) if about[f"d_{c}"] <= BROADCAST // 2 else values
            out = out.withColumn(c, canonical(F.col(c), kind)).join(values, F.col(c).eqNullSafe(F.col("__value"))).drop(c, "__value").withColumnRenamed("__code", c)
    out = out.select(*kinds)
    return _real_codes(out, reals) if reals else out, about["rows"], [about[f"d_{c}"] for c in kinds]
