"""Helpers that the training-data operators share."""

from __future__ import annotations

import atexit
import contextlib
import contextvars
import ctypes
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Prefix of every column an operator adds for its own use, so that a table's own columns never clash with them.
OWN = "__own_"
#: Where stored() notes its folders, inside result_of().
_MADE: contextvars.ContextVar[list[str] | None] = contextvars.ContextVar("made", default=None)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; where it is unset a temporary one, which only a session on one machine can share."""
    sc = spark.sparkContext
    conf = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if conf:
        if sc._jsc.sc().getCheckpointDir().isEmpty():
            sc.setCheckpointDir(conf)
        return conf
    current = sc._jsc.sc().getCheckpointDir()
    if current.isEmpty():
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="orderdep-"))
        current = sc._jsc.sc().getCheckpointDir()
    return current.get()


def _delete(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session may be over already
        pass


def stored(df: DataFrame, label: str, *, codec: str = "zstd") -> DataFrame:
    """Write df as a Parquet table in the shared folder and read it back: cuts lineage, survives lost executors.

    The table goes when the driver process ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    atexit.register(_delete, spark, path)
    if (made := _MADE.get()) is not None:
        made.append(path)
    df.write.option("compression", codec).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def result_of(make: Callable[[], DataFrame], spark: SparkSession, label: str) -> DataFrame:
    """stored(make()); the tables that make() stored on its way are deleted, since nothing else can read them."""
    made: list[str] = []
    token = _MADE.set(made)
    try:
        try:
            out = make()
        finally:
            _MADE.reset(token)
        return stored(out, label)
    finally:
        for path in made:
            _delete(spark, path)


def discard(df: DataFrame) -> None:
    """Delete the files of a stored() table that nothing reads any more."""
    for path in {os.path.dirname(f) for f in df.inputFiles()}:
        if f"{shared_dir(df.sparkSession)}/".removeprefix("file://").split(":")[-1].strip("/") in path:
            _delete(df.sparkSession, path)


def arrow_map(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    return df.mapInArrow(fn, schema)


def batch(schema: pa.Schema, columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, (pa.Array, pa.ChunkedArray)) else pa.array(c, f.type) for c, f in zip(columns, schema)], schema=schema)


_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
_BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int = 1000, size: int | None = None) -> Iterator[None]:
    """Arrow batches of the jobs run here have so many rows at most: whole texts or sets in each row are many bytes.

    size: a batch ends with the row that takes it to so many bytes, too.
    """
    before, bytes_before = spark.conf.get(_BATCH), spark.conf.get(_BATCH_BYTES, None)
    spark.conf.set(_BATCH, str(min(rows, int(before)) if int(before) > 0 else rows))
    if size is not None:
        spark.conf.set(_BATCH_BYTES, str(size))
    try:
        yield
    finally:
        spark.conf.set(_BATCH, before)
        if bytes_before is not None:
            spark.conf.set(_BATCH_BYTES, bytes_before)
        elif size is not None:
            spark.conf.unset(_BATCH_BYTES)


def let_go() -> None:
    """At the end of a task: what its Python worker has freed goes back to the machine, since Spark keeps the worker."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # no glibc
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def own(name: str) -> str:
    return f"{OWN}{name}"
