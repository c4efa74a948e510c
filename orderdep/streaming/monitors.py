"""Monitors on streams.  A dependency can only break as rows arrive, never mend, so a monitor's state only worsens."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import segscan
from ..storage import shared_dir, stored


def file_stream(spark: SparkSession, path: str, per_batch: int = 1) -> DataFrame:
    """A folder of Parquet files, a few of them each time."""
    return spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", per_batch).parquet(path)


def constancy_monitor(stream: DataFrame, context: Sequence[str], attribute: str) -> DataFrame:
    """(context, lo, hi, broken) of each class, in update or complete mode; state is two values a class."""
    g = stream.groupBy(*context).agg(F.min(attribute).alias("lo"), F.max(attribute).alias("hi"))
    return g.withColumn("broken", F.col("lo") != F.col("hi"))


class CompatMonitor:
    """foreachBatch: merges each batch's groups (context, a: least and greatest b) into a table and scans the contexts it touched.

    The table lies in the shared folder; each batch writes a new version and reads the last, so a batch that is run
    again gives the same state.
    """

    def __init__(self, spark: SparkSession, context: Sequence[str], a: str, b: str):
        self.spark, self.context, self.a, self.b = spark, list(context), a, b
        self.state: DataFrame | None = None
        self.versions: dict[int, DataFrame | None] = {}
        self.broken = False

    def groups(self, batch: DataFrame) -> DataFrame:
        return batch.groupBy(*self.context, F.col(self.a).alias("a")).agg(F.min(self.b).alias("lo"), F.max(self.b).alias("hi"))

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        before = self.versions.setdefault(batch_id, self.state)
        new = self.groups(batch)
        if before is not None:
            new = before.unionByName(new).groupBy(*self.context, "a").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
        self.state = stored(new, f"compat-monitor-{batch_id}")
        self.versions = {k: v for k, v in self.versions.items() if k >= batch_id}
        if not self.broken:
            touched = self.state if not self.context else self.state.join(batch.select(*self.context).distinct(), self.context, "left_semi")
            self.broken = not segscan.is_monotone(touched, self.context, "a", "lo", "hi")


#: A key without rows is forgotten this long after its last one, by the watermark.
KEEP_MS = 7 * 86_400_000
LAST_SEEN = "user_id long, n_events long, n_backwards long"


def last_seen(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """Per key: rows seen and how often a row's id went down while its time went up, against the latest row so far."""
    if state.hasTimedOut:
        state.remove()
        return
    last_id, n, back = state.get if state.exists else (-1, 0, 0)
    latest = 0
    for f in frames:
        for i in f.sort_values(["ts", "event_id"])["event_id"].tolist():
            back += int(i < last_id)
            last_id, n = max(last_id, i), n + 1
        latest = max(latest, int(f["ts"].max().timestamp() * 1000))
    state.update((last_id, n, back))
    state.setTimeoutTimestamp(max(latest, state.getCurrentWatermarkMs()) + KEEP_MS)
    yield pd.DataFrame({"user_id": [key[0]], "n_events": [n], "n_backwards": [back]})


def order_monitor(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """Event time decides when a key is forgotten, so a run over all input there is comes to an end."""
    return stream.select("user_id", "event_id", "ts").withWatermark("ts", late).groupBy("user_id").applyInPandasWithState(last_seen, LAST_SEEN, "last_id long, n long, back long", "update", GroupStateTimeout.EventTimeTimeout)


def run_to_table(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a query over all input there is and gives its result, by Parquet in the shared folder in either mode.  In
    complete mode each batch writes the whole result so far; the last one counts and the driver holds none."""
    import uuid

    spark = df.sparkSession
    place = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", f"{place}-state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", place).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(place)
    last: list[str] = []

    def keep(batch: DataFrame, batch_id: int) -> None:
        last[:] = [f"{place}/{batch_id}"]
        batch.write.mode("overwrite").parquet(last[0])

    writer.foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(*last) if last else spark.createDataFrame([], df.schema)
