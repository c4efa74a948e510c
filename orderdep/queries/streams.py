"""Streaming queries over the events, run to the end of their input; the SQL is the batch answer."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources import relations as R
from ..storage import shared_dir
from ..streaming import monitors as M

QUERIES, SQL = {}, {}
CHUNKS = 3


def query(sql=None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def events_of(spark, d) -> DataFrame:
    """The events with their time as an instant, which watermarks need."""
    return R.table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def chunked(spark, d) -> DataFrame:
    """The events as a stream of three files in order of time."""
    events = events_of(spark, d)
    path = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
    events.repartitionByRange(CHUNKS, "ts").write.parquet(path)
    return M.file_stream(spark, path)


def _ends(spark, d) -> DataFrame:
    """The events and one far later row, which moves the watermark past every window; its own window stays open."""
    events = events_of(spark, d)
    late = events.orderBy(F.desc("ts"), "event_id").limit(1).withColumn("ts", F.col("ts") + F.expr("INTERVAL 10 DAYS"))
    path = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
    events.repartitionByRange(CHUNKS, "ts").write.parquet(path)
    late.coalesce(1).write.mode("append").parquet(path)
    return M.file_stream(spark, path, 10)


@query("SELECT to_timestamp(floor(epoch(ts) / 3600) * 3600)::TIMESTAMP AS start, count(*) AS n FROM events GROUP BY 1")
def q_stream_tumbling(spark, d):
    s = chunked(spark, d).groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    return M.run_to_table(s, "tumbling", "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@query("SELECT to_timestamp((floor(epoch(ts) / 1800) - k) * 1800)::TIMESTAMP AS start, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY 1")
def q_stream_sliding(spark, d):
    s = chunked(spark, d).groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count("*").alias("n"))
    return M.run_to_table(s, "sliding", "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@query("""SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM
 (SELECT user_id, ts, event_id, CASE WHEN ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 20 MINUTE THEN 1 ELSE 0 END AS b FROM events)) GROUP BY user_id, s""")
def q_stream_session(spark, d):
    s = _ends(spark, d).withWatermark("ts", "30 days").groupBy("user_id", F.session_window("ts", "20 minutes").alias("w")).agg(F.count("*").alias("n"))
    got = M.run_to_table(s, "session", "complete")
    last = events_of(spark, d).agg((F.max("ts") + F.expr("INTERVAL 1 DAY")).alias("end"))
    return got.join(F.broadcast(last), F.col("w.start") < F.col("end")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("SELECT user_id, min(event_type) AS lo, max(event_type) AS hi, min(event_type) <> max(event_type) AS broken FROM events GROUP BY user_id")
def q_stream_constancy(spark, d):
    return M.run_to_table(M.constancy_monitor(chunked(spark, d), ["user_id"], "event_type"), "constancy", "complete")


@query("SELECT count(*) > 0 AS broken FROM (SELECT event_id, max(hi) OVER (ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM (SELECT ts, min(event_id) AS event_id, max(event_id) AS hi FROM events GROUP BY ts)) WHERE top > event_id")
def q_stream_compat(spark, d):
    """Do event ids and times ever disagree?  State: the least and greatest id of each time."""
    stream = chunked(spark, d).withColumn("t", F.unix_micros("ts"))
    m = M.CompatMonitor(spark, [], "t", "event_id")
    stream.writeStream.foreachBatch(m).option("checkpointLocation", f"{shared_dir(spark)}/compat-{uuid.uuid4().hex}").trigger(availableNow=True).start().awaitTermination()
    return spark.createDataFrame([(m.broken,)], "broken boolean")


@query("SELECT user_id, event_type, count(*) AS n FROM (SELECT DISTINCT event_id, user_id, event_type FROM events) GROUP BY ALL")
def q_stream_dedup(spark, d):
    """Every file comes twice; duplicates go within the watermark."""
    events = events_of(spark, d)
    path = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
    for _ in range(2):
        events.coalesce(1).write.mode("append").parquet(path)
    s = M.file_stream(spark, path).withWatermark("ts", "3650 days").dropDuplicatesWithinWatermark(["event_id"])
    return M.run_to_table(s, "dedup").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


@query("SELECT kind, count(*) AS n FROM events JOIN (VALUES ('click', 'act'), ('view', 'see'), ('error', 'bad')) v(event_type, kind) USING (event_type) GROUP BY kind")
def q_stream_static_join(spark, d):
    kinds = spark.createDataFrame([("click", "act"), ("view", "see"), ("error", "bad")], "event_type string, kind string")
    s = chunked(spark, d).join(F.broadcast(kinds), "event_type").groupBy("kind").agg(F.count("*").alias("n"))
    return M.run_to_table(s, "static_join", "complete")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def q_stream_stream_join(spark, d):
    """Purchases within ten minutes of an error, both sides streams."""
    a = chunked(spark, d).where("event_type = 'error'").select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("ta")).withWatermark("ta", "365 days")
    b = chunked(spark, d).where("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("tb")).withWatermark("tb", "365 days")
    s = a.join(b, (F.col("u") == F.col("v")) & (F.col("tb") >= F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("INTERVAL 10 MINUTES")))
    return M.run_to_table(s.select("a", "b"), "stream_join")


@query("SELECT user_id, count(*) AS n_events FROM events GROUP BY user_id")
def q_stream_last_seen(spark, d):
    """The stateful monitor's last word for each user."""
    path = f"{shared_dir(spark)}/seen-{uuid.uuid4().hex}"
    out: list[DataFrame] = []

    def keep(batch: DataFrame, _: int) -> None:
        batch.write.mode("append").parquet(path)
        out.append(batch)

    M.order_monitor(chunked(spark, d), "3650 days").writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(M.LAST_SEEN).parquet(path).groupBy("user_id").agg(F.max("n_events").alias("n_events"))
