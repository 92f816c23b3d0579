"""Live edges: streams of events as windowed interactions, sessions, transitions and degrees.

Streams read files with ``availableNow`` and write Parquet or memory, so a batch query over the same rows is the oracle.
Rows arrive in the order of event time: the events are first laid out as a few files by day.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import run_dir
from ..plans.shared import Registry
from ..sources.tables import table

registry = Registry()
EVENT = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def timed_events(spark, sf_dir) -> DataFrame:
    """Event time with a zone, as streams need it; results give it back without."""
    return table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def arriving(spark, sf_dir, files: int = 3) -> DataFrame:
    """The events as a stream of ``files`` files, one micro-batch each, in time order."""
    path = run_dir(spark, "arrivals")
    events = timed_events(spark, sf_dir)
    ends = events.agg(F.min("ts").alias("a"), F.max("ts").alias("b")).first()
    width = (ends.b - ends.a) / files
    for k in range(files):
        low, high = ends.a + k * width, ends.a + (k + 1) * width
        rows = events.where(F.col("ts") >= low) if k == files - 1 else events.where((F.col("ts") >= low) & (F.col("ts") < high))
        rows.coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(EVENT).option("maxFilesPerTrigger", 1).parquet(path)


def drained(stream: DataFrame, label: str, mode: str = "append") -> DataFrame:
    """Everything that the stream gives: appended to Parquet, or the last complete table."""
    spark = stream.sparkSession
    path = run_dir(spark, label)
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    else:
        query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).foreachBatch(lambda rows, _: rows.write.mode("overwrite").parquet(f"{path}/out")).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/out")


@registry("SELECT date_trunc('hour', ts) AS start, user_id, count(*) AS n FROM events GROUP BY 1, 2")
def st_tumbling(spark, sf_dir):
    rows = arriving(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour"), "user_id").agg(F.count("*").alias("n"))
    return drained(rows, "tumbling", "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "user_id", "n")


@registry("SELECT date_trunc('hour', ts) - to_hours(k) AS start, event_type, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1, 2")
def st_sliding(spark, sf_dir):
    rows = arriving(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "2 hours", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return drained(rows, "sliding", "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@registry("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 4 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
n AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM n GROUP BY user_id, s""")
def st_session(spark, sf_dir):
    rows = arriving(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "4 hours"), "user_id").agg(F.count("*").alias("n"))
    return drained(rows, "session", "complete").select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


@registry("SELECT event_id FROM events WHERE user_id % 2 = 0 AND ts >= (SELECT max(ts) FROM events WHERE user_id % 2 = 1) - INTERVAL 2 DAY UNION ALL SELECT event_id FROM events WHERE user_id % 2 = 1")
def st_watermark_late(spark, sf_dir):
    """Two large batches, the second older in part: rows beyond the watermark are dropped before the stateful step.

    The watermark of one batch judges the rows of the next but one, so a small batch stands between (one event again).
    """
    path = run_dir(spark, "late")
    events = timed_events(spark, sf_dir)
    odd = events.where("user_id % 2 = 1")
    for rows in (odd, odd.orderBy(F.desc("ts")).limit(1), events.where("user_id % 2 = 0")):
        rows.coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(EVENT).option("maxFilesPerTrigger", 1).parquet(path)
    return drained(stream.withWatermark("ts", "2 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "late-out")


@registry("SELECT event_id, user_id FROM events")
def st_dedup(spark, sf_dir):
    """Every event sent twice; each counts once."""
    path = run_dir(spark, "twice")
    events = timed_events(spark, sf_dir)
    events.unionByName(events).coalesce(1).write.parquet(path)
    stream = spark.readStream.schema(EVENT).parquet(path)
    return drained(stream.withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), "dedup")


@registry("SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")
def st_static_join(spark, sf_dir):
    static = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return drained(arriving(spark, sf_dir).join(static, "user_id").select("event_id", "c_mktsegment"), "static")


@registry("SELECT a.event_id AS view_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def st_stream_join(spark, sf_dir):
    views = arriving(spark, sf_dir).where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("ts").alias("tv"), F.col("user_id").alias("u")).withWatermark("tv", "1 hour")
    buys = arriving(spark, sf_dir).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("ts").alias("tp"), "user_id").withWatermark("tp", "1 hour")
    return drained(views.join(buys, F.expr("u = user_id AND tp >= tv AND tp <= tv + INTERVAL 6 HOURS")).select("view_id", "purchase_id"), "pairs")


@registry("SELECT user_id, event_type AS to_type, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS from_type FROM events QUALIFY from_type IS NOT NULL")
def st_stateful_transitions(spark, sf_dir):
    """Each user's last event is state; every event gives the move from it."""

    def moves(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        before = [last, *rows["event_type"].tolist()[:-1]]
        state.update((rows["event_type"].iloc[-1],))
        out = pd.DataFrame({"user_id": key[0], "from_type": before, "to_type": rows["event_type"].tolist()})
        yield out[out["from_type"].notna()]

    stream = arriving(spark, sf_dir).groupBy("user_id").applyInPandasWithState(moves, "user_id long, from_type string, to_type string", "last string", "append", "NoTimeout")
    return drained(stream, "transitions")


@registry("SELECT user_id AS vid, count(*) AS n FROM events GROUP BY 1")
def st_foreach_batch_degrees(spark, sf_dir):
    """Counts merged batch by batch: each batch writes a new table of all counts and the number of the last batch names it."""
    path = run_dir(spark, "degrees")
    spark.createDataFrame([], "vid long, n long").write.parquet(f"{path}/n=-1")

    def merge(rows: DataFrame, batch: int) -> None:
        old = spark.read.schema("vid long, n long").parquet(f"{path}/n={batch - 1}")
        fresh = rows.groupBy(F.col("user_id").alias("vid")).agg(F.count("*").alias("n"))
        old.unionByName(fresh).groupBy("vid").agg(F.sum("n").alias("n")).write.mode("overwrite").parquet(f"{path}/n={batch}")

    query = arriving(spark, sf_dir).writeStream.option("checkpointLocation", f"{path}-state").trigger(availableNow=True).foreachBatch(merge).start()
    query.awaitTermination()
    return spark.read.schema("vid long, n long").parquet(f"{path}/n={query.lastProgress['batchId']}")
