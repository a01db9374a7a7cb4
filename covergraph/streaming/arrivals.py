"""Query arrivals as a stream: windows, sessions, late rows, duplicates."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.points import shared_dir
from pyspark.sql.streaming.state import GroupStateTimeout


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream, its local times read as UTC."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.to_timestamp(F.date_format("ts", "yyyy-MM-dd HH:mm:ss.SSSSSS")))


shared = shared_dir


def drained(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over what there is and returns its result from the shared folder; batches overwrite (complete) or add."""
    spark = stream.sparkSession
    at = f"{shared(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out" if mode == "complete" else f"{at}/out/batch={n}")  # a retried batch replaces itself

    stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out").select(*stream.columns)


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    counted = events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return drained(counted).select(F.unix_timestamp("w.start").alias("start_s"), "event_type", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    counted = events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drained(counted).select(F.unix_timestamp("w.start").alias("start_s"), "n")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of a user with gaps below 30 minutes."""
    counted = events(spark, sf_dir).groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drained(counted).select("user_id", F.unix_timestamp("w.start").alias("start_s"), "n")


def distinct_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First sight of each event id within the watermark."""
    return drained(events(spark, sf_dir).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), "append")


def joined_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Arrivals met with a static table: a user's nation by customer key."""
    who = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    return drained(events(spark, sf_dir).join(who, "user_id").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n")))


#: Microseconds of a day.
DAY = 86_400_000_000
#: One in so many arrivals comes late, by so many days; days of arrival that make a batch.
LATE_EVERY, LATE_DAYS, BATCH_DAYS = 100, 7, 5


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hours that lose arrivals: each hundredth event comes a week late, past a watermark of a quarter of an hour.

    Arrivals are replayed as files of five days each, one a batch; what the
    windows didn't count is set against all arrivals. A batch drops hours that
    end at or before the watermark that held for the batch before it."""
    home = f"{shared(spark)}/arrivals-{uuid.uuid4().hex}"
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", F.to_timestamp(F.date_format("ts", "yyyy-MM-dd HH:mm:ss.SSSSSS")).alias("ts"))
    came = F.unix_micros("ts") + F.when(F.col("event_id") % LATE_EVERY == 0, LATE_DAYS * DAY).otherwise(0)
    rows = rows.withColumn("batch", F.floor(came / (BATCH_DAYS * DAY)).cast("long"))
    for (b,) in sorted(rows.select("batch").distinct().collect()):  # a number per five days
        rows.where(F.col("batch") == b).drop("batch").coalesce(1).write.mode("append").parquet(home)
    counted = spark.readStream.schema("event_id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(home).withWatermark("ts", "15 minutes").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    kept = drained(counted, "append").select(F.unix_timestamp("w.start").alias("start_s"), "n")
    asked = rows.groupBy(F.unix_timestamp(F.date_trunc("hour", "ts")).alias("start_s")).agg(F.count(F.lit(1)).alias("arrived"))
    # hours after the last one told are still open: what they hold has not been dropped
    top = kept.agg(F.coalesce(F.max("start_s"), F.lit(0)).alias("last"))
    lost = asked.crossJoin(F.broadcast(top)).where("start_s <= last").join(kept, "start_s", "left")
    return lost.select("start_s", (F.col("arrived") - F.coalesce("n", F.lit(0))).alias("n_late")).where("n_late > 0")


def purchases_after_views(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two streams met in time: each purchase with the user's views of the half hour before it."""
    views = events(spark, sf_dir).where("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", F.col("ts").alias("seen")).withWatermark("seen", "1 hour")
    bought = events(spark, sf_dir).where("event_type = 'purchase'").select("event_id", F.col("user_id").alias("buyer"), F.col("ts").alias("at")).withWatermark("at", "1 hour")
    met = bought.join(views, F.expr("buyer = user_id AND seen BETWEEN at - INTERVAL 30 MINUTES AND at"))
    return drained(met.select("event_id", "view_id"), "append")


def last_results(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A state per user: the latest arrival seen so far and the number of them; each batch tells users whose state moved."""

    def fold(key, frames, state):
        last, at, n = state.get if state.exists else (None, -1, 0)
        for f in frames:
            n += len(f)
            row = f.sort_values(["at", "event_id"]).iloc[-1]
            if (int(row["at"]), int(row["event_id"])) > (at, -1 if last is None else last):
                last, at = int(row["event_id"]), int(row["at"])
        state.update((last, at, n))
        yield pd.DataFrame({"user_id": [key[0]], "last_event": [last], "n": [n]})

    asked = events(spark, sf_dir).select("user_id", "event_id", F.unix_micros("ts").alias("at"))
    moved = asked.groupBy("user_id").applyInPandasWithState(fold, "user_id long, last_event long, n long", "last long, at long, n long", "update", GroupStateTimeout.NoTimeout)
    told = drained(moved, "update")
    return told.groupBy("user_id").agg(F.max_by("last_event", "n").alias("last_event"), F.max("n").alias("n"))


QUERIES = {"stream_tumbling": tumbling, "stream_sliding": sliding, "stream_session": sessions, "stream_distinct": distinct_events, "stream_static_join": joined_users, "stream_late_rows": late_rows, "stream_interval_join": purchases_after_views, "stream_last_result": last_results}
ORACLES = {
    "stream_tumbling": "SELECT CAST(epoch(time_bucket(INTERVAL '1 hour', ts)) AS BIGINT) AS start_s, event_type, count(*) AS n FROM events GROUP BY ALL",
    "stream_sliding": "SELECT CAST(epoch(time_bucket(INTERVAL '1 hour', ts)) AS BIGINT) - o AS start_s, count(*) AS n FROM events, (VALUES (0), (3600)) t(o) GROUP BY 1",
    "stream_session": """WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL '30' MINUTE THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
        s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g)
        SELECT user_id, CAST(epoch(date_trunc('second', min(ts))) AS BIGINT) AS start_s, count(*) AS n FROM s GROUP BY user_id, k""",
    "stream_distinct": "SELECT DISTINCT event_id, user_id FROM events",
    # a batch drops by the watermark of the batch before it: the latest time of the batches up to two back, less a quarter of an hour
    "stream_late_rows": """WITH a AS (SELECT event_id, ts, time_bucket(INTERVAL '1 hour', ts) AS h, (epoch_us(ts) + CASE WHEN event_id % 100 = 0 THEN 604800000000 ELSE 0 END) // 432000000000 AS batch FROM events),
        b AS (SELECT batch, max(ts) AS top FROM a GROUP BY 1),
        m AS (SELECT batch, max(date_trunc('milliseconds', top)) OVER (ORDER BY batch ROWS BETWEEN UNBOUNDED PRECEDING AND 2 PRECEDING) - INTERVAL 15 MINUTE AS mark FROM b)
        SELECT CAST(epoch(h) AS BIGINT) AS start_s, count(*) AS n_late FROM a JOIN m USING (batch) WHERE h + INTERVAL 1 HOUR <= mark GROUP BY 1""",
    "stream_interval_join": "SELECT b.event_id, v.event_id AS view_id FROM events b JOIN events v ON b.user_id = v.user_id AND v.ts BETWEEN b.ts - INTERVAL 30 MINUTE AND b.ts WHERE b.event_type = 'purchase' AND v.event_type = 'view'",
    "stream_last_result": "SELECT user_id, arg_max(event_id, row(ts, event_id)) AS last_event, count(*) AS n FROM events GROUP BY 1",
    "stream_static_join": "SELECT c_nationkey, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1",
}
