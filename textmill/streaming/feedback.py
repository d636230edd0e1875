"""Streams over feedback events; each ends with the data at hand and equals a batch query."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import query, table
from ..plans.components import shared_base


def stream(spark: SparkSession, sf_dir: str, name: str = "events", days: str = "40 days") -> DataFrame:
    """A table as a file stream with a watermark; ts becomes a timestamp, which watermarks need."""
    df = spark.readStream.schema(table(spark, sf_dir, name).schema).parquet(f"{sf_dir}/{name}.parquet*")
    return df.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", days) if "ts" in df.columns else df


def drained(df: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over all that is there, into the shared folder, and gives what it wrote."""
    spark = df.sparkSession
    out, state = (f"{shared_base(spark)}/{uuid.uuid4().hex}" for _ in range(2))
    done: list[int] = []

    def put(batch: DataFrame, number: int) -> None:
        (batch.write.mode("overwrite") if mode == "complete" else batch.write.mode("append")).parquet(out)
        done.append(number)

    df.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(out) if done else spark.createDataFrame([], df.schema)


@query("stream_feedback_tumbling", "SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M') AS hour, event_type, count(*) AS n FROM events GROUP BY ALL")
def tumbling(spark, d):
    g = stream(spark, d).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return drained(g, "complete").select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("hour"), "event_type", "n")


@query("stream_feedback_sliding", "SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts) - k * INTERVAL 1 HOUR, '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1")
def sliding(spark, d):
    g = stream(spark, d).groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count("*").alias("n"))
    return drained(g, "complete").select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "n")


@query("stream_feedback_session", "WITH s AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w >= INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), g AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM s) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM g GROUP BY user_id, k")
def session(spark, d):
    g = stream(spark, d).groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("n"))
    return drained(g, "complete").select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm").alias("start"), "n")


@query("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def dedup(spark, d):
    return drained(stream(spark, d).dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"), "append")


@query("stream_static_join", "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")
def static_join(spark, d):
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_name")
    return drained(stream(spark, d).join(c, "user_id").select("event_id", "c_name"), "append")


@query("stream_stream_interval", "SELECT a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def interval(spark, d):
    a = stream(spark, d).filter("event_type = 'view'").select("user_id", F.col("ts").alias("t1"), F.col("event_id").alias("e1"))
    b = stream(spark, d).filter("event_type = 'purchase'").select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"), F.col("event_id").alias("e2"))
    return drained(a.join(b, F.expr("user_id = u2 AND t2 > t1 AND t2 <= t1 + INTERVAL 1 HOUR")).select("e1", "e2"), "append")


@query("stream_upsert", "SELECT user_id, max(event_id) AS last FROM events GROUP BY user_id")
def upsert(spark, d):
    return drained(stream(spark, d).groupBy("user_id").agg(F.max("event_id").alias("last")), "complete")


@query("stream_late_data", "SELECT strftime(ts::DATE, '%Y-%m-%d') AS day, count(*) AS n FROM events WHERE ts >= TIMESTAMP '2024-01-15' GROUP BY 1")
def late_data(spark, d):
    """Three files in three batches: the last holds only rows older than the watermark that the first has set; they go.

    A batch drops rows by the watermark of the batch before the last one, hence the file between."""
    ev = table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    path, schema = f"{shared_base(spark)}/{uuid.uuid4().hex}", "event_id long, ts timestamp"
    for part in ("ts >= '2024-01-15' and ts < '2024-01-29'", "ts >= '2024-01-29'", "ts < '2024-01-14'"):
        ev.filter(part).coalesce(1).write.mode("append").parquet(path)
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", "1 hour")
    g = s.groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    return drained(g, "update").groupBy(F.date_format("window.start", "yyyy-MM-dd").alias("day")).agg(F.max("n").alias("n"))


@query("stream_dislike_alarm", "SELECT user_id, count(*) AS n, count(*) FILTER (event_type = 'error') AS errors FROM events GROUP BY user_id HAVING count(*) FILTER (event_type = 'error') * 4 > count(*)")
def dislike_alarm(spark, d):
    """Per user, the state holds how many events and dislikes there were; users over a quarter raise the alarm."""
    import pandas as pd

    def step(key, frames, state):
        n, errors = state.get if state.exists else (0, 0)
        for f in frames:
            n, errors = n + len(f), errors + int((f.event_type == "error").sum())
        state.update((n, errors))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "errors": [errors]})

    schema = "user_id long, n long, errors long"
    s = stream(spark, d).select("user_id", "event_type").groupBy("user_id").applyInPandasWithState(step, schema, "n long, errors long", "update", "NoTimeout")
    last = drained(s, "update").groupBy("user_id").agg(F.max(F.struct("n", "errors")).alias("x"))
    return last.select("user_id", F.col("x.n").alias("n"), F.col("x.errors").alias("errors")).filter(F.col("errors") * 4 > F.col("n"))
