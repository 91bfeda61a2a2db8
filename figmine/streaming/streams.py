"""Streams of the chain: the run log by event time, files of documents in batches. Every stream has a batch twin."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _events(df: DataFrame) -> DataFrame:
    # a watermark needs TIMESTAMP; the table holds TIMESTAMP_NTZ
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def read_stream(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    path = f"{sf_dir}/{table}.parquet"
    schema = spark.read.parquet(path).schema
    # one file or a folder of files
    return spark.readStream.schema(schema).parquet(path if spark._jvm.org.apache.hadoop.fs.Path(path).getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(spark._jvm.org.apache.hadoop.fs.Path(path)).isDirectory() else f"{sf_dir}/{table}*.parquet")


def tumbling(events: DataFrame) -> DataFrame:
    g = _events(events).withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour"), "event_type")
    return g.agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("window.start").cast("string").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame) -> DataFrame:
    g = _events(events).withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour", "15 minutes"))
    return g.agg(F.count("*").alias("n")).select(F.col("window.start").cast("string").alias("start"), "n")


def session(events: DataFrame) -> DataFrame:
    g = _events(events).withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", "30 minutes"), "user_id")
    return g.agg(F.count("*").alias("n")).select(F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "user_id", "n")


def distinct_events(events: DataFrame) -> DataFrame:
    return _events(events).withWatermark("ts", "10 minutes").dropDuplicatesWithinWatermark(["event_type", "user_id"]).select("event_type", "user_id")


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over all that is there and returns what its sink holds: files for rows that are only added, else a
    table of the driver, which is for results of bounded size."""
    spark = stream.sparkSession
    folder = _shared(spark, "drained")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", f"{folder}/out").outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{folder}/out")
    name = f"drained_{uuid.uuid4().hex}"
    stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def _shared(spark: SparkSession, name: str) -> str:
    return f"{spark.sparkContext._conf.get('spark.checkpoint.dir', None) or tempfile.mkdtemp(prefix='figmine-')}/{name}-{uuid.uuid4().hex}"


def all_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every session of the run log, written to files as it closes. After the log comes one mark a day later, which closes
    what is still open; its own session stays open and is never written."""
    folder = _shared(spark, "sessions")
    log = spark.read.parquet(f"{sf_dir}/events.parquet").select("ts", "user_id")
    log.limit(0).write.parquet(f"{folder}/marks")
    marks = spark.readStream.schema(log.schema).parquet(f"{folder}/marks")
    found = session(read_stream(spark, sf_dir, "events").select("ts", "user_id").unionByName(marks))
    for step in ("log", "mark"):
        if step == "mark":
            log.agg((F.max("ts") + F.expr("INTERVAL 1 DAY")).alias("ts")).select("ts", F.lit(None).cast(log.schema["user_id"].dataType).alias("user_id")).write.mode("append").parquet(f"{folder}/marks")
        found.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(found.schema).parquet(f"{folder}/out")


def process_batches(stream: DataFrame, step, path: str, checkpoint: str):
    """Runs ``step`` (DataFrame to DataFrame) on each arriving batch; a batch that is repeated overwrites itself."""

    def write(batch: DataFrame, number: int) -> None:
        step(batch).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


# ---- streams with state, lookups, late rows and a second stream


def kinds(spark) -> DataFrame:
    """The lookup that the run log meets: a row a kind of step."""
    return spark.createDataFrame([("click", 1), ("view", 2), ("error", 3)], "event_type string, weight int")


def with_lookup(events: DataFrame) -> DataFrame:
    joined = events.join(F.broadcast(kinds(events.sparkSession)), "event_type", "left")
    return joined.select("event_id", F.coalesce("weight", F.lit(0)).alias("weight"))


def distinct_pairs(events: DataFrame) -> DataFrame:
    return events.dropDuplicates(["event_type", "user_id"]).select("event_type", "user_id")


def answered_in_time(requests: DataFrame, responses: DataFrame, seconds: int = 20) -> DataFrame:
    """Requests with the response of the same conversation's next turn within the time allowed. Times are made of the ids."""
    at = lambda c: F.timestamp_seconds(F.lit(1_000_000_000) + F.col("conv_id") * 1000 + F.col("turn") * c)
    a = requests.where("role = 'user'").select(F.col("conv_id").alias("c"), F.col("turn").alias("asked"), at(15).alias("t")).withWatermark("t", "1 hour")
    b = responses.where("role = 'assistant'").select("conv_id", F.col("turn").alias("answered"), at(15).alias("u")).withWatermark("u", "1 hour")
    met = (F.col("c") == F.col("conv_id")) & (F.col("u") > F.col("t")) & (F.col("u") <= F.col("t") + F.expr(f"INTERVAL {seconds} SECONDS"))
    return a.join(b, met).select("conv_id", "asked", "answered")


def running_totals(events: DataFrame) -> DataFrame:
    """Events and the last of them for each worker, in state kept between batches."""
    import pandas as pd

    def update(key, frames, state):
        n, last = state.get if state.exists else (0, -1)
        for frame in frames:
            n, last = n + len(frame), max(last, int(frame["event_id"].max()))
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last": [last]})

    return events.where("user_id IS NOT NULL").select("user_id", "event_id").groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, last long", "n long, last long", "update", "NoTimeout")


def late_parts(events: DataFrame) -> tuple[DataFrame, DataFrame]:
    """What arrives in time, and every tenth event, which arrives after all others."""
    late = F.col("event_id") % 10 == 0
    return events.where(~late), events.where(late)


def closed_hours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by hour of a run log whose every tenth row arrives after the others, in the windows that a watermark of ten
    minutes has closed: rows that come behind it are dropped, as in any run of the stream."""
    folder = f"{spark.sparkContext._conf.get('spark.checkpoint.dir', None) or tempfile.mkdtemp(prefix='figmine-')}/late-{uuid.uuid4().hex}"
    source = _events(spark.read.parquet(f"{sf_dir}/events.parquet"))
    for part in late_parts(source):
        part.write.mode("append").parquet(f"{folder}/in")
        hours = spark.readStream.schema(source.schema).parquet(f"{folder}/in").withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
        hours = hours.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")
        hours.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("start string, n long").parquet(f"{folder}/out")


def closed_hours_twin(spark: SparkSession, sf_dir: str) -> DataFrame:
    timely = late_parts(_events(spark.read.parquet(f"{sf_dir}/events.parquet")))[0]
    edge = timely.agg((F.max("ts") - F.expr("INTERVAL 10 MINUTES")).alias("edge"))
    hours = timely.groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n")).crossJoin(F.broadcast(edge))
    return hours.where(F.col("window.end") <= F.col("edge")).select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


def _table(spark, sf_dir, name):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _totals_twin(s, d):
    return _table(s, d, "events").where("user_id IS NOT NULL").groupBy("user_id").agg(F.count("*").alias("n"), F.max("event_id").alias("last"))


#: name -> (stream, batch twin)
LATER = {
    "op_stream_static_join": (lambda s, d: drain(with_lookup(read_stream(s, d, "events")), "append"), lambda s, d: with_lookup(_table(s, d, "events"))),
    "op_stream_dedup": (lambda s, d: drain(distinct_pairs(read_stream(s, d, "events")), "append"), lambda s, d: distinct_pairs(_table(s, d, "events"))),
    "op_stream_interval_join": (lambda s, d: drain(answered_in_time(read_stream(s, d, "conversations"), read_stream(s, d, "conversations")), "append"), lambda s, d: answered_in_time(_table(s, d, "conversations"), _table(s, d, "conversations"))),
    "op_stream_state": (lambda s, d: drain(running_totals(read_stream(s, d, "events")), "update"), _totals_twin),
    "op_stream_late": (closed_hours, closed_hours_twin),
}

QUERIES = {
    "op_stream_tumbling": lambda s, d: drain(tumbling(read_stream(s, d, "events"))),
    "op_stream_sliding": lambda s, d: drain(sliding(read_stream(s, d, "events"))),
    "op_stream_session": all_sessions,
} | {name: stream for name, (stream, _) in LATER.items()}
ORACLES = {
    "op_stream_tumbling": "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2",
    "op_stream_sliding": "SELECT strftime(time_bucket(INTERVAL 15 MINUTE, ts) - to_minutes(15 * k), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM events, (SELECT unnest(range(0, 4)) AS k) GROUP BY 1",
    "op_stream_session": "WITH a AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS f FROM events), b AS (SELECT user_id, ts, sum(f) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM a) SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, user_id, count(*) AS n FROM b GROUP BY user_id, s",
    "op_stream_static_join": "SELECT event_id, CASE event_type WHEN 'click' THEN 1 WHEN 'view' THEN 2 WHEN 'error' THEN 3 ELSE 0 END::INTEGER AS weight FROM events",
    "op_stream_dedup": "SELECT DISTINCT event_type, user_id FROM events",
    "op_stream_interval_join": "SELECT a.conv_id, a.turn AS asked, b.turn AS answered FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.role = 'user' AND b.role = 'assistant' AND b.turn > a.turn AND (b.turn - a.turn) * 15 <= 20",
    "op_stream_state": "SELECT user_id, count(*) AS n, max(event_id) AS last FROM events WHERE user_id IS NOT NULL GROUP BY 1",
    "op_stream_late": "WITH t AS (SELECT ts FROM events WHERE event_id % 10 <> 0) SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM t GROUP BY date_trunc('hour', ts) HAVING date_trunc('hour', ts) + INTERVAL 1 HOUR <= (SELECT max(ts) FROM t) - INTERVAL 10 MINUTE",
}
