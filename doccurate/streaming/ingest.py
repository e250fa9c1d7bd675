"""Continuous corpus building over a file stream: the batch stage functions, with bounded state."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from doccurate.plans.registry import query
from doccurate.sources.tables import shared_folder


#: Time of the row that closes a stream: later than any event.
END = "9999-01-01 00:00:00"


def event_stream(spark: SparkSession, sf_dir: str, delay: str = "10 minutes", closed: bool = False) -> DataFrame:
    """Events as a stream with a UTC timestamp and a watermark.

    closed: a row of nulls at END comes with the files there are, so that the watermark passes all events once they are read. That
    holds where all files are one batch, as in ``drained``; in a later batch, events would be late.
    """
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    rows = spark.readStream.schema(schema).parquet(path if path.endswith("/") else path + "*")
    rows = rows.withColumn("ts", F.col("ts").cast("timestamp"))
    if closed:
        last = f"{shared_folder(spark)}/end-{uuid.uuid4().hex}"
        spark.range(1).select(F.lit(END).cast("timestamp").alias("ts")).write.parquet(last)
        rows = rows.unionByName(spark.readStream.schema("ts timestamp").parquet(last), allowMissingColumns=True)
    return rows.withWatermark("ts", delay)


def drained(spark: SparkSession, stream: DataFrame, mode: str = "append") -> DataFrame:
    """All that a stream gives for the files there are: appended rows as files in the shared folder, other modes in a memory table,
    which the driver holds (for results of few rows)."""
    name = f"drained_{uuid.uuid4().hex}"
    where = shared_folder(spark)
    if mode == "append":
        out = f"{where}/{name}-rows"
        stream.writeStream.outputMode(mode).format("parquet").option("path", out).option("checkpointLocation", f"{where}/{name}").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    run = stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", f"{where.rstrip('/')}/{name}").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.table(name)


def windowed(events: DataFrame, length: str = "1 hour", slide: str | None = None) -> DataFrame:
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("total"))


def flat(df: DataFrame) -> DataFrame:
    return df.select(F.unix_seconds("w.start").alias("start"), *[c for c in df.columns if c != "w"])



@query("op_stream_tumbling", "SELECT epoch(date_trunc('hour', ts))::BIGINT AS start, event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY ALL")
def tumbling(spark, sf_dir):
    return flat(drained(spark, windowed(event_stream(spark, sf_dir)), "complete"))


@query("op_stream_sliding", "SELECT (epoch(date_trunc('hour', ts))::BIGINT // 1800 + h) * 1800 AS start, event_type, count(*) AS n, round(sum(value), 2) AS total FROM (SELECT *, unnest(CASE WHEN minute(ts) < 30 THEN [0, -1] ELSE [1, 0] END) AS h FROM events) GROUP BY ALL")
def sliding(spark, sf_dir):
    return flat(drained(spark, windowed(event_stream(spark, sf_dir), "1 hour", "30 minutes"), "complete"))


@query("op_stream_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT floor(epoch(min(ts)))::BIGINT AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k")
def session(spark, sf_dir):
    """Sessions are given as the watermark closes them; the row at END closes the last ones, and its own is never given.

    Windows that touch are one session to Spark, and a gap of 30 minutes parts them here: so the gap is a microsecond less."""
    rows = event_stream(spark, sf_dir, closed=True).groupBy(F.session_window("ts", "29 minutes 59 seconds 999 milliseconds 999 microseconds").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drained(spark, flat(rows))


@query("op_stream_dedup", "SELECT DISTINCT user_id, event_type, epoch(date_trunc('hour', ts))::BIGINT AS hour FROM events")
def dedup(spark, sf_dir):
    """First arrival of each (user, type, hour), state kept within the watermark."""
    hour = F.unix_seconds(F.date_trunc("hour", "ts")).alias("hour")
    rows = event_stream(spark, sf_dir).select("user_id", "event_type", hour, "ts").dropDuplicatesWithinWatermark(["user_id", "event_type", "hour"])
    return drained(spark, rows.select("user_id", "event_type", "hour"))


@query("op_stream_join_static", "SELECT event_id, c_nationkey FROM events JOIN customer ON user_id = c_custkey")
def join_static(spark, sf_dir):
    """Users grow with events, so they are dealt out: a broadcast of them would be built in the driver."""
    users = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_nationkey").hint("merge")
    return drained(spark, event_stream(spark, sf_dir).join(users, "user_id").select("event_id", "c_nationkey"))


@query("op_stream_join_stream", "SELECT v.event_id AS view, p.event_id AS purchase FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR")
def join_stream(spark, sf_dir):
    views = event_stream(spark, sf_dir).filter("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("event_id").alias("view"), F.col("ts").alias("seen"))
    bought = event_stream(spark, sf_dir).filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), "ts")
    pairs = views.join(bought, F.expr("u = user_id AND ts >= seen AND ts <= seen + INTERVAL 1 HOUR"))
    return drained(spark, pairs.select("view", "purchase"))


@query("op_stream_late", "SELECT 0 AS late, count(*) AS rows_in FROM events")
def late(spark, sf_dir):
    """Rows behind the watermark are counted from the stream's progress, not lost silently."""
    name = f"late_{uuid.uuid4().hex}"
    where = shared_folder(spark)
    run = windowed(event_stream(spark, sf_dir)).writeStream.outputMode("append").format("memory").queryName(name).option("checkpointLocation", f"{where.rstrip('/')}/{name}").trigger(availableNow=True).start()
    run.awaitTermination()
    dropped = sum(s.numRowsDroppedByWatermark for p in run.recentProgress for s in p.stateOperators)
    return spark.createDataFrame([(dropped, sum(p.numInputRows for p in run.recentProgress))], "late long, rows_in long")


class SeenCounter(StatefulProcessor):
    """Counts a user's events; the count is given with each batch and kept for a time to live, if there is one (processing time)."""

    def __init__(self, ttl_ms: int | None = None):
        self.ttl_ms = ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.count = handle.getValueState("count", "n long", ttlDurationMs=self.ttl_ms)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        n = (self.count.get()[0] if self.count.exists() else 0) + sum(len(r) for r in rows)
        self.count.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    def close(self) -> None:
        pass


@query("op_stream_stateful", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def stateful(spark, sf_dir):
    """Events counted by user in a state of its own; the last count given for each user. Without a time to live, whose
    checks would keep a query over the files there are from ending."""
    store = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(store, None)
    spark.conf.set(store, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")  # which such state needs
    try:
        counts = event_stream(spark, sf_dir).select("user_id").groupBy("user_id").transformWithStateInPandas(SeenCounter(), "user_id long, n long", "Update", "None")
        return drained(spark, counts, "update").groupBy("user_id").agg(F.max("n").alias("n"))
    finally:
        spark.conf.set(store, before) if before else spark.conf.unset(store)


@query("w23_stream_ingest", "SELECT md5(trim(regexp_replace(lower(text), '[^\\p{L}\\p{N}]+', ' ', 'g'))) AS fp, count(*) AS copies FROM documents WHERE length(text) >= 100 GROUP BY ALL")
def ingest(spark, sf_dir):
    """Documents as they arrive: length filter, fingerprint, copies of each; equals the batch answer after the drain."""
    from doccurate.operators.dedup import fp_exact

    path = f"{sf_dir}/documents.parquet"
    arriving = spark.readStream.schema(spark.read.parquet(path).schema).parquet(path + "*")
    return drained(spark, arriving.filter(F.length("text") >= 100).groupBy(fp_exact(F.col("text")).alias("fp")).agg(F.count("*").alias("copies")), "complete")
