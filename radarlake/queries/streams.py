"""Streams over the event files, each run until its input is worked off; SQL gives the batch answer.

The events' file is written anew to the shared folder where a query needs several batches
or planted late rows; what is late, repeated or cut off is stated at each query.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from radarlake.io import shared
from radarlake.registry import query
from radarlake.standins import table
from radarlake.streaming import ingest

C = F.col


def _stream(spark: SparkSession, sf: str) -> DataFrame:
    """The given events as one batch of a stream."""
    return _of(spark, table(spark, sf, "events"))


def _of(spark: SparkSession, *batches: DataFrame) -> DataFrame:
    """A stream whose batches are the given tables, one after another."""
    where = shared.path(spark, "stream")
    for df in batches:
        # a file a batch, in the order in which they are written
        df.coalesce(1).write.mode("append").parquet(where)
    return ingest.source(spark, where)


def _worked_off(df: DataFrame, mode: str = "append") -> DataFrame:
    spark = df.sparkSession
    out, marks = shared.path(spark, "out"), shared.path(spark, "marks")
    spark.createDataFrame([], df.schema).write.parquet(out)
    ingest.run(df, out, marks, mode)
    return spark.read.schema(df.schema).parquet(out)


_HOURS = "SELECT strftime(h, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM (SELECT *, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS h FROM events) GROUP BY ALL"


@query(_HOURS)
def op_win_sliding(spark, sf):
    """Windows of two hours every hour, as tiles of a size and a stride lie over an image."""
    w = table(spark, sf, "events").groupBy(F.window("ts", "2 hours", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS opens FROM events), s AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def op_win_session(spark, sf):
    w = table(spark, sf, "events").groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("n"))
    return w.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("SELECT event_id, user_id FROM events")
def op_stream_dedup(spark, sf):
    """Every event comes twice, the second time in a later batch; one of each stays."""
    events = table(spark, sf, "events")
    once = ingest.deduplicated(_of(spark, events, events), "event_id", "40 days")
    return _worked_off(once.select("event_id", "user_id"))


_LATE = "event_id % 97 = 0"


@query("""WITH on_time AS (SELECT * FROM events WHERE event_id % 97 <> 0), mark AS (SELECT max(ts) - INTERVAL 1 DAY AS m FROM on_time),
seen AS (SELECT * FROM on_time UNION ALL SELECT e.* FROM events e, mark WHERE event_id % 97 = 0 AND date_trunc('hour', ts) + INTERVAL 1 HOUR > m)
SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM seen GROUP BY 1""")
def op_late(spark, sf):
    """One event in 97 comes in a third batch; those behind the watermark of a day are dropped, and a last event far ahead closes all windows.

    A batch drops what was late when the batch before it began, so the first event comes alone in the second batch.
    """
    events = table(spark, sf, "events")
    ahead = events.agg(F.max("ts").alias("ts")).select(F.lit(-1).cast("long").alias("event_id"), (C("ts") + F.expr("INTERVAL 90 DAYS")).alias("ts"), F.lit(0).cast("long").alias("user_id"), F.lit("").alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
    first = events.agg(F.min("event_id").alias("e")).first()["e"]
    on_time = events.filter(f"NOT ({_LATE})")
    stream = _of(spark, on_time.filter(C("event_id") != first), on_time.filter(C("event_id") == first), events.filter(_LATE), ahead.select(events.columns))
    w = stream.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    return _worked_off(w.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n"))


@query("SELECT event_id, n_name FROM events JOIN nation ON n_nationkey = user_id % 25")
def op_stream_static(spark, sf):
    nation = F.broadcast(table(spark, sf, "nation").select("n_nationkey", "n_name"))
    return _worked_off(_stream(spark, sf).join(nation, C("user_id") % 25 == C("n_nationkey")).select("event_id", "n_name"))


@query("SELECT a.event_id AS error, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'error' AND b.event_type = 'purchase'")
def op_stream_interval(spark, sf):
    """Two streams that meet by user within an hour; the watermarks bound what either side keeps."""
    a = _stream(spark, sf).filter("event_type = 'error'").select(C("event_id").alias("error"), "user_id", C("ts").alias("at")).withWatermark("at", "1 hour")
    b = _stream(spark, sf).filter("event_type = 'purchase'").select(C("event_id").alias("purchase"), C("user_id").alias("buyer"), C("ts").alias("then")).withWatermark("then", "1 hour")
    met = a.join(b, (C("user_id") == C("buyer")) & (C("then") >= C("at")) & (C("then") <= C("at") + F.expr("INTERVAL 1 HOUR")))
    return _worked_off(met.select("error", "purchase"))


def _count(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    n, event, value = state.get if state.exists else (0, -1, 0.0)
    for part in parts:
        n += len(part)
        last = part.loc[part["event_id"].idxmax()]
        if last["event_id"] > event:
            event, value = int(last["event_id"]), float(last["value"])
    state.update((n, event, value))
    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last_event": [event], "last_value": [value]})


@query("SELECT user_id, count(*) AS n, max(event_id) AS last_event, arg_max(value, event_id) AS last_value FROM events GROUP BY 1")
def op_stream_state(spark, sf):
    """A counter and the last value of each user, kept over two batches; the row with the highest count is the last one told."""
    events = table(spark, sf, "events")
    stream = _of(spark, events.filter("event_id % 2 = 1"), events.filter("event_id % 2 = 0"))
    told = stream.select("user_id", "event_id", "value").groupBy("user_id").applyInPandasWithState(_count, "user_id long, n long, last_event long, last_value double", "n long, last_event long, last_value double", "update", GroupStateTimeout.NoTimeout)
    out, marks = shared.path(spark, "out"), shared.path(spark, "marks")
    ran = told.writeStream.outputMode("update").option("checkpointLocation", marks).trigger(availableNow=True).foreachBatch(lambda df, k: df.write.mode("overwrite").parquet(f"{out}/batch={k}")).start()
    ran.awaitTermination()
    every = spark.read.schema(told.schema).parquet(f"{out}/batch=*")
    return every.groupBy("user_id").agg(F.max("n").alias("n"), F.max("last_event").alias("last_event"), F.max_by("last_value", "n").alias("last_value"))


@query("SELECT event_id, event_type FROM events")
def op_stream_sink(spark, sf):
    """A sink that replaces a batch by its number, so that a repeated batch changes nothing; it is started a second time from its checkpoint."""
    stream = _stream(spark, sf).select("event_id", "event_type")
    out, marks = shared.path(spark, "out"), shared.path(spark, "marks")

    def put(df: DataFrame, k: int) -> None:
        for _ in range(2):
            df.write.mode("overwrite").parquet(f"{out}/batch={k}")

    for _ in range(2):
        stream.writeStream.option("checkpointLocation", marks).trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{out}/batch=*")
