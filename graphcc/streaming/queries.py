"""Streaming queries over slices of the given tables, each run until its input is read and returned as a table."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from graphcc.oracles import workload_sql
from graphcc.session import scratch_path
from graphcc.sources.workloads import edges
from graphcc.streaming.incremental import ComponentState, incremental_components

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _add(name: str, sql: str):
    def add(f):
        QUERIES[name], ORACLES[name] = f, sql
        return f

    return add


def sliced(df: DataFrame, by: str, files: int = 4, per_batch: int = 1) -> DataFrame:
    """``df`` as a file stream in order of ``by``: one file after the other, so that they are also read in that order."""
    path = scratch_path(df.sparkSession, "slices")
    cuts = df.select(F.percentile_approx(by, [i / files for i in range(1, files)], 1000).alias("c")).first().c or []
    low = None
    for high in [*sorted(set(cuts)), None]:
        part = df.where(F.col(by) >= F.lit(low)) if low is not None else df
        part = part.where(F.col(by) < F.lit(high)) if high is not None else part
        part.coalesce(1).write.mode("append").parquet(path)
        low = high
    return df.sparkSession.readStream.schema(df.schema).option("maxFilesPerTrigger", per_batch).parquet(path)


def settle(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all its input into a table and return that."""
    spark = stream.sparkSession
    out, at = scratch_path(spark, "settled"), scratch_path(spark, "checkpoint")
    if mode == "append":
        q = stream.writeStream.format("parquet").outputMode("append").option("path", out).option("checkpointLocation", at).trigger(availableNow=True).start()
    else:  # each batch's full or changed rows, the last of a key counting
        write = lambda df, i: df.withColumn("__batch", F.lit(i)).write.mode("append").parquet(out)
        q = stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", at).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(out)


def _events(spark: SparkSession, d: str) -> DataFrame:
    e = spark.read.parquet(f"{d}/events.parquet")
    return e.withColumn("ts", F.col("ts").cast("timestamp"))


@_add("stream_cc_w6", workload_sql("w6"))
def _(spark, d):
    path = scratch_path(spark, "components")
    incremental_components(sliced(edges(spark, d, "w6"), "u", 3), path, tail_rows=100_000).awaitTermination()
    return ComponentState(spark, path).components()


@_add("stream_cc_w2b_any_order", workload_sql("w2b"))
def _(spark, d):
    path = scratch_path(spark, "components")
    late = edges(spark, d, "w2b").withColumn("arrives", F.xxhash64("v", "u"))  # edges come in no useful order
    incremental_components(sliced(late, "arrives", 3), path).awaitTermination()  # all rounds, no tail in one task
    return ComponentState(spark, path).components()


@_add("stream_cc_restart_w2b", workload_sql("w2b"))
def _(spark, d):
    """A stream stopped after half of its edges and started again from its checkpoint when the others have come."""
    state, source, checkpoint = (scratch_path(spark, n) for n in ("components", "slices", "checkpoint"))
    e = edges(spark, d, "w2b").select("u", "v")
    for half in (0, 1):
        e.where(F.pmod(F.xxhash64("u", "v"), F.lit(2)) == half).coalesce(1).write.mode("append").parquet(source)
        incremental_components(spark.readStream.schema(e.schema).parquet(source), state, checkpoint).awaitTermination()
    return ComponentState(spark, state).components()


_TUMBLE = "SELECT event_type, time_bucket(INTERVAL 1 DAY, ts) AS day, count(*)::BIGINT AS n FROM events GROUP BY ALL"


@_add("stream_tumbling", _TUMBLE)
def _(spark, d):
    stream = sliced(_events(spark, d), "ts").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    last = settle(stream, "complete")
    return last.where(F.col("__batch") == last.agg(F.max("__batch")).first()[0]).select("event_type", F.col("window.start").cast("timestamp_ntz").alias("day"), "n")


@_add("stream_sliding", "SELECT time_bucket(INTERVAL 1 DAY, ts) - o * INTERVAL 1 DAY AS start, count(*)::BIGINT AS n FROM events, (SELECT unnest([0, 1]) AS o) x GROUP BY 1")
def _(spark, d):
    stream = sliced(_events(spark, d), "ts").groupBy(F.window("ts", "2 days", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    changed = settle(stream, "update")
    return changed.groupBy(F.col("window.start").cast("timestamp_ntz").alias("start")).agg(F.max_by("n", "__batch").alias("n"))


_ISLANDS = """SELECT user_id, island, count(*)::BIGINT AS n, min(ts) AS start FROM (SELECT *, sum(CASE WHEN before IS NULL OR ts >= before + INTERVAL 1 DAY THEN 1 ELSE 0 END)
    OVER (PARTITION BY user_id ORDER BY ts, event_id) AS island FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events) x) y GROUP BY user_id, island"""


@_add("stream_session_w6b", f"SELECT user_id, start, n FROM ({_ISLANDS})")
def _(spark, d):
    """Sessions closed by the watermark; a closing event far in the future lets all of them out."""
    e = _events(spark, d).select("event_id", "user_id", "ts")
    end = e.agg(F.max("ts").alias("m")).select(F.lit(-1).cast("long").alias("event_id"), F.lit(None).cast("long").alias("user_id"), (F.col("m") + F.expr("INTERVAL 90 DAYS")).alias("ts"))
    stream = sliced(e.unionByName(end), "ts").withWatermark("ts", "1 hour")
    per = stream.groupBy(F.session_window("ts", "1 day"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return settle(per).where("user_id IS NOT NULL").select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


_IN_TIME = """SELECT time_bucket(INTERVAL 1 DAY, ts) AS day, count(*)::BIGINT AS n FROM events
    WHERE event_id % 3 <> 0 OR time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY > (SELECT max(ts) FROM events WHERE event_id % 3 = 1) - INTERVAL 1 HOUR GROUP BY 1"""


@_add("stream_late_rows", _IN_TIME)
def _(spark, d):
    """A third of the events comes after the others: of these only those count whose day the watermark has not closed.

    Rows are late by the watermark that held when the batch before theirs began, here that of the first third.
    """
    e, source = _events(spark, d).select("event_id", "ts"), scratch_path(spark, "slices")
    end = e.agg((F.max("ts") + F.expr("INTERVAL 90 DAYS")).alias("ts")).select(F.lit(None).cast("long").alias("event_id"), "ts")
    for part in (*(e.where(F.col("event_id") % 3 == i) for i in (1, 2, 0)), end):  # the last one lets all windows out
        part.coalesce(1).write.mode("append").parquet(source)
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(source).withWatermark("ts", "1 hour")
    per = stream.groupBy(F.window("ts", "1 day")).agg(F.count("event_id").alias("n"))
    return settle(per).where("n > 0").select(F.col("window.start").cast("timestamp_ntz").alias("day"), "n")


@_add("stream_dedup_watermark", "SELECT DISTINCT user_id, event_type, event_id FROM events")
def _(spark, d):
    e = _events(spark, d).select("user_id", "event_type", "event_id", "ts")
    twice = sliced(e.union(e), "ts")
    return settle(twice.withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"]).select("user_id", "event_type", "event_id"))


@_add("stream_stream_join", "SELECT c.event_id AS u, p.event_id AS v FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 12 HOUR")
def _(spark, d):
    """Click to purchase edges within twelve hours; watermarks bound how long either side is remembered."""
    e = _events(spark, d)
    clicks = sliced(e.where("event_type = 'click'").select(F.col("event_id").alias("u"), F.col("user_id").alias("cu"), F.col("ts").alias("ct")), "ct").withWatermark("ct", "1 day")
    buys = sliced(e.where("event_type = 'purchase'").select(F.col("event_id").alias("v"), F.col("user_id").alias("pu"), F.col("ts").alias("pt")), "pt").withWatermark("pt", "1 day")
    near = F.expr("cu = pu AND pt > ct AND pt <= ct + INTERVAL 12 HOURS")
    return settle(clicks.join(buys, near).select("u", "v"))


@_add("stream_stateful_chains", "SELECT user_id, count(*)::BIGINT AS events, max(event_id)::BIGINT AS last_event FROM events GROUP BY user_id")
def _(spark, d):
    """Each user's chain kept as state: how long it is and where it ends."""

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, last = state.get if state.exists else (0, -1)
        for p in parts:
            n, last = n + len(p), max(last, int(p["event_id"].max()))
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "events": [n], "last_event": [last]})

    stream = sliced(_events(spark, d).select("user_id", "event_id", "ts"), "ts")
    per = stream.groupBy("user_id").applyInPandasWithState(step, "user_id long, events long, last_event long", "n long, last long", "update", GroupStateTimeout.NoTimeout)
    changed = settle(per, "update")
    return changed.groupBy("user_id").agg(F.max("events").alias("events"), F.max("last_event").alias("last_event"))
