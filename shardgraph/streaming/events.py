"""Event reports as streams: windows, sessions, late rows, deduplication, joins, instance state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.streaming.query import StreamingQuery


def event_stream(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files as a stream; timestamps without zone become event times."""
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """Arrivals per hour and type; a window's state goes once the watermark passes it."""
    w = F.window("ts", "1 hour")
    return stream.withWatermark("ts", late).groupBy(w, "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("hour"), "event_type", "n")


def sliding(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", "1 hour", "15 minutes")).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start_ts"), "n")


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Bursts of a user: runs of events with gaps under ``gap``."""
    s = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("session_window.start").alias("start_ts"), "n")


def deduplicated(stream: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    """First of repeated notices; keys are remembered until the watermark passes them."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def with_zones(stream: DataFrame, nations: DataFrame) -> DataFrame:
    """Arrivals with their zone: a static side of checked size is broadcast, no state."""
    return stream.join(F.broadcast(nations.select("n_nationkey", "n_name")), F.expr("user_id % 25 = n_nationkey"))


def notice_then_end(stream: DataFrame, how: str = "inner", late: str = "10 minutes") -> DataFrame:
    """Termination notices with the end that follows within five minutes; both sides are kept until the bound passes."""
    a = stream.where("event_type = 'error'").select(F.col("event_id").alias("notice"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts")).withWatermark("a_ts", late)
    b = stream.where("event_type = 'signup'").select(F.col("event_id").alias("gone"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts")).withWatermark("b_ts", late)
    on = F.expr("a_user = b_user and b_ts >= a_ts and b_ts <= a_ts + interval 5 minutes")
    return a.join(b, on, "leftOuter" if how == "left" else how).select("notice", "gone")


class InstanceState(StatefulProcessor):
    """Latest state of an instance and its number of events.

    An event-time timer runs from the last event; once the watermark is ``quiet_ms`` past it without
    a new one, the instance is reported as silent. Every event takes the older timer away.
    """

    def __init__(self, quiet_ms: int = 7 * 24 * 3600 * 1000):
        self.quiet_ms = quiet_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.value = handle.getValueState("latest", "event_id long, state string, n long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        latest = self.value.get() if self.value.exists() else (-1, "", 0)
        event_id, state, n, last = latest[0], latest[1], latest[2], timerValues.getCurrentWatermarkInMs()
        for part in rows:
            n += len(part)
            last = max(last, int(part["ms"].max()))
            at = part["event_id"].idxmax()
            if part.at[at, "event_id"] > event_id:
                event_id, state = int(part.at[at, "event_id"]), str(part.at[at, "event_type"])
        self.value.update((event_id, state, n))
        for old in list(self.handle.listTimers()):
            self.handle.deleteTimer(old)
        self.handle.registerTimer(last + self.quiet_ms)
        yield pd.DataFrame({"user_id": [key[0]], "state": [state], "n": [n]})

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        event_id, state, n = self.value.get()
        yield pd.DataFrame({"user_id": [key[0]], "state": ["silent"], "n": [n]})

    def close(self) -> None:
        pass


def instance_state(stream: DataFrame, quiet_ms: int = 7 * 24 * 3600 * 1000, late: str = "1 hour") -> DataFrame:
    """Active, available and ended instances as keyed state, updated per micro-batch; silent ones by timer."""
    rows = stream.withWatermark("ts", late).select("user_id", "event_id", "event_type", "ts", F.unix_millis("ts").alias("ms"))
    return rows.groupBy("user_id").transformWithStateInPandas(
        InstanceState(quiet_ms), outputStructType="user_id bigint, state string, n bigint", outputMode="Update", timeMode="EventTime"
    )


def run_available(df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> StreamingQuery:
    """Runs what is there into an in-memory table, for tests and small reports."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return q
