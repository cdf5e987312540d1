"""Structured Streaming edition of the monitoring chain: windows, joins, deduplication and state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import DoubleType, LongType, StructField, StructType

from discourselab.session import scratch
from discourselab.sources.files import event_stream

LATE = "1 day"
#: Slices in which the events are replayed.
BATCHES = 5


def drain(stream: DataFrame, mode: str = "append", keys: tuple[str, ...] = (), bounded: bool = True) -> DataFrame:
    """Run a stream over all there is and return what it wrote, from shared storage.

    Sources that cannot say where they end when asked at the start (not ``bounded``) are followed until idle.
    In append mode that is every row written. In update mode a batch restates some rows: each batch is kept
    by its number (so a batch that is run again replaces itself), and the last version of every key is returned.
    """
    spark = stream.sparkSession
    out, log = scratch(spark, "stream-out"), scratch(spark, "stream-log")
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", log).outputMode("append")
        if bounded:
            writer.trigger(availableNow=True).start().awaitTermination()
        else:
            query = writer.start()
            query.processAllAvailable()
            query.stop()
        return spark.read.schema(stream.schema).parquet(out)
    if mode != "update" or not keys:
        raise ValueError("streams that restate rows are drained in update mode, with the keys of a row")

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch_number={number}")

    stream.writeStream.foreachBatch(write).option("checkpointLocation", log).outputMode("update").trigger(availableNow=True).start().awaitTermination()
    written = spark.read.schema(StructType([*stream.schema, StructField("batch_number", LongType())])).option("basePath", out).parquet(out)
    last = written.groupBy(*keys).agg(F.max_by(F.struct(*stream.columns), "batch_number").alias("row"))
    return last.select(*(F.col("row")[c].alias(c) for c in stream.columns))


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", LATE).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", LATE).groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", LATE).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))


def deduplicated(events: DataFrame) -> DataFrame:
    """(user_id, event_type, day): each once. The day's window is a key, so its state goes with the watermark."""
    held = events.withWatermark("ts", LATE).select("user_id", "event_type", F.window("ts", "1 day").alias("window"))
    return held.dropDuplicates(["user_id", "event_type", "window"]).select("user_id", "event_type", F.to_date("window.start").alias("day"))


def scored(events: DataFrame, valence: DataFrame) -> DataFrame:
    """Stream-static join with a small table of valences by event type."""
    return events.join(F.broadcast(valence), "event_type").select("event_id", "event_type", (F.col("value") * F.col("valence")).alias("score"))


def posts_near_incidents(events: DataFrame, hours: int = 1) -> DataFrame:
    """Stream-stream interval join: other events of a user within some hours after an error of theirs."""
    posts = (
        events.where("event_type <> 'error'")
        .select(F.col("event_id").alias("post"), F.col("user_id").alias("pu"), F.col("ts").alias("pt"))
        .withWatermark("pt", LATE)
    )
    errors = (
        events.where("event_type = 'error'")
        .select(F.col("event_id").alias("incident"), F.col("user_id").alias("iu"), F.col("ts").alias("it"))
        .withWatermark("it", LATE)
    )
    near = (F.col("pu") == F.col("iu")) & (F.col("pt") >= F.col("it")) & (F.col("pt") <= F.col("it") + F.expr(f"interval {hours} hours"))
    return posts.join(errors, near).select("incident", "post")


class RunningProfile(StatefulProcessor):
    """Per user: how many events so far and their mean value, kept as state."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.held = handle.getValueState("held", StructType([StructField("n", LongType()), StructField("total", DoubleType())]))

    def handleInputRows(self, key: tuple, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: ANN001, N802, N803
        n, total = self.held.get() if self.held.exists() else (0, 0.0)
        for part in rows:
            n, total = n + len(part), total + float(part["value"].sum())
        self.held.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "mean_value": [total / n]})

    def close(self) -> None:
        pass


def running_profiles(events: DataFrame) -> DataFrame:
    return (
        events.select("user_id", "value")
        .groupBy("user_id")
        .transformWithStateInPandas(RunningProfile(), "user_id long, n long, mean_value double", "Update", "None")
    )


def folded_profiles(events: DataFrame) -> DataFrame:
    """(user_id, n, cents): the same per-user state by ``applyInPandasWithState``, with values summed in hundredths."""

    def fold(key: tuple, rows: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:  # noqa: ANN001
        n, cents = state.get if state.exists else (0, 0)
        for part in rows:
            n, cents = n + len(part), cents + int(part["cents"].sum())
        state.update((n, cents))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "cents": [cents]})

    whole = events.select("user_id", F.round(F.col("value") * 100).cast("long").alias("cents"))
    return whole.groupBy("user_id").applyInPandasWithState(fold, "user_id long, n long, cents long", "n long, cents long", "update", "NoTimeout")


class SpikeDetector(StatefulProcessor):
    """Per key: running mean and variance of daily counts; a day far above them is reported as a spike."""

    def __init__(self, limit: float = 3.0) -> None:
        self.limit = limit

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.held = handle.getValueState("held", StructType([StructField("n", LongType()), StructField("mean", DoubleType()), StructField("m2", DoubleType())]))

    def handleInputRows(self, key: tuple, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: ANN001, N802, N803
        n, mean, m2 = self.held.get() if self.held.exists() else (0, 0.0, 0.0)
        out = []
        for part in rows:
            for day, count in part.sort_values("day")[["day", "n"]].itertuples(index=False):
                spread = (m2 / (n - 1)) ** 0.5 if n > 1 else 0.0
                out.append((key[0], day, int(count), bool(n > 4 and spread and count > mean + self.limit * spread)))
                n += 1
                delta = count - mean
                mean += delta / n
                m2 += delta * (count - mean)
        self.held.update((n, mean, m2))
        yield pd.DataFrame(out, columns=["key", "day", "n", "spike"])

    def close(self) -> None:
        pass


def spikes(daily: DataFrame, key: str, limit: float = 3.0) -> DataFrame:
    """(key, day, n, spike) of a stream of (key, day, n) rows; needs the RocksDB state store."""
    return daily.groupBy(key).transformWithStateInPandas(SpikeDetector(limit), "key string, day date, n long, spike boolean", "Update", "None")


def daily_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(day, event_type, n) from the event stream, drained; days behind the watermark leave the state."""
    counts = tumbling(event_stream(spark, sf_dir, BATCHES)).select(F.to_date("window.start").alias("day"), "event_type", "n")
    return drain(counts, "update", ("day", "event_type"))
