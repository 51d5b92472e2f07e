"""Structured Streaming variants of filtering and marking."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import LongType, StructField, StructType

from dupflow.shared import shared_path

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events`` as a file stream with an event time that watermarks accept."""
    s = spark.readStream.schema(EVENTS).format("parquet").option("pathGlobFilter", "events.parquet").load(sf_dir)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append", sink=None) -> DataFrame:
    """Runs a stream over all there is and returns what it wrote.

    The sink is a folder of Parquet written batch by batch under the batch's
    number, so a batch that runs again overwrites itself.
    """
    spark = stream.sparkSession
    out = shared_path(spark, "stream-out")

    def write(batch: DataFrame, number: int) -> None:
        if sink:
            sink(batch, number)
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

    q = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", shared_path(spark, "stream-state")).trigger(availableNow=True).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    return spark.read.schema(stream.schema).parquet(out).drop("batch")


def first_seen(stream: DataFrame, key: list[str], delay: str = "7 days") -> DataFrame:
    """Keeps the first row of each key within the watermark: all that a stream can know."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(key)


class BestOfSet(StatefulProcessor):
    """Holds the best (score, id) and the count of each key until the watermark passes its last row."""

    def __init__(self, hold_ms: int):
        self.hold_ms = hold_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.state = handle.getValueState("best", StructType([StructField("score", LongType()), StructField("event_id", LongType()), StructField("n", LongType()), StructField("timer", LongType())]))

    def handleInputRows(self, key, rows, timerValues):
        held = self.state.get() if self.state.exists() else None
        best, n, timer = ((held[0], -held[1]), held[2], held[3]) if held else (None, 0, 0)
        latest = 0
        for pdf in rows:
            for score, event_id, ts in zip(pdf["score"], pdf["event_id"], pdf["ts"], strict=True):
                here = (int(score), -int(event_id))
                best = here if best is None or here > best else best
                n += 1
                latest = max(latest, int(ts.timestamp() * 1000))
        when = max(timer, latest + self.hold_ms)
        if when != timer:
            if timer:
                self.handle.deleteTimer(timer)
            self.handle.registerTimer(when)
        self.state.update((best[0], -best[1], n, when))
        yield from ()

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):
        s = self.state.get()
        self.state.clear()
        yield pd.DataFrame({"user_id": [key[0]], "event_type": [key[1]], "kept": [s[1]], "n": [s[2]]})

    def close(self) -> None:
        pass


def best_of_set(stream: DataFrame, delay: str = "1 hour", hold_ms: int = 3_600_000) -> DataFrame:
    """(user_id, event_type, kept, n) once a key has been silent for ``hold_ms`` of event time."""
    s = stream.withWatermark("ts", delay).selectExpr("user_id", "event_type", "event_id", "ts", "cast(round(value * 100) as bigint) score")
    return s.groupBy("user_id", "event_type").transformWithStateInPandas(BestOfSet(hold_ms), "user_id long, event_type string, kept long, n long", "append", "eventTime")


def new_name(prefix: str) -> str:
    return f"{prefix}_{uuid.uuid4().hex[:8]}"
