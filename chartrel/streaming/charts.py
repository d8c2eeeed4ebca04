"""Streams: charts that arrive as files, windowed relations of events, and relations kept per key as points arrive."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.registry import relation
from ..operators import learned, truth
from ..sources.png import unpacked

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def chart_files(spark: SparkSession, folder: str, per_trigger: int = 100) -> DataFrame:
    """path, data of PNG files as they arrive."""
    return spark.readStream.format("binaryFile").option("pathGlobFilter", "*.png").option("maxFilesPerTrigger", per_trigger).schema("path string, modificationTime timestamp, length long, content binary").load(folder).select("path", F.col("content").alias("data"))


def extract_stream(files: DataFrame, out: str, checkpoint: str, model=None, every: str | None = None) -> StreamingQuery:
    """Runs the extraction on every batch and appends its relations; available files only, or ``every`` so often."""

    def one(batch: DataFrame, number: int) -> None:
        # A batch that is repeated after a failure overwrites its own folder.
        learned.predict(unpacked(batch), model).write.mode("overwrite").parquet(f"{out}/batch={number}")

    w = files.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint)
    return (w.trigger(processingTime=every) if every else w.trigger(availableNow=True)).start()


def events(spark: SparkSession, folder: str) -> DataFrame:
    """The events table as a stream, with a time that watermarks accept."""
    return spark.readStream.schema(EVENTS).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_sums(df: DataFrame, size: str = "1 day", slide: str | None = None, gap: str | None = None, watermark: str = "2 hours") -> DataFrame:
    """Per window (tumbling, sliding, or session by ``gap``) and event type: count and sum of cents; late rows are dropped."""
    w = F.session_window("ts", gap) if gap else F.window("ts", size, slide) if slide else F.window("ts", size)
    late = df.withWatermark("ts", watermark)
    by = [w.alias("w"), "event_type"] + (["user_id"] if gap else [])
    return late.groupBy(*by).agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *(b for b in by if isinstance(b, str)), "n", "cents")


def deduplicated(df: DataFrame, watermark: str = "2 hours") -> DataFrame:
    """Each event once, whichever way it arrives again within the watermark."""
    return df.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def batch_relations(sink: Callable[[DataFrame, int], None]) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: relations of value over time per user and type of one batch, handed on to ``sink``."""

    def one(batch: DataFrame, number: int) -> None:
        points = batch.select(F.col("user_id").alias("chart_id"), F.col("event_type").alias("series_key"), F.unix_micros("ts").alias("x"), F.round(F.col("value") * 100).cast("long").alias("y"))
        sink(truth.relations(points), number)

    return one


def _step(most: int | None, idle: str, key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    if state.hasTimedOut:
        state.remove()
        return
    x, y = (list(v) for v in state.get) if state.exists else ([], [])
    for f in frames:
        x += [int(v) for v in f["x"]]
        y += [int(v) for v in f["y"]]
    if most is not None and len(x) > most:
        order = sorted(range(len(x)), key=lambda i: (x[i], y[i]))[len(x) - most :]
        x, y = [x[i] for i in order], [y[i] for i in order]
    state.update((x, y))
    state.setTimeoutDuration(86_400_000 if idle == "1 day" else int(idle))
    yield pd.DataFrame({"user_id": [key[0]], "event_type": [key[1]], "n": [len(x)], "relation": [relation(x, y)]})


def stateful_relations(df: DataFrame, most: int | None = None, idle: str = "1 day") -> DataFrame:
    """user_id, event_type, n, relation, re-emitted whenever points arrive; state ends after ``idle`` without any.

    A rank correlation needs every point, so state holds all of a key until then and the stream ends where a batch does;
    ``most`` bounds it to the latest points where that is wanted, and the relation is then theirs alone.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        yield from _step(most, idle, key, frames, state)

    points = df.select("user_id", "event_type", F.unix_micros("ts").alias("x"), F.round(F.col("value") * 100).cast("long").alias("y"))
    return points.groupBy("user_id", "event_type").applyInPandasWithState(step, "user_id long, event_type string, n long, relation string", "x array<long>, y array<long>", "update", GroupStateTimeout.ProcessingTimeTimeout)
