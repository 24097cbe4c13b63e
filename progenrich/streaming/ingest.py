"""Streams: seed scores at ingestion, windows of expected counts, state across batches, epochs by trigger."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.enrich import EnrichmentRun
from ..operators.scorers import LADDER, simulated
from ..operators.state import Query, seed_state
from ..sources.sinks import work_path


def event_stream(spark: SparkSession, sf_dir: str, batches: int = 4) -> DataFrame:
    """The events table as a file stream, dealt into files that arrive one a trigger.

    Times are cast to ``timestamp``, as watermarks need that type.
    """
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    path = work_path(spark, "events-in")
    lo, hi = events.selectExpr("unix_micros(CAST(min(ts) AS timestamp))", "unix_micros(CAST(max(ts) AS timestamp))").first()
    at = F.least(F.lit(batches - 1), F.floor((F.expr("unix_micros(CAST(ts AS timestamp))") - F.lit(lo)) * batches / F.lit(max(1, hi - lo))))
    for i in range(batches):  # one after the other: files are read in the order in which they were written
        events.where(at == i).coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def finished(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all there is and return its rows, which executors store in the shared folder batch by batch.

    In complete mode each batch holds the whole table, so the last one counts; else all do. No row passes the driver.
    """
    spark, path, stored = stream.sparkSession, work_path(stream.sparkSession, "stream-out"), {}

    def store(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        stored[number] = f"{path}/{number}"

    for_each_batch(stream, store, mode)
    if not stored:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*([stored[max(stored)]] if mode == "complete" else stored.values()))


def for_each_batch(stream: DataFrame, fn: Callable[[DataFrame, int], None], mode: str = "append") -> None:
    q = stream.writeStream.foreachBatch(fn).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", work_path(stream.sparkSession, "stream")).start()
    q.awaitTermination()


def as_objects(events: DataFrame) -> DataFrame:
    return events.select(F.col("event_id").cast("long").alias("object_id"), F.col("event_type").alias("t_kind"), "ts", "user_id")


def stream_seed_state(stream: DataFrame, query: Query) -> DataFrame:
    """Seed states of a stream, written batch by batch (each batch replaces itself if it is run again)."""
    path = work_path(stream.sparkSession, "state")

    def store(batch: DataFrame, epoch: int) -> None:
        seed_state(as_objects(batch), query).withColumn("batch", F.lit(epoch)).write.mode("overwrite").parquet(f"{path}/batch_id={epoch}")

    for_each_batch(stream, store)
    return stream.sparkSession.read.parquet(path).drop("batch", "batch_id")


def seed_probability(tag: str = "purchase", tag_no: int = 2):
    """The seed scorer's output for a tag of the events, as a Column of the stream."""
    return simulated(LADDER[0][1], 0)(F.col("event_id"), F.col("event_type") == tag, tag_no)


def expected_counts(stream: DataFrame, window, late: str = "1 hour") -> DataFrame:
    """Expected number of purchases by window of event time, with a watermark for late rows."""
    scored = stream.withColumn("p", seed_probability())
    return scored.withWatermark("ts", late).groupBy(window.alias("w")).agg(F.sum("p").alias("expected"), F.count("*").alias("n"))


def keyed_masks(stream: DataFrame) -> DataFrame:
    """Done masks of users across batches: each event sets the bit of its type (state with a pandas function)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    kinds = ("view", "signup", "purchase", "error", "click")

    def fold(key, frames, state):
        mask = state.get[0] if state.exists else 0
        for f in frames:
            for k in f["event_type"]:
                mask |= 1 << kinds.index(k)
        state.update((mask,))
        yield pd.DataFrame({"user_id": [key[0]], "mask": [mask]})

    return stream.select("user_id", "event_type").groupBy("user_id").applyInPandasWithState(fold, "user_id long, mask int", "mask int", "update", GroupStateTimeout.NoTimeout)


def stream_epochs(stream: DataFrame, query: Query, table, budget: float) -> DataFrame:
    """One epoch for each batch over its objects: the answer's size and the cost spent, by batch."""
    rows: list[tuple] = []

    def step(batch: DataFrame, number: int) -> None:
        objects = as_objects(batch)
        if objects.isEmpty():
            return
        *_, last = EnrichmentRun(objects, query, budget, table).epochs(1)
        rows.append((number, last.answer.size, float(last.spent), float(last.answer.expected_f)))

    for_each_batch(stream, step)
    return stream.sparkSession.createDataFrame(rows, "batch int, answer_size long, spent double, expected_f double")
