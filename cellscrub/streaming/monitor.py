"""Event streams: windowed error rates, sessions, deduplication within the watermark, and a stateful drift monitor.

Every windowed plan also runs as a batch, which the tests compare with the stream's result.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from cellscrub.operators.inject import draw

WATERMARK = "10 minutes"


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """The events of all Parquet files in a folder, as a stream with the batch table's schema."""
    schema = spark.read.parquet(folder).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def dirtied(events: DataFrame, seed: int = 7, permille: int = 100) -> DataFrame:
    """events with `bad`: upper-case types and broken props by the usual hash draw; every 97th event 3 hours late."""
    d = draw(seed, "event", F.col("event_id").cast("string")) % 1000
    out = events.withColumn("bad", d < permille)
    out = out.withColumn("event_type", F.when(F.col("bad") & (d % 2 == 0), F.upper("event_type")).otherwise(F.col("event_type")))
    out = out.withColumn("props", F.when(F.col("bad") & (d % 2 == 1), F.lit("{")).otherwise(F.col("props")))
    return out.withColumn("ts", F.when(F.col("event_id") % 97 == 0, F.col("ts") - F.expr("INTERVAL 3 HOURS")).otherwise(F.col("ts")))


def is_error() -> Column:
    return (F.col("event_type") != F.lower("event_type")) | F.get_json_object("props", "$.k").isNull()


def _marked(events: DataFrame) -> DataFrame:
    """A stream with its watermark, which needs times with a zone; a batch as it is."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", WATERMARK) if events.isStreaming else events


def error_rate(events: DataFrame, every: str = "1 hour", slide: str | None = None) -> DataFrame:
    """window start, n, n_errors, over tumbling or sliding windows."""
    source = _marked(events)
    w = F.window("ts", every, slide) if slide else F.window("ts", every)
    return source.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.count_if(is_error()).alias("n_errors")).select(F.col("w.start").alias("window_start"), "n", "n_errors")


def sessions(events: DataFrame, gap: str = "4 hours") -> DataFrame:
    """user_id, session start, n."""
    source = _marked(events)
    return source.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("session_start"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    if events.isStreaming:
        return _marked(events).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def enriched(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join with the reference of users."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id")


DRIFT_OUT = "event_type string, n long, rate double, drift boolean"
DRIFT_STATE = "n long, bad long, mean double"


def drift(events: DataFrame, limit: float = 0.1) -> DataFrame:
    """Per event type the running error rate, flagged where a batch's rate leaves it by more than `limit`."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, bad, mean = state.get if state.exists else (0, 0, 0.0)
        new = new_bad = 0
        for f in frames:
            new += len(f)
            new_bad += int(f["error"].sum())
        rate = new_bad / new if new else 0.0
        flagged = bool(n and abs(rate - mean) > limit)
        n, bad = n + new, bad + new_bad
        state.update((n, bad, bad / n if n else 0.0))
        yield pd.DataFrame({"event_type": [key[0]], "n": [n], "rate": [bad / n if n else 0.0], "drift": [flagged]})

    marked = events.select(F.lower("event_type").alias("event_type"), is_error().cast("int").alias("error"))
    return marked.groupBy("event_type").applyInPandasWithState(step, DRIFT_OUT, DRIFT_STATE, "update", GroupStateTimeout.NoTimeout)


def run_to_memory(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """The stream over all files present, as a table in memory; for tests and small results."""
    writer = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    query = writer.start()
    query.awaitTermination()
    return stream.sparkSession.table(name)
