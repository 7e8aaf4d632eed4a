"""Streams to index segments: windows of events as lists, one immutable segment for each micro-batch, compaction."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import coders
from ..operators.postings import Lists, postings_from_column, to_gaps, to_ids
from ..sources.tables import read_index, write_index

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(path)


def on_time(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events, each id once, those later than the watermark dropped."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def windowed_counts(events: DataFrame, length: str = "1 day", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """(window, event_type, n) over tumbling windows, or sliding ones."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", delay).groupBy(w.alias("window"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("window"), "user_id").agg(F.count(F.lit(1)).alias("n"))


def late_rows(query) -> int:
    """Rows that a query dropped as later than its watermark."""
    return sum(op.numRowsDroppedByWatermark for p in query.recentProgress for op in p.stateOperators)


def running_counts(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """(event_type, n, last) after each micro-batch: a stateful operator that holds one row for each type."""
    import pandas as pd

    def step(key, frames, state):
        n, last = state.get if state.exists else (0, -1)
        for f in frames:
            n, last = n + len(f), max(last, int(f["event_id"].max()))
        state.update((n, last))
        yield pd.DataFrame({"event_type": [key[0]], "n": [n], "last": [last]})

    rows = on_time(events, delay).select("event_type", "event_id")
    return rows.groupBy("event_type").applyInPandasWithState(step, "event_type string, n long, last long", "n long, last long", "update", "NoTimeout")


def lists_of_events(events: DataFrame, value: Column | None = None) -> Lists:
    """Value -> event numbers from 1."""
    value = F.col("event_type") if value is None else value
    gaps = to_gaps(postings_from_column(events, value, F.col("event_id") + 1))
    d, i = events.agg(F.coalesce(F.max("event_id") + 1, F.lit(0)), F.count(F.lit(1))).first()
    return Lists(gaps, d, 0, i)


def write_segments(events: DataFrame, path: str, checkpoint: str, value: Column | None = None, delay: str = "1 hour"):
    """A streaming query that turns every micro-batch of on-time events into segments under ``path``. A batch that is run
    again after a failure overwrites its own segments, so each event is indexed once."""

    def batch(df: DataFrame, number: int) -> None:
        if not df.isEmpty():
            segments = coders.encode(lists_of_events(df, value), "trit_adaptive")
            write_index(segments, f"{path}/batch={number}", f"batch-{number}", mode="overwrite")

    return on_time(events, delay).writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def read_segments(spark: SparkSession, path: str) -> DataFrame:
    """(term, ord) of all batches' segments."""
    return to_ids(coders.decode(spark.read.parquet(path)))


def compact(spark: SparkSession, path: str, out: str, index_id: str = "compacted") -> None:
    """One index of all batches' segments."""
    pairs = read_segments(spark, path)
    gaps = to_gaps(pairs)
    d, i = pairs.agg(F.coalesce(F.max("ord"), F.lit(0)), F.count(F.lit(1))).first()
    write_index(coders.encode(Lists(gaps, d, 0, i), "trit_adaptive"), out, index_id, mode="overwrite")


def compacted(spark: SparkSession, out: str) -> DataFrame:
    return to_ids(coders.decode(read_index(spark, out)))
