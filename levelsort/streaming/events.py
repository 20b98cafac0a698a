"""Streaming forms of windowed counts, de-duplication and sorted runs. Every function takes a batch or a stream."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from levelsort.functions.text import fingerprint

LATE = "10 minutes"


def _marked(events: DataFrame, late: str) -> DataFrame:
    return events.withWatermark("ts", late) if events.isStreaming else events


def tumbling(events: DataFrame, width: str = "1 day", late: str = LATE) -> DataFrame:
    return _marked(events, late).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 days", slide: str = "1 day", late: str = LATE) -> DataFrame:
    return _marked(events, late).groupBy(F.window("ts", width, slide).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "12 hours", late: str = LATE) -> DataFrame:
    return _marked(events, late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame, late: str = LATE) -> DataFrame:
    """First event of each property string; a stream keeps keys as long as the watermark asks."""
    if events.isStreaming:
        return _marked(events, late).dropDuplicatesWithinWatermark(["props"]).select("props", F.col("event_id").alias("first"))
    return events.groupBy("props").agg(F.min("event_id").alias("first"))


def sorted_runs(stream: DataFrame, path: str, checkpoint: str, key: str = "s") -> Callable:
    """Each micro-batch becomes one sorted run (folder ``run=<epoch>``); repeating an epoch rewrites the same run."""

    def write(batch: DataFrame, epoch: int) -> None:
        batch.sort(key).write.mode("overwrite").parquet(f"{path}/run={epoch}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def merged_runs(spark: SparkSession, path: str) -> DataFrame:
    """All runs as one sorted set: rank and the runs' columns. Runs are ranges of one order, so they meet in range partitions."""
    from levelsort.operators.baselines import spark_sort

    return spark_sort(spark.read.parquet(path))


def within_stream(left: DataFrame, right: DataFrame, by: str, seconds: int, late: str = LATE) -> DataFrame:
    """Pairs of equal ``by`` with left.ts <= right.ts <= left.ts + seconds, of two streams or two batches.

    The columns of ``right`` other than ``by`` and ts must not be named like those of ``left``. As both sides have a
    watermark and the times bound each other, rows that can find no partner any more leave the state.
    """
    a = _marked(left, late).withColumnsRenamed({by: "_by", "ts": "_from"})
    b = _marked(right, late).withColumnsRenamed({"ts": "_to"})
    met = a.join(b, F.expr(f"_by = {by} AND _to >= _from AND _to <= _from + INTERVAL {seconds} SECONDS"))
    return met.select(*[c for c in left.columns if c not in (by, "ts")], *[c for c in right.columns if c not in (by, "ts")])


def _counted(hours: float):
    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, last = state.get if state.exists else (0, 0)
        for f in frames:
            n, last = n + len(f), max(last, int(f["ms"].max()))
        state.update((n, last))
        state.setTimeoutTimestamp(max(last + round(hours * 3_600_000), state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"fp": [key[0]], "n": [n]})

    return step


def fingerprint_counts(stream: DataFrame, width: int = 16, keep_hours: float = 24, late: str = LATE) -> DataFrame:
    """fp, n: running number of strings per prefix fingerprint, a row whenever it grows (columns s and ts are read).

    A fingerprint not met for ``keep_hours`` of event time is forgotten. On a batch these are the final counts.
    """
    fps = stream.select("ts", F.unix_millis("ts").alias("ms"), fingerprint(F.col("s"), F.lit(width)).alias("fp"))
    if not stream.isStreaming:
        return fps.groupBy("fp").agg(F.count("*").alias("n"))
    return _marked(fps, late).groupBy("fp").applyInPandasWithState(_counted(keep_hours), "fp bigint, n bigint", "n bigint, last bigint", "update", GroupStateTimeout.EventTimeTimeout)
