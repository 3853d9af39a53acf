"""Streaming flows: incremental archive, volumes, rates, sessions, change detection, late data."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def file_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 100) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def incremental_archive(items: DataFrame, ts: str = "captured_at", delay: str = "30 days") -> DataFrame:
    """First sightings of (url, sha256) within the watermark."""
    return items.withWatermark(ts, delay).dropDuplicatesWithinWatermark(["url", "sha256"])


def crawl_volume(items: DataFrame, ts: str = "captured_at", size: str = "1 day", delay: str = "1 day") -> DataFrame:
    return items.withWatermark(ts, delay).groupBy(F.window(ts, size).alias("w"), "source").agg(F.count(F.lit(1)).alias("n"))


def sliding_rate(events: DataFrame, limit: int, size: str = "10 minutes", slide: str = "1 minute", delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.window("ts", size, slide).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > limit)


def session_stream(events: DataFrame, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))


def with_dictionary(lines: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Stream-static join: lines (lang, text) whose text is a key."""
    return lines.join(dictionary.select("lang", F.col("surface").alias("text"), "key_id"), ["lang", "text"])


def changed_content(items: DataFrame) -> DataFrame:
    """(url, sha256, kind): new or changed content by url, with the last hash kept as state."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        out = []
        for pdf in batches:
            for row in pdf.sort_values("captured_at").itertuples():
                if row.sha256 != last:
                    out.append((key[0], row.sha256, "new" if last is None else "changed"))
                    last = row.sha256
        if last is not None:
            state.update((last,))
        yield pd.DataFrame(out, columns=["url", "sha256", "kind"])

    return items.select("url", "sha256", "captured_at").groupBy("url").applyInPandasWithState(step, "url string, sha256 string, kind string", "last string", "append", GroupStateTimeout.NoTimeout)


def run_available(stream: DataFrame, checkpoint: str, write: Callable[[DataFrame, int], None], mode: str = "append") -> None:
    """One periodic run: everything that is there now, then stop."""
    stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(write).start().awaitTermination()


def late_counter(ts: str, bound: str) -> Callable[[DataFrame], DataFrame]:
    """Counts of a batch's events older than a bound (a timestamp text), for a side table of late data."""
    return lambda batch: batch.agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col(ts) < F.lit(bound).cast("timestamp_ntz"), 1)).alias("late"))
