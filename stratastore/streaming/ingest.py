"""Continuous insertion and windows over events."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery

from ..operators import kvs as kv
from ..operators import store, tree
from ..params import StoreParams


def read_table(spark: SparkSession, sf_dir: str, name: str, per_trigger: int = 1) -> DataFrame:
    """A table's files as a stream, with the schema that the batch reader finds."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).option("pathGlobFilter", f"{name}*.parquet").parquet(sf_dir)


def insert_stream(contents: DataFrame, path: str, p: StoreParams, checkpoint: str) -> StreamingQuery:
    """Inserts arriving contents: pairs first, then roots, so no reader meets a root without its nodes.

    Replayed batches do no harm: pairs are idempotent by key, and roots by content.
    """

    def batch(df: DataFrame, _: int) -> None:
        spark = df.sparkSession
        kept = df.persist()
        try:
            have = kv.read(spark, f"{path}/pairs") if _stored(spark, f"{path}/pairs") else kv.empty(spark)
            roots, pairs = store.insert_contents(kept, have, p)
            kv.write(pairs, f"{path}/pairs")
            roots.write.mode("append").parquet(f"{path}/roots")
        finally:
            kept.unpersist()

    return contents.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _stored(spark: SparkSession, path: str) -> bool:
    """Whether there is such a folder; an error in asking is an error."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(at)


def new_chunks(contents: DataFrame, p: StoreParams, time: str, delay: str = "1 hour") -> DataFrame:
    """Chunks first seen within the delay: bounded state, for contents that are sent again soon after."""
    nodes = tree.build_grid(timed(contents, time), [p], [time])
    return nodes.withWatermark(time, delay).dropDuplicatesWithinWatermark(["key"])


def timed(rows: DataFrame, time: str = "ts") -> DataFrame:
    """Watermarks want a timestamp with a zone."""
    return rows.withColumn(time, F.col(time).cast("timestamp"))


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    """(window_start, event_type, events, bytes_in) in fixed windows."""
    return _summed(events, F.window("ts", size))


def sliding(events: DataFrame, size: str = "2 days", step: str = "1 day") -> DataFrame:
    return _summed(events, F.window("ts", size, step))


def _summed(events: DataFrame, window) -> DataFrame:
    size = F.octet_length("props").cast("long")
    return events.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("events"), F.sum(size).alias("bytes_in")).select(F.col("w.start").alias("window_start"), "event_type", "events", "bytes_in")


def sessions(events: DataFrame, gap: str = "2 hours") -> DataFrame:
    """(user_id, session_start, events, bytes_in) by user."""
    size = F.octet_length("props").cast("long")
    out = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("events"), F.sum(size).alias("bytes_in"))
    return out.select("user_id", F.col("w.start").alias("session_start"), "events", "bytes_in")


def split_late(events: DataFrame, watermark: str) -> tuple[DataFrame, DataFrame]:
    """(all events, for insertion; those in time, for windows): late contents are stored though no window counts them."""
    return events, timed(events).withWatermark("ts", watermark)


def running_versions(contents: DataFrame) -> DataFrame:
    """(series, version, bytes_in) after each batch: the state of a series is its number of contents and bytes."""

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        count, total = state.get if state.exists else (0, 0)
        for frame in frames:
            count, total = count + len(frame), total + int(frame["n"].sum())
        state.update((count, total))
        yield pd.DataFrame({"series": [key[0]], "version": [count], "bytes_in": [total]})

    return contents.groupBy("series").applyInPandasWithState(step, "series string, version long, bytes_in long", "version long, bytes_in long", "update", "NoTimeout")
