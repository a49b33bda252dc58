"""Streaming forms: windows, deduplication, joins and stateful consensus over arriving events."""

from __future__ import annotations

import contextlib
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import IntegerType, StructField, StructType

from corpuskit.sources.tables import scratch_path

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def with_time(df: DataFrame, ts: str = "ts") -> DataFrame:
    """Watermarks need a timestamp with a time zone."""
    return df.withColumn(ts, F.col(ts).cast("timestamp"))


def read_events(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events as a file stream; the table may be one file or a folder of files."""
    return with_time(spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{sf_dir}/events*.parquet"))


def tumbling(df: DataFrame, size: str, keys: list[str], watermark: str = "1 hour", ts: str = "ts") -> DataFrame:
    g = df.withWatermark(ts, watermark).groupBy(F.window(ts, size), *keys)
    return g.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("window.start").alias("start"), *keys, "n", "total")


def sliding(df: DataFrame, size: str, slide: str, keys: list[str], watermark: str = "1 hour", ts: str = "ts") -> DataFrame:
    g = df.withWatermark(ts, watermark).groupBy(F.window(ts, size, slide), *keys)
    return g.agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), *keys, "n")


def session(df: DataFrame, gap: str, keys: list[str], watermark: str = "1 hour", ts: str = "ts") -> DataFrame:
    g = df.withWatermark(ts, watermark).groupBy(F.session_window(ts, gap), *keys)
    return g.agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("stop"), *keys, "n")


def dedup(df: DataFrame, keys: list[str], watermark: str = "1 hour", ts: str = "ts") -> DataFrame:
    """The first row of each key; a stream forgets a key once the watermark has passed it."""
    return df.withWatermark(ts, watermark).dropDuplicatesWithinWatermark(keys) if df.isStreaming else df.dropDuplicates(keys)


def enrich_static(df: DataFrame, static: DataFrame, on: str) -> DataFrame:
    return df.join(static, on, "left")


def join_streams(a: DataFrame, b: DataFrame, key: str, a_ts: str, b_ts: str, within: str, watermark: str = "1 hour") -> DataFrame:
    """Interval join; both sides have watermarks, so the state of each is bounded by the interval."""
    left, right = a.withWatermark(a_ts, watermark).alias("l"), b.withWatermark(b_ts, watermark).alias("r")
    cond = (F.col(f"l.{key}") == F.col(f"r.{key}")) & (F.col(f"r.{b_ts}") >= F.col(f"l.{a_ts}")) & (F.col(f"r.{b_ts}") <= F.col(f"l.{a_ts}") + F.expr(f"INTERVAL {within}"))
    return left.join(right, cond)


class Consensus(StatefulProcessor):
    """Per key three numbers: votes, least and greatest value. A row goes out whenever votes come in.

    With ``ttl_seconds`` the state of a key is dropped that long after its last vote.
    """

    def __init__(self, ttl_seconds: int | None = None):
        self.ttl_seconds = ttl_seconds

    def init(self, handle: StatefulProcessorHandle) -> None:
        kind = "n long, low string, high string"
        self.state = handle.getValueState("votes", kind, self.ttl_seconds * 1000) if self.ttl_seconds else handle.getValueState("votes", kind)

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        n, low, high = self.state.get() if self.state.exists() else (0, None, None)
        for batch in rows:
            values = batch["value"].dropna()
            if len(values):
                n, least, most = n + len(values), values.min(), values.max()
                low, high = (least if low is None else min(low, least)), (most if high is None else max(high, most))
        self.state.update((n, low, high))
        label = low if n >= 2 and low == high else None
        outcome = "label" if label else "conflict" if low != high else "insufficient" if n else "no_evidence"
        yield pd.DataFrame({"key": [key[0]], "votes": [n], "label": [label], "outcome": [outcome]})

    def close(self) -> None:
        pass


ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def consensus(df: DataFrame, key: str = "key", ttl_seconds: int | None = None) -> DataFrame:
    """Needs the RocksDB state store (:func:`state_store`); a TTL needs processing time."""
    return df.groupBy(key).transformWithStateInPandas(Consensus(ttl_seconds), "key long, votes long, label string, outcome string", "Update", "ProcessingTime" if ttl_seconds else "None")


@contextlib.contextmanager
def state_store(spark: SparkSession, provider: str = ROCKSDB) -> Iterator[None]:
    """The state store of the queries started inside; the session's own setting comes back afterwards."""
    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name, None)
    spark.conf.set(name, provider)
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def run_to_table(df: DataFrame, mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    """Everything that is there, run as a stream into a shared folder, then read back.

    ``append`` goes to a file sink. ``complete`` and ``update`` write each batch into a
    folder of its own; the result is the last batch, or with ``update`` the last row of
    each of ``keys``.
    """
    spark = df.sparkSession
    path, checkpoint = scratch_path(spark, "stream"), scratch_path(spark, "stream-checkpoint")
    if mode == "append":
        run_once(df, path, checkpoint)
        return spark.read.schema(df.schema).parquet(path)
    run_batches(df, checkpoint, idempotent_sink(path), mode)
    rows = spark.read.schema(StructType([*df.schema.fields, StructField("batch", IntegerType())])).parquet(path)
    if mode == "complete":
        return rows.join(F.broadcast(rows.agg(F.max("batch").alias("batch"))), "batch", "left_semi").drop("batch")
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*[c for c in df.columns if c not in keys]), "batch").alias("last"))
    return last.select(*keys, "last.*")


def run_once(df: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Everything that is there, then stop; a later call goes on from the checkpoint."""
    q = df.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()


def run_batches(df: DataFrame, checkpoint: str, sink: Callable[[DataFrame, int], None], mode: str = "update") -> None:
    q = df.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()


def idempotent_sink(path: str) -> Callable[[DataFrame, int], None]:
    """Each batch writes its own folder, so a repeated batch replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


def late_report(query) -> list[dict]:
    """Rows that each trigger dropped behind the watermark, from the query's progress."""
    return [{"batch": p["batchId"], "dropped": sum(s.get("numRowsDroppedByWatermark", 0) for s in p["stateOperators"])} for p in query.recentProgress]


def run_reporting(df: DataFrame, path: str, checkpoint: str) -> list[dict]:
    """Like :func:`run_once` in append mode; returns the late report."""
    q = df.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    return late_report(q)
