"""Structured Streaming over events: id sets per window, deduplication, interval joins, and lists that grow in state.

Sources are folders of Parquet files; `run` drives a query to the end of what is there (available-now) into a table that can be read
as a DataFrame.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..operators import arrow

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str, per_trigger: int = 1) -> DataFrame:
    """The events table as a stream, ts as a timestamp with time zone (watermarks need one)."""
    r = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).option("pathGlobFilter", "*.parquet")
    return r.parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def run(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream to its present end and returns what it wrote; append goes to files, update and complete to memory."""
    spark = stream.sparkSession
    name = "s" + uuid.uuid4().hex
    base = arrow.fresh(spark, "stream")
    w = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{base}/checkpoint")
    if mode == "append":
        w.format("parquet").start(f"{base}/out").awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")
    w.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)


def run_with_state(stream: DataFrame, state: str) -> tuple[DataFrame, DataFrame]:
    """What `run` gives in append mode, and the named state variable as it stands at that end (key, value)."""
    spark = stream.sparkSession
    base = arrow.fresh(spark, "stream")
    w = stream.writeStream.outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{base}/checkpoint")
    w.format("parquet").start(f"{base}/out").awaitTermination()
    held = spark.read.format("statestore").option("stateVarName", state).load(f"{base}/checkpoint")
    return spark.read.schema(stream.schema).parquet(f"{base}/out"), held.select("key", "value")


def window_sets(stream: DataFrame, window: F.Column, by: str = "user_id", late: str = "0 seconds") -> DataFrame:
    """start, by, n and the ids (ascending) of each window that the watermark has closed."""
    sets = stream.withWatermark("ts", late).groupBy(window.alias("w"), by).agg(F.array_sort(F.collect_set("event_id")).alias("ids"))
    return sets.select(F.col("w.start").alias("start"), by, F.size("ids").cast("long").alias("n"), "ids")


def tumbling(stream: DataFrame, size: str = "1 day", late: str = "0 seconds") -> DataFrame:
    return window_sets(stream, F.window("ts", size), late=late)


def sliding(stream: DataFrame, size: str = "1 day", step: str = "6 hours", late: str = "0 seconds") -> DataFrame:
    return window_sets(stream, F.window("ts", size, step), late=late)


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "0 seconds") -> DataFrame:
    return window_sets(stream, F.session_window("ts", gap), late=late)


def counts(stream: DataFrame) -> DataFrame:
    """event_type and its number so far; complete or update mode."""
    return stream.groupBy("event_type").agg(F.count(F.lit(1)).cast("long").alias("n"))


def distinct_events(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def click_then(stream: DataFrame, other: DataFrame, kind: str = "purchase", within: str = "1 hour") -> DataFrame:
    """Pairs (click, event of a kind) of one user, the second at most `within` after the first; two streams."""
    a = stream.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", "1 hour")
    b = other.filter(F.col("event_type") == kind).select(F.col("event_id").alias("then_id"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", "1 hour")
    return a.join(b, F.expr(f"u1 = u2 AND t2 > t1 AND t2 <= t1 + INTERVAL {within}")).select("click_id", "then_id", F.col("u1").alias("user_id"))


def probe_static(stream: DataFrame, static: DataFrame, on: str) -> DataFrame:
    """Stream rows joined to a static table, such as the lists of an index."""
    return stream.join(static, on)


def upsert(stream: DataFrame, path: str, key: str = "user_id") -> None:
    """Writes each micro-batch's rows under its batch number, so that a batch run twice leaves one copy; readers take all batches."""

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number:012d}")

    w = stream.writeStream.foreachBatch(put).trigger(availableNow=True).option("checkpointLocation", f"{path}/_checkpoint")
    w.start().awaitTermination()


def split_late(stream: DataFrame, seen_until: F.Column, late: str = "1 hour") -> tuple[DataFrame, DataFrame]:
    """Rows in time, and late ones for a dead-letter table: those older than `late` before the time seen."""
    old = F.col("ts") < seen_until - F.expr(f"INTERVAL {late}")
    return stream.filter(~old), stream.filter(old)


class GrowingList(StatefulProcessor):
    """Per user, an open tail of ids; every `seal` ids it is sealed as an Elias-Fano segment, and the segment is told."""

    seal = 64

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.tail = handle.getValueState("tail", "ids array<long>, sealed int")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        from ..functions.listcodecs import EliasFano

        ids, sealed = (list(self.tail.get()[0]), self.tail.get()[1]) if self.tail.exists() else ([], 0)
        for df in rows:
            ids += df["event_id"].tolist()
        out = []
        while len(ids) >= self.seal:
            some, ids = np.unique(np.array(ids[: self.seal])), ids[self.seal :]
            payload, bits = EliasFano(int(some[-1]) + 1).encode(some, np.array([0, len(some)]))
            out.append({"user_id": key[0], "seg": sealed, "n": len(some), "universe": int(some[-1]) + 1, "payload": payload[0], "bits": int(bits[0])})
            sealed += 1
        self.tail.update((ids, sealed))
        yield pd.DataFrame(out, columns=["user_id", "seg", "n", "universe", "payload", "bits"])

    def close(self) -> None:
        pass


def growing_lists(stream: DataFrame) -> DataFrame:
    """Sealed segments of per-user id lists; needs the RocksDB state store."""
    arrow.importable(stream.sparkSession)
    return stream.groupBy("user_id").transformWithStateInPandas(GrowingList(), "user_id long, seg int, n int, universe long, payload binary, bits long", "append", "None")
