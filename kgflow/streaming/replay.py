"""Streams as the driver of batches, event-time windows, late rows and a stateful status tracker."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from kgflow.session import shared_dir


@contextmanager
def column_family_state(spark: SparkSession):
    """Queries started inside keep their state in the store that stateful processors need (a run-time setting)."""
    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name)
    spark.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def folder(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"


def with_utc(df: DataFrame, ts: str = "ts") -> DataFrame:
    """Watermarks need a zoned time: ts as TIMESTAMP, in the session zone."""
    return df.withColumn(ts, F.col(ts).cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append", run: Callable[[DataFrame, int], None] | None = None) -> DataFrame | None:
    """Run the stream over all that is there, and return what reached the sink (or pass each batch to run)."""
    spark = stream.sparkSession
    base = folder(spark, "stream")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True)
    if run is not None:
        writer.foreachBatch(run).start().awaitTermination()
        return None
    if mode == "append":
        writer.format("parquet").option("path", f"{base}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")

    def replace(df: DataFrame, k: int) -> None:
        df.write.parquet(f"{base}/out/{k:09d}", mode="overwrite")

    last = writer.foreachBatch(replace).start()
    last.awaitTermination()
    k = last.lastProgress["batchId"] if last.lastProgress else 0
    for j in range(int(k), -1, -1):  # the newest batch that wrote
        try:
            return spark.read.schema(stream.schema).parquet(f"{base}/out/{j:09d}")
        except Exception:
            if j == 0:
                raise
    return None


def tumbling(events: DataFrame, length: str = "10 days", start: str = "3 days") -> DataFrame:
    return counted(events, F.window("ts", length, startTime=start))


def sliding(events: DataFrame, length: str = "10 days", slide: str = "5 days", start: str = "3 days") -> DataFrame:
    return counted(events, F.window("ts", length, slide, start))


def counted(events: DataFrame, window) -> DataFrame:
    return events.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


def once(events: DataFrame, key: str, ts: str = "ts", delay: str = "2 days") -> DataFrame:
    return events.withWatermark(ts, delay).dropDuplicatesWithinWatermark([key])


def split_late(stream: DataFrame, ts: str, delay: str) -> tuple[DataFrame, DataFrame]:
    """(late, timely) rows of a stream in two sinks. A batch is judged by the newest time of the batches before it
    less the delay; the batch before keeps that time beside the sinks, so a restart judges alike, and a batch that
    is run again replaces its own files."""
    spark, base = stream.sparkSession, folder(stream.sparkSession, "split")
    shape = f"{base}/late", f"{base}/timely", f"{base}/newest"

    def put(df: DataFrame, k: int) -> None:
        before = spark.read.schema(newest_schema).parquet(f"{shape[2]}/{k - 1:09d}").first()[0] if k else None
        late = F.coalesce(F.col(ts) < F.lit(before).cast(stream.schema[ts].dataType) - F.expr(f"interval {delay}"), F.lit(False))
        df.where(late).write.parquet(f"{shape[0]}/{k:09d}", mode="overwrite")
        df.where(~late).write.parquet(f"{shape[1]}/{k:09d}", mode="overwrite")
        newest = F.greatest(F.max(ts), F.lit(before).cast(stream.schema[ts].dataType))
        df.agg(newest.alias("newest")).write.parquet(f"{shape[2]}/{k:09d}", mode="overwrite")

    newest_schema = stream.agg(F.max(ts).alias("newest")).schema
    drained(stream, run=put)
    return tuple(spark.read.schema(stream.schema).option("recursiveFileLookup", True).parquet(p) for p in shape[:2])


class StatusProcessor(StatefulProcessor):
    """Keeps each user's newest status and emits every change; an older event never overrides a newer state."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getValueState("last", "status string, at long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        got = pd.concat(list(rows)).sort_values(["at", "event_id"])
        status, at = self.last.get() if self.last.exists() else (None, -(2**62))
        out = []
        for s, t in zip(got["status"], got["at"], strict=True):
            if t >= at:
                if s != status:
                    out.append((int(key[0]), s, int(t)))
                status, at = s, int(t)
        self.last.update((status, at))
        yield pd.DataFrame(out, columns=["user_id", "status", "at"])

    def close(self) -> None:
        pass


def tracked(events: DataFrame) -> DataFrame:
    """(user_id, status, at) changes of status over a stream of events."""
    rows = events.where(F.col("event_type").isin("signup", "error")).select("user_id", "event_id", F.when(F.col("event_type") == "signup", "active").otherwise("deprecated").alias("status"), F.unix_micros("ts").alias("at"))
    return rows.groupBy("user_id").transformWithStateInPandas(StatusProcessor(), "user_id long, status string, at long", "Append", "None")


def evidence_join(statements: DataFrame, evidence: DataFrame, slack: str = "1 hour") -> DataFrame:
    """Stream-stream join of statements (stmt_id, ts) with evidence (stmt_id, ev_ts) no later than slack."""
    a, b = statements.withWatermark("ts", "2 days"), evidence.withColumnRenamed("stmt_id", "ev_id").withWatermark("ev_ts", "2 days")
    near = (F.col("stmt_id") == F.col("ev_id")) & (F.col("ev_ts") >= F.col("ts")) & (F.col("ev_ts") <= F.col("ts") + F.expr(f"interval {slack}"))
    return a.join(b, near, "leftOuter")
