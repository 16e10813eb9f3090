"""Structured Streaming: arrival counts, domain entropy by window, digest dedup, blacklist, and the incremental soft vote."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import StructType

from ..functions import constants as C
from ..plans.staging import shared_dir


def read_stream(spark: SparkSession, path: str, schema: StructType, ts: str | None = None, lateness: str = "1 hour", files: int = 1) -> DataFrame:
    """Files of a folder as a stream; ``ts`` is made a timestamp and given a watermark."""
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    if where.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(where).isFile():  # a stream reads folders
        reader, path = reader.option("pathGlobFilter", where.getName()), where.getParent().toString()
    df = reader.parquet(path)
    return df.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, lateness) if ts else df


def window_counts(df: DataFrame, ts: str = "ts", key: str = "event_type", length: str = "1 day", slide: str | None = None) -> DataFrame:
    """(start, key, n); the same code serves batch and stream."""
    w = F.window(ts, length, slide) if slide else F.window(ts, length)
    return df.groupBy(w.alias("w"), key).agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), key, "n", "total")


def sessions(df: DataFrame, ts: str = "ts", user: str = "user_id", gap: str = "30 minutes") -> DataFrame:
    return df.groupBy(F.session_window(ts, gap).alias("s"), user).agg(F.count("*").alias("n")).select(user, F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def window_entropy(counts: DataFrame, key: str = "event_type") -> DataFrame:
    """(start, h_bits) from window counts: a batch aggregate over the sink of ``window_counts``."""
    total = counts.groupBy("start").agg(F.sum("n").alias("all"))
    p = F.col("n") / F.col("all")
    return counts.join(total, "start").groupBy("start").agg(F.sum(-p * F.log2(p)).alias("h_bits"))


def dedup_stream(df: DataFrame, text: str = "text", within: bool = True) -> DataFrame:
    """First row of each text digest; with a watermark the state is bounded by it."""
    marked = df.withColumn("digest", F.sha2(F.coalesce(F.col(text), F.lit("")), 256))
    return marked.dropDuplicatesWithinWatermark(["digest"]) if within else marked.dropDuplicates(["digest"])


def block_stream(df: DataFrame, hosts: DataFrame, host: str = "host") -> DataFrame:
    """Stream-static anti join against a host list."""
    return df.join(hosts.select(F.col("host").alias("__h")).distinct(), F.col(host) == F.col("__h"), "left_anti")


def run_once(df: DataFrame, mode: str = "append", name: str = "out") -> DataFrame:
    """Run all available input to a table and return its rows: Parquet for append, one last batch for complete and update."""
    spark = df.sparkSession
    base = f"{shared_dir(spark)}/stream-{name}-{uuid.uuid4().hex[:8]}"
    if mode == "append":
        df.writeStream.format("parquet").option("path", f"{base}/data").option("checkpointLocation", f"{base}/state").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{base}/data")

    def save(batch: DataFrame, number: int) -> None:  # idempotent: a repeated batch overwrites itself
        batch.write.mode("overwrite").parquet(f"{base}/data/batch={number:06d}")

    query = df.writeStream.foreachBatch(save).option("checkpointLocation", f"{base}/state").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.parquet(f"{base}/data")
    return rows.where(F.col("batch") == rows.agg(F.max("batch")).first()[0]).drop("batch") if mode == "complete" else rows.drop("batch")


class SoftVoteProcessor(StatefulProcessor):
    """State of a document: the weights summed so far. Emits it once, when the sum first passes the target."""

    def __init__(self, target: float = C.TARGET):
        self.target = target

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.score = handle.getValueState("score", "score double")

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timerValues: Any) -> Iterator[pd.DataFrame]:
        was = self.score.get()[0] if self.score.exists() else 0.0
        now = was + sum(float(r["weight"].sum()) for r in rows)
        self.score.update((now,))
        if was <= self.target < now:
            yield pd.DataFrame({"id": [key[0]], "score": [now]})

    def close(self) -> None:
        pass


def soft_vote_stream(edges: DataFrame, target: float = C.TARGET) -> DataFrame:
    """(id, score) of each document when it becomes redundant. Needs the RocksDB state store. ``edges``: (id, weight), directed."""
    return edges.groupBy("id").transformWithStateInPandas(SoftVoteProcessor(target), "id long, score double", "update", "none")
