"""Rendezvous (highest random weight) sharding of stable keys over weighted shards, DataFrame functions only.

Every shard draws a number from the key and its own name; the largest draw takes the record. A new shard
can only win records for itself, so growing by one moves that shard's share and nothing else. Weights enter
as w / -ln(u). Draws use the first 48 bits of an MD5, so they are the same in every engine.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import stage, table

SHARDS = 8


def draw(key: Column, shard: int) -> Column:
    """Uniform in (0, 1): 48 bits of md5(key:shard), centred."""
    bits = F.conv(F.substring(F.md5(F.concat_ws(":", key, F.lit(str(shard)))), 1, 12), 16, 10).cast("double")
    return (bits + 0.5) / float(1 << 48)


def rendezvous(key: Column, weights: Sequence[float]) -> Column:
    """Shard number of a string key; ties go to the lower number. A shard of weight 0 takes nothing."""
    draws = [F.struct((F.lit(float(w)) / -F.log(draw(key, i))).alias("score"), F.lit(-i).alias("shard")) for i, w in enumerate(weights) if w > 0]
    if not draws:
        raise ValueError("no shard has a weight")
    best = F.greatest(*draws) if len(draws) > 1 else draws[0]
    return (-best["shard"]).cast("int")


def assign(
    df: DataFrame, shards: int = SHARDS, weights: Sequence[float] | None = None, grown_weight: float = 1.0,
    id_col: str = "doc_id", text_col: str = "text",
) -> DataFrame:
    """One row for each input row: id, size, text_crc32, law, shard, slot, grown_shard.

    ``slot`` numbers the rows of a shard from 0 without gaps, in blocks: rows are counted for each input partition and
    shard, the counts are summed in order, and only rows of one block are sorted together. A null id is a key of its
    own, a null text has no bytes (size 1, crc of nothing); repeated rows get slots of their own.
    """
    weights = list(weights or [1.0] * shards)
    key = F.coalesce(F.col(id_col).cast("string"), F.lit(""))
    rows = stage(
        df.select(
            F.col(id_col),
            (F.coalesce(F.octet_length(text_col), F.lit(0)) + 1).cast("long").alias("size"),
            F.crc32(F.coalesce(F.col(text_col), F.lit(""))).alias("text_crc32"),
            rendezvous(key, weights).alias("shard"),
            rendezvous(key, [*weights, grown_weight]).alias("grown_shard"),
            F.spark_partition_id().alias("block"),
        ),
        "shards",
    )
    before = Window.partitionBy("shard").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    counts = rows.groupBy("shard", "block").agg(F.count("*").alias("n"))  # one row a shard and input partition
    offsets = counts.select("shard", "block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    inside = Window.partitionBy("shard", "block").orderBy(id_col, "text_crc32", "size")
    return (
        rows.withColumn("nth", F.row_number().over(inside))
        .join(offsets, ["shard", "block"])
        .select(
            id_col, "size", "text_crc32", F.lit("key").alias("law"), "shard",
            (F.col("base") + F.col("nth") - 1).cast("long").alias("slot"), "grown_shard",
        )
    )


def write_shards(df: DataFrame, path: str, shards: int = SHARDS, weights: Sequence[float] | None = None, id_col: str = "doc_id") -> None:
    """Write ``df`` as Parquet below ``path``, a folder for each shard; all columns as given."""
    key = F.coalesce(F.col(id_col).cast("string"), F.lit(""))
    df.withColumn("shard", rendezvous(key, list(weights or [1.0] * shards))).write.partitionBy("shard").parquet(path)


def op9_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign(table(spark, sf_dir, "documents"))
