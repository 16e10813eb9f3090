"""Readers and writers: named tables, files with explicit schemas, stage outputs, rejects, bucketed signals."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def spread(scan: DataFrame) -> DataFrame:
    """A scan's rows over all cores where it has fewer partitions than they are; any larger scan as it is. For heavy work on each
    row of small inputs: what is moved is under a partition's size (``spark.sql.files.maxPartitionBytes``) for each core."""
    cores = scan.sparkSession.sparkContext.defaultParallelism
    return scan.repartition(cores) if scan._jdf.queryExecution().toRdd().getNumPartitions() < cores else scan


def load_files(spark: SparkSession, path: str, fmt: str, schema: T.StructType | str) -> DataFrame:
    """CSV, JSON, text, ORC or Parquet with a given schema; rows that don't fit land in ``_corrupt_record`` (CSV, JSON)."""
    reader = spark.read.format(fmt)
    if fmt in ("csv", "json"):
        own = T.StructType.fromDDL(schema) if isinstance(schema, str) else schema
        own = T.StructType([*own.fields, T.StructField("_corrupt_record", T.StringType())])
        reader = reader.schema(own).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt_record")
        if fmt == "csv":
            reader = reader.option("header", "true")
    else:
        reader = reader.schema(schema)
    return reader.load(path)


def require(df: DataFrame, contract: dict[str, str]) -> DataFrame:
    """``df`` unchanged if it has the contract's columns and types; else a clear error. Other columns pass."""
    have = dict(df.dtypes)
    wrong = {c: (t, have.get(c)) for c, t in contract.items() if have.get(c) != t}
    if wrong:
        raise ValueError(f"columns (wanted, found): {wrong}")
    return df


def write_stage(df: DataFrame, path: str, by: tuple[str, ...] = ()) -> None:
    df.write.mode("overwrite").partitionBy(*by).parquet(path)


def write_signals(df: DataFrame, name: str, key: str = "doc_id", buckets: int = 64) -> None:
    """Signals as a table bucketed and sorted on the key: later joins on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def write_rejects(df: DataFrame, path: str, reason: Column) -> None:
    df.withColumn("reason", reason).where(F.col("reason").isNotNull()).write.mode("overwrite").partitionBy("reason").parquet(path)


def write_jsonl(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)


def union_snapshots(frames: list[DataFrame]) -> DataFrame:
    """Crawls of several snapshots as one table; columns that one of them lacks are null there."""
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f, allowMissingColumns=True)
    return out


def assemble_conversations(turns: DataFrame, sep: str = "\n") -> DataFrame:
    """Turns -> one document for each conversation, in turn order: conv_id, turns, text."""
    ordered = F.sort_array(F.collect_list(F.struct("turn", "role", F.coalesce("text", F.lit("")).alias("text"))))
    return turns.groupBy("conv_id").agg(F.count("*").alias("turns"), ordered.alias("t")).select(
        "conv_id", "turns", F.array_join(F.transform("t", lambda x: F.concat(x["role"], F.lit(": "), x["text"])), sep).alias("text")
    )
