"""Tables written to the folder that driver and executors share; they end lineage and survive lost executors."""

from __future__ import annotations

import uuid

from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession

_roots: dict[str, str] = {}
_once: dict[tuple, DataFrame] = {}


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; a local default only where it is unset and the master is local."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file:///tmp/checkpoints"
    app = spark.sparkContext.applicationId
    return _roots.setdefault(f"{base}|{app}", f"{base.rstrip('/')}/sievework-{app}-{uuid.uuid4().hex[:8]}")


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` now and read it back, with its schema and a path of its own."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def unstage(df: DataFrame) -> None:
    """Delete the staged tables that ``df`` reads, inputs of the session excepted; ``df`` becomes invalid."""
    spark = df.sparkSession
    hadoop, conf = spark._jvm.org.apache.hadoop.fs, spark._jsc.hadoopConfiguration()
    root = hadoop.Path(shared_dir(spark))
    fs = root.getFileSystem(conf)
    under = fs.makeQualified(root).toUri().getPath() + "/"
    for folder in {hadoop.Path(f).getParent().toUri().getPath() for f in df.inputFiles()}:
        if folder.startswith(under):
            fs.delete(hadoop.Path(folder), True)


def staged_once(spark: SparkSession, sf_dir: str, tables: Sequence[str], name: str, make: Callable[[], DataFrame]) -> DataFrame:
    """``make()`` staged, once for an application and state of its input files; made again if these or the staged files changed."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    stamp = []
    for t in tables:
        path = jvm.org.apache.hadoop.fs.Path(f"{sf_dir.rstrip('/')}/{t}.parquet")
        status = path.getFileSystem(conf).getFileStatus(path)
        stamp.append((t, status.getLen(), status.getModificationTime()))
    key = (shared_dir(spark), sf_dir, name, tuple(stamp))
    if key in _once:
        path = jvm.org.apache.hadoop.fs.Path(_once[key].inputFiles()[0]) if _once[key].inputFiles() else None
        if path is not None and path.getFileSystem(conf).exists(path):
            return _once[key]
    _once[key] = stage(make(), name)
    return _once[key]


def drop_staging(spark: SparkSession) -> None:
    """Delete this application's staged tables; DataFrames that read them become invalid. For the end of a run, when its results
    are written."""
    _once.clear()
    root = spark._jvm.org.apache.hadoop.fs.Path(shared_dir(spark))
    root.getFileSystem(spark._jsc.hadoopConfiguration()).delete(root, True)
