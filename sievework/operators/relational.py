"""Joins that Spark has no operator for: as-of, binned range, interval, salted, nearest neighbours."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, ts: str, value: str, tolerance: float | None = None) -> DataFrame:
    """``left`` with the latest ``value`` of ``right`` at or before its time (as_ts, as_value), within ``tolerance`` seconds.

    Both sides go through one shuffle and one sort by key and time; nothing is paired. On equal times the right side comes
    first, of several the one with the largest value. Keys that hold many rows: put a coarse time bucket into ``by``.
    """
    extra = [c for c in left.columns if c not in (by, ts)]
    r = right.select(by, ts, F.struct(F.col(ts).alias("t"), F.col(value).alias("v")).alias("__r"), F.lit(0).alias("__side"), *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in extra])
    hit_type = r.schema["__r"].dataType
    both = left.select(by, ts, F.lit(None).cast(hit_type).alias("__r"), F.lit(1).alias("__side"), *extra).unionByName(r)
    w = Window.partitionBy(by).orderBy(ts, "__side", "__r").rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("__hit", F.last("__r", ignorenulls=True).over(w)).where("__side = 1")
    near = F.lit(True) if tolerance is None else (F.col(ts).cast("timestamp").cast("double") - F.col("__hit.t").cast("timestamp").cast("double") <= tolerance)
    return found.select(by, ts, *extra, F.when(near, F.col("__hit.t")).alias("as_ts"), F.when(near, F.col("__hit.v")).alias("as_value"))


def range_join(df: DataFrame, intervals: DataFrame, point: str, lo: str, hi: str, width: float) -> DataFrame:
    """Rows with the intervals lo <= point < hi that hold them, as an equi-join on bins of ``width``: an interval is repeated
    for each bin it touches, a row stands in one bin."""
    bins = F.sequence(F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1e-12) / width))
    spread = intervals.withColumn("__bin", F.explode(bins))
    return df.withColumn("__bin", F.floor(F.col(point) / width)).join(spread, "__bin").where((F.col(point) >= F.col(lo)) & (F.col(point) < F.col(hi))).drop("__bin")


def interval_join(left: DataFrame, right: DataFrame, by: str, lts: str, rts: str, seconds: float) -> DataFrame:
    """Pairs of one key with 0 <= right time - left time <= seconds, by time buckets of that length: two a left row."""
    secs = lambda c: F.col(c).cast("timestamp").cast("double")
    a = left.withColumn("__b", F.explode(F.array(F.floor(secs(lts) / seconds), F.floor(secs(lts) / seconds) + 1)))
    b = right.withColumn("__b", F.floor(secs(rts) / seconds))
    gap = secs(rts) - secs(lts)
    return a.join(b, [by, "__b"]).where((gap >= 0) & (gap <= seconds)).drop("__b")


def salted_join(left: DataFrame, right: DataFrame, on: str, salts: int, key: Column, how: str = "inner") -> DataFrame:
    """Equi-join with the left side spread over ``salts`` parts of each key and the right side repeated for them."""
    a = left.withColumn("__salt", F.pmod(F.xxhash64(key), F.lit(salts)).cast("int"))
    b = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [on, "__salt"], how).drop("__salt")


def top_per_group(df: DataFrame, group: str, order: list, k: int) -> DataFrame:
    """First k rows of each group (WindowGroupLimit keeps k rows a task before the shuffle)."""
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(group).orderBy(*order))).where(F.col("rank") <= k)
