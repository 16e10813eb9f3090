"""Connected components by alternating star contraction; every round is a staged table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.staging import stage

MAX_ROUNDS = 60
#: Edges from which the least neighbours are staged before they are joined: both sides of the join are plain exchanges then, and
#: Spark can split the rows of a centre with very many neighbours.
SPLIT_ROWS = 2_000_000


def _large_star(edges: DataFrame, split: bool = False) -> DataFrame:
    """Each node hangs its larger neighbours on the least of its neighbours and itself."""
    both = edges.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    least = stage(least, "least") if split else least
    return both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small_star(edges: DataFrame, split: bool = False) -> DataFrame:
    """Each node hangs its smaller neighbours and itself on the least of them."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    least = stage(least, "least") if split else least
    moved = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionAll(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def star_forest(edges: DataFrame) -> DataFrame:
    """(u, v) long pairs -> (u, v): every node that is not the least of its component, with that least node.

    Direction, repeated and self edges don't matter; null ends are left out. Stops when a round changes nothing.
    """
    ends = edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    now, seen = stage(ends.distinct(), "edges"), None
    split = now.count() > SPLIT_ROWS
    for _ in range(MAX_ROUNDS):
        now = stage(_small_star(stage(_large_star(now, split), "large-star"), split), "small-star")
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == seen or mark[0] == 0:
            return now
        seen = mark
    raise RuntimeError("components did not settle")
