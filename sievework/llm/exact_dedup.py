"""Exact dedup with a heavy-hitter split, DataFrame functions only.

Each row becomes (id, SHA-256 of its normalised text); the text goes no further. A Misra-Gries
sketch, merged in two levels, names the keys that may be frequent. Their winners are counted exactly
(verified) and joined by broadcast, so their copies never meet in one task; the other keys, each
under 1/CAPACITY of the rows, are aggregated and joined by ordinary shuffles.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import stage, table, unused

#: Counters of a sketch and keys it may name: the bound of what is broadcast.
CAPACITY = 256
#: Groups of copies whose winners are broadcast when rows are dropped (about 100 bytes each); more are joined by a shuffle.
BROADCAST_ROWS = 100_000
#: Fan-in of the first merge level of the sketches.
SKETCH_GROUPS = 64
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def normalised(text_col: str) -> Column:
    """Null counts as empty; only A-Z are lower-cased."""
    return F.translate(F.coalesce(F.col(text_col), F.lit("")), UPPER, LOWER)


def frequent_keys(df: DataFrame, key: str, capacity: int = CAPACITY) -> DataFrame:
    """At most ``capacity`` values of the long column ``key``: every one with over ~1/capacity of the rows is there.

    One sketch for each of SKETCH_GROUPS sets of partitions, then one merge of those.
    """
    parts = df.groupBy((F.spark_partition_id() % SKETCH_GROUPS).alias("part")).agg(
        F.expr(f"approx_top_k_accumulate({key}, {2 * capacity})").alias("sketch")
    )
    # Grouped, if by one value only: a task without sketches then sends none (an empty sketch can't be merged).
    top = parts.groupBy((F.col("part") < 0).alias("all")).agg(F.expr(f"approx_top_k_estimate(approx_top_k_combine(sketch), {capacity})").alias("top"))
    return top.select(F.explode("top").alias("t")).where("t.count > 1").select(F.col("t.item").alias(key))


def group_copies(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each input row: id, keep_id, group_size, kept, text_sha256.

    Equal texts form a group; its largest id is kept (a null id only where all are null). Rows that repeat
    the winning id with the same text are all marked kept: they are one row, written twice. An empty table
    gives no rows; other columns are ignored.
    """
    digests, heavy, rest = _split(df, id_col, text_col)
    by_heavy = digests.join(F.broadcast(heavy), "digest")
    by_rest = rest.join(rest.groupBy("digest").agg(*_winner()), "digest")
    cols = ("id", "keep_id", "group_size", "digest")
    return (
        by_heavy.select(*cols)
        .unionAll(by_rest.select(*cols))
        .select(
            F.col("id").alias(id_col),
            "keep_id",
            "group_size",
            F.col("id").eqNullSafe(F.col("keep_id")).alias("kept"),
            F.col("digest").alias("text_sha256"),
        )
    )


def _winner() -> tuple[Column, Column]:
    return F.max("id").alias("keep_id"), F.count("*").alias("group_size")


def _split(df: DataFrame, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(digests of all rows: id, digest, h; verified winners of the frequent ones; digests of the rows of all others)."""
    digests = stage(
        df.select(F.col(id_col).alias("id"), F.sha2(normalised(text_col), 256).alias("digest")).withColumn(
            "h", F.xxhash64("digest")
        ),
        "digests",
    )
    frequent = F.broadcast(frequent_keys(digests, "h"))
    # At most CAPACITY keys (two digests under one key in theory): counted over all rows, then small.
    heavy = stage(digests.join(frequent, "h").groupBy("digest").agg(*_winner()), "heavy")
    return digests, heavy, digests.join(F.broadcast(heavy.select("digest")), "digest", "left_anti")


def drop_copies(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``df`` with one row for each distinct normalised text: that with the largest id; columns as given.

    Rows with the same id and text count as copies too, so exactly one of them stays.
    """
    digests, heavy, rest = _split(df, id_col, text_col)
    several = stage(rest.groupBy("digest").agg(*_winner()).where("group_size > 1"), "several")
    digest, kept, n = unused(df, "__digest", "__kept", "__n")
    rows = df.withColumn(digest, F.sha2(normalised(text_col), 256))
    for found, small in ((heavy, True), (several, several.count() <= BROADCAST_ROWS)):
        # Losers of groups go where they are read; texts move only where there are too many groups to broadcast.
        side = found.select(F.col("digest").alias(digest), F.col("keep_id").alias(kept), F.col("group_size").alias(n))
        marked = rows.join(F.broadcast(side) if small else side, digest, "left")
        rows = marked.where(F.col(n).isNull() | F.col(id_col).eqNullSafe(F.col(kept))).drop(kept, n)
    # A winner that was written more than once: its rows alone are brought together.
    won = digests.join(F.broadcast(heavy), "digest").select("id", "keep_id", "digest").unionAll(rest.join(several, "digest").select("id", "keep_id", "digest"))
    again = stage(won.where(F.col("id").eqNullSafe(F.col("keep_id"))).groupBy("digest").agg(F.count("*").alias("n")).where("n > 1").select("digest"), "again")
    if again.isEmpty():
        return rows.select(*df.columns)
    again = again.select(F.col("digest").alias(digest))
    twice = rows.join(again, digest, "left_semi").dropDuplicates([digest])
    return rows.join(again, digest, "left_anti").unionAll(twice).select(*df.columns)


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return group_copies(table(spark, sf_dir, "documents"))


OP2_SQL = f"""
WITH d AS (SELECT doc_id, sha256(translate(coalesce(text, ''), '{UPPER}', '{LOWER}')) AS text_sha256 FROM documents)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = max(doc_id) OVER w AS kept, text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256)
"""
