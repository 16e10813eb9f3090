"""SimHash near-dedup at a similarity: one row of each group of texts whose word shingles have a Jaccard of ``theta`` or more.

Shingles are of five words; fewer words make one shingle of all. Fingerprints of these shingles within TAU bits (the search of
``simhash``) are candidates. Few of the pairs just over 0.8 lie so near (their fingerprints differ in 8 bits of 64 on average,
beyond what a pigeonhole can search), so MinHash buckets of the same shingles add candidates, at a chance of 0.9998 for a
pair at 0.8. All candidates are verified by exact Jaccard, and links are closed inside buckets. Texts are read once for both; only
rows with a candidate have their sets made and moved.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import star_forest
from ..operators.fuzzy import BANDS, PERMUTATIONS, SHINGLE, THETA, closed_links
from .common import map_arrow, stage, unused
from .simhash import SEED, TAU, majority, near_links
from .simhash import shingle_hashes as hashes_of

_MAPS = np.random.default_rng(SEED).integers(0, 2**63, (2, PERMUTATIONS), np.uint64) * np.uint64(2) + np.uint64(1)
#: Multipliers that fold a band's values into one bucket.
_FOLD = np.random.default_rng(SEED + 1).integers(0, 2**63, PERMUTATIONS // BANDS, np.uint64) * np.uint64(2) + np.uint64(1)
#: The set of a text without words: one shingle, so that such texts are alike.
_EMPTY = np.zeros(1, np.uint64)


def shingle_set(hashes: np.ndarray) -> np.ndarray:
    """Sorted distinct hashes."""
    return np.unique(hashes) if len(hashes) else _EMPTY


def band_values(hashes: np.ndarray) -> np.ndarray:
    """One value a band of the MinHash signature."""
    least = np.full(PERMUTATIONS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(hashes), 4096):  # long documents in slices
        least = np.minimum(least, (hashes[at : at + 4096, None] * _MAPS[0] + _MAPS[1]).min(0))
    return ((least.reshape(BANDS, -1) >> np.uint64(7)) * _FOLD).sum(1, dtype=np.uint64)


def _lists(rows: list[np.ndarray]) -> pa.ListArray:
    cuts = np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(cuts), pa.array(np.concatenate(rows).view(np.int64) if rows else np.zeros(0, np.int64)))


def _signatures(df: DataFrame) -> DataFrame:
    def build():
        def one(batch: pa.RecordBatch) -> pa.RecordBatch:
            each = [hashes_of(t, SHINGLE) for t in batch.column(1).to_pylist()]
            prints = pa.array(np.array([majority(h) for h in each], np.uint64).view(np.int64))
            return pa.RecordBatch.from_arrays([batch.column(0), prints, _lists([band_values(shingle_set(h)) for h in each])], ["key", "fp", "values"])

        return one

    return map_arrow(df.select("key", "text"), build, "key long, fp long, values array<long>")


def _sets(df: DataFrame) -> DataFrame:
    def build():
        return lambda batch: pa.RecordBatch.from_arrays([batch.column(0), _lists([shingle_set(hashes_of(t, SHINGLE)) for t in batch.column(1).to_pylist()])], ["key", "sh"])

    return map_arrow(df.select("key", "text"), build, "key long, sh array<long>")


def print_pairs(marks: DataFrame) -> DataFrame:
    """(u, v), u < v: rows of one fingerprint with the least of them, and the least of two fingerprints that the search links."""
    prints = stage(marks.groupBy("fp").agg(F.min("key").alias("first")), "near-prints")
    same = marks.select("key", "fp").join(prints, "fp").where(F.col("key") > F.col("first")).select(F.col("first").alias("u"), F.col("key").alias("v"))
    links = stage(near_links(prints.select("fp"), TAU), "near-links")
    side = lambda c: prints.select(F.col("fp").alias(c), F.col("first").alias(f"{c}_first"))
    far = links.join(side("u"), "u").join(side("v"), "v").select(F.least("u_first", "v_first").alias("u"), F.greatest("u_first", "v_first").alias("v"))
    return stage(same.unionAll(far).distinct(), "near-candidates")


def near_texts(df: DataFrame, theta: float = THETA) -> DataFrame:
    """(key, text), keys distinct -> (u, v): each key that isn't the least of its component, with that least key.

    Components are those of the pairs with Jaccard >= ``theta`` that are candidates by fingerprint or by bucket.
    """
    marks = stage(_signatures(df), "near-marks")
    pairs = print_pairs(marks)
    buckets = marks.select("key", F.posexplode("values").alias("band", "bucket"))
    # Staged, so that both sides of the join are plain tables and a bucket with very many rows can be split.
    shared = stage(buckets.groupBy("band", "bucket").agg(F.count("*").alias("n")).where("n > 1").select("band", "bucket"), "near-shared")
    buckets = stage(buckets.join(shared, ["band", "bucket"], "left_semi"), "near-buckets")
    some = buckets.select("key").unionAll(pairs.select("u")).unionAll(pairs.select("v")).distinct()
    sets = stage(_sets(df.join(some, "key", "left_semi")), "near-sets")
    return star_forest(closed_links(buckets, sets, theta, "key", pairs))


def drop_alike(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", theta: float = THETA) -> DataFrame:
    """``df`` with one row for each component of near copies, that with its least id; columns as given. A null id stays only where all are null."""
    (k,) = unused(df, "__k")
    rows = stage(df.withColumn(k, F.monotonically_increasing_id()), "near-rows")
    tree = near_texts(rows.select(F.col(k).alias("key"), F.col(text_col).alias("text")), theta)
    placed = rows.select(F.col(k).alias("k"), F.col(id_col).alias("id")).join(tree.select(F.col("u").alias("k"), F.col("v").alias("root")), "k", "left")
    rank = F.struct(F.col("id").isNull().alias("none"), "id", "k")
    best = placed.groupBy(F.coalesce("root", "k").alias("root")).agg(F.min(rank).alias("b")).select(F.col("b.k").alias(k))
    return rows.join(best, k, "left_semi").select(*df.columns)
