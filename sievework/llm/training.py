"""Bounded labelled samples and logistic calibration shared by the two classifiers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, stage


def labelled_sample(
    docs: DataFrame, labels: DataFrame, label: str, mod: int, rest: int, per_class: int, parts: int = 8,
    id_col: str = "doc_id", text_col: str = "text",
) -> DataFrame:
    """(text, y) of at most ``per_class`` labelled rows of each class that aren't held out, first by a hash of the id.
    An id with several labels has the largest.

    The chosen ids (a bounded table) are broadcast, so the texts aren't shuffled for the join; the sample is staged.
    """
    pool = labels.where(F.col(label).isNotNull() & F.col(id_col).isNotNull() & ~held_out(id_col, mod, rest))
    pool = pool.select(F.col(id_col).alias("__id"), F.col(label).cast("int").alias("y")).groupBy("__id").agg(F.max("y").alias("y"))
    order = F.md5(F.col("__id").cast("string"))
    chosen = pool.where("y = 1").orderBy(order, "__id").limit(per_class).unionAll(pool.where("y = 0").orderBy(order, "__id").limit(per_class))
    rows = docs.select(F.col(id_col).alias("__id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    # Rows that share one id all carry its label; one of each distinct text is enough to learn from.
    return stage(rows.join(F.broadcast(chosen), "__id").select("text", "y").repartition(parts, F.xxhash64("text")), "labelled")


#: Odd multipliers that make three orders of one shingle hash.
ORDERS = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9)


def _least_shingles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(text, y) -> also the least of its 3-word shingles under each order; texts without words are alike."""
    from xxhash import xxh64_intdigest

    for batch in batches:
        least = []
        for text in batch.column(0).to_pylist():
            words = text.encode().lower().split()
            shingles = {b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))}
            h = np.fromiter(map(xxh64_intdigest, shingles), np.uint64, len(shingles))
            least.append([int((h * np.uint64(k)).min() >> np.uint64(1)) for k in ORDERS])
        cols = [pa.array(c, pa.int64()) for c in zip(*least, strict=True)] if least else [pa.array([], pa.int64())] * 3
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *cols], ["text", "y", "m0", "m1", "m2"])


def without_near_copies(sample: DataFrame) -> DataFrame:
    """One of each set of near copies in a bounded sample: what many copies share must not look like what many texts
    share. Texts with one least shingle in common count as copies (three orders, so copies at 0.8 rarely pass)."""
    marked = sample.mapInArrow(_least_shingles, "text string, y int, m0 long, m1 long, m2 long")
    first = F.struct(F.xxhash64("text").alias("h"), "text", "m0", "m1", "m2").alias("r")
    for m in ("m0", "m1", "m2"):  # of copies the first by hash stays, so that every run learns the same
        marked = marked.select("y", F.col(m).alias("m"), first).groupBy("y", "m").agg(F.min("r").alias("r")).select("y", "r.text", "r.m0", "r.m1", "r.m2")
    return stage(marked.select("text", "y").repartition(8, F.xxhash64("text")), "distinct-sample")


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 50) -> np.ndarray:
    """Weights (bias last) by Newton steps on the class-balanced ridge loss; one class only: bias to that class."""
    x = np.column_stack([x, np.ones(len(x))]) if len(x) else np.ones((1, x.shape[1] + 1))
    if not len(y) or y.min() == y.max():
        out = np.zeros(x.shape[1])
        out[-1] = 0.0 if not len(y) else (3.0 if y[0] else -3.0)
        return out
    w = np.zeros(x.shape[1])
    share = np.where(y == 1, 0.5 / y.mean(), 0.5 / (1 - y.mean())) / len(y)
    penalty = np.full(x.shape[1], ridge)
    penalty[-1] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (share * (p - y)) + penalty * w
        hess = (x * (share * np.maximum(p * (1 - p), 1e-9))[:, None]).T @ x + np.diag(penalty)
        step = np.linalg.solve(hess, grad)
        w -= step
        if np.abs(step).max() < 1e-7:
            break
    return w


def logistic(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x @ w[:-1] + w[-1], -30, 30)))
