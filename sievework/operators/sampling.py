"""Sampling: value and presentation scores, cluster diversity, power sampling with its baselines, draws under a budget.

Normalisations need a minimum, a maximum or a sum of all rows: one-row aggregates joined back by broadcast, never collected
and never a window over everything.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import constants as C
from ..functions.text import distance, harmonic, sigmoid, unit
from ..plans.staging import stage

#: Centers, and numbers in them, that go to every task (200 MB).
CENTERS, CENTER_VALUES = 1_000_000, 25_000_000
#: Steps in which capped copies give their share to the others.
FILL_STEPS = 100


def content_value(dims: Sequence[str] = C.VALUE) -> Column:
    return sum((F.col(d) for d in dims[1:]), F.col(dims[0])).cast("double")


def writing_quality(dims: Sequence[str] = C.PRESENTATION) -> Column:
    return harmonic(*[F.col(d).cast("double") for d in dims])


def value_filter(df: DataFrame, cut: float = C.VALUE_CUT) -> DataFrame:
    """Keep rows whose content value is over ``cut``."""
    return df.where(content_value() > cut)


def min_max(df: DataFrame, columns: Sequence[str]) -> DataFrame:
    """``df`` with <c>_n in [0, 1] for each column; a constant column becomes 1."""
    edge = df.agg(*[f(c).alias(f"__{f.__name__}_{c}") for c in columns for f in (F.min, F.max)])
    out = df.crossJoin(F.broadcast(edge))
    for c in columns:
        lo, hi = F.col(f"__min_{c}"), F.col(f"__max_{c}")
        out = out.withColumn(f"{c}_n", F.when(hi > lo, (F.col(c) - lo) / (hi - lo)).otherwise(F.lit(1.0)))
    return out.drop(*edge.columns)


def label_centroids(vectors: DataFrame, cluster: str = "cluster", vec: str = "vec") -> DataFrame:
    """(cluster, center): means of the members, coordinate by coordinate."""
    flat = vectors.select(cluster, F.posexplode(vec).alias("i", "x"))
    means = flat.groupBy(cluster, "i").agg(F.avg(F.col("x").cast("double")).alias("m"))
    return means.groupBy(cluster).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda p: p["m"]).alias("center"))


def center_gaps(centers: DataFrame, inter: str = "mean", cluster: str = "cluster") -> DataFrame:
    """(cluster, inter): mean (or least) distance of each center to the others, none for a single one. The centers are sent to
    the tasks (a table of checked size); each row is held against all of them as one array operation."""
    rows = centers.orderBy(cluster).limit(CENTERS).collect()
    if sum(len(r["center"]) for r in rows) > CENTER_VALUES:
        raise ValueError("too many centers to hold in a task: cluster with fewer")
    table = np.array([r["center"] for r in rows], float)
    shared = centers.sparkSession.sparkContext.broadcast(table)
    kind = centers.schema[cluster].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for c in batch.column(1).to_pylist():
                far = np.sqrt(((shared.value - np.array(c)) ** 2).sum(1))
                own = int(far.argmin())  # itself, at distance zero
                rest = np.delete(far, own)
                out.append(None if not len(rest) else float(rest.mean() if inter == "mean" else rest.min()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.float64())], [cluster, "inter"])

    return centers.select(cluster, "center").mapInArrow(run, f"`{cluster}` {kind}, inter double").where("inter is not null")


def cluster_diversity(vectors: DataFrame, centers: DataFrame, inter: str = "mean", cluster: str = "cluster", vec: str = "vec") -> DataFrame:
    """(cluster, members, intra, inter, d): intra is the mean distance of members to their center, inter the mean (or least)
    distance to the other centers; d is their product. A single cluster has inter 1. Centers are a table of checked size."""
    centers = stage(centers, "centers")
    apart = center_gaps(centers, inter, cluster)  # checks the size
    intra = vectors.join(F.broadcast(centers), cluster).groupBy(cluster).agg(F.count("*").alias("members"), F.avg(distance(F.col(vec), F.col("center"))).alias("intra"))
    out = intra.join(apart, cluster, "left").withColumn("inter", F.coalesce("inter", F.lit(1.0)))
    return out.withColumn("d", F.col("intra") * F.col("inter"))


def sampling_score(df: DataFrame, alpha: float = C.ALPHA, quality: str = "value", d: str = "d") -> DataFrame:
    """``df`` with q, q_n, d_n and s = alpha q_n + (1 - alpha) d_n. quality: ``value``, ``combined`` (harmonic presentation
    times value), ``linear_all`` (all presentation and value scores added: the baseline)."""
    q = {"value": content_value(), "combined": writing_quality() * content_value(), "linear_all": content_value(C.PRESENTATION + C.VALUE)}[quality]
    scored = min_max(df.withColumn("q", q).withColumn("d", F.col(d).cast("double")), ("q", "d"))
    return scored.withColumn("s", alpha * F.col("q_n") + (1 - alpha) * F.col("d_n"))


def _normalised(df: DataFrame, weight: Column) -> DataFrame:
    weighed = df.withColumn("__w", weight)
    total = weighed.agg(F.sum("__w").alias("__all"))
    return weighed.crossJoin(F.broadcast(total)).withColumn("p", F.col("__w") / F.col("__all")).drop("__w", "__all")


def power_probabilities(df: DataFrame, n: float = C.POWER["n"], k: float = C.POWER["k"], a: float = C.POWER["a"], s: str = "s") -> DataFrame:
    """``df`` with x (score on [0, 1]) and p proportional to x^n times a sigmoid gate at a of steepness k."""
    x = min_max(df, (s,)).withColumnRenamed(f"{s}_n", "x")
    power = F.lit(1.0) if n == 0 else F.pow("x", F.lit(float(n)))
    return _normalised(x, power * sigmoid(k * (F.col("x") - a)))


def softmax_probabilities(df: DataFrame, tau: float = 1.0, s: str = "s") -> DataFrame:
    x = min_max(df, (s,)).withColumnRenamed(f"{s}_n", "x")
    return _normalised(x, F.exp((F.col("x") - 1.0) / tau))  # the largest x is 1


def uniform_probabilities(df: DataFrame) -> DataFrame:
    return _normalised(df, F.lit(1.0))


def domain_factor(df: DataFrame, target: DataFrame, strength: float = 1.0, domain: str = "domain_l1") -> DataFrame:
    """``df`` with p moved toward target shares (domain, share): p times (share / current share) ^ strength, summed to 1 again."""
    now = df.groupBy(domain).agg(F.sum("p").alias("__now"))
    factor = now.join(target, domain, "left").select(F.col(domain).alias("__d"), F.pow(F.coalesce("share", F.lit(0.0)) / F.col("__now"), F.lit(float(strength))).alias("__f"))
    moved = df.join(F.broadcast(factor), F.col(domain).eqNullSafe(F.col("__d")))
    weighed = moved.withColumn("p", F.col("p") * F.col("__f")).drop("__d", "__f")
    return _normalised(weighed.withColumnRenamed("p", "__p"), F.col("__p")).drop("__p")


def draw_copies(df: DataFrame, budget: float, tokens: str = "n_words", key: str = "doc_id", seed: str = "draw", max_copies: int | None = None) -> DataFrame:
    """``df`` with ``expected`` and whole ``copies`` whose expected tokens meet the budget: copies = floor of lambda p plus one
    with the chance of the rest, by a draw from the key. With ``max_copies`` lambda grows until rows at the cap and the others
    together meet the budget again (water-filling); a budget over all rows at the cap gives just these."""
    rate = df.agg((F.lit(float(budget)) / F.sum(F.col("p") * F.col(tokens))).alias("r")).first()["r"] or 0.0
    if max_copies is not None:
        for _ in range(FILL_STEPS):  # each step is one aggregate; what is at the cap stays there as lambda grows
            full = F.lit(rate) * F.col("p") >= max_copies
            at = df.agg(F.coalesce(F.sum(F.when(full, F.col(tokens))), F.lit(0)).alias("t"), F.coalesce(F.sum(F.when(~full, F.col("p") * F.col(tokens))), F.lit(0.0)).alias("f")).first()
            left = float(budget) - max_copies * float(at["t"])
            fresh = left / at["f"] if at["f"] and left > 0 else rate
            if fresh <= rate * (1 + 1e-12):
                break
            rate = fresh
    out = df.withColumn("expected", F.coalesce(F.lit(float(rate)) * F.col("p"), F.lit(0.0)))
    if max_copies is not None:
        out = out.withColumn("expected", F.least("expected", F.lit(float(max_copies))))
    rest = F.col("expected") - F.floor("expected")
    return out.withColumn("copies", (F.floor("expected") + F.when(unit(F.col(key), seed) < rest, 1).otherwise(0)).cast("int"))


def draw_without_replacement(df: DataFrame, budget: float, tokens: str = "n_words", key: str = "doc_id", seed: str = "draw", cells: int = 4096) -> DataFrame:
    """Rows with the least -ln(u)/p whose tokens fit the budget, up to the resolution of a histogram of ``cells`` cells: tokens
    are summed by cell, and the prefix sum runs over that bounded table, not over the rows."""
    from pyspark.sql import Window

    race = df.withColumn("__r", -F.log(unit(F.col(key), seed)) / F.nullif("p", F.lit(0.0))).where("__r is not null")
    n = race.agg(F.count("*").alias("__n"))
    ranked = race.crossJoin(F.broadcast(n)).withColumn("__cell", F.floor(F.lit(cells) * (1 - F.exp(-F.col("__r") / F.col("__n")))).cast("int"))
    sums = ranked.groupBy("__cell").agg(F.sum(tokens).alias("__t"))
    upto = sums.select("__cell", F.sum("__t").over(Window.orderBy("__cell")).alias("__upto"))
    return ranked.join(F.broadcast(upto), "__cell").where(F.col("__upto") <= budget).drop("__cell", "__n", "__r", "__upto")


def cluster_allocation(df: DataFrame, budget: float, cluster: str = "cluster", tokens: str = "n_words", key: str = "doc_id") -> DataFrame:
    """Budget split over clusters by their summed p, then drawn inside each: the cluster-level variant."""
    per = df.groupBy(cluster).agg(F.sum("p").alias("__pc"), F.sum(F.col("p") * F.col(tokens)).alias("__ptc"))
    inside = df.join(F.broadcast(per.withColumnRenamed(cluster, "__c")), F.col(cluster).eqNullSafe(F.col("__c"))).drop("__c")
    rate = F.lit(float(budget)) * F.col("__pc") * F.col("p") / F.nullif("__ptc", F.lit(0.0))
    rest = rate - F.floor(rate)
    return inside.withColumn("expected", rate).withColumn("copies", (F.floor(rate) + F.when(unit(F.col(key), "cluster") < rest, 1).otherwise(0)).cast("int")).drop("__pc", "__ptc")


def sampler_profile(df: DataFrame, order: str | None = None) -> DataFrame:
    """(entropy_bits, effective_size, top_p, rows): how sharp a sampler is. With ``order`` (a score) also decile_ratio: the mean
    probability of the rows at or over the ninth decile of the score, by that of the rows at or under the first."""
    p = F.col("p")
    bits = F.sum(F.when(p > 0, -p * F.log2(p)).otherwise(0.0))
    aggs = [bits.alias("entropy_bits"), (1 / F.sum(p * p)).alias("effective_size"), F.max(p).alias("top_p"), F.count("*").alias("rows")]
    if order is None:
        return df.agg(*aggs)
    ends = df.agg(F.percentile_approx(order, [0.1, 0.9], 10000).alias("__e"))
    low, high = F.col(order) <= F.col("__e")[0], F.col(order) >= F.col("__e")[1]
    ratio = F.avg(F.when(high, p)) / F.nullif(F.avg(F.when(low, p)), F.lit(0.0))
    return df.crossJoin(F.broadcast(ends)).agg(*aggs, ratio.alias("decile_ratio"))
