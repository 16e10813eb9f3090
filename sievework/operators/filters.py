"""Model filter over the signal columns, its cascade with the rules, and the baselines."""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Lowest score that passes, by dimension; all must pass.
THRESHOLDS = {"writing": 1, "coherence": 1, "completeness": 1, "safety": 1}


def passes(thresholds: Mapping[str, float] = THRESHOLDS) -> Column:
    out = F.lit(True)
    for name, least in thresholds.items():
        out = out & (F.col(name) >= least)
    return out


def failures(thresholds: Mapping[str, float] = THRESHOLDS) -> Column:
    """Names of the dimensions that fail, in their order; the first is the reason reported."""
    return F.array_compact(F.array(*[F.when(~(F.col(n) >= v), F.lit(n)) for n, v in thresholds.items()]))


def model_filter(df: DataFrame, thresholds: Mapping[str, float] = THRESHOLDS, mode: str = "filter", combine: str = "all", cut: float = 1.0) -> DataFrame:
    """Keep rows that pass on every dimension (``all``), or whose mean score reaches ``cut`` (``mean``, compensatory)."""
    if mode == "annotate":
        return df.withColumn("fail_reasons", failures(thresholds)).withColumn("first_failure", F.try_element_at("fail_reasons", F.lit(1)))
    if combine == "mean":
        return df.where(sum((F.col(n) for n in thresholds), F.lit(0)) / len(thresholds) >= cut)
    return df.where(passes(thresholds))


def single_score_filter(df: DataFrame, column: str, cut: float) -> DataFrame:
    """The monolithic baseline: one score, one cut."""
    return df.where(F.col(column) >= cut)


def cascade(df: DataFrame, stages: tuple[str, ...] = ("rule", "model"), thresholds: Mapping[str, float] = THRESHOLDS) -> DataFrame:
    """Rules, then model; ``df`` carries ``rule_hits`` and the scores. One map stage whatever the stages."""
    if "rule" in stages:
        df = df.where(F.size("rule_hits") == 0)
    return model_filter(df, thresholds) if "model" in stages else df
