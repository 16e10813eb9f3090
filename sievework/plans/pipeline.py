"""The whole funnel over documents: one narrow signals table serves all stages; text is read only where a stage needs it."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import constants as C
from ..operators import filters, fuzzy, ingest, rules, sampling, semantic, signals
from ..operators.fuzzy import THETA
from .staging import drop_staging, stage

STAGES = ("raw", "english", "exact", "rule", "model", "fuzzy", "semantic", "value", "sampled")


@dataclass(frozen=True)
class Config:
    """Parameters of a run; the defaults are the method's, or documented choices where it names none."""

    language: str | None = "en"
    confidence: float = 0.5
    ruleset: tuple = rules.OPTIMIZED
    bypass: tuple = C.BYPASS
    use_model: bool = True
    thresholds: dict = field(default_factory=lambda: dict(filters.THRESHOLDS))
    fuzzy: bool = True
    theta: float = THETA
    per_cell: int = semantic.ROWS_PER_CELL  # rows of a cell inside which the semantic stage compares
    per_group: int = 131_072  # rows of a group of the diversity score; the cells of either grow in number with the rows
    groups: int = 16  # groups at least
    provider: str = "word"
    vectors: DataFrame | None = None  # (doc_id, vec) of unit length: given embeddings in place of the provider's
    semantic: str = "soft"  # soft, hard, none
    target: float = C.TARGET
    keep: str = "component_best"
    sampler: str = "power"  # power, softmax, uniform
    quality: str = "value"
    alpha: float = C.ALPHA
    budget_factor: float = 1.0  # tokens drawn, as a multiple of those of the value stage
    shared_signals: bool = True


def signals_table(docs: DataFrame, config: Config = Config()) -> DataFrame:
    """One row a document, no text: tags, nine scores, rule hits, language guess, digest. One scan, no join, no shuffle."""
    rows = ingest.detect_language(docs).withColumn("digest", ingest.digest())
    own = ("lang_guess", "lang_conf", "digest")
    ruled = rules.rule_features(rows, keep=("doc_id", "text", "source", *own)).withColumn("__hits", rules.hits(config.ruleset))
    joined = signals.annotate(ruled.select("doc_id", "text", "source", *own, "__hits"), keep=("doc_id", *own, "__hits"))
    skip = F.col("domain_l1").isin(*config.bypass) if config.bypass else F.lit(False)
    return joined.withColumn("bypassed", skip).withColumn("rule_hits", F.when(skip, F.array().cast("array<string>")).otherwise(F.col("__hits"))).drop("__hits")


def vectors_of(docs: DataFrame, config: Config = Config()) -> DataFrame:
    """(doc_id, vec) of the documents, from the provider or the vectors given."""
    if config.vectors is not None:
        return stage(config.vectors.join(docs.select("doc_id"), "doc_id", "left_semi").select("doc_id", F.col("vec").cast("array<double>").alias("vec")), "vectors")
    return stage(semantic.hashed_vectors(docs, config.provider), "vectors")


def cells_of(vectors: DataFrame, config: Config = Config()) -> DataFrame:
    """Vectors with the K-Means cells of the semantic stage."""
    return stage(semantic.kmeans_cells(vectors, semantic.cells_for(vectors.count(), config.per_cell)), "cells")


def groups_of(vectors: DataFrame, config: Config = Config()) -> DataFrame:
    """Vectors with the K-Means groups of the diversity score."""
    return stage(semantic.kmeans_cells(vectors, max(config.groups, semantic.cells_for(vectors.count(), config.per_group))), "groups")


def semantic_parts(docs: DataFrame, config: Config) -> tuple[DataFrame, DataFrame]:
    """(vectors in their cells, all weighted edges) of the documents given: for audits; the pipeline doesn't make all edges."""
    clustered = cells_of(vectors_of(docs, config), config)
    return clustered, stage(semantic.weighted(semantic.similarity_edges(clustered)), "edges")


def run_pipeline(docs: DataFrame, config: Config = Config()) -> dict[str, DataFrame]:
    """stage -> narrow table (doc_id, domain_l1, domain_l2, nine scores, n_words, copies). Each is written before the next."""
    sig = stage(signals_table(docs, config), "signals").withColumn("copies", F.lit(1))
    out = {"raw": sig}

    def text_of(narrow: DataFrame) -> DataFrame:
        return docs.join(narrow.select("doc_id"), "doc_id", "left_semi")

    english = sig if config.language is None else ingest.keep_language(sig, config.language, config.confidence)
    out["english"] = stage(english, "english")
    best = out["english"].groupBy("digest").agg(F.min("doc_id").alias("doc_id")).select("doc_id")
    out["exact"] = stage(out["english"].join(best, "doc_id", "left_semi"), "exact")
    out["rule"] = out["exact"].where(F.size("rule_hits") == 0)
    if not config.shared_signals:  # the stage-isolated baseline: rules know no domain, the filter sees its own scores
        own = rules.apply_rules(rules.rule_features(text_of(out["exact"])), config.ruleset)
        out["rule"] = out["exact"].join(own.select("doc_id"), "doc_id", "left_semi")
    out["model"] = stage(filters.model_filter(out["rule"], config.thresholds) if config.use_model else out["rule"], "model")
    if config.fuzzy:
        links = stage(fuzzy.fuzzy_links(text_of(out["model"]), theta=config.theta), "fuzzy-links")
        out["fuzzy"] = stage(fuzzy.fuzzy_dedup(out["model"], links), "fuzzy")
    else:
        out["fuzzy"] = out["model"]
    cells = cells_of(vectors_of(text_of(out["fuzzy"]), config), config)
    if config.semantic == "soft":
        gone = semantic.semantic_removed(cells, config.target, config.keep)
        out["semantic"] = stage(out["fuzzy"].join(gone.select(F.col("id").alias("doc_id")), "doc_id", "left_anti"), "semantic")
    elif config.semantic == "hard":
        gone = semantic.hard_removed(semantic.similarity_edges(cells, C.HARD_THRESHOLD)).select(F.col("id").alias("doc_id"))
        out["semantic"] = stage(out["fuzzy"].join(gone, "doc_id", "left_anti"), "semantic")
    else:
        out["semantic"] = out["fuzzy"]
    out["value"] = sampling.value_filter(out["semantic"])
    groups = groups_of(cells.drop("cluster").join(out["semantic"].select("doc_id"), "doc_id", "left_semi"), config)
    out["sampled"] = sample(out["value"], groups, config)
    return out


def sampling_frame(value: DataFrame, clustered: DataFrame, config: Config = Config()) -> DataFrame:
    """Rows with q_n, d_n and s; diversity comes from the groups, a text without a vector has none (d 0)."""
    members = stage(clustered.join(value.select("doc_id"), "doc_id", "left_semi"), "members")
    diversity = sampling.cluster_diversity(members, sampling.label_centroids(members)).select("cluster", "d")
    placed = value.join(members.select("doc_id", "cluster"), "doc_id", "left").join(F.broadcast(diversity), "cluster", "left").withColumn("d", F.coalesce("d", F.lit(0.0)))
    return sampling.sampling_score(placed, config.alpha, config.quality)


def sample(value: DataFrame, clustered: DataFrame, config: Config = Config()) -> DataFrame:
    frame = stage(sampling_frame(value, clustered, config), "frame")
    p = {"power": sampling.power_probabilities, "softmax": sampling.softmax_probabilities, "uniform": sampling.uniform_probabilities}[config.sampler](frame)
    budget = value.agg((F.sum("n_words") * config.budget_factor).alias("b")).first()["b"] or 0.0
    return stage(sampling.draw_copies(p, float(budget)), "sampled").where("copies > 0")


def finish(spark) -> None:
    """Delete all that a run staged, once its results are written elsewhere."""
    drop_staging(spark)


def stage_table(stages: dict[str, DataFrame]) -> DataFrame:
    """(stage, doc_id, tags, scores, n_words, copies) of all stages."""
    cols = ("doc_id", "domain_l1", "domain_l2", *C.SCORES, "n_words", "copies")
    rows = None
    for name in STAGES:
        one = stages[name].select(F.lit(name).alias("stage"), *cols)
        rows = one if rows is None else rows.unionAll(one)
    return rows
