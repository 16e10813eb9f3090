"""Ablations, comparison corpora, a proxy language model, and published arithmetic on the given tables."""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import constants as C
from ..functions.text import h32, tokens
from ..operators import filters, ingest, measures, rules, sampling, signals
from ..sources.tables import assemble_conversations, load
from .staging import stage

#: Stage and the printed share of the stage before (percent). Documents have no address, so the URL stage isn't here.
PAPER_SHARES = (("raw", None), ("exact", 22.4), ("rule", 87.3), ("model", 68.1), ("fuzzy", 34.2), ("semantic", 80.6))
_rows = ", ".join(f"({i}, '{s}', {'NULL' if p is None else p})" for i, (s, p) in enumerate(PAPER_SHARES))
#: Over ``stage_docs`` (stage, doc_id).
PAPER_SQL = f""", pr(pos, stage, printed) AS (VALUES {_rows}),
pc AS (SELECT pr.pos, pr.stage, count(doc_id) docs, CAST(any_value(printed) AS DOUBLE) printed FROM pr LEFT JOIN stage_docs USING (stage) GROUP BY pr.pos, pr.stage),
ps AS (SELECT *, round(100.0 * docs / nullif(lag(docs) OVER (ORDER BY pos), 0), 3) computed FROM pc)
SELECT pos, stage, docs, printed, computed, coalesce(abs(computed - printed) <= 0.3, true) AS close FROM ps"""
#: Over ``ms`` (domain_l1, quality, and a column of each arm that tells whether it keeps the document).
MACRO_SQL = " UNION ALL ".join(
    f" SELECT '{k}' arm, count(*) tasks, round(avg(x), 3) mean FROM (SELECT domain_l1, 100.0 * avg(CASE WHEN {k} = (quality = 1) THEN 1.0 ELSE 0.0 END) x FROM ms GROUP BY 1)"
    for k in ("rule_only", "model_only", "rule_model", "original_rules", "single_score", "mean_score")
)


def paper_funnel(stages: DataFrame) -> DataFrame:
    """Shares of the funnel's stages (stage, doc_id) against the stage before, with the printed ones; close: within 0.3 points."""
    from pyspark.sql import Window

    printed = stages.sparkSession.createDataFrame([(i, s, p) for i, (s, p) in enumerate(PAPER_SHARES)], "pos int, stage string, printed double")
    rows = printed.join(stages.groupBy("stage").agg(F.count("*").alias("docs")), "stage", "left").withColumn("docs", F.coalesce("docs", F.lit(0)))
    computed = F.round(100.0 * F.col("docs") / F.nullif(F.lag("docs").over(Window.orderBy("pos")), F.lit(0)), 3)  # one row a stage
    shares = rows.select("pos", "stage", "docs", "printed", computed.alias("computed"))
    return shares.withColumn("close", F.coalesce(F.abs(F.col("computed") - F.col("printed")) <= 0.3, F.lit(True)))


def macro_accuracy(labelled: DataFrame, arms: Mapping[str, DataFrame]) -> DataFrame:
    """(arm, tasks, mean): of each arm (tables of the documents it keeps) the accuracy against ``quality``, in percent, as the plain mean
    over the domains. ``labelled``: (doc_id, domain_l1, quality)."""
    kept = _union([a.select("doc_id", F.lit(k).alias("arm"), F.lit(1).alias("kept")) for k, a in arms.items()])
    grid = labelled.select("doc_id", "domain_l1", "quality", F.explode(F.array(*map(F.lit, arms))).alias("arm"))
    right = F.coalesce("kept", F.lit(0)) == F.when(F.col("quality") == 1, 1).otherwise(0)
    by = grid.join(kept, ["doc_id", "arm"], "left").groupBy("arm", "domain_l1").agg((100.0 * F.avg(F.when(right, 1.0).otherwise(0.0))).alias("x"))
    return by.groupBy("arm").agg(F.count("*").alias("tasks"), F.round(F.avg("x"), 3).alias("mean"))


def _union(parts: Sequence[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def sampler_ablation(frame: DataFrame, others: Mapping[str, DataFrame]) -> DataFrame:
    """(arm, expected value, presentation, entropy of tags, sharpness): the same frame and draws in all arms."""
    arms = {"uniform": sampling.uniform_probabilities(frame), "softmax": sampling.softmax_probabilities(frame), "power": sampling.power_probabilities(frame)}
    arms |= {k: sampling.power_probabilities(v) for k, v in others.items()}
    parts = []
    for name, p in arms.items():
        p = p.withColumn("value", sampling.content_value()).withColumn("presentation", sampling.writing_quality())
        tags = p.groupBy("domain_l1").agg(F.sum("p").alias("m")).where("m > 0").agg(F.sum(-F.col("m") * F.log2("m")).alias("h_l1"))
        means = p.agg(F.sum(F.col("p") * F.col("value")).alias("value"), F.sum(F.col("p") * F.col("presentation")).alias("presentation"))
        parts.append(means.crossJoin(tags).crossJoin(sampling.sampler_profile(p)).select(F.lit(name).alias("arm"), *[F.round(c, 6).alias(c) for c in ("value", "presentation", "h_l1", "entropy_bits", "effective_size", "top_p")]))
    return _union(parts)


def corpora(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """(key, text, tag) stand-ins of the compared corpora: raw, English, single-score filtered, pages, conversations."""
    docs = load(spark, sf_dir, "documents")
    raw = docs.select(F.col("doc_id").alias("key"), "text", signals.domain_columns()[0].alias("tag"), "lang")
    scored = signals.annotate_quality(docs).select(F.col("doc_id").alias("key"), "writing")
    pages = ingest.extract_main_text(load(spark, sf_dir, "pages"), "strip_all").select(F.col("page_id").alias("key"), "text", F.element_at(F.split(ingest.host_of("url"), r"\."), -1).alias("tag"))
    talks = assemble_conversations(load(spark, sf_dir, "conversations")).select(F.col("conv_id").alias("key"), "text", F.concat(F.lit("turns"), F.least("turns", F.lit(8))).alias("tag"))
    return {
        "raw": raw.drop("lang"), "english": raw.where("lang = 'en'").drop("lang"),
        "single_score": filters.single_score_filter(raw.join(scored, "key"), "writing", 3).select("key", "text", "tag"), "pages": pages, "conversations": talks,
    }


def corpus_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(corpus, docs, top3_share, h_tag, r_1) at about equal sizes: rows whose hash is under least size / own size."""
    sets = corpora(spark, sf_dir)
    sizes = {k: v.count() for k, v in sets.items()}
    least = min(n for n in sizes.values() if n)
    parts = []
    for name, df in sets.items():
        if not sizes[name]:
            continue
        own = df.where((h32(F.concat(F.lit("eq:"), F.col("key").cast("string"))) + 0.5) / 4294967296.0 < least / sizes[name])
        lex = measures.lexical_diversity(own, 1).select("docs", "r_n")
        parts.append(lex.crossJoin(measures.top_share(own, "tag").select("top_share")).crossJoin(measures.entropy(own, "tag").select("h_bits")).select(F.lit(name).alias("corpus"), "docs", F.round("top_share", 6).alias("top3_share"), F.round("h_bits", 6).alias("h_tag"), F.round("r_n", 6).alias("r_1")))
    return _union(parts)


def proxy_language_models(spark: SparkSession, sf_dir: str, mix: float = 0.7) -> DataFrame:
    """(arm, train_docs, bits): cross-entropy per word of interpolated bigram models on the benchmark items.

    Documents that share an 8-gram with an item aren't trained on. A proxy of data quality; not the published measure.
    """
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    items = load(spark, sf_dir, "benchmark")
    clean = docs.join(measures.overlap(docs, items).select("doc_id").distinct(), "doc_id", "left_anti")
    sig = signals.annotate_quality(clean)
    hits = rules.rule_features(clean).select("doc_id", rules.hits(rules.OPTIMIZED).alias("rule_hits"))
    both = stage(sig.join(hits, "doc_id").join(clean, "doc_id"), "proxy")
    arms = {"all": both, "rule": filters.cascade(both, ("rule",)), "model": filters.cascade(both, ("model",)), "rule_model": filters.cascade(both)}
    train = stage(_union([a.select(F.lit(k).alias("arm"), "doc_id", "text") for k, a in arms.items()]), "proxy-arms")
    words = train.select("arm", tokens(F.col("text")).alias("k"))
    uni = words.select("arm", F.explode("k").alias("w")).groupBy("arm", "w").agg(F.count("*").alias("c"))
    total = uni.groupBy("arm").agg(F.sum("c").alias("all"), F.count("*").alias("v"))
    test = items.select(tokens(F.col("text")).alias("k")).select(F.explode(measures.ngrams(F.col("k"), 2)).alias("g")).select("g", F.split("g", " ")[0].alias("a"), F.split("g", " ")[1].alias("w"))
    asked = F.broadcast(test.select("g").distinct())  # the bigrams of few items: no other bigram's count is read
    big = words.select("arm", F.explode(measures.ngrams(F.col("k"), 2)).alias("g")).join(asked, "g", "left_semi").groupBy("arm", "g").agg(F.count("*").alias("cg"))
    rows = test.join(train.select("arm").distinct(), how="cross")
    scored = (
        rows.join(big, ["arm", "g"], "left")
        .join(uni.select("arm", F.col("w").alias("a"), F.col("c").alias("ca")), ["arm", "a"], "left")
        .join(uni, ["arm", "w"], "left")
        .join(F.broadcast(total), "arm")
    )
    p1 = (F.coalesce("c", F.lit(0)) + 1.0) / (F.col("all") + F.col("v") + 1)
    p2 = F.coalesce(F.col("cg") / F.col("ca"), F.lit(0.0))
    bits = scored.groupBy("arm").agg(F.round(-F.avg(F.log2(mix * p2 + (1 - mix) * p1)), 6).alias("bits"))
    return train.groupBy("arm").agg(F.count("*").alias("train_docs")).join(bits, "arm")
