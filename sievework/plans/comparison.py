"""Arms side by side: corpora at equal size, ablations and budgets, all by the same measures."""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import constants as C
from ..functions.text import h32, tokens
from ..operators import filters, fuzzy, ingest, measures, rules, sampling, semantic, signals
from . import pipeline
from .staging import stage

#: Domains whose share of educational documents is reported.
HQ_DOMAINS = ("Computer Science", "Programming", "Mathematics", "Physics")
MEASURES = ("h_l1", "h_l2", "top3_share", "longtail_share", "education", "knowledge", "helpfulness", "reasoning", "composite", *C.DOMAIN_SETS, "hq_mean")


def union(parts: Sequence[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def reach_of(arms: Mapping[str, DataFrame]) -> DataFrame:
    """(arm, doc_id, copies) of tables with doc_id, and copies or one copy each."""
    return union([a.select(F.lit(k).alias("arm"), "doc_id", (F.col("copies") if "copies" in a.columns else F.lit(1)).cast("long").alias("copies")) for k, a in arms.items()])


def measure_arms(reach: DataFrame, sig: DataFrame, texts: DataFrame, ns: Sequence[int] = (1,)) -> DataFrame:
    """One row an arm: docs, entropy of both levels, top-3 and long-tail shares, means of the values, shares of code, mathematics and
    STEM, mean share of educational documents in the STEM domains, and r_n of each n. Copies count as documents.

    ``reach``: (arm, doc_id, copies); ``sig``: scores and tags; ``texts``: (doc_id, text). Arms are few; a text is read once for all.
    """
    reach = stage(reach.where("copies > 0"), "reach")
    rows = stage(reach.join(sig.select("doc_id", "domain_l1", "domain_l2", *C.VALUE), "doc_id"), "arm-signals")
    by = rows.groupBy("arm", "domain_l1").agg(F.sum("copies").cast("double").alias("n"))
    share = by.join(by.groupBy("arm").agg(F.sum("n").alias("all")), "arm").select("arm", "domain_l1", (F.col("n") / F.col("all")).alias("p"))
    tops = share.groupBy("arm").agg(F.slice(F.sort_array(F.collect_list("p"), asc=False), 1, 3).alias("top"))  # a share for each domain
    top = tops.select("arm", F.aggregate("top", F.lit(0.0), lambda s, x: s + x).alias("top3_share")).withColumn("longtail_share", 1 - F.col("top3_share"))
    h = measures.entropy_by(rows.withColumnRenamed("arm", "stage")).withColumnRenamed("stage", "arm")
    values = measures.value_profile(rows, ("arm",), "copies")
    sets = measures.domain_ratio(rows, by=("arm",), weight="copies")
    rate = rows.where(F.col("domain_l1").isin(*HQ_DOMAINS)).groupBy("arm", "domain_l1").agg((F.sum(F.when(F.col("education") >= 2, F.col("copies")).otherwise(0)) / F.sum("copies")).alias("r"))
    out = rows.groupBy("arm").agg(F.sum("copies").alias("docs")).join(h, "arm").join(top, "arm").join(values, "arm").join(sets, "arm").join(rate.groupBy("arm").agg(F.avg("r").alias("hq_mean")), "arm", "left")
    lexical = measures.lexical_table(texts, reach, ns, by="arm")
    for n in ns:
        out = out.join(lexical.where(F.col("n") == n).select("arm", F.col("r_n").alias(f"r_{n}")), "arm", "left")
    return out.select("arm", "docs", *[F.round(c, 6).alias(c) for c in (*MEASURES, *[f"r_{n}" for n in ns])])


def equal_size(reach: DataFrame, seed: str = "eq") -> DataFrame:
    """``reach`` (arm, doc_id, copies) cut to about the size of the smallest arm: each copy stays by a draw from its document and number."""
    each = reach.where("copies > 0").withColumn("i", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))
    sizes = reach.groupBy("arm").agg(F.sum("copies").alias("size")).where("size > 0")
    least = sizes.agg(F.min("size").alias("least"))
    rated = each.join(F.broadcast(sizes.crossJoin(least)), "arm")  # a row an arm
    draw = (h32(F.concat_ws(":", F.lit(seed), "doc_id", "i")) + 0.5) / 4294967296.0
    return rated.where(draw < F.col("least") / F.col("size")).groupBy("arm", "doc_id").agg(F.count("*").alias("copies"))


def corpora(stages: DataFrame, original: DataFrame) -> dict[str, DataFrame]:
    """Our corpus (the sampled stage, copies counted) and stand-ins of the compared ones from the same crawl: all of it, its English part,
    that filtered by one score for education, and by the original rules. ``stages``: the staged funnel; ``original``: (doc_id) that
    the original rules keep."""
    at = lambda name: stages.where(F.col("stage") == name)
    return {
        "raw": at("raw"), "english": at("english"), "education": filters.single_score_filter(at("english"), "education", 3),
        "original_rules": at("english").join(original, "doc_id", "left_semi"), "ours": at("sampled"),
    }


def filter_arms(s: DataFrame) -> dict[str, DataFrame]:
    """``s``: scores, rule_hits, n_orig."""
    return {
        "all": s, "rule_only": filters.cascade(s, ("rule",)), "model_only": filters.cascade(s, ("model",)), "rule_model": filters.cascade(s), "original_rules": s.where("n_orig = 0"),
        "single_score": filters.single_score_filter(s, "writing", 2), "mean_score": filters.model_filter(s, combine="mean", cut=1.5),
    }


def dedup_arms(docs: DataFrame) -> dict[str, DataFrame]:
    """none, exact, then fuzzy, semantic alone, fuzzy with the hard threshold, fuzzy with the soft vote."""
    base = stage(docs.select("doc_id", "text"), "ablation")
    exact = stage(ingest.exact_dedup(base).select("doc_id", "text"), "exact")
    fz = stage(fuzzy.fuzzy_dedup(exact, stage(fuzzy.fuzzy_links(exact), "links")), "fuzzy")
    cells = {k: pipeline.cells_of(pipeline.vectors_of(d)) for k, d in (("exact", exact), ("fuzzy", fz))}
    without = lambda df, gone: df.join(gone.select(F.col("id").alias("doc_id")), "doc_id", "left_anti")
    hard = semantic.hard_removed(semantic.similarity_edges(cells["fuzzy"], C.HARD_THRESHOLD))
    return {
        "none": base, "exact": exact, "fuzzy": fz, "soft_alone": without(exact, semantic.semantic_removed(cells["exact"])),
        "fuzzy_hard": without(fz, hard), "fuzzy_soft": without(fz, semantic.semantic_removed(cells["fuzzy"])),
    }


def sampler_arms(frame, budget: float) -> dict[str, DataFrame]:
    """Drawn corpora at one budget. ``frame(quality, alpha)`` gives the scored rows."""
    base = frame("value", C.ALPHA)
    p = {
        "uniform": sampling.uniform_probabilities(base), "softmax": sampling.softmax_probabilities(base), "power": sampling.power_probabilities(base),
        "quality_only": sampling.power_probabilities(frame("value", 1.0)), "diversity_only": sampling.power_probabilities(frame("value", 0.0)),
        "linear_sum": sampling.power_probabilities(frame("linear_all", C.ALPHA)), "combined": sampling.power_probabilities(frame("combined", C.ALPHA)),
    }
    return {k: sampling.draw_copies(v, budget) for k, v in p.items()}


def rule_stage_shares(before: DataFrame, after: DataFrame) -> DataFrame:
    """(domain, share_before, share_after, share_removed, delta, filter_rate) around the rule stage, with what it removed."""
    shift = measures.domain_shift(before, after).select("domain", "share_before", "share_after", "delta", "filter_rate")
    removed = before.join(after.select("doc_id"), "doc_id", "left_anti")
    gone = measures.shares(removed).select("domain", F.col("share").alias("share_removed"))
    return shift.join(gone, "domain", "left").withColumn("share_removed", F.coalesce("share_removed", F.lit(0.0)))


def model_stage_shares(exact: DataFrame, rule: DataFrame, model: DataFrame) -> DataFrame:
    """(domain, share_exact, share_rule, share_model, rel_change, filter_rate, main_reason): three stages; the relative change, rate and
    main first failure of the model filter by domain (ties by name)."""
    shift = measures.domain_shift(rule, model).select("domain", F.col("share_before").alias("share_rule"), F.col("share_after").alias("share_model"), "rel_change", "filter_rate")
    first = measures.shares(exact).select("domain", F.col("share").alias("share_exact"))
    failed = filters.model_filter(rule.join(model.select("doc_id"), "doc_id", "left_anti"), mode="annotate").where("first_failure is not null")
    reasons = failed.groupBy(F.col("domain_l1").alias("domain"), "first_failure").agg(F.count("*").alias("n"))
    main = reasons.groupBy("domain").agg(F.min(F.struct((-F.col("n")).alias("n"), "first_failure"))["first_failure"].alias("main_reason"))
    return first.join(shift, "domain", "left").join(main, "domain", "left").na.fill(0.0)


def original_kept(docs: DataFrame) -> DataFrame:
    """(doc_id) that the original rules keep."""
    return rules.apply_rules(rules.rule_features(docs), rules.ORIGINAL).select("doc_id")


def arm_signals(docs: DataFrame) -> DataFrame:
    """Scores, tags and hits of both rule sets, one scan."""
    tagged = docs.select("doc_id", "text", signals.domain_columns()[0].alias("domain_l1"), signals.domain_columns()[1].alias("domain_l2"))
    hit = rules.rule_features(tagged, keep=("doc_id", "text", "domain_l1", "domain_l2"))
    marked = hit.select("doc_id", "text", "domain_l1", "domain_l2", rules.hits(rules.OPTIMIZED).alias("rule_hits"), F.size(rules.hits(rules.ORIGINAL)).alias("n_orig"))
    return signals.annotate_quality(marked, keep=("doc_id", "domain_l1", "domain_l2", "rule_hits", "n_orig"))


def page_documents(pages: DataFrame, hosts: DataFrame, words: Sequence[str] = (), mode: str = "density") -> DataFrame:
    """Pages as documents of the funnel: (doc_id, text, lang, source, n_chars) of the main text of pages whose URL passes; the source, from
    which the taxonomy takes its tags, is the host without ``www.`` or ``m.``."""
    kept = ingest.block_urls(ingest.extract_main_text(pages, mode), hosts, words, mode="filter")
    host = F.regexp_replace(ingest.host_of("url"), r"^(www|m)\.", "")
    return kept.select(F.col("page_id").alias("doc_id"), "text", F.lit(None).cast("string").alias("lang"), host.alias("source"), F.length("text").cast("long").alias("n_chars"))


def whole_funnel(spark: SparkSession, pages: DataFrame, hosts: DataFrame, words: Sequence[str], config: pipeline.Config) -> DataFrame:
    """One funnel from raw pages to the sample: extraction, URL blacklist, then every stage of the document pipeline."""
    text = stage(ingest.extract_main_text(pages, "density").withColumn("n_words", F.size(tokens(F.col("text")))), "extracted")
    docs = stage(page_documents(pages, hosts, words), "page-documents")
    stages = pipeline.run_pipeline(docs, config)
    return measures.funnel({"extracted": text, "url": stages["raw"], **{n: stages[n] for n in pipeline.STAGES[1:]}})
