"""Measures: funnel, accuracy, domain shares and shifts, entropy, lexical diversity, values, retention, upsampling."""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import constants as C
from ..functions.text import ratio, tokens


def funnel(stages: Mapping[str, DataFrame], n_words: str = "n_words") -> DataFrame:
    """(pos, stage, docs, words, kept, removed, cumulative): one row a stage, shares against the stage before and the first."""
    rows = None
    for i, (name, df) in enumerate(stages.items()):
        one = df.agg(F.lit(i).alias("pos"), F.lit(name).alias("stage"), F.count("*").alias("docs"), F.coalesce(F.sum(n_words), F.lit(0)).cast("bigint").alias("words"))
        rows = one if rows is None else rows.unionAll(one)
    w = Window.orderBy("pos")  # one row a stage
    before, first = F.lag("docs").over(w), F.first("docs").over(w)
    kept = F.when(before.isNull(), 1.0).otherwise(ratio(F.col("docs"), before))
    return rows.select(
        "pos", "stage", "docs", "words", kept.alias("kept"), (1 - kept).alias("removed"), ratio(F.col("docs"), first).alias("cumulative"),
    )


def shares(df: DataFrame, domain: str = "domain_l1", weight: str | None = None) -> DataFrame:
    """(domain, n, share); ``weight``: e.g. copies of a sampled corpus."""
    n = F.sum(weight).cast("double") if weight else F.count("*").cast("double")
    by = df.groupBy(F.col(domain).alias("domain")).agg(n.alias("n"))
    total = by.agg(F.sum("n").alias("__all"))
    return by.crossJoin(F.broadcast(total)).select("domain", "n", ratio(F.col("n"), F.col("__all")).alias("share"))


def domain_shift(before: DataFrame, after: DataFrame, domain: str = "domain_l1") -> DataFrame:
    """(domain, share_before, share_after, delta, rel_change, filter_rate, rate_vs_overall)."""
    b = shares(before, domain).select("domain", F.col("n").alias("nb"), F.col("share").alias("share_before"))
    a = shares(after, domain).select("domain", F.col("n").alias("na"), F.col("share").alias("share_after"))
    both = b.join(a, "domain", "full").fillna(0.0, ["nb", "na", "share_before", "share_after"])
    overall = both.agg((1 - F.sum("na") / F.sum("nb")).alias("rate"))
    filtered = 1 - ratio(F.col("na"), F.col("nb"))
    return both.crossJoin(F.broadcast(overall)).select(
        "domain", "share_before", "share_after", (F.col("share_after") - F.col("share_before")).alias("delta"),
        ratio(F.col("share_after") - F.col("share_before"), F.col("share_before")).alias("rel_change"),
        filtered.alias("filter_rate"), ratio(filtered, F.col("rate")).alias("rate_vs_overall"),
    )


def top_share(df: DataFrame, domain: str = "domain_l1", k: int = 3) -> DataFrame:
    """(top_share, domains): joint share of the k largest domains."""
    largest = shares(df, domain).orderBy(F.desc("share"), "domain").limit(k)
    return largest.agg(F.sum("share").alias("top_share"), F.count("*").alias("domains"))


def longtail_share(df: DataFrame, domain: str = "domain_l1", niche: Sequence[str] | None = None, k: int = 3) -> DataFrame:
    """Share of the named domains, or of all but the k largest."""
    by = shares(df, domain)
    if niche is not None:
        return by.where(F.col("domain").isin(*niche)).agg(F.coalesce(F.sum("share"), F.lit(0.0)).alias("longtail_share"))
    return top_share(df, domain, k).select((1 - F.col("top_share")).alias("longtail_share"))


def entropy(df: DataFrame, domain: str = "domain_l1", weight: str | None = None) -> DataFrame:
    """(h_bits, domains, h_max)."""
    by = shares(df, domain, weight).where("share > 0")
    return by.agg(F.coalesce(F.sum(-F.col("share") * F.log2("share")), F.lit(0.0)).alias("h_bits"), F.count("*").alias("domains"), F.coalesce(F.log2(F.count("*").cast("double")), F.lit(0.0)).alias("h_max"))


def entropy_by(stages: DataFrame, l1: str = "domain_l1", l2: str = "domain_l2", weight: str = "copies") -> DataFrame:
    """(stage, h_l1, h_l2) of a table of (stage, l1, l2, weight): both levels from one grouping-sets aggregate."""
    by = stages.groupingSets([["stage", l1], ["stage", l2]], "stage", l1, l2).agg(F.sum(weight).cast("double").alias("n"), F.grouping(l1).alias("g1"))
    total = by.groupBy("stage", "g1").agg(F.sum("n").alias("all"))
    h = by.join(total, ["stage", "g1"]).where("n > 0").groupBy("stage").agg(
        F.sum(F.when(F.col("g1") == 0, -(F.col("n") / F.col("all")) * F.log2(F.col("n") / F.col("all")))).alias("h_l1"),
        F.sum(F.when(F.col("g1") == 1, -(F.col("n") / F.col("all")) * F.log2(F.col("n") / F.col("all")))).alias("h_l2"),
    )
    return h


def ngrams(k: Column, n: int) -> Column:
    """n-grams of a column of tokens (a plain column: its expression would run again for every element)."""
    if n == 1:
        return k
    return F.when(F.size(k) >= n, F.transform(F.sequence(F.lit(1), F.size(k) - (n - 1)), lambda i: F.array_join(F.slice(k, i, n), " "))).otherwise(F.array().cast("array<string>"))


def lexical_diversity(df: DataFrame, n: int = 1, text: str = "text", weight: str | None = None, approx: bool = False, by: Sequence[str] = ()) -> DataFrame:
    """(by..., docs, total, unique, r_n, per_doc). Exact: n-grams are counted map-side by hash, then distinct; ``approx``: sketches.

    r_n is null where there are no n-grams.
    """
    w = F.col(weight).cast("bigint") if weight else F.lit(1).cast("bigint")
    docs = df.groupBy(*by).agg(F.sum(w).alias("docs"))
    grams = df.select(*by, w.alias("__w"), tokens(F.col(text)).alias("__k")).where("__w > 0").select(*by, "__w", F.explode(ngrams(F.col("__k"), n)).alias("g"))
    if approx:
        counted = grams.groupBy(*by).agg(F.sum("__w").alias("total"), F.approx_count_distinct("g").alias("unique"))
    else:
        counted = grams.groupBy(*by, F.xxhash64("g").alias("h"), F.xxhash64(F.lit(n), "g").alias("i")).agg(F.sum("__w").alias("c")).groupBy(*by).agg(F.sum("c").alias("total"), F.count("*").alias("unique"))
    joined = docs.join(counted, list(by), "left") if by else docs.crossJoin(counted)
    total, unique = F.coalesce("total", F.lit(0)), F.coalesce("unique", F.lit(0))
    return joined.select(*by, "docs", total.alias("total"), unique.alias("unique"), (unique / F.nullif(total, F.lit(0))).alias("r_n"), ratio(total, F.col("docs")).alias("per_doc"))


def lexical_table(texts: DataFrame, reach: DataFrame, ns: Sequence[int] = (1,), by: str = "stage", key: str = "doc_id", text: str = "text") -> DataFrame:
    """(n, by, docs, total, unique, r_n, per_doc) of several collections of the same documents, for each n.

    ``reach``: (by, key, copies); collections are few (a pass takes 62). Totals come from the documents' lengths; so of an n-gram only its
    128-bit hash and one number, a bit for each collection it is in, are shuffled.
    """
    names = [r[0] for r in reach.select(by).distinct().orderBy(by).collect()]
    if not names:
        return reach.select(F.lit(0).alias("n"), by, *[F.lit(0).cast("long").alias(c) for c in ("docs", "total", "unique")], *[F.lit(0.0).alias(c) for c in ("r_n", "per_doc")]).where("false")
    if len(names) > 62:  # the bits of a number
        halves = (names[:62], names[62:])
        first, rest = (lexical_table(texts, reach.where(F.col(by).isin(half)), ns, by, key, text) for half in halves)
        return first.unionByName(rest)
    cols = [f"c{i}" for i in range(len(names))]
    wide = reach.groupBy(key).agg(*[F.coalesce(F.sum(F.when(F.col(by) == v, F.col("copies"))), F.lit(0)).cast("long").alias(c) for v, c in zip(names, cols, strict=True)])
    docs = wide.agg(*[F.sum(c).alias(f"d{i}") for i, c in enumerate(cols)])
    reached = sum((F.when(F.col(c) > 0, 1 << i).otherwise(0) for i, c in enumerate(cols)), F.lit(0).cast("long"))  # a bit a collection
    words = wide.select(key, *cols, reached.alias("__in")).where(F.col("__in") > 0).join(texts.select(key, text), key).select(*cols, "__in", tokens(F.col(text)).alias("__k"))
    held = words.select(*cols, F.size("__k").alias("__n"))
    totals = held.agg(*[F.coalesce(F.sum(F.col(c) * F.greatest(F.col("__n") - (n - 1), F.lit(0))), F.lit(0)).alias(f"t{n}_{i}") for n in ns for i, c in enumerate(cols)]).first()
    out = None
    for n in ns:
        grams = words.select("__in", F.explode(ngrams(F.col("__k"), n)).alias("g")).select("__in", F.xxhash64("g").alias("a"), F.xxhash64(F.lit(n), "g").alias("b"))
        sums = grams.groupBy("a", "b").agg(F.bit_or("__in").alias("__in"))
        row = sums.agg(*[e for i in range(len(cols)) for e in (F.lit(totals[f"t{n}_{i}"]).cast("long").alias(f"t{i}"), F.count(F.when(F.col("__in").bitwiseAND(1 << i) > 0, 1)).alias(f"u{i}"))]).crossJoin(docs)
        quoted = [str(v).replace("'", "''") for v in names]
        stacked = ", ".join(f"'{v}', d{i}, t{i}, u{i}" for i, v in enumerate(quoted))
        one = row.selectExpr(f"stack({len(names)}, {stacked}) AS ({by}, docs, total, unique)").select(
            F.lit(n).alias("n"), by, "docs", "total", "unique", (F.col("unique") / F.nullif("total", F.lit(0))).alias("r_n"), ratio(F.col("total"), F.col("docs")).alias("per_doc")
        )
        out = one if out is None else out.unionAll(one)
    return out


def composite(weights: Mapping[str, float] | None = None, intercept: float = 0.0) -> Column:
    """Mean of the value scores on [0, 1], or a linear preset."""
    weights = weights or {d: 1 / (3 * len(C.VALUE)) for d in C.VALUE}
    return sum((F.col(d) * w for d, w in weights.items()), F.lit(float(intercept)))


#: A linear fit to the published stage means (inferred, not stated): weights and intercept.
FITTED = ({"education": 0.168, "knowledge": 0.005, "helpfulness": 0.069, "reasoning": 0.106}, 0.107)


def value_profile(df: DataFrame, by: Sequence[str] = (), weight: str | None = None) -> DataFrame:
    """Means of the value scores and of the composite."""
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    mean = lambda c: ratio(F.sum(c * w), F.sum(w))
    return df.groupBy(*by).agg(*[mean(F.col(d)).alias(d) for d in ("education", "knowledge", "helpfulness", "reasoning")], mean(composite()).alias("composite"))


def domain_ratio(df: DataFrame, sets: Mapping[str, Sequence[str]] = C.DOMAIN_SETS, domain: str = "domain_l1", by: Sequence[str] = (), weight: str | None = None) -> DataFrame:
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    return df.groupBy(*by).agg(*[ratio(F.sum(F.when(F.col(domain).isin(*v), w).otherwise(0.0)), F.sum(w)).alias(k) for k, v in sets.items()])


def hq_retention(df: DataFrame, domains: Sequence[str], score: str = "education", cut: int = 2, domain: str = "domain_l1") -> DataFrame:
    """(domain, docs, rate) of the named domains and a row ``mean`` (unweighted)."""
    by = df.where(F.col(domain).isin(*domains)).groupBy(F.col(domain).alias("domain")).agg(F.count("*").alias("docs"), F.avg(F.when(F.col(score) >= cut, 1.0).otherwise(0.0)).alias("rate"))
    return by.unionAll(by.agg(F.lit("mean").alias("domain"), F.coalesce(F.sum("docs"), F.lit(0)).alias("docs"), F.avg("rate").alias("rate")))


def upsampling(sampled: DataFrame, domain: str = "domain_l2", copies: str = "copies", top: int = 20) -> DataFrame:
    """(domain, share, share_after, ratio): the ``top`` domains by ratio of their share after sampling to that before."""
    by = sampled.groupBy(F.col(domain).alias("domain")).agg(F.count("*").cast("double").alias("n"), F.sum(copies).cast("double").alias("m"))
    total = by.agg(F.sum("n").alias("all_n"), F.sum("m").alias("all_m"))
    full = by.crossJoin(F.broadcast(total)).select("domain", ratio(F.col("n"), F.col("all_n")).alias("share"), ratio(F.col("m"), F.col("all_m")).alias("share_after"))
    return full.withColumn("ratio", ratio(F.col("share_after"), F.col("share"))).orderBy(F.desc(F.round("ratio", 9)), "domain").limit(top)


def overlap(df: DataFrame, items: DataFrame, n: int = 8, key: str = "doc_id", item: str = "item_id", text: str = "text") -> DataFrame:
    """(key, item, grams): shared distinct n-grams of documents and (few) benchmark items, whose n-grams are sent to the documents."""
    grams = lambda rows, k: rows.select(k, tokens(F.col(text)).alias("__k")).select(k, F.explode(F.array_distinct(ngrams(F.col("__k"), n))).alias("g"))
    left, right = grams(df, key), grams(items, item)
    return left.join(F.broadcast(right), "g").groupBy(key, item).agg(F.count("*").alias("grams"))
