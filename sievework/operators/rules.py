"""Heuristic rules: features, the original and the optimised set, domain bypass, calibration and retirement.

All features come from one projection; a rule set compiles to one column of hits, so filtering is a single map stage.
"""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import constants as C
from ..functions.text import lines, ratio, words


def rule_features(df: DataFrame, text: str = "text", keep: Sequence[str] = ("doc_id",)) -> DataFrame:
    """One row for each input row; null texts count as empty (all counts 0, all shares 0)."""
    body = F.coalesce(F.col(text), F.lit(""))
    arrays = df.select(*keep, body.alias("__t"), words(body).alias("__w"), lines(body).alias("__l"))
    sizes = arrays.withColumn("__s", F.array_sort(F.transform("__w", F.length)))
    n = F.size("__w")
    middle = (F.element_at("__s", F.floor((n + 1) / 2).cast("int")) + F.element_at("__s", (F.floor(n / 2) + 1).cast("int"))) / 2.0
    share = lambda f: ratio(F.size(F.filter("__l", f)), F.size("__l"))
    letters = F.length(F.regexp_replace("__t", r"[^\p{L}]", ""))
    return sizes.select(
        *keep,
        F.when(n > 0, middle).otherwise(F.lit(0.0)).alias("median_word_len"),
        F.size(F.filter("__w", lambda w: F.lower(w).isin(*C.REQUIRED))).alias("required_words"),
        F.length("__t").alias("text_len"),
        share(lambda x: F.ltrim(x).rlike(r"^[•*\-]")).alias("bullet_frac"),
        share(lambda x: F.rtrim(x).rlike(r"(\.\.\.|…)$")).alias("ellipsis_frac"),
        n.alias("word_count"),
        ratio(F.length(F.regexp_replace("__t", "[^#…]", "")) + (F.length("__t") - F.length(F.regexp_replace("__t", r"\.\.\.", ""))) / 3, n).alias("symbol_ratio"),
        ratio(letters, F.length("__t")).alias("alpha_ratio"),
        ratio(letters, F.length(F.regexp_replace("__t", r"\s", ""))).alias("alpha_nonspace"),
        ratio(F.size(F.filter("__w", lambda w: w.rlike(r"\p{L}"))), n).alias("alpha_word"),
        ratio(F.aggregate("__s", F.lit(0), lambda a, x: a + x), n).alias("mean_word_len"),
        (1 - F.when(F.size("__l") > 0, ratio(F.size(F.array_distinct("__l")), F.size("__l"))).otherwise(1.0)).alias("dup_line_frac"),
        ratio(F.length(F.regexp_replace("__t", r"[^.,;:!?]", "")), F.length("__t")).alias("punct_density"),
        ratio(F.length(F.regexp_replace("__t", r"[\p{L}\p{N}\s]", "")), F.length("__t")).alias("special_ratio"),
        share(lambda x: F.length(x) < 30).alias("short_line_frac"),
    )


def family_features(df: DataFrame, text: str = "text", keep: Sequence[str] = ("doc_id",)) -> DataFrame:
    """``rule_features`` with the shares that only the unchanged rules read: dup_para_frac (paragraphs that repeat another) and
    top_bigram_frac (the most frequent pair of words, of all pairs)."""
    body = F.coalesce(F.col(text), F.lit(""))
    paras = F.filter(F.split(body, r"\n\s*\n"), lambda x: F.trim(x) != "")
    first = df.select(*keep, text, paras.alias("__p"), words(body).alias("__v"))
    pairs = F.when(F.size("__v") > 1, F.transform(F.sequence(F.lit(1), F.size("__v") - 1), lambda i: F.array_join(F.slice("__v", i, 2), " "))).otherwise(F.array().cast("array<string>"))
    sorted_ = first.select(*keep, text, (1 - F.when(F.size("__p") > 0, ratio(F.size(F.array_distinct("__p")), F.size("__p"))).otherwise(1.0)).alias("dup_para_frac"), F.array_sort(pairs).alias("__g"))
    zero = F.struct(F.lit("").alias("last"), F.lit(0).alias("run"), F.lit(0).alias("best"))

    def count(state, gram):
        run = F.when(gram == state["last"], state["run"] + 1).otherwise(1)
        return F.struct(gram.alias("last"), run.alias("run"), F.greatest(state["best"], run).alias("best"))

    more = sorted_.select(*keep, text, "dup_para_frac", ratio(F.aggregate("__g", zero, count, lambda st: st["best"]), F.size("__g")).alias("top_bigram_frac"))
    return rule_features(more, text, (*keep, "dup_para_frac", "top_bigram_frac"))


@dataclass(frozen=True)
class Rule:
    """``feature op cut`` drops the document."""

    name: str
    feature: str
    op: str
    cut: float

    def hit(self, cut: Column | None = None) -> Column:
        x, c = F.col(self.feature), F.lit(self.cut) if cut is None else cut
        return {"<=": x <= c, "<": x < c, ">=": x >= c, ">": x > c}[self.op]


ORIGINAL = (
    Rule("median_word_length", "median_word_len", "<=", 3),
    Rule("required_words", "required_words", "<=", 2),
    Rule("text_length", "text_len", ">=", 10000),
    Rule("bullet_lines", "bullet_frac", ">=", 0.9),
    Rule("ellipsis_lines", "ellipsis_frac", ">=", 0.3),
    Rule("word_count", "word_count", "<=", 50),
    Rule("symbol_ratio", "symbol_ratio", ">", 0.1),
    Rule("alphabetic_ratio", "alpha_ratio", "<", 0.8),
)
OPTIMIZED = (
    Rule("word_count", "word_count", "<=", 25),
    Rule("symbol_ratio", "symbol_ratio", ">", 0.38),
    Rule("alphabetic_ratio", "alpha_ratio", "<", 0.26),
)
#: Members of the public rule family that neither set changes.
UNCHANGED = (
    Rule("mean_word_length_low", "mean_word_len", "<", 3),
    Rule("mean_word_length_high", "mean_word_len", ">", 12),
    Rule("duplicate_lines", "dup_line_frac", ">", 0.3),
    Rule("special_characters", "special_ratio", ">", 0.25),
    Rule("duplicate_paragraphs", "dup_para_frac", ">", 0.3),
    Rule("top_bigram", "top_bigram_frac", ">", 0.2),
    Rule("short_lines", "short_line_frac", ">", 0.67),
    Rule("little_punctuation", "punct_density", "<", 0.002),
)


def with_alpha_unit(rules: Iterable[Rule], unit: str) -> tuple[Rule, ...]:
    """The alphabetic rule by ``char``, ``nonspace`` or ``word``."""
    feature = {"char": "alpha_ratio", "nonspace": "alpha_nonspace", "word": "alpha_word"}[unit]
    return tuple(Rule(r.name, feature, r.op, r.cut) if r.feature.startswith("alpha") else r for r in rules)


def hits(rules: Iterable[Rule]) -> Column:
    """Names of the rules that drop a document, as one array column over ``rule_features``."""
    return F.array_compact(F.array(*[F.when(r.hit(), F.lit(r.name)) for r in rules])) if rules else F.array().cast("array<string>")


def apply_rules(features: DataFrame, rules: Sequence[Rule], bypass: Sequence[str] = (), domain: str = "domain_l1", mode: str = "filter", thresholds: DataFrame | None = None) -> DataFrame:
    """Filter or annotate a table of features.

    Documents of the ``bypass`` domains are not tested. ``thresholds`` (domain, rule, value) overrides cuts for its domains; it
    has a row for each domain and rule of a taxonomy, so it is a map of bounded size and travels as a broadcast join.
    """
    df = features
    if thresholds is not None:
        table = thresholds.groupBy("domain").agg(F.map_from_entries(F.collect_list(F.struct("rule", "value"))).alias("__cuts"))
        df = df.join(F.broadcast(table), df[domain] == table["domain"], "left").drop(table["domain"])
        found = F.array_compact(F.array(*[F.when(r.hit(F.coalesce(F.col("__cuts")[r.name], F.lit(float(r.cut)))), F.lit(r.name)) for r in rules]))
    else:
        found = hits(rules)
    skip = F.col(domain).isin(*bypass) if bypass else F.lit(False)
    out = df.withColumn("bypassed", F.coalesce(skip, F.lit(False))).withColumn("rule_hits", F.when(F.col("bypassed"), F.array().cast("array<string>")).otherwise(found))
    if thresholds is not None:
        out = out.drop("__cuts")
    return out if mode == "annotate" else out.where(F.size("rule_hits") == 0)


def rule_accuracy(annotated: DataFrame, labels: DataFrame, by_rule: bool = True) -> DataFrame:
    """(rule or ``all``, removed, labelled, precision, hq_recall).

    Precision: low-quality share of the labelled documents removed. Recall: share of high-quality ones that are kept.
    """
    marked = annotated.select("doc_id", "rule_hits").join(labels.select("doc_id", "quality"), "doc_id", "left")
    names = F.concat(F.array(F.lit("all")), F.col("rule_hits")) if by_rule else F.array(F.lit("all"))
    good = marked.agg(F.sum(F.when(F.col("quality") == 1, 1).otherwise(0)).alias("good"))
    counted = (
        marked.where(F.size("rule_hits") > 0)
        .select(F.explode(names).alias("rule"), "quality")
        .groupBy("rule")
        .agg(F.count("*").alias("removed"), F.count("quality").alias("labelled"), F.sum(F.when(F.col("quality") == 0, 1).otherwise(0)).alias("bad"), F.sum(F.when(F.col("quality") == 1, 1).otherwise(0)).alias("lost"))
    )
    return counted.crossJoin(F.broadcast(good)).select("rule", "removed", "labelled", (F.col("bad") / F.nullif("labelled", F.lit(0))).alias("precision"), (1 - F.col("lost") / F.nullif("good", F.lit(0))).alias("hq_recall"))


def calibration_curve(labelled: DataFrame, rule: Rule, grid: Sequence[float]) -> DataFrame:
    """(cut, removed, bad, good, precision, hq_recall) of each cut of a small grid, in one pass over (feature, quality)."""
    sums = []
    for i, cut in enumerate(grid):
        hit = rule.hit(F.lit(float(cut)))
        for name, q in (("bad", 0), ("good", 1)):
            sums.append(F.sum(F.when(hit & (F.col("quality") == q), 1).otherwise(0)).alias(f"{name}{i}"))
    total = F.sum(F.when(F.col("quality") == 1, 1).otherwise(0)).alias("all_good")
    row = labelled.agg(*sums, total)
    stacked = ", ".join(f"{float(c)}D, bad{i}, good{i}" for i, c in enumerate(grid))
    return row.selectExpr("all_good", f"stack({len(grid)}, {stacked}) AS (cut, bad, good)").select(
        "cut", (F.col("bad") + F.col("good")).alias("removed"), "bad", "good",
        (F.col("bad") / F.nullif(F.col("bad") + F.col("good"), F.lit(0))).alias("precision"),
        (1 - F.col("good") / F.nullif("all_good", F.lit(0))).alias("hq_recall"),
    )


def calibrate(curve: DataFrame, min_precision: float, min_recall: float) -> DataFrame:
    """The cut that removes most among those that meet both floors (none: no row); ties to the lower cut."""
    ok = curve.where((F.col("precision") >= min_precision) & (F.col("hq_recall") >= min_recall) & (F.col("removed") > 0))
    return ok.orderBy(F.desc("removed"), "cut").limit(1)


def retire_rules(stats: DataFrame, floor: float) -> DataFrame:
    """Rules to drop: labelled precision below ``floor`` (unlabelled rules stay)."""
    return stats.where((F.col("rule") != "all") & (F.col("precision") < floor))


def template_score(features: DataFrame) -> Column:
    """Linear template and advertisement score over the rule features, as a probability."""
    z = -4.0 + 8 * F.col("special_ratio") + 6 * F.col("dup_line_frac") + 2 * F.col("short_line_frac") + 10 * F.greatest(F.lit(0.0), 0.7 - F.col("alpha_ratio"))
    return 1 / (1 + F.exp(-z))


def fit_template_model(df: DataFrame, text: str = "text", label: str = "template", features: int = 1 << 15):
    """Trained template and advertisement classifier (pyspark.ml): hashed words, word pairs and signs, logistic regression. ``label``:
    1 for templated text. The model's ``probability`` is the score."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF, NGram, RegexTokenizer, SQLTransformer, VectorAssembler

    stages = [
        SQLTransformer(statement=f"SELECT *, coalesce({text}, '') AS __t, CAST({label} AS DOUBLE) AS __y FROM __THIS__"),
        RegexTokenizer(inputCol="__t", outputCol="__w", pattern=r"\w+|[^\w\s]", gaps=False), NGram(n=2, inputCol="__w", outputCol="__g"),
        HashingTF(inputCol="__w", outputCol="__a", numFeatures=features, binary=True), HashingTF(inputCol="__g", outputCol="__b", numFeatures=features, binary=True),
        VectorAssembler(inputCols=["__a", "__b"], outputCol="__f"), LogisticRegression(featuresCol="__f", labelCol="__y", maxIter=30, regParam=0.01),
    ]
    return Pipeline(stages=stages).fit(df)


def deciles(features: DataFrame, feature: str, parts: int = 10) -> DataFrame:
    """(bucket, n, low, high) by a sketch of quantiles: no global sort."""
    cuts = features.agg(F.percentile_approx(feature, [i / parts for i in range(1, parts)], 10000).alias("cuts"))
    bucket = F.size(F.filter("cuts", lambda c: F.col(feature) > c))
    return features.crossJoin(F.broadcast(cuts)).groupBy(bucket.alias("bucket")).agg(F.count("*").alias("n"), F.min(feature).alias("low"), F.max(feature).alias("high"))


def running_share(curve: DataFrame) -> DataFrame:
    """Share of removals up to each cut of a (small) calibration curve."""
    w = Window.orderBy("cut").rowsBetween(Window.unboundedPreceding, 0)
    return curve.withColumn("upto", F.sum("removed").over(w))
