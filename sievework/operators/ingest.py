"""Ingest: main text of pages, language identification, exact dedup, URL blacklist and normalisation."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import ratio, tokens
from ..plans.staging import stage

#: Elements whose content is never main text, and block elements that end a line.
DROPPED = ("script", "style", "noscript", "nav", "header", "footer", "aside", "form")
BLOCKS = ("p", "div", "article", "section", "li", "ul", "ol", "h1", "h2", "h3", "h4", "h5", "h6", "tr", "table", "br", "main", "body")
ENTITIES = (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&"))
#: Function words that stand for a language.
STOPWORDS = {
    "en": ("the", "of", "and", "to", "in", "is", "that", "for", "it", "with", "was", "on", "be"),
    "de": ("der", "die", "und", "das", "ist", "nicht", "von", "mit", "sich", "zu", "den", "für", "ein"),
    "fr": ("le", "la", "et", "les", "des", "est", "que", "pour", "dans", "qui", "une", "du", "sur"),
    "es": ("el", "que", "los", "del", "las", "por", "con", "una", "para", "su", "al", "y", "se"),
}


def strip_html(html: Column) -> Column:
    """Text of a page by replacement only: drops comments, dropped elements and tags, decodes common entities."""
    out = F.regexp_replace(F.coalesce(html, F.lit("")), r"(?s)<!--.*?-->", " ")
    for name in DROPPED:
        out = F.regexp_replace(out, rf"(?is)<{name}\b.*?</{name}\s*>", " ")
    out = F.regexp_replace(out, r"(?s)<[^>]*>", " ")
    for code, char in ENTITIES:
        out = F.replace(out, F.lit(code), F.lit(char))
    return F.trim(F.regexp_replace(out, r"[ \t\r\n]+", " "))


def article_text(html: Column) -> Column:
    """Text of the first ``article`` element; of the whole page where there is none."""
    inner = F.regexp_extract(F.coalesce(html, F.lit("")), r"(?is)<article\b[^>]*>(.*?)</article\s*>", 1)
    return F.when(inner != "", strip_html(inner)).otherwise(strip_html(html))


class _Blocks(HTMLParser):
    """Blocks of a page with the length of their text and of the text inside links."""

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.skip = self.link = 0
        self.title, self.in_title = "", False
        self.blocks: list[list] = [["", 0, 0]]

    def handle_starttag(self, tag, attrs):
        if tag in DROPPED or tag == "div" and any("ad" in (v or "").split() or (v or "").startswith("ad-") for k, v in attrs if k in ("class", "id")):
            self.skip += 1
        elif self.skip and tag == "div":
            self.skip += 1
        self.link += tag == "a"
        self.in_title |= tag == "title"
        if tag in BLOCKS:
            self.blocks.append(["", 0, 0])
        self.blocks[-1][2] += 1

    def handle_endtag(self, tag):
        if self.skip and (tag in DROPPED or tag == "div"):
            self.skip -= 1
        self.link = max(0, self.link - (tag == "a"))
        if tag == "title":
            self.in_title = False
        if tag in BLOCKS:
            self.blocks.append(["", 0, 0])

    def handle_data(self, data):
        if self.in_title:
            self.title += data
        elif not self.skip:
            self.blocks[-1][0] += data
            self.blocks[-1][1] += len(data) if self.link else 0


def dense_text(html: str | None, least: int = 20, links: float = 0.5) -> tuple[str, str, int]:
    """(text, title, blocks dropped): blocks with enough text for their tags and few linked characters."""
    parser = _Blocks()
    parser.feed(html or "")
    parser.close()
    kept, dropped = [], 0
    for text, linked, tags in parser.blocks:
        text = " ".join(text.split())
        if not text:
            continue
        if len(text) >= least * max(1, min(tags, 3)) ** 0.5 and linked <= links * len(text):
            kept.append(text)
        else:
            dropped += 1
    return "\n".join(kept), " ".join(parser.title.split()), dropped


def extract_main_text(df: DataFrame, mode: str = "density", html: str = "html", keep: Sequence[str] = ("page_id", "url")) -> DataFrame:
    """(keep..., text, title, n_removed). Modes: ``strip_all``, ``article_first`` (native), ``density`` (parsed, by batch)."""
    if mode in ("strip_all", "article_first"):
        text = strip_html(F.col(html)) if mode == "strip_all" else article_text(F.col(html))
        title = F.trim(F.regexp_extract(F.coalesce(html, F.lit("")), r"(?is)<title\b[^>]*>(.*?)</title\s*>", 1))
        return df.select(*keep, text.alias("text"), title.alias("title"), (F.length(F.coalesce(html, F.lit(""))) - F.length(text)).cast("int").alias("n_removed"))
    schema = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in keep) + ", text string, title string, n_removed int"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [dense_text(h) for h in batch.column(len(keep)).to_pylist()]
            cols = [pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.string(), pa.string(), pa.int32()))]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], *cols], [*keep, "text", "title", "n_removed"])

    return df.select(*keep, html).mapInArrow(run, schema)


def language_scores(text: Column, stopwords: dict[str, Sequence[str]] = STOPWORDS) -> dict[str, Column]:
    words = tokens(text)
    count = lambda own: F.size(F.filter(words, lambda w: w.isin(*own)))
    return {k: count(v) for k, v in stopwords.items()}


def detect_language(df: DataFrame, text: str = "text", stopwords: dict[str, Sequence[str]] = STOPWORDS) -> DataFrame:
    """``df`` with lang_guess and lang_conf: the language whose function words are most of those found (smoothed share).

    Ties go to the first language by name; a text with no function word has ``und`` and confidence 0.
    """
    marked = df
    for k, c in language_scores(F.col(text), stopwords).items():
        marked = marked.withColumn(f"__{k}", c)
    total = sum((F.col(f"__{k}") for k in stopwords), F.lit(0))
    best = F.array_max(F.array(*[F.struct(F.col(f"__{k}").alias("n"), F.lit(-i).alias("i"), F.lit(k).alias("k")) for i, k in enumerate(sorted(stopwords))]))
    return marked.withColumn("lang_guess", F.when(total > 0, best["k"]).otherwise("und")).withColumn("lang_conf", (best["n"] / (total + 1.0)).cast("double")).drop(*[f"__{k}" for k in stopwords])


def fit_language_model(df: DataFrame, text: str = "text", label: str = "lang", features: int = 4096):
    """Character 3-gram multinomial logistic regression (pyspark.ml): a pipeline model whose ``probability`` is the confidence."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF, NGram, RegexTokenizer, StringIndexer

    stages = [
        RegexTokenizer(inputCol=text, outputCol="__c", pattern="", toLowercase=True), NGram(n=3, inputCol="__c", outputCol="__g"),
        HashingTF(inputCol="__g", outputCol="__f", numFeatures=features), StringIndexer(inputCol=label, outputCol="__y"),
        LogisticRegression(featuresCol="__f", labelCol="__y", maxIter=20, regParam=1e-3),
    ]
    return Pipeline(stages=stages).fit(df)


def keep_language(df: DataFrame, lang: str = "en", least: float = 0.5, guess: str = "lang_guess", conf: str = "lang_conf") -> DataFrame:
    """Strictly over ``least``."""
    return df.where((F.col(guess) == lang) & (F.col(conf) > least))


def digest(text: str = "text", normalize: str = "none") -> Column:
    body = F.coalesce(F.col(text), F.lit(""))
    body = {"none": body, "whitespace": F.trim(F.regexp_replace(body, r"\s+", " ")), "lower": F.lower(body)}[normalize]
    return F.sha2(body, 256)


def exact_groups(df: DataFrame, key: str = "doc_id", text: str = "text", normalize: str = "none", order: Column | None = None) -> DataFrame:
    """(digest, keep, copies): only ids and digests are shuffled, copies combine map-side. ``order``: least is kept."""
    rank = F.struct((order if order is not None else F.col(key)).alias("o"), F.col(key).alias("k"))
    return df.select(digest(text, normalize).alias("digest"), rank.alias("r")).groupBy("digest").agg(F.min("r").alias("r"), F.count("*").alias("copies")).select("digest", F.col("r.k").alias("keep"), "copies")


def exact_dedup(df: DataFrame, key: str = "doc_id", text: str = "text", normalize: str = "none", order: Column | None = None) -> DataFrame:
    """``df`` with one row of each digest and its number of copies. Null keys rank first; of rows that repeat a key and a digest one
    stays. Ids and digests are joined back, null-safe, and the last step keeps that partitioning."""
    groups = exact_groups(df, key, text, normalize, order).select(F.col("digest").alias("__digest"), F.col("keep").alias("__keep"), "copies")
    marked = df.withColumn("__digest", digest(text, normalize))
    return marked.join(groups, (marked["__digest"] == groups["__digest"]) & marked[key].eqNullSafe(groups["__keep"])).drop(groups["__digest"]).drop("__keep").dropDuplicates(["__digest"]).drop("__digest")


def host_of(url: str) -> Column:
    """Lower-cased host without port or user."""
    rest = F.regexp_extract(F.lower(F.coalesce(url, F.lit(""))), r"^[a-z][a-z0-9+.\-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1)
    return rest


def block_urls(df: DataFrame, hosts: DataFrame, words: Sequence[str] = (), url: str = "url", key: str = "page_id", mode: str = "annotate") -> DataFrame:
    """``df`` with ``reason``: ``host`` if the host or a parent domain is listed, ``pattern`` if the URL has a word, else null.

    The page's parent domains (a few) are looked up; the list is joined by its key, broadcast if Spark finds it small.
    """
    labels = F.split(host_of(url), r"\.")
    parents = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    listed = hosts.select(F.lower("host").alias("__h")).distinct()
    hit = df.select(F.col(key).alias("__k"), F.explode(parents).alias("__h")).join(listed, "__h", "left_semi").select("__k").distinct().withColumn("__hit", F.lit(True))
    pattern = F.lower(url).rlike("|".join(words)) if words else F.lit(False)
    reason = F.when(F.col("__hit"), "host").when(pattern, "pattern")
    out = df.join(hit, df[key] == hit["__k"], "left").withColumn("reason", reason).drop("__k", "__hit")
    return out if mode == "annotate" else out.where("reason is null").drop("reason")


def normalize_url(url: str) -> Column:
    """Lower-cased host without ``www.`` or ``m.``, path without a closing slash, query parts sorted, no scheme or fragment."""
    u = F.regexp_replace(F.coalesce(url, F.lit("")), r"#.*$", "")
    path = F.regexp_replace(F.regexp_extract(u, r"^[^:]*://[^/?]*([^?]*)", 1), r"/+$", "")
    query = F.array_join(F.array_sort(F.filter(F.split(F.regexp_extract(u, r"\?(.*)$", 1), "&"), lambda p: (p != "") & ~p.startswith("utm_"))), "&")
    return F.concat(F.regexp_replace(host_of(url), r"^(www|m)\.", ""), path, F.when(query != "", F.concat(F.lit("?"), query)).otherwise(""))


def redundant_crawls(pages: DataFrame, url: str = "url", key: str = "page_id") -> DataFrame:
    """(url_key, crawls, first): addresses that were crawled more than once."""
    return pages.groupBy(normalize_url(url).alias("url_key")).agg(F.count("*").alias("crawls"), F.min(key).alias("first")).where("crawls > 1")


def text_share(extracted: DataFrame, pages: DataFrame) -> DataFrame:
    """Share of a page's bytes that is main text, by mode of extraction."""
    return extracted.join(pages.select("page_id", "html"), "page_id").agg(ratio(F.sum(F.length("text")), F.sum(F.length("html"))).alias("text_share"))


def near_identical_crawls(pages: DataFrame, vectors: DataFrame, sets: DataFrame, theta: float = 0.8, floor: float = 0.9) -> DataFrame:
    """(url_key, u, v, jaccard, sim): crawls of one address that stay under the LSH threshold though their vectors are alike.

    All crawls of an address are compared, through tiles of bounded size. Equal ones (vector and shingles) are compared once, by
    their least id: a pair of such classes gives a row from each crawl of one class to the least of the other.
    """
    from ..functions.text import jaccard
    from .semantic import similarity_edges

    keyed = pages.select("page_id", normalize_url("url").alias("url_key"))
    again = keyed.groupBy("url_key").agg(F.count("*").alias("n")).where("n > 1").select("url_key")
    rows = keyed.join(again, "url_key").join(vectors, "page_id").join(sets, "page_id").withColumn("same", F.xxhash64("vec", "sh"))
    rows = stage(rows.select("page_id", "url_key", "vec", "sh", "same"), "crawls")
    reps = stage(rows.groupBy("url_key", "same").agg(F.min("page_id").alias("rep")), "crawl-classes")
    kept = rows.join(reps.select(F.col("rep").alias("page_id")), "page_id", "left_semi")
    edges = similarity_edges(kept.select("page_id", "vec", F.col("url_key").alias("cluster")), floor, key="page_id")
    sides = {side: kept.select(F.col("page_id").alias(side), F.col("sh").alias(f"sh_{side}"), *(["url_key"] if side == "u" else [])) for side in "uv"}
    scored = edges.join(sides["u"], "u").join(sides["v"], "v").select("url_key", "u", "v", jaccard(F.col("sh_u"), F.col("sh_v")).alias("jaccard"), "sim")
    links = stage(scored.where(F.col("jaccard") < theta), "crawl-links")
    members = rows.join(reps, ["url_key", "same"]).where("page_id > rep").select("rep", "page_id", "url_key", "sh")
    out = links
    for side, other in ("uv", "vu"):
        more = links.join(members.select(F.col("rep").alias(side), F.col("page_id").alias("m")), side)
        out = out.unionAll(more.select("url_key", F.least("m", other).alias("u"), F.greatest("m", other).alias("v"), "jaccard", "sim"))
    # Equal texts too short for a shingle have no Jaccard.
    short = members.where((F.size("sh") == 0) & F.lit(theta > 0)).select("url_key", F.col("rep").alias("u"), F.col("page_id").alias("v"), F.lit(0.0).alias("jaccard"), F.lit(1.0).alias("sim"))
    return out.unionAll(short)
