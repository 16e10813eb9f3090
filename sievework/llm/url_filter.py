"""URL filter as a sort-merge range join, DataFrame functions only.

A rule (host, path prefix) holds for the host, all its subdomains, and paths that start with the prefix.
Reversed host labels followed by the path make one string in which each rule is a prefix, that is an
interval of the sorted keys; intervals of prefixes are nested or apart. Each distinct (host, path) gives one
probe for each of its host's suffixes that is a rule's host. Rules and probes are range-partitioned and
sorted together; the sweep carries the last rule that began, and with it the stack of rules it is nested in
(found beforehand); the top of that stack that still covers the probe is its rule. What a range begins with
is carried over from the ranges before it, one row a range.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import stage, table

#: Host, path, verdict.
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
#: Verdict where no rule holds: the list blocks, so what it does not name passes.
DEFAULT = "allow"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Ends a host in a key; sorts before all that hosts and paths hold.
END = "\x01"
RANGES_PER_PARTITION = 1


def host_and_path(url: str) -> tuple[Column, Column]:
    """Host: after the first ``://`` up to ``/ ? #``, A-Z lower-cased; path: on from there up to ``? #``. Else empty."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.expr(f"substring(`{url}`, instr(`{url}`, '://') + 3)")).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    bare = F.substring_index(F.substring_index(rest, "?", 1), "#", 1)
    host = F.substring_index(bare, "/", 1)
    return F.translate(host, UPPER, LOWER), F.substring(bare, F.length(host) + 1, F.length(bare))


def host_key(labels: Column) -> Column:
    return F.concat(F.array_join(F.reverse(labels), "."), F.lit(END))


def rule_table(spark: SparkSession, rules=RULES) -> DataFrame:
    """(host, path, verdict) -> also key and rule text; hosts are lower-cased, repeated rules count once (last verdict by name)."""
    df = spark.createDataFrame(list(rules), "host string, path string, verdict string") if not isinstance(rules, DataFrame) else rules
    df = df.select(F.translate("host", UPPER, LOWER).alias("host"), F.coalesce("path", F.lit("")).alias("path"), "verdict")
    return (
        df.where("host is not null and host <> ''")
        .groupBy("host", "path")
        .agg(F.max("verdict").alias("verdict"))
        .select(
            "host",
            F.concat(host_key(F.split("host", r"\.")), "path").alias("key"),
            F.concat("host", "path").alias("rule"),
            "verdict",
        )
    )


def rule_stacks(rules: DataFrame) -> DataFrame:
    """Each rule's key with the stack of rules it is nested in, itself on top (longest last).

    A rule's own prefixes are looked up among the rules: as many as its key has characters, so nothing is paired.
    """
    prefixes = rules.select(
        F.col("key").alias("inner"),
        F.explode(F.sequence(F.lit(1), F.length("key"))).alias("n"),
    ).select("inner", F.expr("substring(inner, 1, n)").alias("key"))
    return (
        prefixes.join(rules, "key")
        .groupBy("inner")
        .agg(F.array_sort(F.collect_list(F.struct(F.length("key").alias("n"), "key", "rule", "verdict"))).alias("stack"))
        .select(F.col("inner").alias("key"), "stack")
    )


def match_rules(probes: DataFrame, rules: DataFrame) -> DataFrame:
    """(key, ...) probes -> the probes that a rule's key is a prefix of, with ``hit`` (its longest such rule)."""
    spark = probes.sparkSession
    starts = rule_stacks(rules).select("key", F.lit(0).alias("kind"), "stack", *[F.lit(None).cast(t).alias(c) for c, t in probes.dtypes if c != "key"])
    marks = probes.select("key", F.lit(1).alias("kind"), F.lit(None).cast(starts.schema["stack"].dataType).alias("stack"), *[c for c in probes.columns if c != "key"])
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions"))) * RANGES_PER_PARTITION
    spread = F.xxhash64(*[c for c in probes.columns if c != "key"])
    ranged = stage(
        starts.unionAll(marks).repartitionByRange(n, "key", "kind", spread).withColumn("range", F.spark_partition_id()),
        "url-ranges",
    )
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)  # one row a range
    carried = (
        ranged.groupBy("range")
        .agg(F.max_by("stack", F.when(F.col("kind") == 0, F.col("key"))).alias("stack"))
        .select("range", F.last("stack", ignorenulls=True).over(before).alias("carried"))
    )
    sweep = Window.partitionBy("range").orderBy("key", "kind").rowsBetween(Window.unboundedPreceding, 0)
    swept = ranged.withColumn("open", F.last("stack", ignorenulls=True).over(sweep)).where("kind = 1")
    covering = F.filter(F.coalesce("open", "carried"), lambda r: F.col("key").startswith(r["key"]))
    return (
        swept.join(carried, "range")
        .select(*probes.columns, F.try_element_at(covering, F.lit(-1)).alias("hit"))
        .where("hit is not null")
    )


def judge_urls(df: DataFrame, rules: DataFrame, default: str = DEFAULT, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """One row for each input row: id, host, path, rule (null where none holds), verdict.

    The longest rule that holds wins (characters of host and path; on a tie the longer host). A null url or one without
    ``://`` has empty host and path and gets ``default``. Repeated urls are judged once; rows with null or repeated
    ids stay rows of their own; an empty table gives no rows; other columns are ignored.
    """
    host, path = host_and_path(url_col)
    pages = df.select(F.col(id_col), host.alias("host"), path.alias("path"))
    urls = pages.where("host <> ''").groupBy("host", "path").agg(F.lit(1).alias("one"))
    labels = F.split("host", r"\.")
    suffixes = F.transform(
        F.sequence(F.lit(1), F.size(labels)), lambda i: F.slice(labels, i, F.size(labels))
    )
    probes = urls.select("host", "path", F.explode(suffixes).alias("suffix")).select(
        F.concat(host_key(F.col("suffix")), "path").alias("key"), "host", "path"
    )
    hits = (
        match_rules(probes, rules)
        .groupBy("host", "path")
        .agg(F.max_by("hit", F.struct(F.length("hit.rule"), F.instr("hit.key", END))).alias("hit"))
        .select("host", "path", F.col("hit.rule").alias("rule"), F.col("hit.verdict").alias("verdict"))
    )
    # Rows without a host, perhaps very many, are spread: no hit has their key. The hits are staged, so that both sides of the join
    # are plain exchanges and an address with very many rows can be split.
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    spread = F.when(F.col("host") == "", F.pmod(F.xxhash64(id_col), F.lit(n))).otherwise(F.lit(0)).cast("int")
    hits = stage(hits, "url-hits").withColumn("__part", F.lit(0)).hint("merge")  # they grow with the rows: never broadcast
    return pages.withColumn("__part", spread).join(hits, ["host", "path", "__part"], "left").select(
        id_col, "host", "path", "rule", F.coalesce("verdict", F.lit(default)).alias("verdict")
    )


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(table(spark, sf_dir, "pages"), rule_table(spark))


OP3_SQL = """
WITH u AS (
  SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages
), b AS (SELECT page_id, split_part(split_part(coalesce(rest, ''), '?', 1), '#', 1) AS bare FROM u
), p AS (
  SELECT page_id, translate(split_part(bare, '/', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         substr(bare, length(split_part(bare, '/', 1)) + 1) AS path FROM b
), r(rh, rp, v) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')
), m AS (
  SELECT p.page_id, rh || rp AS rule, v, row_number() OVER (PARTITION BY p.page_id ORDER BY length(rh || rp) DESC, length(rh) DESC) AS k
  FROM p JOIN r ON (p.host = rh OR p.host LIKE '%.' || rh) AND starts_with(p.path, rp)
)
SELECT p.page_id, p.host, p.path, m.rule, coalesce(m.v, 'allow') AS verdict
FROM p LEFT JOIN m ON m.page_id = p.page_id AND m.k = 1
"""
