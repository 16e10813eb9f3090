"""Worked examples, boundaries, properties and odd inputs of the methods."""

import gzip
import hashlib
import math
import os
import random
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from sievework.functions import constants as C
from sievework.functions.sql import register
from sievework.functions.text import tokens
from sievework.operators import filters, fuzzy, ingest, measures, relational, rules, sampling, semantic, signals
from sievework.operators.components import star_forest
from sievework.catalog import ORACLES, QUERIES
from sievework.plans import comparison, pipeline
from sievework.plans.staging import shared_dir, stage, staged_once
from sievework.sources.tables import load, load_files, require, union_snapshots, write_jsonl, write_rejects
from sievework.sources.warc import read_warc, record_bytes
from sievework.streaming import monitor


def edges(spark, rows):
    return semantic.weighted(spark.createDataFrame(rows, "u long, v long, sim double"))


GRAPH = [(1, 2, 0.995), (1, 3, 0.985), (2, 3, 0.97), (3, 4, 0.93)]


def test_vote_worked_example(spark):
    e = edges(spark, GRAPH)
    votes = {r["id"]: (r["score"], r["redundant"]) for r in semantic.soft_vote(e).collect()}
    assert votes == {1: (15, True), 2: (14, True), 3: (16, True), 4: (3, False)}
    assert {r["id"] for r in semantic.redundant_ids(semantic.soft_vote(e), e).collect()} == {2, 3}
    assert {r["id"] for r in semantic.redundant_ids(semantic.soft_vote(e), e, "none").collect()} == {1, 2, 3}
    assert {r["id"] for r in semantic.soft_vote(e, policy="ranked").where("redundant").collect()} == {3}
    assert {r["id"] for r in semantic.hard_removed(e).collect()} == {2, 3}


def test_vote_is_strict_and_monotone(spark):
    e = edges(spark, [(1, 2, 0.98), (1, 3, 0.92)])
    assert not any(r["redundant"] for r in semantic.soft_vote(e).collect())  # exactly ten stays
    graph = edges(spark, GRAPH)
    sizes = [semantic.soft_vote(graph, t).where("redundant").count() for t in (3, 10, 14, 15, 16)]
    assert sizes == sorted(sizes, reverse=True)


def test_band_edges(spark):
    sims = (0.8999, 0.90, 0.92, 0.94, 0.95, 0.96, 0.98, 0.99, 1.0)
    got = [r[0] for r in spark.createDataFrame([(s,) for s in sims], "sim double").select(semantic.band_weight()).collect()]
    assert got == [0, 2, 3, 4, 5, 6, 7, 8, 8]


def test_retained_policy_equals_loop(spark):
    random.seed(5)
    rows = [(a, b, random.uniform(0.9, 1.0)) for a in range(14) for b in range(a + 1, 14) if random.random() < 0.5]
    e = edges(spark, rows)
    weight = {(r["u"], r["v"]): r["weight"] for r in e.collect()}
    kept = {}
    for n in range(14):
        kept[n] = sum(w for (a, b), w in weight.items() if b == n and kept[a]) <= C.TARGET
    got = {r["id"]: not r["redundant"] for r in semantic.soft_vote(e, policy="retained").collect()}
    assert all(kept[k] == v for k, v in got.items())


def test_pruned_votes_decide_alike(spark):
    rows = [(a, b, 0.905) for a in range(30) for b in range(a + 1, 30)]
    e = edges(spark, rows)
    full = {r["id"] for r in semantic.soft_vote(e).where("redundant").collect()}
    cut = semantic.prune_edges(e)
    assert cut.count() == 30 * 6
    assert {r["id"] for r in cut.groupBy("id").agg(F.sum("weight").alias("s")).where("s > 10").collect()} == full


def test_tiles_equal_all_pairs(spark):
    random.seed(1)
    vecs = []
    for i in range(60):
        v = [random.gauss(0, 1) for _ in range(4)]
        n = math.sqrt(sum(x * x for x in v))
        vecs.append((i, 0, [x / n for x in v]))
    df = spark.createDataFrame(vecs, "doc_id long, cluster int, vec array<double>")
    want = {(i, j) for i, _, a in vecs for j, _, b in vecs if i < j and round(sum(x * y for x, y in zip(a, b, strict=True)), 12) >= 0.5}
    for tile in (7, 1000):
        assert {(r["u"], r["v"]) for r in semantic.similarity_edges(df, 0.5, tile).collect()} == want


def test_components(spark):
    random.seed(2)
    pairs = [(random.randrange(300), random.randrange(300)) for _ in range(180)] + [(1000 + i, 1001 + i) for i in range(40)] + [(7, 7)]
    parent = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in pairs:
        x, y = find(a), find(b)
        parent[max(x, y)] = min(x, y)
    got = {r["u"]: r["v"] for r in star_forest(spark.createDataFrame(pairs, "u long, v long")).collect()}
    assert got == {k: find(k) for k in parent if find(k) != k}
    assert star_forest(spark.createDataFrame([], "u long, v long")).count() == 0


def test_power_sampling_example(spark):
    df = spark.createDataFrame([(1, 0.0), (2, 0.5), (3, 1.0)], "doc_id long, s double")
    p = [round(r["p"], 5) for r in sampling.power_probabilities(df).orderBy("doc_id").collect()]
    assert p == [0.0, 0.11178, 0.88822]
    flat = sampling.power_probabilities(df, n=0, k=0).select("p").collect()
    assert all(abs(r[0] - 1 / 3) < 1e-12 for r in flat)
    same = sampling.power_probabilities(spark.createDataFrame([(1, 2.0), (2, 2.0)], "doc_id long, s double")).collect()
    assert [r["p"] for r in same] == [0.5, 0.5]
    sharp = {n: sampling.sampler_profile(f(df)).first()["top_p"] for n, f in (("power", sampling.power_probabilities), ("uniform", sampling.uniform_probabilities))}
    assert sharp["power"] > sharp["uniform"]


def test_harmonic_and_value(spark):
    rows = [(3, 3, 3, 3), (3, 3, 3, 0), (1, 2, 3, 3)]
    df = spark.createDataFrame(rows, "writing int, coherence int, completeness int, logicality int")
    assert [round(r[0], 6) for r in df.select(sampling.writing_quality()).collect()] == [3.0, 0.0, 1.846154]
    v = spark.createDataFrame([(0, 0, 0, 0), (1, 0, 0, 0), (1, 1, 0, 0)], "knowledge int, education int, helpfulness int, reasoning int")
    assert sampling.value_filter(v).count() == 1


def test_draw_meets_budget(spark):
    df = spark.range(4000).select(F.col("id").alias("doc_id"), (F.col("id") % 7 + 1).cast("double").alias("s"), F.lit(10).alias("n_words"))
    drawn = sampling.draw_copies(sampling.power_probabilities(df), 80000).agg(F.sum(F.col("copies") * 10)).first()[0]
    assert abs(drawn - 80000) < 2000
    once = sampling.draw_without_replacement(sampling.power_probabilities(df), 10000)
    assert 9000 <= once.agg(F.sum("n_words")).first()[0] <= 10000
    assert sampling.draw_copies(sampling.power_probabilities(df), 80000, max_copies=1).agg(F.max("copies")).first()[0] <= 1


def test_rules_at_their_cuts(spark):
    names = ("median_word_len", "required_words", "text_len", "bullet_frac", "ellipsis_frac", "word_count", "symbol_ratio", "alpha_ratio")
    clean = dict(zip(names, (5.0, 5, 100, 0.0, 0.0, 100, 0.0, 0.9), strict=True))
    cases = [("word_count", 50, 1), ("word_count", 51, 0), ("symbol_ratio", 0.1, 0), ("symbol_ratio", 0.11, 1), ("alpha_ratio", 0.8, 0), ("alpha_ratio", 0.79, 1), ("bullet_frac", 0.9, 1), ("ellipsis_frac", 0.3, 1), ("text_len", 9999, 0), ("text_len", 10000, 1), ("median_word_len", 3.0, 1), ("required_words", 2, 1)]
    for feature, value, hits in cases:
        row = clean | {feature: value}
        df = spark.createDataFrame([tuple(float(x) for x in row.values())], list(row))
        assert df.select(F.size(rules.hits(rules.ORIGINAL))).first()[0] == hits, (feature, value)


def test_rule_features_of_lines(spark):
    text = "• one two\n- three\nfour..."
    r = rules.rule_features(spark.createDataFrame([(1, text), (2, None), (3, "")], "doc_id long, text string")).orderBy("doc_id").collect()
    assert round(r[0]["bullet_frac"], 4) == 0.6667 and round(r[0]["ellipsis_frac"], 4) == 0.3333
    assert r[1]["word_count"] == r[2]["word_count"] == 0 and r[1]["alpha_ratio"] == 0.0


def test_bypass_and_loosening(spark, sf):
    docs = load(spark, sf, "documents").withColumn("domain_l1", signals.domain_columns()[0])
    feats = rules.rule_features(docs, keep=("doc_id", "domain_l1"))
    kept = rules.apply_rules(feats, rules.ORIGINAL, ("Mathematics",))
    assert kept.where("domain_l1 = 'Mathematics'").count() == docs.where("domain_l1 = 'Mathematics'").count()
    orig = {r[0] for r in rules.apply_rules(feats, rules.ORIGINAL).select("doc_id").collect()}
    assert orig <= {r[0] for r in rules.apply_rules(feats, rules.OPTIMIZED).select("doc_id").collect()}


def test_model_filter_needs_all(spark):
    df = spark.createDataFrame([(1, 3, 3, 3, 1), (2, 0, 3, 3, 1), (3, 3, 3, 3, 0)], "doc_id int, writing int, coherence int, completeness int, safety int")
    assert [r[0] for r in filters.model_filter(df).select("doc_id").collect()] == [1]
    assert [r["first_failure"] for r in filters.model_filter(df, mode="annotate").orderBy("doc_id").collect()] == [None, "writing", "safety"]
    assert filters.model_filter(df, combine="mean", cut=1.0).count() == 3


def test_entropy_and_ngrams(spark, sf):
    docs = load(spark, sf, "documents")
    assert abs(measures.entropy(docs, "source").first()["h_bits"] - math.log2(20)) < 1e-9
    r = [measures.lexical_diversity(spark.createDataFrame([("a a b",)], "text string"), n).first()["r_n"] for n in (1, 2, 4)]
    assert round(r[0], 4) == 0.6667 and r[1] == 1.0 and r[2] is None


def test_minhash_recall_follows_curve(spark):
    random.seed(4)
    rows, i = [], 0
    for _ in range(60):
        base = [f"w{random.randrange(5000)}" for _ in range(120)]
        rows += [(i, " ".join(base)), (i + 1, " ".join(w if random.random() < 0.98 else "x" for w in base))]
        i += 2
    df = spark.createDataFrame(rows, "doc_id long, text string")
    sets = fuzzy.shingle_sets(df)
    exact = {(r["u"], r["v"]) for r in fuzzy.exact_jaccard_pairs(sets, 0.8).collect()}
    found = {(r["u"], r["v"]) for r in fuzzy.fuzzy_links(df, theta=0.8).collect()}
    assert found <= exact and len(found) >= 0.9 * len(exact) and exact


def test_odd_texts(spark):
    rows = [(1, None, None), (2, "", "src0"), (3, "one", "src1"), (4, "word " * 30000, "nowhere")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").withColumn("score", F.lit("extra"))
    assert signals.annotate(df).count() == 4 and rules.rule_features(df).count() == 4
    assert ingest.detect_language(df).count() == 4
    assert fuzzy.fuzzy_dedup(df).count() == 4
    assert semantic.hashed_vectors(df).count() == 2
    empty = df.where("doc_id < 0")
    assert signals.annotate(empty).count() == rules.rule_features(empty).count() == fuzzy.fuzzy_dedup(empty).count() == 0


def test_host_rules(spark):
    pages = spark.createDataFrame([(1, "http://a.spam.example/x"), (2, "http://notspam.example/x"), (3, None)], "page_id long, url string")
    got = ingest.block_urls(pages, spark.createDataFrame([("spam.example",)], "host string")).orderBy("page_id").collect()
    assert [r["reason"] for r in got] == ["host", None, None]


def test_html_modes(spark):
    html = "<html><title>T</title><nav>menu</nav><script>var a='</p>'</script><article><p>Main text with enough words &amp; more of it here.<b>bold</article><footer>f</footer><!-- c -->"
    df = spark.createDataFrame([(1, "u", html), (2, "u", None), (3, "u", "<p>open")], "page_id long, url string, html string")
    for mode in ("strip_all", "article_first", "density"):
        r = ingest.extract_main_text(df, mode).orderBy("page_id").collect()
        assert "Main text with enough words & more" in r[0]["text"] and "menu" not in r[0]["text"] and "var a" not in r[0]["text"] and len(r) == 3


def test_asof_and_joins(spark):
    left = spark.createDataFrame([(1, 10), (1, 5), (2, 7)], "k int, ts long")
    right = spark.createDataFrame([(1, 6, 1.0), (1, 10, 2.0)], "k int, ts long, v double")
    got = {(r["k"], r["ts"]): r["as_value"] for r in relational.asof_join(left, right, "k", "ts", "v").collect()}
    assert got == {(1, 10): 2.0, (1, 5): None, (2, 7): None}
    bands = spark.createDataFrame([(0.0, 2.5), (2.5, 9.0)], "lo double, hi double")
    assert relational.range_join(spark.createDataFrame([(2.5,), (2.4,), (9.0,)], "x double"), bands, "x", "lo", "hi", 1.0).count() == 2


def test_categories_merge(spark):
    df = spark.createDataFrame([("b", [1.0, 0.0]), ("a", [0.99, 0.01]), ("c", [0.0, 1.0])], "tag string, vec array<double>")
    assert {r["tag"]: r["merged"] for r in signals.merge_categories(df, 0.95).collect()} == {"a": "a", "b": "a", "c": "c"}


def test_student_learns(spark, sf):
    rows = load(spark, sf, "documents").select("text", "lang")
    student, history = signals.fit_student(rows, ("lang",), epochs=8)
    assert history[-1]["loss"]["lang"] < history[0]["loss"]["lang"]
    scored = signals.score_student(rows, student)
    assert scored.where("student_lang = lang").count() > 0.8 * scored.count()


def test_sql_surface(spark):
    register(spark)
    row = spark.sql("SELECT harmonic4(1, 2, 3, 3) h, power_weight(0.5, 2, 10, 0.5) p, band_weight(0.97) b").first()
    assert round(row["h"], 6) == 1.846154 and row["p"] == 0.125 and row["b"] == 6
    assert spark.sql("SELECT * FROM shingle('a b c', 2)").count() == 2


def test_sources(spark, tmp_path):
    (tmp_path / "a.warc.gz").write_bytes(gzip.compress(record_bytes("1", "http://x/", "<p>é</p>")) + gzip.compress(record_bytes("2", "http://y/", "z")))
    got = read_warc(spark, str(tmp_path)).orderBy("record_id").collect()
    assert [(r["url"], r["html"]) for r in got] == [("http://x/", "<p>é</p>"), ("http://y/", "z")]
    df = spark.createDataFrame([(1, "a")], "doc_id long, text string")
    write_jsonl(df, str(tmp_path / "j"))
    assert load_files(spark, str(tmp_path / "j"), "json", "doc_id long, text string").drop("_corrupt_record").collect() == df.collect()
    write_rejects(df, str(tmp_path / "r"), F.lit("short"))
    assert spark.read.parquet(str(tmp_path / "r")).count() == 1
    with pytest.raises(ValueError):
        require(df, {"doc_id": "string"})
    assert union_snapshots([df, df.drop("text")]).count() == 2


def test_stream_vote(spark, tmp_path):
    e = semantic.directed(edges(spark, GRAPH)).select("id", "weight")
    e.coalesce(1).write.parquet(str(tmp_path / "e"))
    s = monitor.read_stream(spark, str(tmp_path / "e"), e.schema)
    got = {r["id"]: r["score"] for r in monitor.run_once(monitor.soft_vote_stream(s), "update", "vote").collect()}
    assert got == {1: 15.0, 2: 14.0, 3: 16.0}


def test_pipeline_of_nothing(spark, sf):
    stages = pipeline.run_pipeline(load(spark, sf, "documents").where("doc_id < 0"))
    assert all(stages[n].count() == 0 for n in pipeline.STAGES)


def test_pipeline_stages_shrink(spark, sf):
    stages = pipeline.run_pipeline(load(spark, sf, "documents"))
    ids = [{r[0] for r in stages[n].select("doc_id").collect()} for n in pipeline.STAGES]
    assert all(b <= a for a, b in zip(ids, ids[1:], strict=False)) and ids[-1]


def test_links_of_many_versions_equal_exact_pairs(spark, monkeypatch):
    random.seed(11)
    base = [f"w{i}" for i in range(200)]
    rows = []
    for i in range(80):
        words = list(base)
        for at in random.sample(range(200), 3):
            words[at] = f"x{random.random()}"
        rows.append((i, " ".join(words)))
    rows += [(150 + i, rows[70][1]) for i in range(5)] + [(200 + i, rows[i][1] + " tail") for i in range(3)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    exact = fuzzy.exact_jaccard_pairs(fuzzy.shingle_sets(df), 0.8).cache()
    found = {tuple(sorted(r)) for r in star_forest(exact.select("u", "v")).collect()}
    for tile in (512, 20):
        monkeypatch.setattr(fuzzy, "TILE", tile)
        links = fuzzy.fuzzy_links(df).cache()
        assert {(r["u"], r["v"]) for r in links.collect()} <= {(r["u"], r["v"]) for r in exact.collect()}
        assert {tuple(sorted(r)) for r in star_forest(links.select("u", "v")).collect()} == found
        assert {r["v"] for r in links.collect()} == {r["v"] for r in exact.collect()}
    buckets = fuzzy.lsh_bands(fuzzy.minhash(fuzzy.shingle_sets(df)))
    assert fuzzy.verify(fuzzy.all_candidates(buckets), fuzzy.shingle_sets(df)).count() == exact.count()
    star = fuzzy.verify(fuzzy.star_candidates(buckets), fuzzy.shingle_sets(df))
    assert star_forest(star.select("u", "v")).count() < len(found)


def test_later_crawls_are_compared_with_each_other(spark):
    vec = lambda *x: [v / math.sqrt(sum(y * y for y in x)) for v in x]
    a, b, c = vec(1.0, 0.0), vec(0.0, 1.0), vec(0.1, 1.0)
    rows = [(1, a, [1, 2]), (2, b, [3, 4, 5]), (3, c, [3, 4, 9]), (4, c, [3, 4, 9]), (5, vec(0.05, 1.0), []), (6, vec(0.05, 1.0), [])]
    pages = spark.createDataFrame([(i, "http://x.org/p") for i, _, _ in rows] + [(7, "http://x.org/q")], "page_id long, url string")
    vectors = spark.createDataFrame([(i, v) for i, v, _ in rows] + [(7, b)], "page_id long, vec array<double>")
    sets = spark.createDataFrame([(i, s) for i, _, s in rows] + [(7, [3, 4, 8])], "page_id long, sh array<bigint>")
    got = ingest.near_identical_crawls(pages, vectors, sets)
    assert got.columns == ["url_key", "u", "v", "jaccard", "sim"]
    assert sorted((r["u"], r["v"]) for r in got.collect()) == [(2, 3), (2, 4), (2, 5), (2, 6), (3, 5), (3, 6), (4, 5), (5, 6)]


def _cloud(spark, groups, each, dims=8, noise=0.05, seed=3):
    rng = np.random.default_rng(seed)
    x = np.repeat(rng.normal(size=(groups, dims)), each, 0) + noise * rng.normal(size=(groups * each, dims))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    random.Random(seed).shuffle(rows)
    return spark.createDataFrame(rows, "doc_id long, vec array<double>"), x


def test_cells_are_the_same_in_any_order_and_keep_near_pairs_together(spark):
    df, x = _cloud(spark, 30, 40)
    for flat in (256, 4):  # one level, two levels
        a, b = ({r["doc_id"]: r["cluster"] for r in semantic.kmeans_cells(df.repartition(n), 25, flat=flat).collect()} for n in (1, 7))
        assert a == b and 10 <= len(set(a.values())) <= 40
        near = np.argwhere(np.triu(x @ x.T >= 0.9, 1))
        assert np.mean([a[i] == a[j] for i, j in near]) >= 0.8
    assert {r["cluster"] for r in semantic.kmeans_cells(df, 1).collect()} == {r["cluster_id"] for r in semantic.seed_centroids(df, 1).collect()}
    assert semantic.kmeans_cells(df.where("false"), 3).count() == 0
    assert semantic.cells_for(10) == 1 and semantic.cells_for(10**7) == 153 and semantic.cells_for(10**13) == semantic.CENTROID_VALUES // semantic.DIMS


def test_passes_are_as_good_as_the_library(spark, sf):
    got = {r["method"]: r["mean_square"] for r in QUERIES["kmeans_library"](spark, sf).collect()}
    assert got["passes"] <= 1.05 * got["library"]


@pytest.mark.parametrize("tile", [16384, 37])
def test_bounded_vote_removes_what_all_edges_remove(spark, tile, monkeypatch):
    monkeypatch.setattr(semantic, "BLOCK", 50)
    df, _ = _cloud(spark, 40, 9, noise=0.09)
    cells = df.withColumn("cluster", (F.col("doc_id") / 90).cast("long"))
    edges = semantic.weighted(semantic.similarity_edges(cells)).cache()
    votes = semantic.soft_vote(edges)
    want = {r["id"] for r in semantic.redundant_ids(votes, edges).collect()}
    assert {r["id"] for r in semantic.semantic_removed(cells, tile=tile).collect()} == want and want
    rank = df.select(F.col("doc_id").alias("id"), (-F.col("doc_id")).alias("rank"))
    assert {r["id"] for r in semantic.semantic_removed(cells, tile=tile, order=rank).collect()} == {r["id"] for r in semantic.redundant_ids(votes, edges, order=rank).collect()}


def test_template_cluster_stays_linear(spark):
    n = 20_000
    df = spark.range(n).select(F.col("id").alias("doc_id"), F.lit(0).cast("long").alias("cluster"), F.array(F.lit(1.0), F.lit(0.0)).alias("vec"))
    pruned = semantic.weighted(semantic.vote_edges(df)).groupBy("id").agg(F.count("*").alias("n"), F.sum("weight").alias("s"))
    r = pruned.agg(F.count("*").alias("rows"), F.max("n").alias("most"), F.min("s").alias("least")).first()
    tiles = -(-n // semantic.TILE)
    assert r["rows"] == n and r["most"] <= 6 * tiles and r["least"] > C.TARGET
    assert semantic.semantic_removed(df).count() == n - 1


def test_links_with_colliding_buckets_equal_exact_pairs(spark):
    random.seed(12)
    rows = []
    for i in range(30):
        words = [f"{i}w{random.randrange(10**6)}" for _ in range(120)]
        rows.append((2 * i, " ".join(words)))
        words[random.randrange(120)] = "x"
        rows.append((2 * i + 1, " ".join(words)))
    sets = fuzzy.shingle_sets(spark.createDataFrame(rows, "doc_id long, text string")).cache()
    strangers = sets.select("doc_id", F.lit(0).alias("band"), F.lit(7).cast("long").alias("bucket"))  # all in one bucket
    found = {(r["u"], r["v"]) for r in fuzzy.closed_links(strangers, sets).collect()}
    assert found == {(r["u"], r["v"]) for r in fuzzy.exact_jaccard_pairs(sets, 0.8).collect()} and len(found) == 30


def test_exact_dedup_with_null_and_repeated_ids(spark):
    df = spark.createDataFrame([(1, "a"), (1, "a"), (None, "b"), (None, "b"), (2, "b"), (3, "c"), (None, None)], "doc_id long, text string")
    got = [(r["doc_id"], r["text"], r["copies"]) for r in ingest.exact_dedup(df).collect()]
    assert sorted(got, key=str) == sorted([(1, "a", 2), (None, "b", 3), (3, "c", 1), (None, None, 1)], key=str)


def test_capped_copies_meet_the_budget(spark):
    df = spark.range(1000).select(F.col("id").alias("doc_id"), (F.col("id") % 50).cast("double").alias("s"), F.lit(10).alias("n_words"))
    p = sampling.power_probabilities(df)
    drawn = sampling.draw_copies(p, 12000, max_copies=3)
    row = drawn.agg(F.sum(F.col("expected") * 10).alias("t"), F.max("copies").alias("m")).first()
    assert abs(row["t"] - 12000) < 1e-6 and row["m"] == 3
    full = sampling.draw_copies(p, 10**9, max_copies=3).where("p > 0").agg(F.min("copies")).first()[0]
    assert full == 3


def test_teacher_distributions(spark, sf):
    rows = signals.annotate_soft(load(spark, sf, "documents"), width=0.01)
    for c in C.SCORES:
        mean = F.aggregate(F.transform(f"soft_{c}", lambda x, i: x * i), F.lit(0.0), lambda a, x: a + x)
        r = rows.agg(F.max(F.abs(F.aggregate(f"soft_{c}", F.lit(0.0), lambda a, x: a + x) - 1)).alias("mass"), F.avg(F.abs(mean - F.col(c))).alias("off")).first()
        assert r["mass"] < 1e-9 and r["off"] < 0.1


def test_student_learns_from_distributions(spark, sf):
    rows = signals.annotate_soft(load(spark, sf, "documents"), keep=("doc_id", "text"))
    student, history = signals.fit_student(rows, ("writing", "completeness"), epochs=6, loss="soft")
    assert all(history[-1]["loss"][t] < history[0]["loss"][t] for t in ("writing", "completeness"))
    assert student.tasks["writing"] == [0, 1, 2, 3]
    scored = signals.score_student(rows, student)
    assert scored.where("student_completeness = cast(completeness as string)").count() > 0.5 * scored.count()


def test_student_has_heads_for_all_signals(spark, sf):
    got = {r["task"] for r in QUERIES["student_agreement"](spark, sf).collect()}
    assert got >= {*C.SCORES, "domain_l1", "domain_l2"}


def test_template_model_on_unseen_rows(spark):
    rows = {r["template"]: (r["n"], r["flagged"]) for r in QUERIES["template_model"](spark, "/root/testdata/sf0.01").collect()}
    assert rows[1][1] >= 0.8 * rows[1][0] and rows[0][1] <= 0.05 * rows[0][0]


def test_language_model_on_unseen_rows(spark):
    assert all(r["accuracy"] >= 0.9 for r in QUERIES["language_model"](spark, "/root/testdata/sf0.01").collect())


def test_page_funnel_by_loop(spark, sf):
    pages = load(spark, sf, "pages").collect()
    ok = [r for r in pages if not any((h := (r["url"] or "").lower().split("://")[-1].split("/")[0]) == b or h.endswith("." + b) for b in C.BLOCKED_HOSTS) and not any(w in (r["url"] or "").lower() for w in C.BLOCKED_WORDS)]
    got = {r["stage"]: r["docs"] for r in QUERIES["page_funnel"](spark, sf).collect()}
    assert got == {"extracted": len(pages), "url": len(ok), "exact": len({ingest.dense_text(r["html"])[0] for r in ok})}
    whole = [r["docs"] for r in QUERIES["page_to_sample_funnel"](spark, sf).orderBy("pos").collect()]
    assert whole[:2] == [len(pages), len(ok)] and whole == sorted(whole, reverse=True) and len(whole) == 10


def test_embedding_probes_find_the_prefix_bias(spark, sf):
    got = {r["provider"]: r for r in QUERIES["embedding_probes"](spark, sf).collect()}
    assert got["prefix"]["bias"] > 0.9 and got["word"]["bias"] < 0.1 and got["char"]["auc"] > 0.9


def test_sketches_are_near_the_exact_counts(spark, sf):
    docs = load(spark, sf, "documents")
    exact = measures.lexical_diversity(docs, 2).first()
    assert abs(QUERIES["lexical_diversity_sketch"](spark, sf).first()["unique"] - exact["unique"]) < 0.1 * exact["unique"]
    words = measures.lexical_diversity(docs, 1).first()["unique"]
    assert abs(QUERIES["unique_words_sketch"](spark, sf).first()["unique_words"] - words) < 0.05 * words
    top = {r["g"]: r["docs"] for r in QUERIES["heavy_shingles"](spark, sf).collect()}
    sketch = {r["g"]: r["docs"] for r in QUERIES["heavy_shingles_sketch"](spark, sf).collect()}
    assert sketch and all(n >= min(top.values()) for n in sketch.values())


def test_library_pairs_are_true_and_many(spark, sf):
    exact = {(r["u"], r["v"]) for r in fuzzy.exact_jaccard_pairs(fuzzy.shingle_sets(load(spark, sf, "documents")), 0.8).collect()}
    got = {(r["u"], r["v"]) for r in QUERIES["minhash_library_pairs"](spark, sf).collect()}
    assert got <= exact and len(got) >= 0.8 * len(exact)


def test_word2vec_of_equal_texts(spark):
    df = spark.createDataFrame([(1, "a b c a b"), (2, "a b c a b"), (3, "x y z x y z"), (4, None)], "doc_id long, text string")
    v = {r["doc_id"]: r["vec"] for r in semantic.word2vec_vectors(df, 8).collect()}
    assert np.allclose(v[1], v[2]) and 4 not in v and abs(sum(x * x for x in v[3]) - 1) < 1e-9
    assert QUERIES["word2vec_edges"](spark, "/root/testdata/sf0.001").agg(F.sum("n")).first()[0] > 0


def test_staged_once_is_made_again_when_the_files_change(spark, tmp_path):
    made = []

    def make():
        made.append(1)
        return spark.range(len(made))

    (tmp_path / "t.parquet").mkdir()
    a = staged_once(spark, str(tmp_path), ("t",), "n", make)
    assert staged_once(spark, str(tmp_path), ("t",), "n", make).count() == a.count() == 1
    os.utime(tmp_path / "t.parquet", (1, 1))
    assert staged_once(spark, str(tmp_path), ("t",), "n", make).count() == 2


def test_equal_size_corpora(spark):
    reach = spark.range(3000).select(F.lit("big").alias("arm"), F.col("id").alias("doc_id"), F.lit(2).cast("long").alias("copies")).unionAll(spark.range(500).select(F.lit("small"), "id", F.lit(1).cast("long")))
    got = {r["arm"]: r["n"] for r in comparison.equal_size(reach).groupBy("arm").agg(F.sum("copies").alias("n")).collect()}
    assert got["small"] == 500 and 400 < got["big"] < 600


def test_given_vectors_take_the_place_of_the_provider(spark, sf):
    docs = load(spark, sf, "documents")
    given = load(spark, sf, "embeddings").select(F.col("vec_id").alias("doc_id"), F.col("embedding").alias("vec"))
    stages = pipeline.run_pipeline(docs, pipeline.Config(vectors=given))
    assert stages["semantic"].count() == stages["fuzzy"].count() and stages["sampled"].count() > 0  # no cosine of 0.90 among them


def test_length_quantiles_are_exact(spark, tmp_path):
    """30,011 distinct lengths: more than the sketch of 10,000 held apart."""
    n = 30_011
    spark.range(n).select(F.col("id").alias("doc_id"), (F.col("id") * 7919 % n * 3 + 1).alias("n_chars")).write.parquet(str(tmp_path / "documents.parquet"))
    got = {r["pos"]: r["chars"] for r in QUERIES["length_quantiles"](spark, str(tmp_path)).collect()}
    assert got == {i: (math.ceil(q * n / 10) - 1) * 3 + 1 for i, q in enumerate((1, 5, 9))}


@pytest.mark.parametrize("dims", (4, 160))
def test_counted_pairs_are_those_of_the_edges(spark, dims):
    """By cosine and home, in one tile and in several, with copies; many dimensions go over the bound of the first ones."""
    random.seed(3)
    x = np.array([[random.gauss(0, 1) + 2 * (j % 7 == i % 5) for j in range(dims)] for i in range(90)])
    x = np.concatenate([x / np.sqrt((x * x).sum(1))[:, None]] * 2)[:130]
    rows = [(i, i % 2, i % 3, v.tolist()) for i, v in enumerate(x)]
    df = spark.createDataFrame(rows, "doc_id long, cluster long, home long, vec array<double>")
    for floor in (0.9, 0.2):
        want = {}
        for r in semantic.similarity_edges(df, floor).collect():
            k = 2 * int(r["sim"] >= 0.95) + (r["u"] % 3 == r["v"] % 3)
            want[k] = want.get(k, 0) + 1
        for tile in (11, 1000):
            got = semantic.pair_counts(df, lambda s, same: 2 * (s >= 0.95) + same, floor, tile, home="home")
            assert want and dict(got) == want
    edges = semantic.weighted(semantic.similarity_edges(df)).groupBy("weight").count().collect()
    assert {r["weight"]: r["n"] for r in semantic.band_counts(df).collect()} == {r["weight"]: r["count"] for r in edges}


@pytest.mark.parametrize("name", ("cell_edge_recall", "word2vec_edges"))
def test_counts_of_pairs_make_no_pairs(spark, sf, name, monkeypatch):
    def none(*_, **__):
        raise AssertionError("lists pairs")

    monkeypatch.setattr(semantic, "similarity_edges", none)
    assert QUERIES[name](spark, sf).collect()


def test_nearest_in_clusters_equal_all_pairs(spark):
    """With copies (ties) and small clusters, in one pair of tiles and in several."""
    random.seed(4)
    x = np.array([[random.gauss(0, 1) for _ in range(5)] for _ in range(40)])
    x = np.concatenate([x / np.sqrt((x * x).sum(1))[:, None]] * 2)
    rows = [(i, 9 if i < 2 else i % 3, v.tolist()) for i, v in enumerate(x)]
    sims = np.round(x @ x.T, 9)
    want = set()
    for i, c, _ in rows:
        near = sorted((-sims[i, j], j) for j, cj, _ in rows if cj == c and j != i)[:3]
        want |= {(i, j, -s) for s, j in near}
    df = spark.createDataFrame(rows, "doc_id long, cluster long, vec array<double>")
    for tile in (6, 1000):
        found = semantic.nearest_in_clusters(df, 3, tile=tile)
        assert {tuple(r) for r in found.collect()} == want


@pytest.mark.parametrize("name", ("embedding_pairs_topk", "embedding_benchmark", "embedding_choice", "embedding_probes"))
def test_embedding_queries_list_no_pairs(spark, sf, name, monkeypatch):
    def none(*_, **__):
        raise AssertionError("lists pairs")

    monkeypatch.setattr(semantic, "similarity_edges", none)
    if name in ORACLES and name != "embedding_pairs_topk":
        con = duckdb.connect()
        con.sql(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{sf}/documents.parquet')")
        got, want = QUERIES[name](spark, sf), con.sql(ORACLES[name])
        at = got.columns
        assert sorted(map(str, map(tuple, got.collect()))) == sorted(map(str, want.select(", ".join(at)).fetchall()))
    else:
        assert QUERIES[name](spark, sf).collect()


def test_mean_jaccard_of_arms_pairs_no_copies(spark):
    """Against all pairs, with copies, empty texts and an arm of one row; 3,000 copies of one text cost one class."""
    words = "a b c d e f g h".split()
    random.seed(6)
    texts = [" ".join(random.choices(words, k=k)) for k in (0, 2, 5, 9, 12, 30, 30, 60)] * 3
    rows = [(i, t, True, i % 3 > 0, i == 5) for i, t in enumerate(texts)]
    sets = [{tuple(t.split()[i : i + 3]) for i in range(len(t.split()) - 2)} for t in texts]
    df = spark.createDataFrame(rows, "doc_id long, text string, x boolean, y boolean, z boolean")
    got = {r["arm"]: (r["docs"], r["mean_jaccard"]) for r in fuzzy.mean_jaccard_arms(df, ("x", "y", "z")).collect()}
    for at, arm in ((2, "x"), (3, "y")):
        own = [sets[r[0]] for r in rows if r[at]]
        each = [len(a & b) / max(1, len(a | b)) for i, a in enumerate(own) for b in own[:i]]
        assert got[arm][0] == len(own) and abs(got[arm][1] - sum(each) / len(each)) < 1e-12
    assert got["z"] == (1, None)
    copies = spark.range(3000).select(F.col("id").alias("doc_id"), F.lit("one two three four").alias("text"))
    assert fuzzy.mean_jaccard_exact(copies).first()[0] == 1.0


def test_overlap_shuffles_no_grams_of_documents(spark):
    docs = spark.createDataFrame([(1, "a b c d"), (2, "x b c d"), (3, None)], "doc_id long, text string")
    items = spark.createDataFrame([(7, "b c d e"), (8, "q")], "item_id long, text string")
    found = measures.overlap(docs, items, 2)
    assert {tuple(r) for r in found.collect()} == {(1, 7, 2), (2, 7, 2)}
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "rightHint=(strategy=broadcast)" in plan


def test_lexical_table_shuffles_one_number_a_gram(spark):
    texts = spark.createDataFrame([(1, "a b a"), (2, "b c"), (3, ""), (4, None)], "doc_id long, text string")
    reach = spark.createDataFrame([("x", 1, 2), ("x", 3, 1), ("y", 1, 1), ("y", 2, 3), ("z", 4, 1), ("w", 2, 0)], "stage string, doc_id long, copies long")
    table = measures.lexical_table(texts, reach, (1, 2))
    got = {(r["n"], r["stage"]): (r["docs"], r["total"], r["unique"]) for r in table.collect()}
    assert got == {(1, "x"): (3, 6, 2), (1, "y"): (4, 9, 3), (1, "z"): (1, 0, 0), (1, "w"): (0, 0, 0), (2, "x"): (3, 4, 2), (2, "y"): (4, 5, 3), (2, "z"): (1, 0, 0), (2, "w"): (0, 0, 0)}
    assert "bit_or" in table._jdf.queryExecution().optimizedPlan().toString()
    many = spark.range(130).select(F.concat(F.lit("s"), "id").alias("stage"), F.lit(1).cast("long").alias("doc_id"), F.col("id").alias("copies"))
    assert {r["stage"]: (r["docs"], r["total"], r["unique"]) for r in measures.lexical_table(texts, many).collect()} == {f"s{i}": (i, 3 * i, 2 * (i > 0)) for i in range(130)}


def test_terms_are_those_of_a_loop(spark):
    """All providers and gram sets against plain counting: empty, short and null texts, other scripts."""
    random.seed(9)
    texts = [None, "", "a", "é x", "日本", "😀😀"] + [" ".join(random.choices(["a", "b", "Ça", "日本", "x" * 5], k=k)) for k in (1, 2, 3, 19, 21, 60)] * 3
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    h = lambda w: int(hashlib.md5(w.encode()).hexdigest()[:8], 16)
    plain = {r["doc_id"]: (r["k"], r["c"]) for r in df.select("doc_id", tokens(F.col("text")).alias("k"), F.lower(F.coalesce("text", F.lit(""))).alias("c")).collect()}
    for p in ("word", "bigram", "char", "prefix"):
        for r in semantic.term_counts(df, p).collect():
            k, c = plain[r["doc_id"]]
            want = {"word": k, "prefix": k[:20], "bigram": [f"{a} {b}" for a, b in zip(k, k[1:])] or k, "char": [c[i : i + 3] for i in range(len(c) - 2)] or [c] * bool(c)}[p]
            assert dict(zip(r["h"], r["tf"], strict=True)) == {h(w): n for w, n in Counter(want).items()}
    for n in (1, 3):
        assert semantic.gram_sets(df, n).exceptAll(fuzzy.shingle_sets(df, n)).count() == 0


@pytest.mark.parametrize("name", ("embedding_choice", "embedding_probes"))
def test_providers_leave_no_tables_behind(spark, name):
    """What a provider stages is deleted before the next one's; the duplicates, which queries share, stay."""
    folder = shared_dir(spark).removeprefix("file://")
    before = set(os.listdir(folder)) if os.path.isdir(folder) else set()
    QUERIES[name](spark, "/root/testdata/sf0.001").collect()
    left = {f.rsplit("-", 1)[0] for f in set(os.listdir(folder)) - before}
    assert left <= {"duplicates", "class-pairs", "chimeras"}


def test_prefixes_join_no_shingle_without_partner(spark, monkeypatch):
    """Against all pairs, with cells that many shingles share; what is alone in its cell isn't staged."""
    random.seed(11)
    sets = [sorted({random.randrange(90) for _ in range(random.choice((0, 1, 4, 30)))}) for _ in range(80)] + [list(range(10_000, 10_400))]
    df = spark.createDataFrame([(i, s) for i, s in enumerate(sets)], "doc_id long, sh array<bigint>")
    for cells in (1 << 6, 1 << 16):
        monkeypatch.setattr(fuzzy, "CELLS", cells)
        monkeypatch.setattr(fuzzy, "SLICE", min(cells, 1 << 6))
        made = []
        monkeypatch.setattr(fuzzy, "stage", lambda x, n, made=made: made.append(stage(x, n)) or made[-1])
        got = {(r["u"], r["v"]) for r in fuzzy.exact_jaccard_pairs(df, 0.5).collect()}
        assert got == {(i, j) for i in range(81) for j in range(i + 1, 81) if len({*sets[i]} & {*sets[j]}) >= 0.5 * len({*sets[i]} | {*sets[j]}) > 0}
        assert len(made) == 1 and (cells < 1 << 16 or made[0].where("doc_id = 80").count() == 0)


def test_library_pairs_carry_no_vectors_through_the_tables(spark, tmp_path, monkeypatch):
    """Without the library's join; copies are expanded from one class."""
    from pyspark.ml.feature import MinHashLSHModel

    def none(*_, **__):
        raise AssertionError("joins whole vectors")

    monkeypatch.setattr(MinHashLSHModel, "approxSimilarityJoin", none)
    words = [f"w{i}" for i in range(60)]
    texts = [(7, " ".join(words)), (3, " ".join(words)), (5, " ".join([*words, "x"])), (4, " ".join(words[::-1])), (1, "a b"), (2, "a b"), (6, None)]
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    got = {tuple(r) for r in QUERIES["minhash_library_pairs"](spark, str(tmp_path)).collect()}
    near = round(56 / 57, 6)
    assert (3, 7, 1.0) in got and got <= {(3, 7, 1.0), (3, 5, near), (5, 7, near)} and len(got) in (1, 3)


def test_embedding_quality_of_equal_ranks(spark):
    """Steps of one error have no rank correlation; they don't fail."""
    row = lambda fpr: semantic.embedding_quality(spark.createDataFrame([(k, 10, x) for k, x in enumerate(fpr)], "step int, n long, fpr double")).first()
    assert row([0.5] * 4)["spearman"] is None and row([0.5])["spearman"] is None
    assert abs(row([0.9, 0.5, 0.1])["spearman"] + 1) < 1e-12


def test_embedding_queries_judge_all_pairs_whatever_the_size(spark, sf, monkeypatch):
    """As if there were more rows than one cell takes: the results are those of all pairs all the same."""
    probes = sorted(map(tuple, QUERIES["embedding_probes"](spark, sf).collect()))
    monkeypatch.setattr(semantic, "cells_for", lambda *_, **__: 8)
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{sf}/documents.parquet')")
    got = QUERIES["embedding_benchmark"](spark, sf)
    assert sorted(map(str, map(tuple, got.collect()))) == sorted(map(str, con.sql(ORACLES["embedding_benchmark"]).select(", ".join(got.columns)).fetchall()))
    assert sorted(map(tuple, QUERIES["embedding_probes"](spark, sf).collect())) == probes


def test_pair_counts_at_the_borders_of_kinds(spark, monkeypatch):
    """Cosines at the borders of kinds and at the floor, where single precision can't tell, with a bound and without; all pairs by a loop."""
    rng = np.random.default_rng(3)
    x = rng.normal(size=(40, 160)) * (np.arange(160) < 9)
    x /= np.sqrt((x * x).sum(1))[:, None]
    side = rng.normal(size=x.shape)
    side -= (side * x).sum(1)[:, None] * x
    side /= np.sqrt((side * side).sum(1))[:, None]
    cos = np.array([0.8, 0.9, 0.95, 0.9 + 1e-9, 0.9 - 1e-9] * 8)[:, None]
    x = np.concatenate([x, x[:10], cos * x + np.sqrt(1 - cos * cos) * side])
    df = spark.createDataFrame([(i, 0, v.tolist()) for i, v in enumerate(x)], "doc_id long, cluster long, vec array<double>")
    step = lambda s, _: np.floor(s * 1000).astype(np.int64)
    once, x4 = np.tri(len(x), k=-1, dtype=bool), x.astype(np.float32)
    xl = semantic._led(x4, semantic._turn(x))
    for floor in (0.8, 0.9):
        want = Counter(int(np.floor(s * 1000)) for i in range(len(x)) for j in range(i) if (s := min(round(float(np.einsum("i,i", x[i], x[j])), 12), 1.0)) >= floor)
        assert dict(semantic.pair_counts(df, step, floor, 30)) == want
        for sparse in (0.0, 1.0):
            monkeypatch.setattr(semantic, "SPARSE", sparse)
            got = semantic._block_counts(x, x4, xl, x, x4, xl, once, lambda i, j: i == j, step, floor)
            assert {k: n for k, n in enumerate(got) if n} == want


def test_pairs_far_apart_are_dropped_where_they_meet(spark):
    """All sets in one bucket: no pair of Jaccard 0.8 or more is lost, hardly any other is kept; empty and equal sets."""
    rng = random.Random(6)
    sets = [sorted(rng.sample(range(1 << 20), k)) for k in (300, 300, 40, 4, 0, 0)] * 2
    for base, k in ((0, 30), (0, 33), (0, 34), (1, 120), (2, 4), (3, 1)):
        sets.append(sorted({*sets[base][k:], *rng.sample(range(1 << 20), k if base else 0)}))
    sets += [sorted(rng.sample(range(1 << 20), 300)) for _ in range(60)]
    df = spark.createDataFrame(list(enumerate(sets)), "doc_id long, sh array<long>")
    met = fuzzy.near_in_buckets(df.where(F.size("sh") > 0).select("doc_id", F.lit(1).cast("long").alias("bucket")), df, 0.8)
    got = {tuple(r) for r in met.collect()}
    alike = lambda i, j: len({*sets[i]} & {*sets[j]}) / max(1, len({*sets[i]} | {*sets[j]}))
    near = {(i, j) for i in range(len(sets)) for j in range(i + 1, len(sets)) if alike(i, j) >= 0.8}
    assert near and near <= got and len(got - near) <= 30
