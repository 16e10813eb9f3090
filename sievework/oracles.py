"""SQL that checks the queries: common table expressions in DuckDB's dialect, written apart from the operators."""

from __future__ import annotations

from .functions import constants as C
from .operators import fuzzy, rules

LF = "chr(10)"


def h32(x: str) -> str:
    return f"CAST('0x' || substr(md5({x}), 1, 8) AS BIGINT)"


def h60(x: str) -> str:
    return f"CAST('0x' || substr(md5({x}), 1, 15) AS BIGINT)"


def words(t: str) -> str:
    return f"list_filter(regexp_split_to_array(coalesce({t}, ''), '\\s+'), lambda x: x <> '')"


def toks(t: str) -> str:
    return f"regexp_extract_all(lower(coalesce({t}, '')), '[\\p{{L}}\\p{{N}}_]+')"


def lines(t: str) -> str:
    return f"list_filter(string_split(coalesce({t}, ''), {LF}), lambda x: trim(x) <> '')"


def ratio(a: str, b: str) -> str:
    return f"coalesce(CAST({a} AS DOUBLE) / nullif(CAST({b} AS DOUBLE), 0), 0)"


def count_of(t: str, pattern: str) -> str:
    """Characters of a class, by removing all others."""
    return f"length(regexp_replace({t}, '{pattern}', '', 'g'))"


def in_list(xs) -> str:
    return "(" + ", ".join(f"'{x}'" for x in xs) + ")"


def flags(*cs: str) -> str:
    return "(" + " + ".join(f"CASE WHEN {c} THEN 1 ELSE 0 END" for c in cs) + ")"


def cte(*parts: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(p for p in parts)


def shapes(src: str = "documents", name: str = "shapes") -> str:
    per = ratio("n_words", "sentences")
    return f"""{name}_a AS (SELECT doc_id, coalesce(text, '') t, {words('text')} w, {toks('text')} k, {lines('text')} l FROM {src}),
{name} AS (SELECT doc_id, len(w) n_words, len(l) n_lines,
 {ratio(count_of('t', '[^\\p{Lu}]'), count_of('t', '[^\\p{L}]'))} upper_share,
 {ratio(count_of('t', '[^%$#&*|]'), 'len(w)')} symbols,
 {ratio("len(list_filter(l, lambda x: regexp_matches(rtrim(x), '[.!?]$')))", 'len(l)')} terminal,
 {ratio('len(list_distinct(l))', 'len(l)')} line_variety, {ratio('len(list_distinct(k))', 'len(k)')} token_variety,
 {ratio(f"len(list_filter(k, lambda x: x IN {in_list(C.FUNCTION_WORDS)}))", 'len(k)')} function_share,
 {ratio('len(list_filter(w, lambda x: length(x) >= 8))', 'len(w)')} long_share,
 {count_of('t', '[^.!?]')} sentences, {count_of('t', '[^,]')} commas,
 len(list_filter({list_of(C.TOXIC)}, lambda x: list_contains(k, x))) toxic_words, regexp_matches(rtrim(t), '[.!?]$') closed FROM {name}_a),
signals AS (SELECT doc_id, n_words,
 {flags('upper_share < 0.3', 'symbols < 0.1', 'terminal >= 0.5')} writing,
 {flags('token_variety >= 0.25', 'line_variety >= 0.7', 'n_lines >= 2')} coherence,
 {flags('n_words >= 50', 'closed', 'n_words >= 200')} completeness,
 {flags('function_share >= 0.05', 'function_share >= 0.15', 'sentences >= 3')} logicality,
 CASE WHEN toxic_words = 0 THEN 1 ELSE 0 END safety,
 {flags('long_share >= 0.1', 'long_share >= 0.2', 'long_share >= 0.35')} knowledge,
 {flags(f'{per} >= 4 AND {per} <= 40', 'n_words >= 100', 'function_share >= 0.1')} education,
 {flags('n_lines >= 3', 'n_words >= 150', 'token_variety >= 0.5')} helpfulness,
 {flags('commas >= 3', f"{ratio('commas', 'sentences')} >= 0.3", 'n_words >= 300')} reasoning FROM {name})"""


def list_of(xs) -> str:
    return "[" + ", ".join(f"'{x}'" for x in xs) + "]"


DOMAIN_MAP = "dmap(source, l1) AS (VALUES " + ", ".join(f"('{k}', '{v}')" for k, v in C.DOMAINS.items()) + ")"
TAGS = DOMAIN_MAP + """,
tags AS (SELECT d.doc_id, coalesce(m.l1, 'Other') domain_l1, coalesce(m.l1, 'Other') || '/' || coalesce(d.source, 'unknown') domain_l2
 FROM documents d LEFT JOIN dmap m ON m.source = d.source)"""


def features(src: str = "documents") -> str:
    letters = count_of("t", "[^\\p{L}]")
    ell = "(length(t) - length(replace(t, '...', ''))) / 3"
    return f"""rf_a AS (SELECT doc_id, coalesce(text, '') t, {words('text')} w, {lines('text')} l FROM {src}),
rf_b AS (SELECT *, list_sort(list_transform(w, lambda x: length(x))) s, len(w) n FROM rf_a),
rf AS (SELECT doc_id,
 CASE WHEN n > 0 THEN (s[CAST(floor((n + 1) / 2.0) AS INT)] + s[CAST(floor(n / 2.0) AS INT) + 1]) / 2.0 ELSE 0 END median_word_len,
 len(list_filter(w, lambda x: lower(x) IN {in_list(C.REQUIRED)})) required_words, length(t) text_len,
 {ratio("len(list_filter(l, lambda x: regexp_matches(ltrim(x), '^[•*\\-]')))", 'len(l)')} bullet_frac,
 {ratio("len(list_filter(l, lambda x: regexp_matches(rtrim(x), '(\\.\\.\\.|…)$')))", 'len(l)')} ellipsis_frac,
 n word_count, {ratio(f"{count_of('t', '[^#…]')} + {ell}", 'n')} symbol_ratio,
 {ratio(letters, 'length(t)')} alpha_ratio, {ratio(letters, count_of('t', '\\s'))} alpha_nonspace,
 {ratio("len(list_filter(w, lambda x: regexp_matches(x, '\\p{L}')))", 'n')} alpha_word,
 {ratio('coalesce(list_sum(s), 0)', 'n')} mean_word_len,
 1 - CASE WHEN len(l) > 0 THEN {ratio('len(list_distinct(l))', 'len(l)')} ELSE 1 END dup_line_frac,
 {ratio(count_of('t', '[^.,;:!?]'), 'length(t)')} punct_density,
 {ratio(count_of('t', '[\\p{L}\\p{N}\\s]'), 'length(t)')} special_ratio,
 {ratio("len(list_filter(l, lambda x: length(x) < 30))", 'len(l)')} short_line_frac FROM rf_b)"""


def family(src: str = "documents") -> str:
    """fam(doc_id, dup_para_frac, top_bigram_frac)."""
    return f"""fam_a AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '\\n\\s*\\n'), lambda x: trim(x) <> '') p, {words('text')} w FROM {src}),
fam_b AS (SELECT doc_id, p, list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) g FROM fam_a),
fam AS (SELECT doc_id, 1 - CASE WHEN len(p) > 0 THEN {ratio('len(list_distinct(p))', 'len(p)')} ELSE 1 END dup_para_frac,
 CASE WHEN len(g) > 0 THEN list_max(map_values(list_histogram(g))) / CAST(len(g) AS DOUBLE) ELSE 0 END top_bigram_frac FROM fam_b)"""


def rule_case(r: rules.Rule) -> str:
    return f"CASE WHEN {r.feature} {r.op} {r.cut} THEN '{r.name}' END"


def rule_hits(rs) -> str:
    return "list_filter([" + ", ".join(rule_case(r) for r in rs) + "], lambda x: x IS NOT NULL)"


def language(src: str = "documents") -> str:
    from .operators.ingest import STOPWORDS

    names = sorted(STOPWORDS)
    counts = ", ".join(f"len(list_filter({toks('text')}, lambda x: x IN {in_list(STOPWORDS[k])})) n_{k}" for k in names)
    total = " + ".join(f"n_{k}" for k in names)
    top = "greatest(" + ", ".join(f"n_{k}" for k in names) + ")"
    case = " ".join(f"WHEN n_{k} = {top} THEN '{k}'" for k in names)
    return f"""lang_a AS (SELECT doc_id, {counts} FROM {src}),
lang AS (SELECT doc_id, CASE WHEN {total} > 0 THEN CASE {case} END ELSE 'und' END lang_guess, {top} / ({total} + 1.0) lang_conf FROM lang_a)"""


def shingle_sets(src: str, n: int, name: str = "sh") -> str:
    gram = h32(f"array_to_string(k[i:i + {n - 1}], ' ')")
    return f"""{name}_k AS (SELECT doc_id, {toks('text')} k FROM {src}),
{name} AS MATERIALIZED (SELECT doc_id, list_distinct(list_transform(range(1, len(k) - {n - 2}), lambda i: {gram})) s FROM {name}_k)"""


def fuzzy_pairs(src: str, n: int = fuzzy.SHINGLE, perms: int = fuzzy.PERMUTATIONS, bands: int = fuzzy.BANDS, theta: float = fuzzy.THETA) -> str:
    maps = ", ".join("({}, {}, {})".format(i, *fuzzy.permutation(i)) for i in range(perms))
    r = perms // bands
    return f"""{shingle_sets(src, n)},
maps(i, a, b) AS (VALUES {maps}),
sh_flat AS (SELECT doc_id, unnest(s) g FROM sh),
sig AS (SELECT doc_id, i, min((a * (g % {fuzzy.PRIME}) + b) % {fuzzy.PRIME}) m FROM sh_flat, maps GROUP BY ALL),
buckets AS (SELECT doc_id, i // {r} band, {h60("string_agg(CAST(m AS VARCHAR), ':' ORDER BY i)")} bucket FROM sig GROUP BY doc_id, i // {r}),
least AS (SELECT band, bucket, min(doc_id) u FROM buckets GROUP BY ALL HAVING count(*) > 1),
cands AS (SELECT DISTINCT l.u, b.doc_id v FROM buckets b JOIN least l USING (band, bucket) WHERE b.doc_id > l.u),
jac AS (SELECT u, v, len(list_intersect(a.s, b.s)) * 1.0 / (len(a.s) + len(b.s) - len(list_intersect(a.s, b.s))) jaccard
 FROM cands JOIN sh a ON a.doc_id = u JOIN sh b ON b.doc_id = v),
links AS (SELECT * FROM jac WHERE jaccard >= {theta})"""


def components(links: str, name: str = "comp") -> str:
    """(doc_id, root) of all ends of links."""
    return f"""{name}_e AS (SELECT u a, v b FROM {links} UNION SELECT v, u FROM {links}),
{name}_r(doc_id, root) AS (SELECT DISTINCT a, a FROM {name}_e UNION SELECT e.b, r.root FROM {name}_r r JOIN {name}_e e ON e.a = r.doc_id WHERE r.root < e.b),
{name} AS (SELECT doc_id, min(root) root FROM {name}_r GROUP BY doc_id)"""


def vectors(src: str, dims: int = 256, cells: int = 65536, term: str = "unnest(k)", name: str = "vec") -> str:
    chars = ", CASE WHEN coalesce(text, '') = '' THEN [] ELSE string_split(lower(text), '') END c" if "(c)" in term else ""
    return f"""{name}_k AS MATERIALIZED (SELECT doc_id, {toks("text")} k{chars} FROM {src}),
{name}_t AS (SELECT doc_id, w, count(*) tf FROM (SELECT doc_id, {term} w FROM {name}_k) GROUP BY ALL),
{name}_h AS (SELECT doc_id, tf, {h32('w')} h FROM {name}_t),
{name}_d AS (SELECT h % {cells} cell, count(*) df FROM {name}_h GROUP BY ALL),
{name}_n AS (SELECT count(*) n FROM {src}),
{name}_x AS (SELECT doc_id, h % {dims} i, CAST(sum(CAST((CASE WHEN (h >> 16) % 2 = 0 THEN 1.0 ELSE -1.0 END) * (1 + ln(tf)) * ln(1 + n / CAST(df AS DOUBLE)) AS DECIMAL(30,12))) AS DOUBLE) x
 FROM {name}_h JOIN {name}_d ON cell = h % {cells}, {name}_n GROUP BY ALL),
{name}_l AS (SELECT doc_id, sqrt(sum(x * x)) norm FROM {name}_x GROUP BY doc_id HAVING norm > 0),
{name}_f AS (SELECT l.doc_id, r.i, coalesce(x.x, 0) / l.norm x FROM {name}_l l CROSS JOIN range({dims}) r(i) LEFT JOIN {name}_x x ON x.doc_id = l.doc_id AND x.i = r.i),
{name} AS MATERIALIZED (SELECT doc_id, list(x ORDER BY i) v FROM {name}_f GROUP BY doc_id)"""


def clusters(k: int, vec: str = "vec") -> str:
    return f"""seeds AS (SELECT doc_id cluster_id, v center FROM {vec} ORDER BY {h32("'seed:' || doc_id")}, doc_id LIMIT {k}),
assign AS (SELECT doc_id, v, arg_max(cluster_id, (round(list_dot_product(v, center), 12), -cluster_id)) AS cluster FROM {vec}, seeds GROUP BY doc_id, v)"""


def lloyd(src: str, k: int, name: str = "km", passes: int = 3) -> str:
    """K-Means of ``src`` (doc_id, v): <name>(doc_id, v, cluster). Sums in fixed point; nearest by inner product less half the length."""
    near = "arg_max(cluster_id, (round(list_dot_product(v, center) - list_dot_product(center, center) / 2, 9), -cluster_id))"
    parts = [f"{name}_c0 AS MATERIALIZED (SELECT doc_id cluster_id, v center FROM {src} ORDER BY {h32("'seed:' || doc_id")}, doc_id LIMIT {k})"]
    for i in range(passes):
        parts.append(f"{name}_a{i} AS MATERIALIZED (SELECT doc_id, any_value(v) v, {near} AS cluster FROM {src}, {name}_c{i} GROUP BY doc_id)")
        parts.append(
            f"{name}_c{i + 1} AS MATERIALIZED (SELECT cluster cluster_id, list(m ORDER BY i) center FROM (SELECT cluster, i, sum(CAST(round(x * 1e9) AS BIGINT)) / count(*) / 1e9 m"
            f" FROM (SELECT cluster, unnest(v) x, unnest(range(len(v))) i FROM {name}_a{i}) GROUP BY ALL) GROUP BY cluster)"
        )
    parts.append(f"{name} AS MATERIALIZED (SELECT doc_id, any_value(v) v, {near} AS cluster FROM {src}, {name}_c{passes} GROUP BY doc_id)")
    return ",\n".join(parts)


def diversity(src: str) -> str:
    """cen, intra, inter and dv(cluster, members, intra, inter, nearest, d) of ``src`` (doc_id, v, cluster)."""
    return f"""cf AS (SELECT cluster, i, avg(x) m FROM (SELECT cluster, unnest(v) x, unnest(range(len(v))) i FROM {src}) GROUP BY ALL),
cen AS (SELECT cluster, list(m ORDER BY i) c FROM cf GROUP BY cluster),
intra AS (SELECT s.cluster, count(*) members, avg(list_distance(v, c)) intra FROM {src} s JOIN cen USING (cluster) GROUP BY ALL),
inter AS (SELECT a.cluster, avg(list_distance(a.c, b.c)) inter, min(list_distance(a.c, b.c)) nearest FROM cen a JOIN cen b ON a.cluster <> b.cluster GROUP BY ALL),
dv AS (SELECT cluster, members, intra, coalesce(inter, 1) inter, nearest, intra * coalesce(inter, 1) d FROM intra LEFT JOIN inter USING (cluster))"""


def edges(floor: float = 0.90, src: str = "assign") -> str:
    case = " ".join(f"WHEN sim >= {lo} THEN {w}" for lo, w in C.BANDS)
    return f"""edges_s AS (SELECT a.doc_id u, b.doc_id v, least(round(list_dot_product(a.v, b.v), 12), 1.0) sim FROM {src} a JOIN {src} b ON a.cluster = b.cluster AND a.doc_id < b.doc_id),
edges AS MATERIALIZED (SELECT u, v, sim, CASE {case} ELSE 0 END weight FROM edges_s WHERE sim >= {floor}),
dir AS (SELECT u id, v other, sim, weight FROM edges UNION ALL SELECT v, u, sim, weight FROM edges)"""


def votes(target: float = C.TARGET) -> str:
    return f"votes AS (SELECT id, CAST(sum(weight) AS BIGINT) score, count(*) edges, sum(weight) > {target} redundant FROM dir GROUP BY id)"


def removed(name: str = "gone") -> str:
    """Redundant rows but the least of each connected set of them."""
    return f"""red_e AS (SELECT u, v FROM edges WHERE u IN (SELECT id FROM votes WHERE redundant) AND v IN (SELECT id FROM votes WHERE redundant)),
{components('red_e', 'rc')},
{name} AS (SELECT doc_id FROM rc WHERE root <> doc_id)"""


def funnel_ctes(ruleset=rules.OPTIMIZED, k: int = 16, budget: float = 1.0, bypass=C.BYPASS) -> str:
    """Every stage of the pipeline as CTEs st_<stage>(doc_id), the sampled one with copies, and stage_docs over all."""
    n, kk, a = C.POWER["n"], C.POWER["k"], C.POWER["a"]
    return ",\n".join(
        [
            shapes(), TAGS, features(), language(),
            f"""sig_all AS (SELECT s.*, t.domain_l1, t.domain_l2, g.lang_guess, g.lang_conf, sha256(coalesce(d.text, '')) digest,
 CASE WHEN {f'domain_l1 IN {in_list(bypass)}' if bypass else 'false'} THEN 0 ELSE len({rule_hits(ruleset)}) END n_hits
 FROM signals s JOIN tags t USING (doc_id) JOIN lang g USING (doc_id) JOIN rf USING (doc_id) JOIN documents d USING (doc_id)),
st_raw AS (SELECT doc_id FROM sig_all), st_english AS (SELECT doc_id FROM sig_all WHERE lang_guess = 'en' AND lang_conf > 0.5),
st_exact AS (SELECT min(doc_id) doc_id FROM sig_all WHERE lang_guess = 'en' AND lang_conf > 0.5 GROUP BY digest),
st_rule AS (SELECT doc_id FROM sig_all WHERE doc_id IN (SELECT doc_id FROM st_exact) AND n_hits = 0),
st_model AS (SELECT doc_id FROM sig_all WHERE doc_id IN (SELECT doc_id FROM st_rule) AND writing >= 1 AND coherence >= 1 AND completeness >= 1 AND safety >= 1),
model_docs AS (SELECT doc_id, text FROM documents WHERE doc_id IN (SELECT doc_id FROM st_model))""",
            fuzzy_pairs("model_docs"), components("links"),
            """st_fuzzy AS (SELECT doc_id FROM st_model WHERE doc_id NOT IN (SELECT doc_id FROM comp WHERE root <> doc_id)),
fuzzy_docs AS (SELECT doc_id, text FROM documents WHERE doc_id IN (SELECT doc_id FROM st_fuzzy))""",
            vectors("fuzzy_docs"), clusters(1), edges(), votes(), removed(),
            f"""st_semantic AS (SELECT doc_id FROM st_fuzzy WHERE doc_id NOT IN (SELECT doc_id FROM gone)),
st_value AS (SELECT doc_id FROM sig_all WHERE doc_id IN (SELECT doc_id FROM st_semantic) AND knowledge + education + helpfulness + reasoning > 1),
surv AS MATERIALIZED (SELECT doc_id, v FROM vec WHERE doc_id IN (SELECT doc_id FROM st_semantic)),
{lloyd("surv", k)},
mem AS (SELECT doc_id, v, cluster FROM km WHERE doc_id IN (SELECT doc_id FROM st_value)),
{diversity("mem")},
fr_a AS (SELECT s.doc_id, n_words, CAST(knowledge + education + helpfulness + reasoning AS DOUBLE) q, coalesce(d, 0) d FROM sig_all s LEFT JOIN mem m USING (doc_id) LEFT JOIN dv USING (cluster) WHERE s.doc_id IN (SELECT doc_id FROM st_value)),
fr_b AS (SELECT *, CASE WHEN max(q) OVER () > min(q) OVER () THEN (q - min(q) OVER ()) / (max(q) OVER () - min(q) OVER ()) ELSE 1 END q_n,
 CASE WHEN max(d) OVER () > min(d) OVER () THEN (d - min(d) OVER ()) / (max(d) OVER () - min(d) OVER ()) ELSE 1 END d_n FROM fr_a),
fr_c AS (SELECT *, {C.ALPHA} * q_n + (1 - {C.ALPHA}) * d_n s FROM fr_b),
fr_d AS (SELECT *, CASE WHEN max(s) OVER () > min(s) OVER () THEN (s - min(s) OVER ()) / (max(s) OVER () - min(s) OVER ()) ELSE 1 END x FROM fr_c),
fr AS (SELECT *, w / sum(w) OVER () p FROM (SELECT *, power(x, {n}) / (1 + exp(-{kk} * (x - {a}))) w FROM fr_d)),
dr AS (SELECT *, (SELECT sum(n_words) * {budget} FROM sig_all WHERE doc_id IN (SELECT doc_id FROM st_value)) / sum(p * n_words) OVER () * p expected FROM fr),
st_sampled AS (SELECT doc_id, CAST(floor(expected) + CASE WHEN ({h32("doc_id || ':draw'")} + 0.5) / 4294967296.0 < expected - floor(expected) THEN 1 ELSE 0 END AS INT) copies FROM dr),
stage_ids AS ("""
            + " UNION ALL ".join(f"SELECT {i} pos, '{s}' stage, doc_id, 1 copies FROM st_{s}" for i, s in enumerate(("raw", "english", "exact", "rule", "model", "fuzzy", "semantic", "value")))
            + " UNION ALL SELECT 8, 'sampled', doc_id, copies FROM st_sampled WHERE copies > 0),\nstage_docs AS (SELECT i.pos, i.stage, i.copies, s.* FROM stage_ids i JOIN sig_all s USING (doc_id))",
        ]
    )


def grams(n: int, k: str = "k") -> str:
    """List of the n-grams of a list of tokens."""
    return k if n == 1 else f"list_transform(range(1, len({k}) - {n - 2}), lambda i: array_to_string({k}[i:i + {n - 1}], ' '))"


def lexical(ns, arms: str = "arms", texts: str = "documents") -> str:
    """lx<n>(arm, total, uniq) of ``arms`` (arm, doc_id, copies) for each n."""
    parts = [f"lx_k AS MATERIALIZED (SELECT doc_id, {toks('text')} k FROM {texts})"]
    parts += [f"lx{n} AS MATERIALIZED (SELECT arm, CAST(sum(c) AS BIGINT) total, count(*) uniq FROM (SELECT arm, g, sum(copies) c FROM {arms} JOIN (SELECT doc_id, unnest({grams(n)}) g FROM lx_k) USING (doc_id) GROUP BY ALL) GROUP BY 1)" for n in ns]
    return ",\n".join(parts)


def measured(ns=(1,)) -> str:
    """``measured`` (arm, docs, measures): of ``arms`` (arm, doc_id, copies) with ``sg`` (scores and tags by doc_id)."""
    hq = "('Computer Science', 'Programming', 'Mathematics', 'Physics')"
    level = lambda i: f"""m{i} AS (SELECT arm, k, n / sum(n) OVER (PARTITION BY arm) p FROM (SELECT arm, domain_l{i} k, sum(copies) n FROM ar GROUP BY ALL)),
e{i} AS (SELECT arm, -sum(p * log2(p)) h FROM m{i} GROUP BY 1)"""  # noqa: E731
    means = ", ".join(f"sum({c} * copies) / sum(copies) {c}" for c in ("education", "knowledge", "helpfulness", "reasoning"))
    sets = ", ".join(f"sum(CASE WHEN domain_l1 IN {in_list(v)} THEN copies ELSE 0 END) / sum(copies) {k}" for k, v in C.DOMAIN_SETS.items())
    shown = ", ".join(f"round({c}, 6) {c}" for c in ("education", "knowledge", "helpfulness", "reasoning"))
    rn = ", ".join(f"round(lx{n}.uniq / nullif(lx{n}.total, 0), 6) r_{n}" for n in ns)
    joins = " ".join(f"LEFT JOIN lx{n} ON lx{n}.arm = vm.arm" for n in ns)
    return f"""ar AS MATERIALIZED (SELECT a.arm, a.copies, s.* FROM arms a JOIN sg s USING (doc_id)),
{level(1)},
{level(2)},
t3 AS (SELECT arm, sum(p) t FROM (SELECT arm, p, row_number() OVER (PARTITION BY arm ORDER BY p DESC) r FROM m1) WHERE r <= 3 GROUP BY 1),
vm AS (SELECT arm, CAST(sum(copies) AS BIGINT) docs, {means}, sum((education + knowledge + helpfulness + reasoning) * copies) / 12.0 / sum(copies) composite, {sets} FROM ar GROUP BY 1),
hm AS (SELECT arm, avg(r) hq_mean FROM (SELECT arm, domain_l1, sum(CASE WHEN education >= 2 THEN copies ELSE 0 END) / sum(copies) r FROM ar WHERE domain_l1 IN {hq} GROUP BY ALL) GROUP BY 1),
{lexical(ns)},
measured AS (SELECT vm.arm, docs, round(e1.h, 6) h_l1, round(e2.h, 6) h_l2, round(t, 6) top3_share, round(1 - t, 6) longtail_share, {shown}, round(composite, 6) composite,
 round(code, 6) code, round(math, 6) math, round(stem, 6) stem, round(hq_mean, 6) hq_mean, {rn} FROM vm JOIN e1 USING (arm) JOIN e2 USING (arm) JOIN t3 USING (arm) LEFT JOIN hm USING (arm) {joins})"""


PROVIDERS = {
    "word": "unnest(k)", "prefix": "unnest(k[1:20])", "bigram": "unnest(CASE WHEN len(k) > 1 THEN list_transform(range(1, len(k)), lambda i: k[i] || ' ' || k[i + 1]) ELSE k END)",
    "char": "unnest(CASE WHEN len(c) > 2 THEN list_transform(range(1, len(c) - 1), lambda i: c[i] || c[i + 1] || c[i + 2]) WHEN len(c) > 0 THEN [array_to_string(c, '')] ELSE [] END)",
}


def provider_bench(names=tuple(PROVIDERS)) -> str:
    """bench(provider, steps, mean_fpr, spearman) over the pairs of cosine 0.90 or more of all documents."""
    parts = [shingle_sets("documents", 3)]
    for p in names:
        parts.append(vectors("documents", term=PROVIDERS[p], name=f"v_{p}"))
        parts.append(
            f"""e_{p} AS MATERIALIZED (SELECT * FROM (SELECT a.doc_id u, b.doc_id v, least(round(list_dot_product(a.v, b.v), 12), 1.0) sim FROM v_{p} a JOIN v_{p} b ON a.doc_id < b.doc_id) WHERE sim >= 0.9),
s_{p} AS (SELECT CAST(least(floor((sim - 0.9) / 0.01 + 1e-9), 9) AS INT) step, count(*) n, avg(CASE WHEN coalesce(len(list_intersect(a.s, b.s)) / nullif(CAST(len(a.s) + len(b.s) - len(list_intersect(a.s, b.s)) AS DOUBLE), 0), 0) >= 0.5 THEN 0.0 ELSE 1.0 END) fpr
 FROM e_{p} JOIN sh a ON a.doc_id = u JOIN sh b ON b.doc_id = v GROUP BY 1),
r_{p} AS (SELECT n, fpr, rank() OVER (ORDER BY step) + (count(*) OVER (PARTITION BY step) - 1) / 2.0 a, rank() OVER (ORDER BY fpr) + (count(*) OVER (PARTITION BY fpr) - 1) / 2.0 b FROM s_{p})"""
        )
    rows = " UNION ALL ".join(f"SELECT '{p}' provider, count(*) steps, round(sum(n * fpr) / sum(n), 6) mean_fpr, round(CASE WHEN isnan(corr(a, b)) THEN NULL ELSE corr(a, b) END, 6) spearman FROM r_{p}" for p in names)
    return ",\n".join([*parts, f"bench AS MATERIALIZED ({rows})"])
