"""SimHash near-dedup with the generalised pigeonhole.

Fingerprints: each word shingle (repeats count) is hashed with XXH64; a bit is set if over half of the hashes have it.
Copies of a fingerprint are aggregated first, so all that follows works on distinct fingerprints.

Search for pairs at Hamming distance <= tau: correlated bits are grouped into m parts; part i gets a threshold t_i
with sum t_i = tau - m + 1 (t_i = -1: unused). Then any pair within tau is within t_i on some part i. Number of parts and
thresholds come from dynamic programming on candidate counts that a bounded sample of fingerprints predicts; the
sample sways cost only, never the result. A fingerprint goes to the bucket of each part value within t_i of its own.
Buckets are swept in sorted order by the task that holds them; every link is verified on all 64 bits, and a bucket
gives a spanning forest of its links, never all pairs.

A bucket with more than BUCKET_CAP members is split, exactly: what lies within tau of the bucket's least member is
linked to it; a pair within tau agrees on one of tau + 1 parts of any partition of the bits, so members go on to
sub-buckets by such parts; sub-buckets in which all are linked to the same member already are done.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import accumulate, combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.components import star_forest
from .common import map_arrow, stage, table, unused

BITS = 64
SEED = 42
SHINGLE = 4
TAU = 4
#: Distinct fingerprints that plan the partition; a bounded sample by hash order.
SAMPLE = 2048
#: Members of a bucket that one task sweeps as a whole.
BUCKET_CAP = 20_000
MAX_SPLITS = 3
#: Cost of moving a row to a bucket, in verified pairs.
ROW_COST = 40.0
SMALL = 48
BROADCAST_ROWS = 100_000

_BIT = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.int64)


def shingle_hashes(text: str | None, size: int = SHINGLE, seed: int = SEED) -> np.ndarray:
    """XXH64 of each word shingle of the whole text, repeats included; no words: none; fewer than ``size``: one of all words."""
    from xxhash import xxh64_intdigest

    words = (text or "").encode(errors="replace").lower().split()
    line = b" ".join(words)
    if len(words) <= size:
        return np.array([xxh64_intdigest(line, seed)] * bool(words), np.uint64)
    ends = list(accumulate(len(w) + 1 for w in words))
    starts = [0, *ends[: len(words) - size]]
    return np.fromiter((xxh64_intdigest(line[a : b - 1], seed) for a, b in zip(starts, ends[size - 1 :], strict=True)), np.uint64, len(starts))


def majority(hashes: np.ndarray) -> int:
    """The bits that are set in over half of the hashes; zero without any."""
    lanes = np.ascontiguousarray(hashes).view(np.uint8).reshape(-1, 8)
    ones = np.concatenate([np.bincount(lanes[:, k], minlength=256) @ _BIT for k in range(8)])
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprint(text: str | None, size: int = SHINGLE, seed: int = SEED) -> int:
    """64-bit SimHash of the whole text; no words: zero; fewer words than ``size``: one shingle of all words."""
    return majority(shingle_hashes(text, size, seed))


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE) -> DataFrame:
    """(id, fp long): one row for each input row; null text counts as empty; other columns go."""
    id_type = df.schema[id_col].dataType.simpleString()

    def build():
        def one(batch: pa.RecordBatch) -> pa.RecordBatch:
            fps = np.array([fingerprint(t, size) for t in batch.column(1).to_pylist()], np.uint64).view(np.int64)
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps)], [id_col, "fp"])

        return one

    return map_arrow(df.select(id_col, text_col), build, f"`{id_col}` {id_type}, fp long")


def group_bits(sample: np.ndarray, parts: int) -> list[np.ndarray]:
    """Partition of the 64 bits: each part takes the bits most correlated with those it has, so that parts are
    as independent of each other as they can be."""
    widths = [BITS // parts + (i < BITS % parts) for i in range(parts)]
    bits = ((sample[:, None] >> np.arange(BITS, dtype=np.uint64)) & np.uint64(1)).astype(float)
    bits -= bits.mean(0)
    norm = np.sqrt((bits**2).sum(0))
    link = np.abs(bits.T @ bits) / np.maximum(np.outer(norm, norm), 1e-12)
    np.fill_diagonal(link, 0)
    left, out = set(range(BITS)), []
    for w in widths:
        rest = sorted(left)
        own = [max(rest, key=lambda b: (link[b, rest].sum(), -b))]
        left.discard(own[0])
        while len(own) < w:
            best = max(sorted(left), key=lambda b: (link[b, own].sum(), -b))
            own.append(best)
            left.discard(best)
        out.append(np.array(sorted(own)))
    return out


def part_value(fps: np.ndarray, bits: np.ndarray) -> np.ndarray:
    out = np.zeros(len(fps), np.uint64)
    for k, b in enumerate(bits):
        out |= ((fps >> np.uint64(b)) & np.uint64(1)) << np.uint64(k)
    return out


def allocate(costs: list[list[float]], total: int) -> tuple[float, list[int]]:
    """Thresholds t_i >= -1 that add up to ``total`` at least cost; costs[i][t + 1] is the cost of t_i = t."""
    best: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
    for own in costs:
        step: dict[int, tuple[float, list[int]]] = {}
        for spent, (cost, chosen) in best.items():
            for k, c in enumerate(own):
                to = spent + k - 1
                if to not in step or cost + c < step[to][0]:
                    step[to] = (cost + c, [*chosen, k - 1])
        best = step
    return best[total]


def plan_search(sample: np.ndarray, count: int, tau: int = TAU) -> list[tuple[list[int], int]]:
    """[(bits of a part, threshold)]: the cheapest generalised pigeonhole for ``count`` distinct fingerprints."""
    best = None
    pairs = max(1, len(sample) * (len(sample) - 1) // 2)
    # Linked pairs are left out: a sweep never compares again what it has reached.
    apart = [np.bitwise_count(sample[k:] ^ sample[:-k]) > tau for k in range(1, len(sample))]
    for m in range(1, tau + 3):
        groups, costs = group_bits(sample, m), []
        for bits in groups:
            w, values = len(bits), part_value(sample, bits)
            seen = np.zeros(w + 1)
            for k in range(1, len(values)):
                seen += np.bincount(np.bitwise_count(values[k:] ^ values[:-k])[apart[k - 1]], minlength=w + 1)[: w + 1]
            own = [0.0]
            for t in range(min(tau, w) + 1):
                volume = sum(comb(w, k) for k in range(t + 1))
                share = max(seen[: t + 1].sum() / pairs, volume / 2.0**w)
                own.append(ROW_COST * count * volume + count * count / 2 * share)
            costs.append(own)
        cost, thresholds = allocate(costs, tau - m + 1)
        if best is None or cost < best[0]:
            best = (cost, [(b.tolist(), t) for b, t in zip(groups, thresholds, strict=True) if t >= 0])
    return best[1]


def _probes(parts: list[tuple[list[int], int]]):
    """fp -> rows (bucket key, fp); a key names its part."""
    masks = [[sum(1 << b for b in flip) for t in range(limit + 1) for flip in combinations(range(len(bits)), t)] for bits, limit in parts]

    def build():
        def one(batch: pa.RecordBatch) -> pa.RecordBatch:
            fps = batch.column(0).to_numpy().view(np.uint64)
            keys, owners = [], []
            for i, (bits, _) in enumerate(parts):
                value = part_value(fps, np.array(bits))
                for mask in masks[i]:
                    keys.append((value ^ np.uint64(mask)) * np.uint64(8) + np.uint64(i) if len(bits) <= 60 else value ^ np.uint64(mask))
                    owners.append(fps)
            return pa.RecordBatch.from_arrays(
                [pa.array(np.concatenate(keys).view(np.int64)), pa.array(np.concatenate(owners).view(np.int64))], ["key", "fp"]
            )

        return one

    return build


def _forest(fps: np.ndarray, tau: int, out: list[tuple[np.ndarray, np.ndarray]]) -> None:
    """Spanning forest of one bucket: what is reached is not compared again, so dense groups cost little."""
    rest = np.unique(fps)
    while rest.size > 1:
        root, rest, todo = rest[0], rest[1:], [rest[0]]
        while todo and rest.size:
            near = np.bitwise_count(rest ^ todo.pop()) <= tau
            if near.any():
                found, rest = rest[near], rest[~near]
                todo.extend(found)
                out.append((np.full(found.size, root), found))


def _sweep(tau: int):
    """Rows (key, fp) sorted by key -> links (u, v). A bucket may span Arrow batches; at most one is held open."""

    def links(keys: np.ndarray, fps: np.ndarray) -> pa.RecordBatch:
        out: list[tuple[np.ndarray, np.ndarray]] = []
        cuts = np.flatnonzero(np.diff(keys)) + 1
        starts, ends = np.concatenate([[0], cuts]), np.concatenate([cuts, [len(keys)]])
        sizes = ends - starts
        for a, b in zip(starts[sizes > SMALL], ends[sizes > SMALL], strict=True):
            _forest(fps[a:b], tau, out)
        small = np.repeat((sizes > 1) & (sizes <= SMALL), sizes)
        k, f = keys[small], fps[small]
        hits: list[tuple[np.ndarray, np.ndarray]] = []
        for gap in range(1, min(SMALL, len(k))):  # all small buckets at once: compare rows a fixed gap apart
            same = k[gap:] == k[:-gap]
            if not same.any():
                break
            x, y = f[gap:][same], f[:-gap][same]
            near = np.bitwise_count(x ^ y) <= tau
            near &= x != y
            if near.any():
                hits.append((np.flatnonzero(same)[near], np.flatnonzero(same)[near] + gap))
        if hits:
            a, b = np.concatenate([h[0] for h in hits]), np.concatenate([h[1] for h in hits])
            parent: dict[int, int] = {}

            def find(x: int) -> int:
                while (up := parent.get(x, x)) != x:
                    parent[x] = x = parent.get(up, up)
                return x

            us, vs = [], []
            for x, y in zip(a.tolist(), b.tolist(), strict=True):
                p, q = find(x), find(y)
                if p != q:
                    parent[max(p, q)] = min(p, q)
                    us.append(x)
                    vs.append(y)
            out.append((f[us], f[vs]))
        u = np.concatenate([o[0] for o in out]) if out else np.zeros(0, np.uint64)
        v = np.concatenate([o[1] for o in out]) if out else np.zeros(0, np.uint64)
        return pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(v.view(np.int64))], ["u", "v"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_k, held_f = [], []
        for batch in batches:
            if not batch.num_rows:
                continue
            k, f = batch.column(0).to_numpy(), batch.column(1).to_numpy().view(np.uint64)
            cut = int(np.searchsorted(k, k[-1]))  # the last bucket may go on
            if cut or held_k and held_k[-1][-1] != k[0]:
                yield links(np.concatenate([*held_k, k[:cut]]), np.concatenate([*held_f, f[:cut]]))
                held_k, held_f = [], []
            held_k.append(k[cut:])
            held_f.append(f[cut:])
        if held_k:
            yield links(np.concatenate(held_k), np.concatenate(held_f))

    return run


def _bucket_links(rows: DataFrame, tau: int, cap: int, depth: int) -> DataFrame:
    spark = rows.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    sizes = rows.groupBy("key").agg(F.count("*").alias("n"), F.min("fp").alias("pivot"))
    hot = stage(sizes.where(F.col("n") > cap).select("key", "pivot"), "hot-buckets") if depth < MAX_SPLITS else None
    found = hot.count() if hot is not None else 0
    split = found > 0
    # Hot keys are at most rows/cap; they are broadcast up to BROADCAST_ROWS of them.
    near_by = F.broadcast if found <= BROADCAST_ROWS else lambda d: d
    cold = rows.join(near_by(hot.select("key")), "key", "left_anti") if split else rows
    out = cold.repartition(n, "key").sortWithinPartitions("key", "fp").mapInArrow(_sweep(tau), "u long, v long")
    if not split:
        return out
    inside = rows.join(near_by(hot), "key")
    near = F.bit_count(F.col("fp").bitwiseXOR(F.col("pivot"))) <= tau
    stars = inside.where(near & (F.col("fp") != F.col("pivot"))).select(F.col("pivot").alias("u"), F.col("fp").alias("v"))
    subs = []
    for j in range(tau + 1):
        mask = sum(1 << b for b in range(BITS) if (b // (2 * depth + 1)) % (tau + 1) == j)
        mask -= (mask >> 63) << 64
        subs.append(F.xxhash64("key", F.lit(j), F.col("fp").bitwiseAND(F.lit(mask))))
    deeper = stage(inside.select(F.explode(F.array(*subs)).alias("key"), "fp", near.alias("near")), "sub-buckets")
    open_keys = deeper.groupBy("key").agg(F.min("near").alias("all_near")).where("not all_near").select("key")
    return out.unionAll(stars).unionAll(_bucket_links(deeper.join(open_keys, "key", "left_semi").select("key", "fp"), tau, cap, depth + 1))


def near_links(fps: DataFrame, tau: int = TAU, cap: int = BUCKET_CAP) -> DataFrame:
    """Distinct fingerprints (column fp) -> (u, v) links that connect exactly what distances <= tau connect."""
    count = fps.count()
    rows = fps.select("fp").orderBy(F.xxhash64("fp", F.lit(7)), "fp").limit(SAMPLE).collect()  # bounded
    if count < 2:
        return fps.sparkSession.createDataFrame([], "u long, v long")
    parts = plan_search(np.array([r[0] for r in rows], np.int64).view(np.uint64), count, tau)
    buckets = stage(map_arrow(fps.select("fp"), _probes(parts), "key long, fp long"), "buckets")
    return _bucket_links(buckets, tau, cap, 0)


def near_groups(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE, tau: int = TAU, cap: int = BUCKET_CAP) -> DataFrame:
    """(id, fp long, component_id): one row for each input row.

    component_id is the least id of all rows whose fingerprints are linked, directly or over others, at ``tau`` or fewer
    differing bits. Texts without words share fingerprint zero. A null id never names a component unless all its ids are
    null. Repeated rows stay; an empty table gives no rows; other columns are ignored.
    """
    docs = stage(fingerprints(df, id_col, text_col, size), "fingerprints")
    fps = stage(docs.groupBy("fp").agg(F.min(id_col).alias("first")), "distinct-fingerprints")
    tree = star_forest(near_links(fps, tau, cap))
    roots = tree.select(F.col("u").alias("fp"), F.col("v").alias("root"))
    roots = stage(roots.unionAll(tree.select(F.col("v").alias("fp"), F.col("v").alias("root")).distinct()), "roots")
    linked = stage(fps.join(roots, "fp"), "linked")
    # Staged, so that both sides of the join are plain exchanges and a component with very many members can be split.
    least = stage(linked.groupBy("root").agg(F.min("first").alias("component_id")), "least")
    of = linked.join(least, "root").select("fp", "component_id")
    classes = stage(fps.join(of, "fp", "left").select("fp", F.coalesce("component_id", "first").alias("component_id")), "classes")
    return docs.join(classes, "fp").select(id_col, "fp", "component_id")


def drop_near_copies(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE, tau: int = TAU) -> DataFrame:
    """``df`` with one row for each component, that with its least id (one of them if repeated); columns as given."""
    groups = near_groups(df, id_col, text_col, size, tau)
    name, null = unused(df, "__id", "__null")
    key = lambda c: (F.coalesce(F.col(c).cast("string"), F.lit("")).alias(name), F.col(c).isNull().alias(null))
    keep = groups.where(F.col(id_col).eqNullSafe(F.col("component_id"))).select("component_id").distinct().select(*key("component_id"))
    marked = df.select("*", *key(id_col))
    return marked.join(keep, [name, null], "left_semi").dropDuplicates([name, null]).drop(name, null)


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints and components of all documents: 4-word shingles, 4 bits."""
    groups = near_groups(table(spark, sf_dir, "documents"))
    return groups.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
