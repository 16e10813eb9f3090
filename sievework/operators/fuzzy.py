"""Fuzzy dedup: word shingles, MinHash, banded LSH in star form, verification, components."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import PRIME, h32, h60, jaccard, shingles, tokens
from ..plans.staging import stage
from .components import star_forest

SHINGLE, PERMUTATIONS, BANDS, THETA = 5, 64, 16, 0.8
#: Rows and shingles of a tile of an open bucket; vocabulary of one block of its matrix product.
TILE, TILE_SHINGLES, BLOCK = 512, 500_000, 4096
#: Cells of the bits that tell sets apart before they are compared.
PARITIES = 1024
#: Cells of the frequencies that order a prefix, at most (bytes sent to every task), and those of a slice.
CELLS, SLICE = 1 << 25, 1 << 16


def permutation(i: int, seed: str = "perm") -> tuple[int, int]:
    """Multiplier (not zero) and shift of the i-th affine map modulo PRIME."""
    a, b = (int(hashlib.md5(f"{seed}:{k}:{i}".encode()).hexdigest()[:8], 16) % (PRIME - 1) for k in "ab")
    return a + 1, b


def shingle_sets(df: DataFrame, n: int = SHINGLE, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, sh): sorted distinct shingle hashes; null or short texts have none."""
    parts = df.select(key, tokens(F.col(text)).alias("__k"))
    return parts.select(key, F.array_sort(shingles(F.col("__k"), n)).alias("sh"))


def minhash(sets: DataFrame, perms: int = PERMUTATIONS, key: str = "doc_id", seed: str = "perm") -> DataFrame:
    """(key, sig array<bigint>): least value of each affine map; sets without shingles are left out."""
    maps = np.array([permutation(i, seed) for i in range(perms)], np.int64)
    kind = sets.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(1)
            values, cuts = column.flatten().to_numpy() % PRIME, column.offsets.to_numpy() - column.offsets[0].as_py()
            out = np.empty((batch.num_rows, perms), np.int64)
            some = np.diff(cuts[: batch.num_rows + 1]) > 0
            for i in np.flatnonzero(some):
                h = values[cuts[i] : cuts[i + 1]]
                out[i] = PRIME
                for at in range(0, len(h), 4096):  # long documents in slices
                    out[i] = np.minimum(out[i], ((maps[:, :1] * h[at : at + 4096] + maps[:, 1:]) % PRIME).min(1))
            sig = pa.ListArray.from_arrays(pa.array(np.arange(0, batch.num_rows * perms + 1, perms, np.int32)), pa.array(out.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0), sig], [key, "sig"]).filter(pa.array(some))

    return sets.select(key, "sh").mapInArrow(run, f"`{key}` {kind}, sig array<bigint>")


def _mapped(a: int, b: int):
    return F.transform("sh", lambda h: (F.lit(a) * (h % PRIME) + b) % PRIME)


def minhash_native(sets: DataFrame, perms: int = 8, key: str = "doc_id", seed: str = "perm") -> DataFrame:
    """The same signature from array functions only (wide plans: for few maps). Stage the sets first: a filter on an array
    expression is pushed below it and makes it twice."""
    maps = [permutation(i, seed) for i in range(perms)]
    least = [F.array_min(_mapped(a, b)) for a, b in maps]
    return sets.where(F.size("sh") > 0).select(key, F.array(*least).alias("sig"))


def lsh_bands(sigs: DataFrame, bands: int = BANDS, key: str = "doc_id") -> DataFrame:
    """(key, band, bucket): one narrow row a band; the bucket is a 60-bit hash of the band's part of the signature, so that strangers
    rarely share one, however many rows there are."""
    rows = F.size("sig") / bands
    parts = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda b: F.struct(b.alias("band"), h60(F.array_join(F.slice("sig", (b * rows + 1).cast("int"), rows.cast("int")), ":")).alias("bucket")))
    return sigs.select(key, F.explode(parts).alias("x")).select(key, "x.band", "x.bucket")


def star_candidates(buckets: DataFrame, key: str = "doc_id") -> DataFrame:
    """(u, v), u < v: each member with its bucket's least. Linear in the rows whatever the bucket sizes.

    The least member of each bucket is found with map-side combining, staged and joined back: no bucket is gathered, few least
    members are broadcast by their known size, and in a join of two plain exchanges Spark can split a bucket with very many rows.
    """
    least = buckets.groupBy("band", "bucket").agg(F.min(key).alias("u"), F.count("*").alias("n")).where("n > 1")
    return buckets.join(stage(least.select("band", "bucket", "u"), "bucket-least"), ["band", "bucket"]).where(F.col(key) > F.col("u")).select("u", F.col(key).alias("v")).distinct()


def all_candidates(buckets: DataFrame, key: str = "doc_id") -> DataFrame:
    """(u, v), u < v: all pairs that share a bucket (costs the squared bucket sizes)."""
    a, b = buckets.select("band", "bucket", F.col(key).alias("u")), buckets.select("band", "bucket", F.col(key).alias("v"))
    return a.join(b, ["band", "bucket"]).where("u < v").select("u", "v").distinct()


def parities(sets: DataFrame, key: str = "doc_id") -> DataFrame:
    """(key, n, p0, p1, ...): size of each set, and for PARITIES cells of values whether it has an odd number of values in the cell, as bits of
    longs. Each cell in which two sets differ holds a value that only one of them has."""
    kind = sets.schema[key].dataType.simpleString()
    names = [f"p{i}" for i in range(PARITIES // 64)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                lists = part.column(1)
                size = np.nan_to_num(lists.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64)
                cell = np.repeat(np.arange(len(size)), size) * PARITIES + lists.flatten().to_numpy() % PARITIES
                odd = np.bincount(cell, minlength=len(size) * PARITIES).astype(np.uint8) & 1
                bits = np.packbits(odd).view(np.int64).reshape(len(size), -1)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(size), *[pa.array(np.ascontiguousarray(c)) for c in bits.T]], [key, "n", *names])

    return sets.select(key, F.col("sh").cast("array<long>").alias("sh")).mapInArrow(run, f"`{key}` {kind}, n long, " + ", ".join(f"{x} long" for x in names))


def near_in_buckets(buckets: DataFrame, sets: DataFrame, theta: float, key: str = "doc_id") -> DataFrame:
    """(u, v), u < v: pairs that share a ``bucket``, but those whose sizes or ``parities`` show that their Jaccard is below ``theta``. Such
    pairs are dropped where they meet; of Jaccard ``theta`` or more none is."""
    marked = stage(buckets.join(parities(sets, key), key), "bucket-parities")
    names = [c for c in marked.columns if c not in (key, "bucket")]
    side = lambda x: marked.select("bucket", F.col(key).alias(x), *[F.col(c).alias(f"{x}_{c}") for c in names])
    apart = sum((F.bit_count(F.col(f"u_{c}").bitwiseXOR(F.col(f"v_{c}"))) for c in names if c != "n"), F.lit(0))
    sizes = (F.col("v_n") >= theta * F.col("u_n") - 1e-6) & (F.col("u_n") >= theta * F.col("v_n") - 1e-6)
    near = sizes & (apart <= (1 - theta) / (1 + theta) * (F.col("u_n") + F.col("v_n")) + 1e-6)
    return side("u").join(side("v"), "bucket").where((F.col("u") < F.col("v")) & near).select("u", "v").distinct()


def verify(pairs: DataFrame, sets: DataFrame, theta: float = THETA, key: str = "doc_id") -> DataFrame:
    """(u, v, jaccard) of the pairs whose exact Jaccard reaches ``theta``."""
    left = sets.select(F.col(key).alias("u"), F.col("sh").alias("a"))
    right = sets.select(F.col(key).alias("v"), F.col("sh").alias("b"))
    return pairs.join(left, "u").join(right, "v").select("u", "v", jaccard(F.col("a"), F.col("b")).alias("jaccard")).where(F.col("jaccard") >= theta)


def estimate(pairs: DataFrame, sigs: DataFrame, key: str = "doc_id") -> DataFrame:
    """(u, v, estimate): share of equal signature places."""
    left, right = sigs.select(F.col(key).alias("u"), F.col("sig").alias("a")), sigs.select(F.col(key).alias("v"), F.col("sig").alias("b"))
    same = F.aggregate(F.zip_with("a", "b", lambda x, y: F.when(x == y, 1).otherwise(0)), F.lit(0), lambda s, x: s + x)
    return pairs.join(left, "u").join(right, "v").select("u", "v", (same / F.size("a")).alias("estimate"))


def fuzzy_links(df: DataFrame, n: int = SHINGLE, perms: int = PERMUTATIONS, bands: int = BANDS, theta: float = THETA, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(u, v, jaccard), u < v: verified links of LSH buckets, closed inside each bucket (``closed_links``)."""
    sets = stage(shingle_sets(df, n, key, text), "shingles")
    return closed_links(stage(lsh_bands(minhash(sets, perms, key), bands, key), "buckets"), sets, theta, key)


def closed_links(buckets: DataFrame, sets: DataFrame, theta: float = THETA, key: str = "doc_id", more: DataFrame | None = None) -> DataFrame:
    """(u, v, jaccard), u < v, that connect what the links of all pairs inside buckets connect, and that lead each row which
    has such a link to a smaller id to one. The star first; then, in buckets with members that aren't linked to the least,
    these members against all others. ``more``: pairs (u, v), u < v, that another search found; they are verified with the star."""
    pairs = star_candidates(buckets, key)
    pairs = pairs if more is None else pairs.unionByName(more).distinct()
    star = stage(verify(pairs, sets, theta, key), "star-links")
    return star.unionAll(_open_links(buckets, star, sets, theta, key))


def _open_links(buckets: DataFrame, star: DataFrame, sets: DataFrame, theta: float, key: str) -> DataFrame:
    """What the star misses. Two members that the star has linked to smaller ids, in the component of the bucket's least, need no
    comparison; all other pairs are compared exactly. Equal sets count once; a bucket is cut into tiles and each pair of tiles
    is one group of bounded size."""
    at = ["band", "bucket"]
    low = star.select(F.col("v").alias(key), F.lit(True).alias("low")).distinct()
    state = stage(star_forest(star.select("u", "v")).select(F.col("u").alias(key), F.col("v").alias("root")).join(low, key, "left"), "star-state")

    def root_of(rows: DataFrame, column: str) -> DataFrame:
        known = state.select(F.col(key).alias(column), F.col("root").alias(f"root_{column}"), F.col("low").alias(f"low_{column}"))
        return rows.join(known, column, "left").withColumn(f"root_{column}", F.coalesce(f"root_{column}", column))

    many = buckets.groupBy(*at).agg(F.min(key).alias("u"), F.count("*").alias("n")).where("n > 2")
    rows = root_of(buckets.join(stage(root_of(many, "u").select(*at, "u", "root_u"), "bucket-roots"), at).where(F.col(key) > F.col("u")), key)
    rows = stage(rows.select(*at, key, ((F.col(f"root_{key}") != F.col("root_u")) | F.col(f"low_{key}").isNull()).alias("open")), "bucket-members")
    rows = stage(rows.join(stage(rows.where("open").select(*at).distinct(), "open-buckets"), at, "left_semi"), "open-members")
    own = stage(sets.join(rows.select(key).distinct(), key, "left_semi").select(key, "sh", F.xxhash64("sh").alias("same")), "open-sets")
    reps = own.groupBy("same").agg(F.min(key).alias("rep"))
    of = stage(own.select(key, "same", F.size("sh").alias("w")).join(reps, "same").select(key, "rep", "w"), "copies")
    copies = of.where(F.col(key) > F.col("rep")).select(F.col("rep").alias("u"), F.col(key).alias("v"), F.lit(1.0).alias("jaccard"))
    members = stage(rows.join(of, key).groupBy(*at, "rep").agg(F.max("open").alias("open"), F.max("w").alias("w")), "members")
    size = F.greatest(F.ceil(F.col("n") / TILE), F.ceil(F.col("all") / TILE_SHINGLES)).cast("int")
    sizes = members.groupBy(*at).agg(F.count("*").alias("n"), F.sum("w").alias("all"), F.max("open").alias("some")).where("n > 1 and some")
    tiled = members.join(sizes.select(*at, size.alias("tiles")), at).withColumn("own", (h32(F.concat(F.lit("tile:"), F.col("rep"))) % F.col("tiles")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("tiles") - 1))
    sent = tiled.select(*at, "own", other.alias("o"), F.col("rep").alias(key), "open").join(own.select(key, "sh"), key)
    pairs = sent.select(*at, F.least("own", "o").alias("ta"), F.greatest("own", "o").alias("tb"), "own", F.col(key).cast("bigint").alias("id"), "open", "sh")

    def product(name, group):  # no hints: Spark would try to infer another kind of function from them
        group = group.sort_by("id")
        ids, own, free = (group.column(c).to_numpy() for c in ("id", "own", "open"))
        sh = group.column("sh").combine_chunks()
        values, lengths = sh.flatten().to_numpy(), sh.value_lengths().to_numpy().astype(np.int64)
        row, sizes = np.repeat(np.arange(len(ids)), lengths), lengths.astype(float)
        hit, sim = np.zeros((len(ids), len(ids)), bool), np.zeros((len(ids), len(ids)))
        ta, tb = name[2].as_py(), name[3].as_py()
        for left, right in {(ta, tb), (tb, ta)}:
            i, j = np.flatnonzero((own == left) & free), np.flatnonzero(own == right)
            if len(i) and len(j):
                both = _shared(values, row, i, j)
                alike = both / (sizes[i][:, None] + sizes[j] - both)
                found = (alike >= theta) & (ids[i][:, None] != ids[j])
                hit[np.ix_(i, j)] |= found
                hit[np.ix_(j, i)] |= found.T
                sim[np.ix_(i, j)], sim[np.ix_(j, i)] = alike, alike.T
        links = {(int(hit[v, :v].argmax()), v) for v in range(len(ids)) if hit[v, :v].any()}  # the least of each row's partners
        rest = np.ones(len(ids), bool)
        while rest.any():  # and a spanning forest
            todo = [int(rest.argmax())]
            rest[todo[0]] = False
            while todo:
                at = todo.pop()
                new = np.flatnonzero(hit[at] & rest)
                rest[new] = False
                todo.extend(new.tolist())
                links.update((min(at, k), max(at, k)) for k in new.tolist())
        a, b = (np.array([x[k] for x in sorted(links)], int) for k in (0, 1))
        return pa.table({"u": ids[a], "v": ids[b], "jaccard": sim[a, b]})

    found = pairs.groupBy(*at, "ta", "tb").applyInArrow(product, "u long, v long, jaccard double")
    more = copies.select(F.col("u").cast("bigint").alias("u"), F.col("v").cast("bigint").alias("v"), "jaccard").unionAll(found)
    needed = (F.col("root_u") != F.col("root_v")) | F.col("low_v").isNull()
    return root_of(root_of(stage(more.dropDuplicates(["u", "v"]), "open-links"), "u"), "v").where(needed).select("u", "v", "jaccard")


def _shared(values: np.ndarray, row: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Numbers of values that rows ``left`` and ``right`` share, as dense products over blocks of their common vocabulary."""
    place = np.full(row.max() + 1, -1)
    sides = []
    for side in (left, right):
        place[:] = -1
        place[side] = np.arange(len(side))
        mine = place[row] >= 0
        sides.append((values[mine], place[row[mine]]))
    words = np.intersect1d(sides[0][0], sides[1][0])
    out = np.zeros((len(left), len(right)), np.float64)
    for at in range(0, len(words), BLOCK):
        part, dense = words[at : at + BLOCK], []
        for (v, r), side in zip(sides, (left, right), strict=True):
            k = np.minimum(np.searchsorted(part, v), len(part) - 1)
            known = part[k] == v
            m = np.zeros((len(side), len(part)), np.float32)
            m[r[known], k[known]] = 1
            dense.append(m)
        out += dense[0] @ dense[1].T
    return out


def fuzzy_components(df: DataFrame, links: DataFrame, key: str = "doc_id") -> DataFrame:
    """(key, component): least id that links lead to, itself included."""
    tree = star_forest(links.select("u", "v")).select(F.col("u").alias(key), F.col("v").alias("__root"))
    return df.select(key).join(tree, key, "left").select(key, F.coalesce("__root", key).alias("component"))


def fuzzy_dedup(df: DataFrame, links: DataFrame | None = None, order: Sequence[str] | None = None, closure: str = "components", key: str = "doc_id", text: str = "text") -> DataFrame:
    """``df`` without near copies. ``components``: one row of each component (least id, or first by ``order``);
    ``greedy``: drop every row that has a verified link to a smaller id."""
    links = fuzzy_links(df, key=key, text=text) if links is None else links
    if closure == "greedy":
        return df.join(links.select(F.col("v").alias(key)).distinct(), key, "left_anti")
    parts = fuzzy_components(df, links, key)
    if order:
        parts = parts.join(df.select(key, *order), key)
    best = parts.groupBy("component").agg(F.min(F.struct(*(order or ()), key)).alias("b")).select(F.col(f"b.{key}").alias(key))
    return df.join(best, key, "left_semi")


def _cell_frequencies(sets: DataFrame) -> np.ndarray:
    """Number of sets by cell of their shingles (shingle modulo the cells), at most 255. Tasks send slices of bytes."""
    total = sets.agg(F.sum(F.size("sh"))).first()[0] or 0
    cells = min(max(1 << int(3 * total // 2).bit_length(), SLICE), CELLS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(cells, np.uint8)
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                cell, n = np.unique(batch.column(0).slice(at, 512).flatten().to_numpy() % cells, return_counts=True)
                seen[cell] = np.minimum(seen[cell] + n, 255)
        some = [i for i in range(cells // SLICE) if seen[i * SLICE : (i + 1) * SLICE].any()]
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array([seen[i * SLICE : (i + 1) * SLICE].tobytes() for i in some], pa.binary())], ["slice", "seen"])

    def add(group):  # no hints: Spark would try to infer another kind of function from them
        seen = np.zeros(SLICE, np.int64)
        for x in group.column("seen"):
            seen += np.frombuffer(x.as_buffer(), np.uint8)
        return pa.table({"slice": group.column("slice")[:1], "seen": pa.array([np.minimum(seen, 255).astype(np.uint8).tobytes()], pa.binary())})

    out = np.zeros(cells, np.uint8)
    for r in sets.select("sh").mapInArrow(run, "slice int, seen binary").groupBy("slice").applyInArrow(add, "slice int, seen binary").toLocalIterator():  # CELLS bytes
        out[r["slice"] * SLICE : (r["slice"] + 1) * SLICE] = np.frombuffer(r["seen"], np.uint8)
    return out


def exact_jaccard_pairs(sets: DataFrame, theta: float, key: str = "doc_id") -> DataFrame:
    """All pairs with Jaccard >= theta by prefix filtering: shingles have one order, rare first, and only a set's first
    |s| - ceil(theta |s|) + 1 shingles can be the first shared one, so only those are joined.

    Rare is what has a rare cell: cells are counted and sent to the tasks, so no shingle is shuffled for its frequency. A shingle alone
    in its cell has no partner and isn't joined."""
    shared = sets.sparkSession.sparkContext.broadcast(_cell_frequencies(sets))
    kind = sets.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                lists = part.column(1)
                size, values = np.nan_to_num(lists.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64), lists.flatten().to_numpy()
                row, often = np.repeat(np.arange(len(size)), size), seen[values % len(seen)]
                order = np.lexsort((values, often, row))
                place = np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)
                own = order[(place < (size - np.ceil(theta * size) + 1)[row]) & (often[order] > 1)]
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(row[own])), pa.array(size[row[own]]), pa.array(values[own])], [key, "n", "g"])

    prefix = stage(sets.select(key, F.col("sh").cast("array<long>").alias("sh")).mapInArrow(run, f"`{key}` {kind}, n long, g long"), "prefixes")
    a, b = prefix.select(F.col(key).alias("u"), F.col("n").alias("nu"), "g"), prefix.select(F.col(key).alias("v"), F.col("n").alias("nv"), "g")
    near = (F.col("u") < F.col("v")) & (F.col("nv") >= theta * F.col("nu")) & (F.col("nu") >= theta * F.col("nv"))
    return verify(a.join(b, "g").where(near).select("u", "v").distinct(), sets, theta, key)


def lsh_curve(pairs: DataFrame, bands: int = BANDS, rows: int = PERMUTATIONS // BANDS, steps: int = 20) -> DataFrame:
    """(s, pairs, detected): of the pairs (u, v, jaccard) by steps of s, their number and the mean chance that such a pair meets in a
    band."""
    s = F.floor(F.col("jaccard") * steps + 1e-9) / float(steps)
    chance = 1 - F.pow(1 - F.pow(F.col("jaccard"), F.lit(float(rows))), F.lit(float(bands)))
    return pairs.groupBy(s.alias("s")).agg(F.count("*").alias("pairs"), F.avg(chance).alias("detected"))


def mean_jaccard(df: DataFrame, n: int = 3, key: str = "doc_id", text: str = "text", partners: int = 4, seed: str = "pairs") -> DataFrame:
    """Mean Jaccard of random pairs of distinct rows: each row with ``partners`` others, drawn by joining rows on the neighbours
    of a random position. Linear; for all pairs use exact counts on small tables."""
    sets = shingle_sets(df, n, key, text)
    spots = sets.select(F.col(key).alias("u"), F.col("sh").alias("a"), F.explode(F.sequence(F.lit(1), F.lit(partners))).alias("k"))
    cell = sets.select(F.col(key).alias("v"), F.col("sh").alias("b"), F.explode(F.sequence(F.lit(1), F.lit(partners))).alias("k"))
    slots = F.greatest(F.lit(1), F.col("n"))
    total = sets.agg(F.count("*").alias("n"))
    left = spots.crossJoin(F.broadcast(total)).withColumn("slot", h32(F.concat_ws(":", F.lit(seed), "k", "u", F.lit("l"))) % slots)
    right = cell.crossJoin(F.broadcast(total)).withColumn("slot", h32(F.concat_ws(":", F.lit(seed), "k", "v", F.lit("r"))) % slots)
    pairs = left.join(right.drop("n"), ["k", "slot"]).where("u <> v")
    return pairs.agg(F.avg(jaccard(F.col("a"), F.col("b"))).alias("mean_jaccard"), F.count("*").alias("pairs"))


def mean_jaccard_exact(df: DataFrame, n: int = 3, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Mean over all pairs: only pairs that share a shingle add to the sum (``mean_jaccard_arms``)."""
    return mean_jaccard_arms(df.withColumn("__all", F.lit(True)), ("__all",), n, key, text).select("mean_jaccard")


def mean_jaccard_arms(df: DataFrame, arms: Sequence[str], n: int = 3, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(arm, docs, mean_jaccard): mean over all pairs of the rows of each arm (a boolean column), all arms in one pass.

    Equal sets are one class that counts for its rows in each arm, and shingles of exactly the same classes are one shingle that
    counts for all of them (classes and shingles are compared by 128 bits). What is left costs the sum of squared frequencies
    of such shingles: for tables of moderate size, or after dedup; otherwise ``mean_jaccard``.
    """
    count = lambda c: F.count(F.when(F.col(c), 1))
    sizes = df.agg(*[count(a).alias(a) for a in arms])
    sets = stage(shingle_sets(df, n, key, text), "jaccard-sets").where(F.size("sh") > 0)
    own = sets.select(key, F.size("sh").alias("n"), F.xxhash64("sh").alias("a"), F.xxhash64(F.lit(1), "sh").alias("b")).join(df.select(key, *arms), key)
    classes = stage(own.groupBy("a", "b").agg(F.min(key).alias(key), F.first("n").alias("n"), *[count(a).alias(a) for a in arms]).drop("a", "b"), "jaccard-classes")
    flat = sets.join(classes.select(key), key, "left_semi").select(key, F.explode("sh").alias("g"))
    lists = flat.groupBy("g").agg(F.count("*").alias("f"), F.bit_xor(F.xxhash64(key)).alias("a"), F.bit_xor(F.xxhash64(F.lit(1), key)).alias("b")).where("f > 1")
    shared = stage(lists.groupBy("f", "a", "b").agg(F.min("g").alias("g"), F.count("*").alias("w")).select("g", "w"), "jaccard-shared")
    places = stage(flat.join(shared, "g").join(classes, key), "jaccard-places")
    side = lambda c: places.select("g", F.col(key).alias(c), F.col("n").alias(f"n{c}"), *[F.col(x).alias(f"{c}_{x}") for x in arms], *(["w"] if c == "u" else []))
    more = [f"{c}_{x}" for c in "uv" for x in arms]
    pairs = side("u").join(side("v"), "g").where("u < v").groupBy("u", "v").agg(F.sum("w").alias("c"), *[F.first(x).alias(x) for x in ("nu", "nv", *more)])
    alike = F.col("c") / (F.col("nu") + F.col("nv") - F.col("c"))
    apart = pairs.agg(*[F.coalesce(F.sum(alike * F.col(f"u_{x}") * F.col(f"v_{x}")), F.lit(0.0)).alias(f"s_{x}") for x in arms])
    inside = classes.agg(*[F.coalesce(F.sum(F.col(x) * (F.col(x) - 1) / 2), F.lit(0.0)).alias(f"i_{x}") for x in arms])
    row = sizes.crossJoin(apart).crossJoin(inside)
    flat_rows = row.selectExpr(f"stack({len(arms)}, " + ", ".join(f"'{x}', {x}, s_{x} + i_{x}" for x in arms) + ") AS (arm, docs, s)")
    every = F.col("docs").cast("double") * (F.col("docs") - 1) / 2
    return flat_rows.select("arm", "docs", (F.col("s") / F.nullif(every, F.lit(0.0))).alias("mean_jaccard"))
