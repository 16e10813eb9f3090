"""Exact BM25 top-k by block-max WAND on inverted indexes of shards.

A shard is a bounded run of documents of one task, indexed by term hash (64 bits of XXH64). Statistics (rows, mean length,
document frequencies) are global, so scores of different shards compare and their top-k lists merge exactly. In a shard,
documents with alike frequent words stand together, on one grid of blocks of BLOCK documents for all terms; each term has its
largest impact in each block it occurs in.

A query runs on a shard with one cursor a term, sorted by what a posting can add. Shallow moves add up block maxima, never
reading postings; the cursors that can add most are moved over their postings. Both together bound every document. The pivot is
the next document in document order whose bound reaches the k-th best score so far; all before it are skipped. Only pivots are
scored on all their postings (the deep move), which feeds the heap of the best k and so raises the bar. As the grid of blocks is
common to all terms, the moves of all cursors are vector sums, and some pivots are scored at a time.

Whole texts as queries share their common words: these have most of the postings, and each query would move its cursors over the
same ones. Queries with many such postings go in batches. The impacts of a shard's common terms stand in a slab of bounded size,
with their block maxima beside it, and one product moves the common cursors of a batch: over the block maxima first, then over the
blocks that a query of the batch can still reach. Products in single precision are raised by their error, so they stay bounds.

A fixed share of the shards is searched first; the k-th best score found there is where the search of the others starts from,
so that these skip nearly all blocks and send on only documents that may be among the best of all.
"""

from __future__ import annotations

import heapq
import re
import uuid
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import map_arrow, shared_dir, stage, table

K1, B = 1.2, 0.75
TOP = 10
#: Bounds of a shard, documents in a block, pivots that are scored together, blocks that prime the heap.
SHARD_DOCS, SHARD_POSTINGS = 8192, 6_000_000
BLOCK = 16
PIVOTS, PRIME = 64, 4
#: Share of the floor that cursors may add together and still count by their block maxima only.
LAZY = 0.2
#: Queries of a batch. A term of one in COMMON documents is common; numbers in the slab of a shard's common terms; multiply-adds
#: of a product that take as long as a posting.
BATCH, COMMON, SLAB, DENSE = 32, 16, 8_000_000, 200
#: Bytes of query terms in a set that travels to the tasks.
SET_BYTES = 32 << 20
#: Terms whose frequencies travel as one row.
SLICE = 4096
#: One in so many shards is searched first.
FIRST = 8
DIGITS = 6
#: Scores are ranked as rounded: what is within this of the bar may still tie with it.
SLACK = 2e-6
WORD = re.compile(r"[^\W_]+")

INDEX = "n_docs int, n_words long, ids binary, lengths binary, terms binary, cuts binary, docs binary, counts binary"


def words_of(text: str | None) -> list[str]:
    """Runs of letters and digits of the lower-cased whole text."""
    return WORD.findall((text or "").lower())


class _Vocabulary(dict):
    def __missing__(self, word: str) -> int:
        self[word] = n = len(self)
        return n


def _narrow(numbers: np.ndarray) -> np.ndarray:
    """As unsigned numbers of the least width that holds all: a shard's row is what the JVM holds whole."""
    most = int(numbers.max()) if len(numbers) else 0
    return numbers.astype(np.uint8 if most < 1 << 8 else np.uint16 if most < 1 << 16 else np.uint32)


def _widened(blob, n: int) -> np.ndarray:
    return np.frombuffer(blob, f"u{len(memoryview(blob)) // n}") if n else np.zeros(0, np.uint8)


class _ShardBuilder:
    def __init__(self) -> None:
        self.vocab = _Vocabulary()
        self.ids: list[int] = []
        self.lengths: list[int] = []
        self.terms: list[np.ndarray] = []
        self.counts: list[np.ndarray] = []
        self.size = 0

    def add(self, key: int, text: str | None) -> None:
        words = words_of(text)
        bag = Counter(words)
        self.ids.append(key)
        self.lengths.append(len(words))
        self.terms.append(np.fromiter(map(self.vocab.__getitem__, bag), np.int32, len(bag)))
        self.counts.append(np.fromiter(bag.values(), np.int32, len(bag)))
        self.size += len(bag)

    def full(self) -> bool:
        return len(self.ids) >= SHARD_DOCS or self.size >= SHARD_POSTINGS

    def build(self) -> pa.RecordBatch:
        from xxhash import xxh64_intdigest

        hashes = np.fromiter((xxh64_intdigest(w) for w in self.vocab), np.uint64, len(self.vocab))
        sizes = np.array([len(t) for t in self.terms])
        terms = np.concatenate(self.terms) if self.size else np.zeros(0, np.int32)
        counts = np.concatenate(self.counts) if self.size else np.zeros(0, np.int32)
        # Order of documents: by their most frequent words, then length, so that blocks hold documents that score alike.
        lead = np.array([int(hashes[t[np.argmax(c)]] >> np.uint64(1)) if len(t) else 0 for t, c in zip(self.terms, self.counts, strict=True)])
        order = np.lexsort((np.array(self.lengths), lead))
        place = np.empty(len(order), np.int32)
        place[order] = np.arange(len(order), dtype=np.int32)
        docs = np.repeat(place, sizes)
        rank = np.argsort(hashes, kind="stable")
        nth = np.empty(len(rank), np.int32)
        nth[rank] = np.arange(len(rank), dtype=np.int32)
        by_term = np.lexsort((docs, nth[terms])) if self.size else np.zeros(0, int)
        cuts = np.concatenate([[0], np.cumsum(np.bincount(nth[terms], minlength=len(rank)))]).astype(np.int64)
        blob = lambda a: pa.array([a.tobytes()], pa.binary())
        return pa.RecordBatch.from_arrays(
            [
                pa.array([len(self.ids)], pa.int32()), pa.array([int(sum(self.lengths))], pa.int64()),
                blob(np.array(self.ids, np.int64)[order]), blob(np.array(self.lengths, np.int32)[order]),
                blob(hashes[rank]), blob(cuts), blob(_narrow(docs[by_term])), blob(_narrow(counts[by_term])),
            ],
            ["n_docs", "n_words", "ids", "lengths", "terms", "cuts", "docs", "counts"],
        )


def build_index(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One staged row for each shard. Rows with a null id are left out (they can't be named in a result)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard = _ShardBuilder()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                for key, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    shard.add(key, text)
                    if shard.full():
                        yield shard.build()
                        shard = _ShardBuilder()
        if shard.ids:
            yield shard.build()

    rows = df.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), text_col)
    return stage(rows.mapInArrow(run, INDEX), "search-index")


@dataclass
class Queries:
    """A bounded set of queries: sorted term hashes with idf, and for each query its terms and their counts."""

    ids: np.ndarray
    terms: np.ndarray
    idf: np.ndarray
    cuts: np.ndarray
    which: np.ndarray
    counts: np.ndarray
    mean: float


def _query_bags(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    def build():
        from xxhash import xxh64_intdigest

        def one(batch: pa.RecordBatch) -> pa.RecordBatch:
            terms, counts = [], []
            for text in batch.column(1).to_pylist():
                bag = Counter(words_of(text))
                terms.append(np.fromiter(map(xxh64_intdigest, bag), np.uint64, len(bag)).tobytes())
                counts.append(np.fromiter(bag.values(), np.int32, len(bag)).tobytes())
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(terms, pa.binary()), pa.array(counts, pa.binary())], ["id", "terms", "counts"])

        return one

    rows = df.where(F.col(id_col).isNotNull()).groupBy(F.col(id_col).cast("long").alias("id")).agg(F.min(text_col).alias("text"))
    return stage(map_arrow(rows, build, "id long, terms binary, counts binary"), "queries")


class Shard:
    """The postings of one index row, cut to the terms of a set of queries, with their block maxima.

    Documents stand on one grid of blocks for all terms. Postings are kept by term (for the cursors) and by document (to score
    a pivot). An entry is a term's run of postings in one block, with the largest impact in it.
    """

    def __init__(self, row: dict, queries: Queries):
        self.ids = np.frombuffer(row["ids"], np.int64)
        n, lengths = len(self.ids), np.frombuffer(row["lengths"], np.int32)
        terms, cuts = np.frombuffer(row["terms"], np.uint64), np.frombuffer(row["cuts"], np.int64)
        n_postings = int(cuts[-1])
        docs, counts = _widened(row["docs"], n_postings), _widened(row["counts"], n_postings)
        self.blocks = -(-n // BLOCK)
        at = np.searchsorted(terms, queries.terms)
        at[at == len(terms)] = 0
        held = terms[at] == queries.terms if len(terms) else np.zeros(len(queries.terms), bool)
        begin, size = np.where(held, cuts[at] if len(terms) else 0, 0), np.where(held, cuts[at + 1] - cuts[at] if len(terms) else 0, 0)
        flat = np.repeat(begin - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum())
        tf, self.doc = counts[flat].astype(float), docs[flat].astype(np.int32)
        norm = K1 * (1 - B + B * lengths / max(queries.mean, 1e-9))
        self.impact = tf * (K1 + 1) / (tf + norm[self.doc]) * np.repeat(queries.idf, size)
        self.begin = np.concatenate([[0], np.cumsum(size)])
        block = self.doc // BLOCK
        fresh = np.ones(len(block), bool)
        fresh[1:] = block[1:] != block[:-1]
        fresh[self.begin[:-1][size > 0]] = True
        starts = np.flatnonzero(fresh)
        self.block = block[starts]
        self.peak = np.maximum.reduceat(self.impact, starts) if len(starts) else np.zeros(0)
        self.entries = np.searchsorted(starts, self.begin)  # those of term t: entries[t] to entries[t + 1]
        self.most = np.zeros(len(size))
        np.maximum.at(self.most, np.repeat(np.arange(len(size)), np.diff(self.entries)), self.peak)
        order = np.argsort(self.doc.astype(np.uint16) if n <= 1 << 16 else self.doc, kind="stable")
        self.own_term, self.own_impact = np.repeat(np.arange(len(size), dtype=np.int32), size)[order], self.impact[order]
        self.own_begin = np.concatenate([[0], np.cumsum(np.bincount(self.doc, minlength=n))])
        self.weight = np.zeros(len(size))  # of the query at work
        self._slab(size)

    def _slab(self, size: np.ndarray) -> None:
        """Impacts of the common terms (``column`` of the slab by term, else -1), a row a document, and the largest of each block."""
        n = len(self.ids)
        most = np.argsort(-size, kind="stable")[: SLAB // max(self.blocks * BLOCK, 1)]
        common = most[size[most] * COMMON >= max(n, COMMON)]
        self.column = np.full(len(size), -1, np.int32)
        self.column[common] = np.arange(len(common), dtype=np.int32)
        own, each = _spans(self.begin, common)
        self.slab = np.zeros((self.blocks * BLOCK, len(common)), np.float32)
        self.slab[self.doc[own], np.repeat(np.arange(len(common)), each)] = self.impact[own]
        self.peaks = self.slab.reshape(self.blocks, BLOCK, len(common)).max(1)
        self.raised = 1 + (len(common) + 8) * 2.0**-23  # all impacts are positive: more than a product can lose


def _spans(begin: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions begin[i]..begin[i + 1] of all i end to end, and how many each has."""
    size = begin[which + 1] - begin[which]
    return np.repeat(begin[which] - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum()), size


class Cursors:
    """One query's cursors on a shard: a term each, sorted by what they can add for a posting, moved in document order."""

    def __init__(self, shard: Shard, terms: np.ndarray, counts: np.ndarray, shallow: bool = True):
        self.shard, self.read = shard, 0
        size = shard.begin[terms + 1] - shard.begin[terms]
        if not shallow:  # of a batch
            self.terms, self.counts = terms[size > 0], counts[size > 0].astype(float)
            return
        order = np.argsort(counts * shard.most[terms] / np.maximum(size, 1), kind="stable")
        order = order[size[order] > 0]
        self.terms, self.counts = terms[order], counts[order].astype(float)
        self.upto = np.cumsum(self.counts * shard.most[self.terms])
        self.bound = self._shallow(0, len(self.terms))

    def _shallow(self, a: int, b: int) -> np.ndarray:
        """Sum of the block maxima of cursors a to b, for each block; no posting is read."""
        own, size = _spans(self.shard.entries, self.terms[a:b])
        return np.bincount(self.shard.block[own], np.repeat(self.counts[a:b], size) * self.shard.peak[own], self.shard.blocks)

    def limits(self, floor: float) -> np.ndarray:
        """An upper bound for each document. The last cursors, which can add most, are moved over their postings; the others
        (together at most LAZY of ``floor``) count by the maximum of the document's block."""
        lead = int(np.searchsorted(self.upto, LAZY * floor, "right"))
        own, size = _spans(self.shard.begin, self.terms[lead:])
        self.read += len(own)
        exact = np.bincount(self.shard.doc[own], np.repeat(self.counts[lead:], size) * self.shard.impact[own], len(self.shard.ids))
        return exact + np.repeat(self._shallow(0, lead), BLOCK)[: len(exact)]

    def moved(self, which: np.ndarray, places: int) -> np.ndarray:
        """Sums of these cursors, moved over all their postings, by document."""
        own, size = _spans(self.shard.begin, self.terms[which])
        self.read += len(own)
        return np.bincount(self.shard.doc[own], np.repeat(self.counts[which], size) * self.shard.impact[own], places)

    def pivot(self, best: Best, limit: np.ndarray, docs: np.ndarray | None = None) -> None:
        """Scores the documents (``docs``, or all) whose limit reaches the floor, PIVOTS at a time, in document order."""
        at = 0
        while True:
            pivots = at + np.flatnonzero(limit[at:] >= best.floor)[:PIVOTS]
            if not len(pivots):
                return
            self.deepen(best, pivots if docs is None else docs[pivots])
            at = int(pivots[-1]) + 1

    def deepen(self, best: Best, docs: np.ndarray) -> None:
        best.add(self.score(docs), self.shard.ids[docs])

    def score(self, docs: np.ndarray) -> np.ndarray:
        """The deep move: scores of the documents, from all their postings."""
        shard = self.shard
        shard.weight[self.terms] = self.counts
        own, size = _spans(shard.own_begin, docs)
        self.read += len(own)
        out = np.bincount(np.repeat(np.arange(len(docs)), size), shard.weight[shard.own_term[own]] * shard.own_impact[own], len(docs))
        shard.weight[self.terms] = 0.0
        return out


class Best:
    """Heap of the best ``top`` (score, -id); ``floor`` is what a bound must reach to matter."""

    def __init__(self, top: int, start: float):
        self.top, self.heap, self.floor = top, [], max(start - SLACK, SLACK / 10)

    def add(self, scores: np.ndarray, ids: np.ndarray) -> None:
        for score, key in zip(np.round(scores, DIGITS).tolist(), ids.tolist(), strict=True):
            if score <= 0 or len(self.heap) == self.top and (score, -key) <= self.heap[0]:
                continue
            (heapq.heappush if len(self.heap) < self.top else heapq.heapreplace)(self.heap, (score, -key))
        if len(self.heap) == self.top:
            self.floor = max(self.floor, self.heap[0][0] - SLACK)

    def found(self, start: float) -> list[tuple[float, int]]:
        return sorted(((s, -k) for s, k in self.heap if s >= start), key=lambda x: (-x[0], x[1]))


def search_one(cursors: Cursors, top: int, start: float = 0.0) -> list[tuple[float, int]]:
    """(score, id) of the shard's best ``top`` for one query, of those that reach ``start``, best first.

    Without a start, the blocks of the highest bounds prime the heap. Then the pivot is the next document, in document order, whose bound reaches
    the floor; PIVOTS of them are scored together, which raises the floor for those behind.
    """
    shard, best = cursors.shard, Best(top, start)
    if cursors.bound.size and cursors.bound.max() >= best.floor:
        ahead = np.argsort(-cursors.bound, kind="stable")[: 0 if start else PRIME]
        docs = _documents(ahead, len(shard.ids))
        cursors.deepen(best, docs)
        limit = cursors.limits(best.floor)
        limit[docs] = 0.0
        cursors.pivot(best, limit)
    return best.found(start)


def search_batch(shard: Shard, queries: list[Cursors], starts: list[float], top: int) -> list[list[tuple[float, int]]]:
    """What ``search_one`` finds, for queries with many postings of common terms, whose common cursors move together.

    The other cursors move over their postings. Their sums and the block maxima of the common terms bound each block; only blocks that a
    query of the batch can reach are moved over document by document. Pivots are as in ``search_one``.
    """
    columns = [shard.column[q.terms] for q in queries]
    weights = np.zeros((len(queries), shard.slab.shape[1]), np.float32)
    for w, q, c in zip(weights, queries, columns, strict=True):
        w[c[c >= 0]] = q.counts[c >= 0]
    exact = np.zeros((len(queries), shard.blocks, BLOCK))
    for x, q, c in zip(exact, queries, columns, strict=True):
        x.ravel()[:] = q.moved(c < 0, shard.blocks * BLOCK)
    bound = (weights @ shard.peaks.T) * shard.raised + exact.max(2)
    best = [Best(top, s) for s in starts]
    for q, x, b, h in zip(queries, exact, bound, best, strict=True):
        if h.floor < SLACK:  # no start: the block of the highest bound primes the heap
            docs = _documents(b.argmax()[None], len(shard.ids))
            q.deepen(h, docs)
            x.ravel()[docs] = -np.inf
    blocks = np.flatnonzero((bound >= np.array([h.floor for h in best])[:, None]).any(0))
    docs = _documents(blocks, len(shard.ids))
    rows = shard.slab[: len(shard.ids)] if len(blocks) == shard.blocks else shard.slab[docs]
    limits = (weights @ rows.T) * shard.raised
    for q, x, limit, h in zip(queries, exact, limits, best, strict=True):
        limit = limit + x.ravel()[docs]
        ahead = np.flatnonzero(limit >= h.floor)
        if len(ahead) > PIVOTS:  # those of the highest limits raise the floor for the others
            high = ahead[np.argpartition(-limit[ahead], top)[:top]] if len(ahead) > top else ahead
            q.deepen(h, docs[high])
            limit[high] = -np.inf
        q.pivot(h, limit, docs)
    return [h.found(s) for h, s in zip(best, starts, strict=True)]


def _documents(blocks: np.ndarray, n: int) -> np.ndarray:
    docs = (blocks[:, None] * BLOCK + np.arange(BLOCK)).ravel()
    return docs[docs < n]


def search_shard(shard: Shard, queries: Queries, top: int, start: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, int]]:
    """(query ids, document ids, scores, postings read) of some hundred queries at a time."""
    size = np.diff(shard.begin)
    common = np.where(shard.column >= 0, size, 0)
    price = shard.slab.size / DENSE  # postings that take as long as the product
    out: tuple[list, list, list] = ([], [], [])
    read, batch = 0, []

    def add(q: int, found: list) -> None:
        out[0].extend([queries.ids[q]] * len(found))
        out[1].extend(k for _, k in found)
        out[2].extend(s for s, _ in found)

    last = len(queries.ids) - 1
    for q in range(len(queries.ids)):
        own = slice(queries.cuts[q], queries.cuts[q + 1])
        terms, counts, floor = queries.which[own], queries.counts[own], 0.0 if start is None else start[q]
        if common[terms].sum() > price:
            batch.append((q, Cursors(shard, terms, counts, shallow=False), floor))
        else:
            cursors = Cursors(shard, terms, counts)
            add(q, search_one(cursors, top, floor))
            read += cursors.read
        if batch and (len(batch) == BATCH or q == last):
            for (k, cursors, _), found in zip(batch, search_batch(shard, [b[1] for b in batch], [b[2] for b in batch], top), strict=True):
                add(k, found)
                read += cursors.read
            batch = []
        if len(out[0]) > 4096:
            yield np.array(out[0], np.int64), np.array(out[1], np.int64), np.array(out[2], float), read
            out, read = ([], [], []), 0
    if out[0] or read:
        yield np.array(out[0], np.int64), np.array(out[1], np.int64), np.array(out[2], float), read


def _row(batch: pa.RecordBatch, at: int) -> dict[str, pa.Buffer]:
    """The binary columns of one row, not copied."""
    return {f.name: batch.column(k)[at].as_buffer() for k, f in enumerate(batch.schema) if pa.types.is_binary(f.type) or pa.types.is_large_binary(f.type)}


def _gather(bags: list, mean: float) -> Queries:
    ids = np.array([r["id"] for r in bags], np.int64)
    each = [np.frombuffer(r["terms"], np.uint64) for r in bags]
    flat = np.concatenate(each) if each else np.zeros(0, np.uint64)
    terms, which = np.unique(flat, return_inverse=True)
    counts = np.concatenate([np.frombuffer(r["counts"], np.int32) for r in bags]) if bags else np.zeros(0, np.int32)
    cuts = np.concatenate([[0], np.cumsum([len(e) for e in each])]).astype(np.int64)
    return Queries(ids, terms, np.zeros(len(terms)), cuts, which.astype(np.int64), counts, mean)


def _frequencies(index: DataFrame, queries: Queries) -> np.ndarray:
    """Document frequency of each term of the set over all shards: every task adds up its shards, then slices of the sums are
    added in two levels, so that rows grow with tasks and not with tasks times terms."""
    n, terms = len(queries.terms), index.sparkSession.sparkContext.broadcast(queries.terms)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(n, np.int64)
        for batch in batches:
            for row in (_row(batch, at) for at in range(batch.num_rows)):
                own, cuts = np.frombuffer(row["terms"], np.uint64), np.frombuffer(row["cuts"], np.int64)
                if len(own):
                    at = np.minimum(np.searchsorted(own, terms.value), len(own) - 1)
                    hit = np.flatnonzero(own[at] == terms.value)
                    total[hit] += cuts[at[hit] + 1] - cuts[at[hit]]
        if total.any():
            parts = [total[a : a + SLICE].tobytes() for a in range(0, n, SLICE)]
            yield pa.RecordBatch.from_arrays([pa.array(range(len(parts)), pa.int32()), pa.array(parts, pa.binary())], ["slice", "sums"])

    def add(group):  # no hints: Spark would try to infer another kind of function from them
        sums = sum(np.frombuffer(x, np.int64) for x in group.column("sums").to_pylist())
        return pa.table({"slice": pa.array([group.column("slice")[0].as_py()], pa.int32()), "sums": pa.array([sums.tobytes()], pa.binary())})

    parts = index.select("terms", "cuts").mapInArrow(run, "slice int, sums binary").withColumn("part", F.spark_partition_id() % 64)
    level = parts.groupBy("slice", "part").applyInArrow(add, "slice int, sums binary")
    out = np.zeros(n)
    for r in level.groupBy("slice").applyInArrow(add, "slice int, sums binary").collect():  # one number a term of the set
        own = np.frombuffer(r["sums"], np.int64)
        out[r["slice"] * SLICE : r["slice"] * SLICE + len(own)] = own
    return out


def search(index: DataFrame, queries: DataFrame, top: int = TOP, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(query_id, rank, doc_id, score): the best ``top`` documents of each query by BM25, ties by the lower document id.

    A query is a whole text; each of its words counts as often as it occurs. Documents without a word of the query aren't
    returned, so an empty query has no rows. Of queries with one id the one with the least text is run; null ids are left out;
    documents with one id each stand for themselves. Scores are rounded to DIGITS decimals before they are ranked.
    Queries go in sets of bounded size; each set makes one pass over the index and is written before the next.
    """
    spark = index.sparkSession
    bags = _query_bags(queries, id_col, text_col)
    total = index.agg(F.sum("n_docs"), F.sum("n_words")).first()
    n_docs, mean = total[0] or 0, (total[1] or 0) / max(total[0] or 0, 1)
    size = bags.agg(F.sum(F.length("terms") + F.length("counts"))).first()[0] or 0
    sets, early = max(1, -(-size // SET_BYTES)), F.pmod(F.xxhash64("ids"), F.lit(FIRST)) == 0
    path = f"{shared_dir(spark)}/hits-{uuid.uuid4().hex[:12]}"
    for k in range(sets):  # each set is done before the next: plans and what tasks hold don't grow with the queries
        own = _gather(bags.where(F.pmod(F.xxhash64("id"), F.lit(sets)) == k).collect(), mean)  # SET_BYTES on average
        df = _frequencies(index, own)
        own.idf = np.log(1 + (n_docs - df + 0.5) / (df + 0.5))
        first = stage(_best(_hits(index.where(early), own, np.zeros(len(own.ids)), top), top), "first-hits")
        kth = {r["query_id"]: r["score"] for r in first.where(F.col("rank") == top).collect()}  # one number a query of the set
        start = np.array([kth.get(int(q), 0.0) for q in own.ids])
        hits = _best(first.drop("rank").unionAll(_hits(index.where(~early), own, start, top)), top)
        hits.select("query_id", "rank", "doc_id", "score").write.parquet(f"{path}/set={k}")
    return spark.read.schema("query_id long, rank int, doc_id long, score double").parquet(*[f"{path}/set={k}" for k in range(sets)])


def _best(hits: DataFrame, top: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "doc_id")  # at most ``top`` rows of each shard
    return hits.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= top)


def _hits(index: DataFrame, queries: Queries, start: np.ndarray, top: int) -> DataFrame:
    shared = index.sparkSession.sparkContext.broadcast((queries, start))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(batch.num_rows):
                own, floor = shared.value
                shard = Shard(_row(batch, at), own)
                for q, d, s, _ in search_shard(shard, own, top, floor):
                    yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(d), pa.array(s)], ["query_id", "doc_id", "score"])

    return index.mapInArrow(run, "query_id long, doc_id long, score double")


def op8_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document whose id is divisible by 100, as a query against all documents."""
    docs = table(spark, sf_dir, "documents")
    return search(build_index(docs), docs.where("doc_id % 100 = 0"))
