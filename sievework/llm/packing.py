"""Best-fit packing improved by a swap-based local search.

Documents become token ids with an end id; what is longer than a sequence is cut into full pieces behind a shorter
first one. Full pieces are sequences of their own. The others are packed in groups bounded by pieces and tokens, in
the task that made them: best fit by decreasing length, then the local search, which takes the emptiest bin and moves
pieces out of it, exchanges one for one, or one for two (either way), always so that the sum of squared fills grows,
until the bin is empty; it ends at the least possible number of bins or when nothing helps. Pieces of the bins that
stay underfull go through a second pass that brings those of many groups together.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import stage, table
from .tokens import token_ids

CAPACITY = 1024
END_ID = 2
#: Bounds of a packing group.
GROUP_PIECES, GROUP_TOKENS = 50_000, 12_000_000
#: A bin below this share of the capacity is packed again in the second pass.
FULL = 0.985
#: Groups of the first pass whose leftovers one task of the second pass gets.
FAN_IN = 32
ROUNDS, TRIES, EACH = 6, 4, 1000


class Bins:
    """Bins of pieces by length; finds the fullest bin with room in constant time."""

    def __init__(self, capacity: int):
        self.capacity = capacity
        self.pieces: list[list[int]] = []
        self.fill: list[int] = []
        self.by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
        self.mask = 0

    def best_fit(self, lengths: Sequence[int]) -> None:
        """Longest first, each into the bin it leaves least room in."""
        for i in sorted(range(len(lengths)), key=lambda k: -lengths[k]):
            n = lengths[i]
            rooms = self.mask >> n
            if rooms:
                room = n + (rooms & -rooms).bit_length() - 1
                b = self.by_room[room].pop()
                if not self.by_room[room]:
                    self.mask &= ~(1 << room)
            else:
                b, room = len(self.pieces), self.capacity
                self.pieces.append([])
                self.fill.append(0)
            self.pieces[b].append(i)
            self.fill[b] += n
            self.by_room[room - n].append(b)
            self.mask |= 1 << (room - n)

    def improve(self, lengths: Sequence[int], rounds: int = ROUNDS) -> None:
        """Empty bins by moves and swaps among the underfull ones, the emptiest first, into the fullest first.

        Every step adds to the sum of squared fills. Ends at the least possible number of bins, when a round gains nothing, or
        after ``rounds`` rounds; a round looks at TRIES pairs of bins for each open bin at most, and at EACH for one source (what
        is left unpaired stays packed as it is). A source that gave nothing is not tried again until others changed.
        """
        least = -(-sum(lengths) // self.capacity)
        used = sum(f > 0 for f in self.fill)
        stuck: set[int] = set()
        for _ in range(rounds):
            open_bins = sorted((b for b in range(len(self.pieces)) if 0 < self.fill[b] < self.capacity), key=lambda b: self.fill[b])
            gained, tries, most = False, 0, TRIES * len(open_bins)
            for i, source in enumerate(open_bins):
                if used <= least or tries > most:
                    break
                if source in stuck:
                    continue
                before, own = self.fill[source], 0
                for target in reversed(open_bins[i + 1 :]):
                    if self.fill[target] < self.fill[source] or self.fill[target] == self.capacity:
                        continue
                    own += 1
                    while self.fill[source] and self._transfer(source, target, lengths):
                        gained = True
                    if not self.fill[source]:
                        used -= 1
                        break
                    if own >= EACH:
                        break
                tries += own
                if self.fill[source] == before:
                    stuck.add(source)
                else:
                    stuck.clear()
            if used <= least or not gained:
                return

    def _transfer(self, source: int, target: int, lengths: Sequence[int]) -> bool:
        """The exchange between two bins that fills ``target`` most; False if none fits."""
        room = self.capacity - self.fill[target]
        if not room:
            return False
        s = {lengths[i]: i for i in self.pieces[source]}
        t = {lengths[i]: i for i in self.pieces[target]}
        best: tuple[int, tuple[int, ...], tuple[int, ...]] = (0, (), ())
        two_t = {lengths[a] + lengths[b]: (a, b) for k, a in enumerate(self.pieces[target]) for b in self.pieces[target][:k]}
        two_s = {lengths[a] + lengths[b]: (a, b) for k, a in enumerate(self.pieces[source]) for b in self.pieces[source][:k]}
        for n, i in s.items():
            if best[0] < n <= room:
                best = (n, (i,), ())
            for m, j in t.items():
                if best[0] < n - m <= room:
                    best = (n - m, (i,), (j,))
            for m, pair in two_t.items():
                if best[0] < n - m <= room:
                    best = (n - m, (i,), pair)
        for n, pair in two_s.items():
            for m, j in t.items():
                if best[0] < n - m <= room:
                    best = (n - m, pair, (j,))
        gain, out, back = best
        if not gain:
            return False
        self.pieces[source] = [i for i in self.pieces[source] if i not in out] + list(back)
        self.pieces[target] = [i for i in self.pieces[target] if i not in back] + list(out)
        self.fill[source] -= gain
        self.fill[target] += gain
        return True


def pack(lengths: Sequence[int], capacity: int = CAPACITY) -> list[list[int]]:
    """Indices of the pieces of each bin."""
    bins = Bins(capacity)
    bins.best_fit(lengths)
    bins.improve(lengths)
    return [p for p in bins.pieces if p]


def cut(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, length) of the pieces of a document of ``n`` tokens; only the first may be short."""
    first = (n - 1) % capacity + 1
    return [(0, first), *((at, capacity) for at in range(first, n, capacity))]


class _Group:
    """Pieces of one packing group: (id, piece, start, ids) rows."""

    def __init__(self, capacity: int, prefix: int):
        self.capacity, self.next = capacity, prefix
        self.rows: list[tuple] = []
        self.tokens = 0

    def add(self, row: tuple) -> bool:
        self.rows.append(row)
        self.tokens += len(row[3])
        return len(self.rows) >= GROUP_PIECES or self.tokens >= GROUP_TOKENS

    def flush(self, final: bool) -> Iterator[list[tuple]]:
        """Packed rows (id, piece, start, ids, length, sequence, offset, open), some thousand at a time."""
        lengths = [len(r[3]) // 4 for r in self.rows]
        out: list[tuple] = []
        for members in pack(lengths, self.capacity):
            fill, at = sum(lengths[i] for i in members), 0
            for i in members:
                out.append((*self.rows[i], lengths[i], self.next, at, not final and fill < FULL * self.capacity))
                at += lengths[i]
            self.next += 1
            if len(out) > 4096:
                yield out
                out = []
        yield out
        self.rows, self.tokens = [], 0


def _batch(rows: list[tuple], id_type: pa.DataType) -> pa.RecordBatch:
    names = ["__id", "piece", "start", "ids", "length", "sequence_id", "offset", "open"]
    types = [id_type, pa.int32(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.bool_()]
    cols = list(zip(*rows, strict=True)) if rows else [[] for _ in names]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)


def pack_documents(
    df: DataFrame, tokenizer_file: str, end_id: int = END_ID, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """One row for each piece: id, piece, start, length, ids (binary, little-endian unsigned 32-bit), sequence_id, offset.

    A null or empty text is the end id alone. Rows with null or repeated ids are documents of their own; an empty
    table gives no rows; other columns go. Sequence numbers are unique, not consecutive.
    """
    spark = df.sparkSession
    id_type = df.schema[id_col].dataType.simpleString()
    schema = f"__id {id_type}, piece int, start long, ids binary, length long, sequence_id long, offset long, open boolean"

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, kind = _Group(capacity, TaskContext.get().partitionId() << 36), None
        for batch in batches:
            kind = batch.schema.field(0).type
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                whole: list[tuple] = []
                for key, ids in zip(part.column(0).to_pylist(), token_ids(tokenizer_file, part.column(1).to_pylist(), end_id), strict=True):
                    for k, (start, n) in enumerate(cut(len(ids), capacity)):
                        packed = ids[start : start + n].tobytes()
                        if n == capacity:
                            whole.append((key, k, start, packed, n, group.next, 0, False))
                            group.next += 1
                        elif group.add((key, k, start, packed)):
                            for rows in group.flush(False):
                                yield _batch(rows, kind)
                if whole:
                    yield _batch(whole, kind)
        if group.rows:
            for rows in group.flush(False):
                yield _batch(rows, kind)

    def second(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, kind = _Group(capacity, (1 << 60) + (TaskContext.get().partitionId() << 36)), None
        for batch in batches:
            kind = batch.schema.field(0).type
            for row in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if group.add(row):
                    for rows in group.flush(True):
                        yield _batch(rows, kind)
        if group.rows:
            for rows in group.flush(True):
                yield _batch(rows, kind)

    source = df.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text"))
    packed = stage(source.mapInArrow(first, schema), "packed")
    left = packed.where("open")
    groups = left.select(F.expr("sequence_id >> 36").alias("g")).distinct().count()  # tasks of the first pass that left some
    again = left.repartition(max(1, -(-groups // FAN_IN)), F.expr("sequence_id >> 36"))
    both = packed.where("not open").unionAll(again.mapInArrow(second, schema))
    return both.select(F.col("__id").alias(id_col), "piece", "start", "length", "ids", "sequence_id", "offset")


def pack_table(docs: DataFrame) -> DataFrame:
    """Pieces of ``docs`` with the checksum of their ids in place of the ids."""
    import public_tokenizers

    pieces = pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"))
    return pieces.select(
        "doc_id", "piece", "start", "length", F.crc32("ids").alias("ids_crc32"), "sequence_id", "offset"
    )


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_table(table(spark, sf_dir, "documents"))
