"""Byte-level BPE as a lazily determinised finite-state transducer, with a streaming decoder.

A merge list fixes, for each byte string, one canonical token sequence, and a sequence is canonical
exactly when each token is reachable by merges and each adjacent pair is what the merges make of its
two tokens' bytes. The transducer reads bytes; a nondeterministic configuration is (token before,
trie node of the token being read). A deterministic state is the tuple of live configurations, made
when first met; its transition also names the one token that ends a canonical sequence at that byte.
Tokens are emitted as soon as all live configurations share them, so a window of a few token
lengths is all that is held. Transition and piece memos are bounded and start afresh when full.
"""

from __future__ import annotations

import base64
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import map_arrow, table
from .tokens import PLAIN, plain_pattern

MAX_TRANSITIONS = 500_000
MAX_PAIRS = 400_000
MAX_PIECES = 400_000
MEMO_CHARS = 48
START = -1


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class Transducer:
    """Encodes one piece (bytes between two pattern borders) into token ids."""

    def __init__(self, ranks: dict[bytes, int], max_transitions: int = MAX_TRANSITIONS):
        self.ranks = ranks
        self.max_transitions = max_transitions
        self.width = max(map(len, ranks))
        self.bytes_of = {i: b for b, i in ranks.items()}
        self.size_of = {i: len(b) for b, i in ranks.items()}
        self.reachable: dict[int, bool] = {}
        self.pairs: dict[tuple[int, int], bool] = {}
        self.split: dict[int, tuple[int, int] | None] = {}
        self.trie: list[dict[int, int]] = [{}]
        self.token_at: list[int] = [START]
        for token, rank in ranks.items():
            node = 0
            for b in token:
                child = self.trie[node].get(b)
                if child is None:
                    child = self.trie[node][b] = len(self.trie)
                    self.trie.append({})
                    self.token_at.append(START)
                node = child
            self.token_at[node] = rank
        self.reset()

    def reset(self) -> None:
        self.states: list[tuple[tuple[int, int], ...]] = [((START, 0),)]
        self.number = {self.states[0]: 0}
        self.moves: dict[int, tuple[int, int]] = {}

    def merged(self, data: bytes, until: int = 1) -> list[int]:
        """The merges applied to a short byte string, lowest rank first, leftmost on ties; stops at ``until`` parts."""
        parts = [data[i : i + 1] for i in range(len(data))]
        while len(parts) > until:
            best, at = None, -1
            for i in range(len(parts) - 1):
                r = self.ranks.get(parts[i] + parts[i + 1])
                if r is not None and (best is None or r < best):
                    best, at = r, i
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return [self.ranks[p] for p in parts]

    def halves(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes ``token``; None for a single byte."""
        if token not in self.split:
            data = self.bytes_of[token]
            self.split[token] = tuple(self.merged(data, 2)) if len(data) > 1 else None
        return self.split[token]

    def fits(self, left: int, right: int) -> bool:
        """Whether ``right`` may follow ``left`` in a canonical sequence.

        The last merges of both sides are undone, latest first: the pair fails if a merge across the border
        would have come before the merge that is being undone.
        """
        key = (left, right)
        known = self.pairs.get(key)
        if known is None:
            if len(self.pairs) >= MAX_PAIRS:
                self.pairs.clear()
            self.pairs[key] = known = self._apart(left, right)
        return known

    def _apart(self, left: int, right: int) -> bool:
        bytes_of, rank, bound = self.bytes_of, self.ranks.get, 1 << 62
        while True:
            across = rank(bytes_of[left] + bytes_of[right])
            if across is not None and across < bound:
                return False
            in_left, in_right = self.halves(left), self.halves(right)
            if in_left is None and in_right is None:
                return True
            if in_right is None or in_left is not None and left > right:
                bound, left = left, in_left[1]
            else:
                bound, right = right + 1, in_right[0]

    def move(self, state: int, byte: int) -> tuple[int, int]:
        """Determinise one transition: the next state, and the token that ends here."""
        live, last = [], None
        trie, token_at, pairs = self.trie, self.token_at, self.pairs
        for config in self.states[state]:
            before, node = config
            child = trie[node].get(byte)
            if child is None:
                continue
            if last is None:
                token = token_at[child]
                if token != START:
                    alone = self.reachable.get(token)
                    if alone is None:
                        alone = self.reachable[token] = self.merged(self.bytes_of[token]) == [token]
                    if alone:
                        fit = before == START or pairs.get((before, token))
                        if fit is None:
                            fit = self.fits(before, token)
                        if fit:
                            last = token
            if trie[child]:
                live.append((before, child))
        if last is None:
            raise ValueError(f"the vocabulary has no token for byte {byte}")
        live.append((last, 0))
        key = tuple(live)
        to = self.number.get(key)
        if to is None:
            to = self.number[key] = len(self.states)
            self.states.append(key)
        self.moves[state << 8 | byte] = found = (to, last)
        return found

    def encode(self, data: bytes) -> list[int]:
        whole = self.ranks.get(data)
        if whole is not None:
            return [whole]
        if len(self.moves) > self.max_transitions:
            self.reset()
        if len(data) <= 8 * self.width:
            return self._encode_short(data)
        out: list[int] = []
        length, moves = self.bytes_of, self.moves
        state, base, ends = 0, 0, [START]
        for at, byte in enumerate(data, 1):
            found = moves.get(state << 8 | byte)
            if found is None:
                found = self.move(state, byte)
            state, last = found
            ends.append(last)
            if len(ends) > 8 * self.width:
                base, ends = self._commit(state, at, base, ends, out)
                if len(moves) > self.max_transitions:
                    kept = self.states[state]
                    self.reset()
                    moves = self.moves
                    state = self.number.setdefault(kept, len(self.states))
                    if state == len(self.states):
                        self.states.append(kept)
        tail, at = [], len(ends) - 1
        while at:
            tail.append(ends[at])
            at -= len(length[ends[at]])
        out.extend(reversed(tail))
        return out

    def _encode_short(self, data: bytes) -> list[int]:
        """A piece within the window: one walk, then the tokens from its end."""
        moves, size, state, ends = self.moves, self.size_of, 0, [START]
        for byte in data:
            found = moves.get(state << 8 | byte)
            if found is None:
                found = self.move(state, byte)
            state, last = found
            ends.append(last)
        tail, at = [], len(data)
        while at:
            last = ends[at]
            tail.append(last)
            at -= size[last]
        tail.reverse()
        return tail

    def _commit(self, state: int, at: int, base: int, ends: list[int], out: list[int]):
        """Emit what all live configurations share and keep the window behind it."""
        depth = self._depths(state)
        alive = {at - d - base for d in depth}
        while len(alive) > 1:
            top = max(alive)
            alive.discard(top)
            alive.add(top - len(self.bytes_of[ends[top]]))
        cut = to = alive.pop()
        fresh = []
        while to:
            fresh.append(ends[to])
            to -= len(self.bytes_of[ends[to]])
        out.extend(reversed(fresh))
        return base + cut, [START, *ends[cut + 1 :]]

    def _depths(self, state: int) -> list[int]:
        if not hasattr(self, "depth"):
            self.depth = [0] * len(self.trie)
            for node, children in enumerate(self.trie):
                for child in children.values():
                    self.depth[child] = self.depth[node] + 1
        return [self.depth[node] for _, node in self.states[state]]


#: Expected continuation bytes by class of a UTF-8 lead byte (first byte, last byte, how many follow).
UTF8_LEADS = ((0x00, 0x7F, 0), (0xC2, 0xDF, 1), (0xE0, 0xEF, 2), (0xF0, 0xF4, 3))


class Utf8Machine:
    """Incremental UTF-8 reader: its state is the unfinished tail of the last character (at most 3 bytes)."""

    follow = [next((n for lo, hi, n in UTF8_LEADS if lo <= b <= hi), 0) for b in range(256)]

    def __init__(self) -> None:
        self.tail = b""

    def feed(self, data: bytes) -> str:
        data = self.tail + data
        cut = len(data)
        for back in range(1, min(3, len(data)) + 1):
            byte = data[-back]
            if byte & 0xC0 != 0x80:
                if self.follow[byte] >= back:
                    cut = len(data) - back
                break
        self.tail = data[cut:]
        return data[:cut].decode("utf-8", "replace")

    def finish(self) -> str:
        tail, self.tail = self.tail, b""
        return tail.decode("utf-8", "replace")


class PieceMemo(dict):
    """piece -> its ids as little-endian unsigned 32-bit integers, filled by the transducer.

    Two generations of at most ``limit`` pieces: a full one becomes the old one, whose pieces move up when met again.
    """

    def __init__(self, transducer: Transducer, limit: int = MAX_PIECES):
        super().__init__()
        self.transducer, self.limit, self.old = transducer, limit, {}
        self.packed = {i: i.to_bytes(4, "little") for i in transducer.bytes_of}

    def __missing__(self, piece: str) -> bytes:
        ids = self.old.get(piece)
        if ids is None:
            ids = b"".join(map(self.packed.__getitem__, self.transducer.encode(piece.encode())))
        if len(piece) <= MEMO_CHARS:
            if len(self) >= self.limit:
                self.old = dict(self)
                self.clear()
            self[piece] = ids
        return ids


class Codec:
    """Text -> packed ids -> text."""

    def __init__(self, rank_file: str, pattern: str):
        import regex

        ranks = load_ranks(rank_file)
        self.pieces = regex.compile(pattern).findall
        self.plain_pieces = plain_pattern(pattern).findall
        self.memo = PieceMemo(Transducer(ranks))
        self.table = [b""] * (max(ranks.values()) + 1)
        for b, i in ranks.items():
            self.table[i] = b

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        pieces = self.pieces if PLAIN.search(text) else self.plain_pieces
        return b"".join(map(self.memo.__getitem__, pieces(text)))

    def decode(self, packed: bytes, chunk: int = 1 << 16) -> str:
        machine, out = Utf8Machine(), []
        for at in range(0, len(packed), 4 * chunk):
            ids = memoryview(packed[at : at + 4 * chunk]).cast("I")
            out.append(machine.feed(b"".join(map(self.table.__getitem__, ids))))
        out.append(machine.finish())
        return "".join(out)


_codecs: dict[tuple[str, str], Codec] = {}


def codec(rank_file: str, pattern: str) -> Codec:
    """One codec per Python worker and vocabulary, kept over tasks."""
    key = (rank_file, pattern)
    if key not in _codecs:
        _codecs[key] = Codec(rank_file, pattern)
    return _codecs[key]


def encode_documents(
    df: DataFrame, rank_file: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", decode: bool = False
) -> DataFrame:
    """(id, ids binary[, decoded string]) for each row; ids are packed little-endian unsigned 32-bit integers.

    A null or empty text gives no ids. Rows with null or repeated ids each give their own row; other columns go.
    """
    id_type = df.schema[id_col].dataType.simpleString()

    def build():
        own = codec(rank_file, pattern)

        def one(batch: pa.RecordBatch) -> pa.RecordBatch:
            ids = [own.encode(t) for t in batch.column(1).to_pylist()]
            cols = [batch.column(0), pa.array(ids, pa.binary())]
            names = [id_col, "ids"]
            if decode:
                cols.append(pa.array([own.decode(x) for x in ids], pa.string()))
                names.append("decoded")
            return pa.RecordBatch.from_arrays(cols, names)

        return one

    schema = f"`{id_col}` {id_type}, ids binary" + (", decoded string" if decode else "")
    return map_arrow(df.select(id_col, text_col), build, schema)


def decode_documents(df: DataFrame, rank_file: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, text) from packed ids; bytes that are no UTF-8 become U+FFFD, null ids an empty text."""
    id_type = df.schema[id_col].dataType.simpleString()

    def build():
        own = codec(rank_file, pattern)

        def one(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = [own.decode(x or b"") for x in batch.column(1).to_pylist()]
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], [id_col, "text"])

        return one

    return map_arrow(df.select(id_col, ids_col), build, f"`{id_col}` {id_type}, text string")


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encode and decode every document; digests of ids and of decoded bytes."""
    import public_tokenizers

    coded = encode_documents(
        table(spark, sf_dir, "documents"),
        public_tokenizers.path("byte_bpe_multi_50k.tiktoken"),
        public_tokenizers.PATTERN,
        decode=True,
    )
    return coded.select(
        "doc_id",
        (F.length("ids") / 4).cast("long").alias("n_tokens"),
        F.sha2("ids", 256).alias("ids_sha256"),
        F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"),
    )
