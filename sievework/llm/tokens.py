"""Token ids of texts by a tokenizer file.

Texts of common letters and signs go through a merge table built from the file's own merges and run by a compiled
byte-pair encoder, which gives the ids that the tokenizers library gives several times faster; all others (and any
vocabulary whose table doesn't reproduce it) go through the library itself. Tests hold both ways against each other.
"""

from __future__ import annotations

import json
import os
import re
import unicodedata
from collections.abc import Iterable, Iterator

import numpy as np



#: Ranges of code points whose classes and lower case all engines agree on (Latin, Greek, Cyrillic, dashes,
#: quotes and other signs); of them letters, digits 0-9, punctuation and symbols count.
RANGES = ((0x20, 0x7E), (0xA1, 0x24F), (0x391, 0x3C9), (0x400, 0x481), (0x48A, 0x4FF), (0x2010, 0x2027), (0x20AC, 0x20AC))
#: Capital sigma: its lower case depends on its place in some engines.
ODD = "Σ"


def _char_class(kinds: str) -> str:
    """Inside of a character class: the code points of RANGES of these general categories."""
    out: list[list[int]] = []
    for lo, hi in RANGES:
        for c in range(lo, hi + 1):
            kind = unicodedata.category(chr(c))[0]
            lower = chr(c).lower()
            same = len(lower) == 1 and any(a <= ord(lower) <= b for a, b in RANGES) and chr(c) not in ODD
            if kind in kinds and same and (kind != "N" or chr(c) in "0123456789"):
                if out and out[-1][1] == c - 1:
                    out[-1][1] = c
                else:
                    out.append([c, c])
    return "".join(re.escape(chr(a)) + (f"-{re.escape(chr(b))}" if b > a else "") for a, b in out)


LETTERS, SIGNS = _char_class("L"), _char_class("PS")
#: Finds what is not plain.
PLAIN = re.compile(f"[^\t\n\r 0-9{LETTERS}{SIGNS}]")


def plain_pattern(pattern: str) -> re.Pattern:
    """A splitting pattern with Unicode classes as one that does the same on plain texts, several times faster."""
    for old, new in (("[^\\s\\p{L}\\p{N}]", f"[{SIGNS}]"), ("[\\p{L}]", f"[{LETTERS}]"), ("\\p{L}", f"[{LETTERS}]"), ("[\\p{N}]", "[0-9]"), ("\\p{N}", "[0-9]")):
        pattern = pattern.replace(old, new)
    if "\\p" in pattern:
        raise ValueError("a class that plain texts don't cover")
    return re.compile(pattern)


#: Stands behind a piece where the vocabulary marks word ends; not in PLAIN.
END = "\x01"
#: The printable bytes of the byte-level alphabet; the others follow from U+0100 in order.
PRINTABLE = ((0x21, 0x7E), (0xA1, 0xAC), (0xAE, 0xFF))


def byte_alphabet() -> dict[str, int]:
    """Character -> byte of the byte-level alphabet."""
    shown = [b for lo, hi in PRINTABLE for b in range(lo, hi + 1)]
    rest = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(rest)}


class MergeTable:
    """A byte-level BPE file as ranks of byte strings."""

    def __init__(self, spec: dict):
        import tiktoken
        from public_tokenizers import PATTERN

        model = spec["model"]
        if model["type"] != "BPE" or model.get("byte_fallback") or model.get("continuing_subword_prefix"):
            raise ValueError("no byte-level BPE")
        self.suffix = model.get("end_of_word_suffix") or ""
        normal = spec.get("normalizer")
        steps = [s["type"] for s in normal["normalizers"]] if normal else []
        pre = spec["pre_tokenizer"]
        if self.suffix:
            if steps != ["NFC", "Replace", "Lowercase"] or pre["type"] != "Sequence" or not pre["pretokenizers"][0].get("invert"):
                raise ValueError("another normaliser or splitter")
            self.pieces = plain_pattern(pre["pretokenizers"][0]["pattern"]["Regex"]).findall
        elif steps or pre["type"] != "ByteLevel" or not pre["use_regex"] or pre["add_prefix_space"]:
            raise ValueError("another normaliser or splitter")
        alphabet, vocab = byte_alphabet(), model["vocab"]
        ranks, ids = {}, []

        def add(token: str, data: bytes) -> None:
            if data not in ranks:
                ranks[data] = len(ids)
                ids.append(vocab.get(token, 0))

        def raw(token: str) -> bytes:
            end = bool(self.suffix) and token.endswith(self.suffix)
            body = token[: -len(self.suffix)] if end else token
            return bytes(alphabet[c] for c in body) + (END.encode() if end else b"")

        for char, b in alphabet.items():
            add(char, bytes([b]))
        if self.suffix:
            for char, b in alphabet.items():
                add(char + self.suffix, bytes([b]) + END.encode())
        for merge in model["merges"]:
            left, right = merge.split(" ") if isinstance(merge, str) else merge
            add(left + right, raw(left + right))
        self.ids = np.array(ids, np.uint32)
        self.core = tiktoken.Encoding("merges", pat_str=f"[^{END}]+{END}" if self.suffix else PATTERN, mergeable_ranks=ranks, special_tokens={})

    def encode(self, text: str) -> np.ndarray:
        if self.suffix:
            text = unicodedata.normalize("NFC", text).lower()
            text = END.join([*self.pieces(text), ""])
        return self.ids[self.core.encode_to_numpy(text, disallowed_special=())]


class Tokens:
    """Ids of texts; strings of special tokens are ordinary text."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.encode_special_tokens = True
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        try:
            self.table = MergeTable(spec)
        except (KeyError, ValueError):  # not that kind of vocabulary: the library does all
            self.table = None

    def by_library(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def encode(self, text: str) -> np.ndarray:
        if self.table is not None and not PLAIN.search(text):
            return self.table.encode(text)
        return self.by_library([text])[0]


_loaded: dict[str, Tokens] = {}


def tokenizer(path: str) -> Tokens:
    """One per Python worker and file, kept over tasks."""
    if path not in _loaded:
        _loaded[path] = Tokens(path)
    return _loaded[path]


def token_ids(path: str, texts: Iterable[str | None], end_id: int) -> Iterator[np.ndarray]:
    """uint32 ids of each text with ``end_id`` behind; null counts as empty."""
    own, end = tokenizer(path), np.array([end_id], np.uint32)
    for text in texts:
        yield np.concatenate([own.encode(text), end]) if text else end
