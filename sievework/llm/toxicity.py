"""Toxicity by a weighted lexicon, matched with Aho-Corasick after folding.

Folding lower-cases, maps homoglyphs, compatibility forms and digit or sign substitutions to letters, drops invisible characters
and turns all that is no letter into a space; accents stay, since they tell words of other languages apart. Words with
accents or rarer look-alikes are read a second time in plain letters, against the entries that are of plain letters. Lexicon
entries are word beginnings of four letters or more, or whole words of two or three, with weights (log odds), learned from a
bounded sample of labelled rows; an exception phrase cancels the entries inside it. The score is a logistic function of the
weight of the matches, by the number of words and in all.
"""

from __future__ import annotations

import math
import unicodedata
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import held_out, table, with_score
from .training import fit_logistic, labelled_sample, logistic, without_near_copies

#: Labelled rows of each class that the lexicon is learned from.
PER_CLASS = 4000
#: Entries of the lexicon at most (by significance).
MAX_ENTRIES = 5000
PREFIXES = (4, 5, 6, 7, 8, 10, 12)
#: Letters of whole words that may be entries.
SHORT = (2, 3)
#: Share of the documents with a prefix that must have the longer one for the longer one to stand for it.
CLOSED = 0.9
#: Log odds that an entry needs, and by which a longer prefix must be purer to stand for it.
LEAST, PURER = 2.0, 1.0
MAX_WEIGHT = 6.0
CUT = 0.5
#: Highest log odds of a text without matches.
NO_MATCH = -1.0
#: Look-alikes, one letter each, and the Latin letters they stand for.
LOOKALIKES = ("аеорсхуіѕјһԁґоαειορυνκτ", "aeopcxyisjhdroaeiopuvkt")
#: Rarer look-alikes, one letter each, and the plain letters they stand for; read in the second view only.
RARER = ("ткмнвгѵӏωητβμγłøđħŧıɪʟɴʀʏɢʜʙɑɡɩʋᴀᴄᴅᴇᴊᴋᴍᴏᴘꜱᴛᴜᴠᴡᴢ", "tkmhbrvlwntbuylodhtiilnryghbagivacdejkmopstuvwz")
#: Digits and signs written for letters.
SUBSTITUTES = ("0134578@$€", "oieastbase")
INVISIBLE = "​‌‍⁠﻿­"
#: Harmless phrases that hold words of common lexicons.
EXCEPTIONS = ("clown fish", "clownfish", "trash can", "trash bin", "trash bag", "pond scum", "soap scum")


class _Fold(dict):
    """Code point -> folded character; filled as characters are met."""

    def __init__(self):
        super().__init__({ord(a): b for a, b in zip(*LOOKALIKES, strict=True)})
        self.update({ord(a): b for a, b in zip(*SUBSTITUTES, strict=True)})
        self.update(dict.fromkeys(map(ord, INVISIBLE)))

    def __missing__(self, code: int):
        char = chr(code)
        plain = unicodedata.normalize("NFKC", char).lower()
        to = plain if plain.isalpha() else char if 0x300 <= code <= 0x36F else " "
        self[code] = to
        return to


class _Plain(dict):
    """Word -> the word in plain letters, or "" if it is of plain letters already; bounded."""

    MOST = 200_000
    _rarer = str.maketrans(dict(zip(*RARER, strict=True)))

    def __missing__(self, word: str) -> str:
        if len(self) >= self.MOST:
            self.clear()
        bare = "".join(c for c in unicodedata.normalize("NFD", word.translate(self._rarer)) if not unicodedata.combining(c))
        self[word] = to = "" if bare == word else bare
        return to


_fold, _plain = _Fold(), _Plain()


def fold(text: str) -> str:
    if not text.isascii() and not unicodedata.is_normalized("NFC", text):
        text = unicodedata.normalize("NFC", text)
    return text.lower().translate(_fold)


@dataclass
class Lexicon:
    weights: dict[str, float]
    exceptions: tuple[str, ...] = EXCEPTIONS
    logistic: list[float] = field(default_factory=lambda: [1.0, 1.0, -4.0])

    def automaton(self):
        """Of all entries, and of those in plain letters: (length, weight) by entry; a weight of None marks an exception."""
        import ahocorasick

        machines = ahocorasick.Automaton(), ahocorasick.Automaton()
        for entry, weight in self.weights.items():
            word = fold(entry).strip()
            key = f" {word} " if entry.endswith(" ") else f" {word}"
            for machine in machines[: 1 + word.isascii()]:
                machine.add_word(key, (len(key) - 1, weight))
        for phrase in self.exceptions:
            word = " ".join(fold(phrase).split())
            for machine in machines:
                machine.add_word(f" {word}", (len(word), None))
        for machine in machines:
            if len(machine):
                machine.make_automaton()
        return machines

    @staticmethod
    def _total(machine, words: list[str]) -> float:
        if not len(machine) or not words:
            return 0.0
        found = list(machine.iter(f" {' '.join(words)} "))
        if not found:
            return 0.0
        safe = [(end - n + 1, end) for end, (n, w) in found if w is None]
        return sum(w for end, (n, w) in found if w is not None and not any(a <= end - n + 1 and end <= b for a, b in safe))

    def features(self, texts: Iterable[str | None], machines=None) -> np.ndarray:
        """Rows (log of weight per thousand words, log of weight)."""
        whole, plain = machines or self.automaton()
        out = []
        for text in texts:
            words = fold(text or "").split()
            total = self._total(whole, words)
            if text and not text.isascii():
                total += self._total(plain, [p for p in map(_plain.__getitem__, words) if p])
            out.append((math.log1p(1000 * total / (len(words) + 20)), math.log1p(total)))
        return np.array(out, float).reshape(-1, 2)

    def scorer(self):
        """list of texts -> list of scores, with the automata built once."""
        machines, w = self.automaton(), np.array(self.logistic)
        return lambda texts: logistic(self.features(texts, machines), w).tolist()


def _prefix_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(text, y) -> (prefix, toxic documents, other documents), summed in the task; ``$`` stands for all documents."""
    pos, neg = Counter(), Counter()
    for batch in batches:
        for text, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            words = set(fold(text).split())
            seen = {w[:n] for w in words for n in PREFIXES if len(w) >= n}
            seen.update(f"{w} " for w in words if len(w) in SHORT)
            seen.add("$")
            (pos if y else neg).update(seen)
    keys = list(pos)  # a prefix of no toxic document in any task is of no use; the others' counts are kept
    keys += [k for k in neg if k not in pos]
    for at in range(0, len(keys), 50_000):
        part = keys[at : at + 50_000]
        yield pa.RecordBatch.from_pydict({"prefix": part, "pos": [pos[k] for k in part], "neg": [neg[k] for k in part]})


def choose_entries(rows: list[tuple[str, int, int]], all_pos: int, all_neg: int) -> dict[str, float]:
    """Entries among counted prefixes, weighted by log odds. A prefix gives way to longer ones where one of them stands for it
    (CLOSED) or is purer by PURER; of those left, one with a chosen shorter one isn't needed."""
    counts = {p: (a, b) for p, a, b in rows}
    odds = {p: math.log((a + 0.5) / (all_pos + 1)) - math.log((b + 0.5) / (all_neg + 1)) for p, (a, b) in counts.items()}
    covered: dict[str, int] = {}
    purest: dict[str, float] = {}
    for p, (a, _) in counts.items():
        for n in PREFIXES:
            if n < len(p) and not p.endswith(" "):
                covered[p[:n]] = max(covered.get(p[:n], 0), a)
                purest[p[:n]] = max(purest.get(p[:n], 0.0), odds[p])
    chosen: dict[str, float] = {}
    for p in sorted(counts, key=lambda x: (len(x), x)):
        if odds[p] <= LEAST or covered.get(p, 0) >= CLOSED * counts[p][0] or purest.get(p, 0.0) > odds[p] + PURER:
            continue
        if p.endswith(" ") or not any(p[:n] in chosen for n in PREFIXES if n < len(p)):
            chosen[p] = min(odds[p], MAX_WEIGHT)
    return chosen


def learn_lexicon(docs: DataFrame, labels: DataFrame, label: str = "toxic", mod: int = 5, rest: int = 0, per_class: int = PER_CLASS) -> Lexicon:
    """Learn entries, weights and the logistic function; rows with crc32(id) mod ``mod`` = ``rest`` are never seen."""
    sample = labelled_sample(docs, labels, label, mod, rest, per_class)
    distinct = without_near_copies(sample)
    counts = distinct.mapInArrow(_prefix_counts, "prefix string, pos long, neg long").groupBy("prefix").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    total = counts.where("prefix = '$'").first()
    if total is None or not total["pos"] or not total["neg"]:
        return Lexicon({})
    all_pos, all_neg = total["pos"], total["neg"]
    base = all_pos / (all_pos + all_neg)
    n = F.col("pos") + F.col("neg")
    lean = F.when(F.col("pos") > n * base, 2 * (F.col("pos") * F.log(F.col("pos") / (n * base)) + F.when(F.col("neg") > 0, F.col("neg") * F.log(F.col("neg") / (n * (1 - base)))).otherwise(0.0))).otherwise(0.0)
    floor = 10 + 2 * math.log(100_000)  # beyond chance among a hundred thousand prefixes
    rows = counts.where("prefix <> '$' and pos >= 3").where(lean >= min(floor, 4 * all_pos)).orderBy(lean.desc(), "prefix").limit(MAX_ENTRIES).collect()
    lexicon = Lexicon(choose_entries([(r["prefix"], r["pos"], r["neg"]) for r in rows], all_pos, all_neg))

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machines = lexicon.automaton()
        for batch in batches:
            x = lexicon.features(batch.column(0).to_pylist(), machines)
            yield pa.RecordBatch.from_arrays([pa.array(x[:, 0]), pa.array(x[:, 1]), batch.column(1)], ["a", "b", "y"])

    points = sample.mapInArrow(measure, "a double, b double, y int").toPandas().sort_values(["a", "b", "y"])  # two numbers a sampled row
    w = fit_logistic(points[["a", "b"]].to_numpy(), points["y"].to_numpy())
    # Matches never lower a score, and a text without any isn't toxic, also where the sample taught no entries.
    lexicon.logistic = [max(w[0], 0.0), max(w[1], 0.0), min(w[2], NO_MATCH)]
    return lexicon


def score_toxicity(df: DataFrame, lexicon: Lexicon, text_col: str = "text", name: str = "score") -> DataFrame:
    """``df`` with the score of each whole text; null and empty texts have no matches; an old column ``name`` is replaced."""
    return with_score(df, text_col, lexicon.scorer, name)


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    lexicon = learn_lexicon(docs, table(spark, sf_dir, "labels"))
    return score_toxicity(docs, lexicon).select(
        "doc_id", held_out("doc_id", 5, 0).alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted")
    )
