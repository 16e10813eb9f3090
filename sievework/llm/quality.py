"""Quality by a linear-chain conditional random field over lines.

Each line is good or bad; it is described by its own features and those of its two neighbours, and adjacent labels are
tied by transition weights. The labels of lines are latent: a document's label says only on which side of one half the
length-weighted share of its good lines lies. Training starts with all lines on their document's side and then moves, in
rounds, the lines that the model is sure are otherwise, as long as the document's share stays on its side; so good lines of bad
documents, bad lines of good ones and the transitions between them are learned. The marginals of forward-backward, weighted
by line length, give a document's share of good text; a logistic function fitted on the sample turns it into the score.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import held_out, table, with_score
from .training import fit_logistic, labelled_sample, logistic

#: Labelled rows of each class that the model is fitted on.
PER_CLASS = 2500
#: Lines of a training chain, and chains that a document may give to the sample (spread over it; scoring takes all lines).
CHAIN, CHAINS = 64, 4
#: Rounds in which lines may change sides; how sure the model must be; the most of a document that may be on the other side.
ROUNDS, SURE, OTHER = 2, 0.9, 0.45
#: Lines whose features are held at once; lines of a segment of a long chain.
PART, SEGMENT = 16_384, 1024
STEPS = 120
CUT = 0.7
SIGNS = "#$%&*|!<>=+~^@"
FEATURES = 14


def line_features(line: str) -> tuple[float, ...]:
    words = line.split()
    n, size = len(words), len(line)
    if not n:
        return (1.0, *[0.0] * (FEATURES - 1))
    lens = list(map(len, words))
    distinct = len(set(words))
    return (
        0.0,
        min(n, 60) / 60,
        min(size / n, 20) / 20,
        distinct / n,
        sum(map(eq, words, words[1:])) / n,
        sum(map(str.isupper, words)) / n,
        min(line.count("|") / n, 1.0),
        min(line.count("!") / n, 2.0),
        min(sum(map(line.count, SIGNS)) / n, 3.0) / 3,
        sum(x <= 3 for x in lens) / n,
        sum(x >= 14 for x in lens) / n,
        float(line[0].isupper()),
        float(words[-1][-1] in ".!?"),
        min(sum(map(line.count, "0123456789")) / size, 1.0),
    )


def line_table(lines: list[str]) -> np.ndarray:
    """(lines x FEATURES) of each line alone; equal lines are looked at once."""
    known: dict[str, tuple[float, ...]] = {}
    return np.array([known.get(x) or known.setdefault(x, line_features(x)) for x in lines], float).reshape(-1, FEATURES)


def with_neighbours(own: np.ndarray) -> np.ndarray:
    """(lines x 3 FEATURES + 1): own, before, after, constant."""
    x = np.zeros((len(own), 3 * FEATURES + 1))
    x[:, -1] = 1
    x[:, :FEATURES] = own
    x[1:, FEATURES : 2 * FEATURES] = own[:-1]
    x[:-1, 2 * FEATURES : 3 * FEATURES] = own[1:]
    return x


def line_scores(lines: list[str], weights: np.ndarray) -> np.ndarray:
    """``with_neighbours`` of all lines times ``weights``, in parts: of a line only three numbers stay."""
    by = weights[: 3 * FEATURES].reshape(3, FEATURES).T
    each = np.concatenate([line_table(lines[at : at + PART]) @ by for at in range(0, len(lines), PART)])
    out = each[:, 0] + weights[-1]
    out[1:] += each[:-1, 1]
    out[:-1] += each[1:, 2]
    return out


def _lockstep(lens: np.ndarray) -> list[int]:
    """For chains sorted by length, longest first: how many are longer than t, for each t."""
    return [int(np.searchsorted(-lens, -t, "left")) for t in range(int(lens[0]) if len(lens) else 0)]


def _ends(emit: np.ndarray, step: np.ndarray, starts: np.ndarray, lens: np.ndarray, follows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Messages into and out of segments of chains: (forward, before each segment; backward, behind it), two numbers each.

    The product of a segment's transition matrices is found for all segments in lockstep; only these are then chained one
    after the other. ``follows``: whether a segment goes on the chain of the one before.
    """
    order = np.argsort(-lens, kind="stable")
    m = np.tile(np.eye(2), (len(lens), 1, 1))
    for t, n in enumerate(_lockstep(lens[order])):
        rows = order[:n]
        into = m[rows] @ step if t else np.where(follows[rows][:, None, None], step, np.eye(2))
        m[rows] = into * emit[starts[rows] + t][:, None, :]
        m[rows] /= m[rows].sum((1, 2), keepdims=True)
    before, behind = np.ones((len(lens), 2)), np.ones((len(lens), 2))
    for k in range(1, len(lens)):
        if follows[k]:
            v = before[k - 1] @ m[k - 1]
            before[k] = v / v.sum()
    for k in range(len(lens) - 2, -1, -1):
        if follows[k + 1]:
            v = m[k + 1] @ behind[k + 1]
            behind[k] = v / v.sum()
    return before, behind


def marginals(unary: np.ndarray, sizes: np.ndarray, ties: np.ndarray, pairs: bool = False):
    """Forward-backward over many chains at once; a chain of n lines takes about SEGMENT + n / SEGMENT steps.

    unary: rows of all chains end to end, score of good over bad; sizes: chain lengths; ties: 2 x 2 transition scores.
    Returns P(good) of each row, and with ``pairs`` the expected counts of the four transitions and log Z.
    """
    cuts = np.concatenate([[0], np.cumsum(sizes)[:-1]]).astype(int)
    starts = np.concatenate([np.arange(a, a + n, SEGMENT) for a, n in zip(cuts, sizes, strict=True)]) if len(sizes) else cuts
    ends = np.concatenate([starts[1:], [len(unary)]]).astype(int)
    follows = np.ones(len(starts), bool)
    follows[np.searchsorted(starts, cuts)] = False
    lens = ends - starts
    shift = np.maximum(unary, 0)
    emit = np.stack([np.exp(-shift), np.exp(unary - shift)], 1)
    step = np.exp(ties)
    before, behind = _ends(emit, step, starts, lens, follows) if follows.any() else (None, np.ones((len(lens), 2)))
    order = np.argsort(-lens, kind="stable")
    alive = _lockstep(lens[order])
    alpha, beta, scale = np.zeros_like(emit), np.ones_like(emit), np.ones(len(unary))
    for t, n in enumerate(alive):
        rows = starts[order[:n]] + t
        if t:
            a = (alpha[rows - 1] @ step) * emit[rows]
        else:
            a = emit[rows]
            if before is not None:
                on = follows[order[:n]]
                a[on] = (before[order[:n]][on] @ step) * emit[rows][on]
        scale[rows] = s = a.sum(1)
        alpha[rows] = a / s[:, None]
    beta[ends - 1] = behind
    for t in range(len(alive) - 2, -1, -1):
        rows = starts[order[: alive[t + 1]]] + t
        b = (beta[rows + 1] * emit[rows + 1]) @ step.T
        beta[rows] = b / (scale[rows + 1][:, None] if before is None else b.sum(1)[:, None])
    both = alpha * beta
    good = both[:, 1] / both.sum(1)
    if not pairs:
        return good
    if before is not None:
        raise ValueError(f"training chains have at most {SEGMENT} lines")
    counts = np.zeros((2, 2))
    for t in range(len(alive) - 1):
        rows = starts[order[: alive[t + 1]]] + t
        right = beta[rows + 1] * emit[rows + 1] / scale[rows + 1][:, None]
        counts += step * (alpha[rows].T @ right)
    return good, counts, float((np.log(scale) + shift).sum())


@dataclass
class LineModel:
    weights: np.ndarray
    ties: np.ndarray
    calibration: np.ndarray

    def shares(self, texts: list[str | None]) -> np.ndarray:
        """Length-weighted share of good text of each document; memory grows with the lines by some numbers each."""
        out = np.zeros(len(texts))
        at = 0
        while at < len(texts):
            docs: list[list[str]] = []
            while at + len(docs) < len(texts) and len(docs) < 128 and sum(map(len, docs)) < PART:
                docs.append((texts[at + len(docs)] or "").split("\n"))
            sizes = np.array([len(d) for d in docs])
            good = marginals(np.concatenate([line_scores(d, self.weights) for d in docs]), sizes, self.ties)
            cuts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
            lens = np.fromiter((len(x) + 1 for d in docs for x in d), float, int(sizes.sum()))
            out[at : at + len(docs)] = np.add.reduceat(good * lens, cuts) / np.add.reduceat(lens, cuts)
            at += len(docs)
        return out

    def scorer(self):
        return lambda texts: logistic(_logit(self.shares(texts))[:, None], self.calibration).tolist() if texts else []


def _logit(p: np.ndarray) -> np.ndarray:
    p = np.clip(p, 1e-4, 1 - 1e-4)
    return np.log(p / (1 - p))


@dataclass
class Chain:
    """A training chain: features, lengths and present labels of its lines, its document and that document's label."""

    x: np.ndarray
    sizes: np.ndarray
    labels: np.ndarray
    doc: int
    y: int


def fit_chain(chains: list[Chain], steps: int = STEPS, rate: float = 0.1, ridge: float = 1e-3, theta: np.ndarray | None = None) -> np.ndarray:
    """Weights, then transition scores, by Adam on the conditional likelihood of the present labels, balanced by documents' labels."""
    k = chains[0].x.shape[1]
    groups = []
    for y in (0, 1):
        own = [c for c in chains if c.y == y]
        if own:
            x, z, sizes = np.concatenate([c.x for c in own]), np.concatenate([c.labels for c in own]), np.array([len(c.x) for c in own])
            inner = np.ones(len(z), bool)
            inner[np.cumsum(sizes) - 1] = False  # the last line of a chain has no next
            at = np.flatnonzero(inner)
            groups.append((x, z, sizes, np.bincount(2 * z[at] + z[at + 1], minlength=4).reshape(2, 2)))
    theta = np.zeros(k + 4) if theta is None else theta.copy()
    m, v = np.zeros(k + 4), np.zeros(k + 4)
    for i in range(1, steps + 1):
        grad = ridge * theta
        for x, z, sizes, seen in groups:
            good, counts, _ = marginals(x @ theta[:k], sizes, theta[k:].reshape(2, 2), True)
            grad[:k] += x.T @ (good - z) / len(x)
            grad[k:] += ((counts - seen) / len(x)).ravel()
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        theta = theta - rate * (m / (1 - 0.9**i)) / (np.sqrt(v / (1 - 0.99**i)) + 1e-8)
    return theta


def relabel(chains: list[Chain], theta: np.ndarray) -> None:
    """Lines that the model is sure are on the other side than their document go there, the surest first, until OTHER of the
    document's sampled text is there: its label bounds the share."""
    k = chains[0].x.shape[1]
    good = marginals(np.concatenate([c.x for c in chains]) @ theta[:k], np.array([len(c.x) for c in chains]), theta[k:].reshape(2, 2))
    cuts = np.cumsum([0] + [len(c.x) for c in chains])
    by_doc: dict[int, list[int]] = {}
    for i, c in enumerate(chains):
        by_doc.setdefault(c.doc, []).append(i)
    for own in by_doc.values():
        y = chains[own[0]].y
        p = np.concatenate([good[cuts[i] : cuts[i + 1]] for i in own])
        against = p if y == 0 else 1 - p
        lens = np.concatenate([chains[i].sizes for i in own])
        order = np.argsort(-against, kind="stable")
        fits = np.cumsum(lens[order]) <= OTHER * lens.sum()
        z = np.full(len(p), y)
        z[order[fits & (against[order] > SURE)]] = 1 - y
        at = 0
        for i in own:
            chains[i].labels = z[at : at + len(chains[i].x)]
            at += len(chains[i].x)


def _chains(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(text, y) -> one row a training chain: features of its lines and of the one before and behind as bytes, whether there is one before,
    line lengths, the document's digest, the label. A document of more than CHAINS chains gives CHAINS of them, at even distances."""
    from xxhash import xxh64_intdigest

    for batch in batches:
        rows = []
        for text, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            lines = text.split("\n")
            n, doc = -(-len(lines) // CHAIN), xxh64_intdigest(text.encode(errors="replace")) >> 1
            for a in sorted({k * n // min(n, CHAINS) * CHAIN for k in range(min(n, CHAINS))}):
                own = line_table(lines[max(0, a - 1) : a + CHAIN + 1]).astype(np.float32).tobytes()
                rows.append((own, min(a, 1), np.array([len(v) + 1 for v in lines[a : a + CHAIN]], np.float32).tobytes(), doc, y))
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.binary(), pa.int32(), pa.binary(), pa.int64(), pa.int32()), strict=True)], ["own", "before", "sizes", "doc", "y"])


def learn_quality(docs: DataFrame, labels: DataFrame, label: str = "quality", mod: int = 4, rest: int = 2, per_class: int = PER_CLASS) -> LineModel:
    """Fit on the bounded sample (per_class documents of each class, CHAINS chains of CHAIN lines each at most); rows with crc32(id)
    mod ``mod`` = ``rest`` are never seen. Without labelled rows nothing is known against any text: all score 0.95; with one
    class only all lean to it."""
    sample = labelled_sample(docs, labels, label, mod, rest, per_class)
    rows = sample.mapInArrow(_chains, "own binary, before int, sizes binary, doc long, y int").collect()  # bounded in rows and lines
    width = 3 * FEATURES + 1
    if not rows:
        return LineModel(np.zeros(width), np.zeros((2, 2)), np.array([0.0, 3.0]))
    chains = []
    for r in sorted(rows, key=lambda r: (r["doc"], r["own"])):
        sizes = np.frombuffer(r["sizes"], np.float32).astype(float)
        x = with_neighbours(np.frombuffer(r["own"], np.float32).reshape(-1, FEATURES).astype(float))[r["before"] :][: len(sizes)]
        chains.append(Chain(x, sizes, np.full(len(x), r["y"]), r["doc"], r["y"]))
    theta = fit_chain(chains)
    for _ in range(ROUNDS):
        relabel(chains, theta)
        theta = fit_chain(chains, STEPS // 2, theta=theta)
    model = LineModel(theta[:width], theta[width:].reshape(2, 2), np.array([1.0, 0.0]))

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(model.shares(batch.column(0).to_pylist())), batch.column(1)], ["q", "y"])

    points = sample.mapInArrow(measure, "q double, y int").toPandas().sort_values(["q", "y"])
    model.calibration = fit_logistic(_logit(points["q"].to_numpy())[:, None], points["y"].to_numpy())
    return model


def score_quality(df: DataFrame, model: LineModel, text_col: str = "text", name: str = "score") -> DataFrame:
    """``df`` with the score of each whole text; a null text counts as empty; an old column ``name`` is replaced."""
    return with_score(df, text_col, model.scorer, name)


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = learn_quality(docs, table(spark, sf_dir, "labels"))
    return score_quality(docs, model).select(
        "doc_id", held_out("doc_id", 4, 2).alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted")
    )
