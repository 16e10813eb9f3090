"""Signals: nine quality scores and a two-level domain tag, their correlation, strata, and the distilled student."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import constants as C
from ..functions.text import h32, lines, ratio, tokens, words
from ..plans.staging import stage


def _flags(*conditions: Column) -> Column:
    """How many hold: a score of 0 to 3."""
    return sum((F.when(c, 1).otherwise(0) for c in conditions[1:]), F.when(conditions[0], 1).otherwise(0)).cast("int")


def _chances(conditions: Sequence[tuple], width: float) -> list[Column]:
    """Chance that each condition (column, sign, cut) holds, by how far the column is from its cut: a sigmoid as wide as ``width`` of the cut.
    A condition without a cut is a boolean column, which is believed to ``1 - width / 2``."""
    out = []
    for column, sign, cut in conditions:
        if cut is None:
            out.append(F.when(column, 1 - width / 2).otherwise(width / 2))
        else:
            z = (column - cut) / (width * max(abs(cut), 1e-9)) * (1 if sign == ">" else -1)
            out.append(1 / (1 + F.exp(-F.greatest(F.lit(-30.0), F.least(F.lit(30.0), z)))))
    return out


def text_features(df: DataFrame, text: str = "text", keep: Sequence[str] = ("doc_id",)) -> DataFrame:
    """Shapes of a text that the teacher reads; one pass, no shuffle. Null texts count as empty."""
    body = F.coalesce(F.col(text), F.lit(""))
    arrays = df.select(*keep, body.alias("__t"), words(body).alias("__w"), tokens(body).alias("__k"), lines(body).alias("__l"))
    letters = F.length(F.regexp_replace("__t", r"[^\p{L}]", ""))
    sized = lambda f: F.size(F.filter("__w", f))
    return arrays.select(
        *keep,
        F.size("__w").alias("n_words"),
        F.size("__l").alias("n_lines"),
        ratio(F.length(F.regexp_replace("__t", r"[^\p{Lu}]", "")), letters).alias("upper"),
        ratio(F.length(F.regexp_replace("__t", r"[^%$#&*|]", "")), F.size("__w")).alias("symbols"),
        ratio(F.size(F.filter("__l", lambda x: F.rtrim(x).rlike(r"[.!?]$"))), F.size("__l")).alias("terminal"),
        ratio(F.size(F.array_distinct("__l")), F.size("__l")).alias("line_variety"),
        ratio(F.size(F.array_distinct("__k")), F.size("__k")).alias("token_variety"),
        ratio(F.size(F.filter("__k", lambda x: x.isin(*C.FUNCTION_WORDS))), F.size("__k")).alias("function_share"),
        ratio(sized(lambda w: F.length(w) >= 8), F.size("__w")).alias("long_share"),
        F.length(F.regexp_replace("__t", r"[^.!?]", "")).alias("sentences"),
        F.length(F.regexp_replace("__t", r"[^,]", "")).alias("commas"),
        F.length(F.regexp_replace("__t", r"[^0-9]", "")).alias("digits"),
        F.size(F.array_intersect("__k", F.array(*map(F.lit, C.TOXIC)))).alias("toxic_words"),
        F.rtrim("__t").rlike(r"[.!?]$").alias("closed"),
    )


def _conditions() -> dict[str, tuple[tuple, ...]]:
    """Score -> its conditions (column, sign, cut); a cut of None is a boolean."""
    c = F.col
    per_sentence, per_comma = ratio(c("n_words"), c("sentences")), ratio(c("commas"), c("sentences"))
    return {
        "writing": ((c("upper"), "<", 0.3), (c("symbols"), "<", 0.1), (c("terminal"), ">", 0.5)),
        "coherence": ((c("token_variety"), ">", 0.25), (c("line_variety"), ">", 0.7), (c("n_lines"), ">", 2)),
        "completeness": ((c("n_words"), ">", 50), (c("closed"), ">", None), (c("n_words"), ">", 200)),
        "logicality": ((c("function_share"), ">", 0.05), (c("function_share"), ">", 0.15), (c("sentences"), ">", 3)),
        "safety": ((c("toxic_words") == 0, ">", None),),
        "knowledge": ((c("long_share"), ">", 0.1), (c("long_share"), ">", 0.2), (c("long_share"), ">", 0.35)),
        "education": (((per_sentence >= 4) & (per_sentence <= 40), ">", None), (c("n_words"), ">", 100), (c("function_share"), ">", 0.1)),
        "helpfulness": ((c("n_lines"), ">", 3), (c("n_words"), ">", 150), (c("token_variety"), ">", 0.5)),
        "reasoning": ((c("commas"), ">", 3), (per_comma, ">", 0.3), (c("n_words"), ">", 300)),
    }


def teacher_scores() -> dict[str, Column]:
    """Score expressions over ``text_features``: the deterministic stand-in for a labelling model. ``>`` includes the cut."""
    return {k: _flags(*[x if cut is None else x >= cut if sign == ">" else x < cut for x, sign, cut in own]) for k, own in _conditions().items()}


def teacher_distributions(width: float = 0.15) -> dict[str, Column]:
    """Score -> array of the chances of its classes (0 to the number of conditions): what the teacher would give as soft targets. Flags
    near their cut are uncertain, and the score is the number of them that hold (independently)."""
    out = {}
    for k, own in _conditions().items():
        mass = [F.lit(1.0)]
        for q in _chances(own, width):
            mass = [(mass[i] * (1 - q) if i < len(mass) else F.lit(0.0)) + (mass[i - 1] * q if i else F.lit(0.0)) for i in range(len(mass) + 1)]
        out[k] = F.array(*mass)
    return out


def annotate_soft(df: DataFrame, text: str = "text", keep: Sequence[str] = ("doc_id",), width: float = 0.15) -> DataFrame:
    """Hard scores and soft_<score> arrays, one pass over the text."""
    hard, soft = teacher_scores(), teacher_distributions(width)
    return text_features(df, text, keep).select(*keep, "n_words", *[e.alias(n) for n, e in hard.items()], *[e.alias(f"soft_{n}") for n, e in soft.items()])


def annotate_quality(df: DataFrame, text: str = "text", keep: Sequence[str] = ("doc_id",)) -> DataFrame:
    return text_features(df, text, keep).select(*keep, "n_words", *[e.alias(n) for n, e in teacher_scores().items()])


def domain_columns(source: str = "source", mapping: dict[str, str] = C.DOMAINS) -> tuple[Column, Column]:
    """(L1, L2) of a source; unknown sources are ``Other``."""
    table = F.create_map(*[F.lit(x) for kv in mapping.items() for x in kv])
    l1 = F.coalesce(table[F.col(source)], F.lit("Other"))
    return l1, F.concat(l1, F.lit("/"), F.coalesce(F.col(source), F.lit("unknown")))


def annotate(df: DataFrame, text: str = "text", source: str = "source", keep: Sequence[str] = ("doc_id",)) -> DataFrame:
    """All signals, computed once and used by every later stage: nine scores, domain_l1, domain_l2, n_words."""
    l1, l2 = domain_columns(source)
    tagged = df.select(*keep, text, l1.alias("domain_l1"), l2.alias("domain_l2"))
    return annotate_quality(tagged, text, (*keep, "domain_l1", "domain_l2"))


def signal_correlation(df: DataFrame, columns: Sequence[str] = C.FOUR_POINT) -> DataFrame:
    """(x, y, r) for every pair x < y, in one aggregate; a constant column has r null."""
    pairs = [(a, b) for i, a in enumerate(columns) for b in columns[i + 1 :]]
    row = df.agg(*[F.corr(a, b).alias(f"{a}|{b}") for a, b in pairs])
    stacked = ", ".join(f"'{a}', '{b}', `{a}|{b}`" for a, b in pairs)
    return row.selectExpr(f"stack({len(pairs)}, {stacked}) AS (x, y, r)").withColumn("r", F.nanvl("r", F.lit(None).cast("double")))


def collinearity(corr: DataFrame) -> DataFrame:
    return corr.agg(F.max(F.abs("r")).alias("max_abs"), F.avg(F.abs("r")).alias("mean_abs"))


def stratified_sample(df: DataFrame, stratum: str, size: int, seed: str = "s", allocation: str = "proportional", key: str = "doc_id") -> DataFrame:
    """A seeded sample of about ``size`` rows: ``proportional``, ``equal`` or ``sqrt`` shares of the strata.

    Each stratum keeps the rows whose draw is below its share of rows, so no stratum is sorted or held in one task.
    """
    counts = df.groupBy(stratum).agg(F.count("*").alias("__n"))
    weight = {"proportional": F.col("__n").cast("double"), "equal": F.lit(1.0), "sqrt": F.sqrt("__n")}[allocation]
    share = counts.withColumn("__w", weight)
    total = share.agg(F.sum("__w").alias("__all"))
    rate = share.crossJoin(F.broadcast(total)).select(F.col(stratum).alias("__s"), F.least(F.lit(1.0), size * F.col("__w") / F.col("__all") / F.col("__n")).alias("__rate"))
    draw = (h32(F.concat(F.col(key).cast("string"), F.lit(f":{seed}"))) + 0.5) / 4294967296.0
    return df.join(rate, df[stratum].eqNullSafe(rate["__s"])).where(draw < F.col("__rate")).drop("__s", "__rate")


def merge_categories(vectors: DataFrame, threshold: float, key: str = "tag", vec: str = "vec") -> DataFrame:
    """(tag, merged): categories whose centroids have cosine >= threshold become one, named by the least tag.

    A taxonomy has some hundred categories; their pairs are formed by a join on tag order over that small table.
    """
    from .components import star_forest

    unit = F.transform(F.col(vec), lambda x: x / F.sqrt(F.aggregate(F.col(vec), F.lit(0.0), lambda s, v: s + v * v)))
    rows = vectors.select(F.col(key).alias("tag"), unit.alias("v"), h32(F.col(key)).alias("id"))
    a, b = rows.alias("a"), F.broadcast(rows.alias("b"))
    near = F.aggregate(F.zip_with("a.v", "b.v", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x) >= threshold
    tree = star_forest(a.join(b, (F.col("a.id") < F.col("b.id")) & near).select(F.col("a.id").alias("u"), F.col("b.id").alias("v")))
    roots = tree.select(F.col("u").alias("id"), F.col("v").alias("root"))
    rooted = rows.select("tag", "id").join(roots, "id", "left").select("tag", F.coalesce("root", "id").alias("root"))
    names = rooted.groupBy("root").agg(F.min("tag").alias("merged"))
    return rooted.join(names, "root").select("tag", "merged")


# --- the student ---------------------------------------------------------------------------------

WIDTH = 256


def _hashed(text: str | None) -> np.ndarray:
    """Unit vector of hashed tokens and shape features: the shared representation of both heads."""
    import re
    import zlib

    x = np.zeros(WIDTH)
    for w in re.findall(r"\w+", (text or "").lower()):
        x[zlib.crc32(w.encode()) % (WIDTH - 8)] += 1
    x[: WIDTH - 8] = np.log1p(x[: WIDTH - 8])
    norm = np.linalg.norm(x)
    x = x / norm if norm else x
    parts = (text or "").split()
    n = max(len(parts), 1)
    x[-8:] = (
        min(len(parts), 500) / 500, len(set(parts)) / n, sum(p.isupper() for p in parts) / n, min((text or "").count("\n"), 50) / 50,
        sum(len(p) >= 8 for p in parts) / n, (text or "").count(",") / n, (text or "").count("|") / n, 1.0,
    )
    return x


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


class Student:
    """Two linear heads (quality: one softmax a score; domain: one softmax) on a shared hashed representation.

    The weights of a task's loss are learned with it: total = sum of loss * exp(-eta) + eta (``uncertainty``), or fixed.
    """

    def __init__(self, tasks: dict[str, list], weighting: str = "uncertainty"):
        self.tasks, self.weighting = tasks, weighting
        self.heads = {t: np.zeros((WIDTH, len(v))) for t, v in tasks.items()}
        self.eta = dict.fromkeys(tasks, 0.0)

    def predict(self, x: np.ndarray) -> dict[str, np.ndarray]:
        return {t: _softmax(x @ w) for t, w in self.heads.items()}


def fit_student(df: DataFrame, tasks: Sequence[str], epochs: int = 15, rate: float = 4.0, weighting: str = "uncertainty", loss: str = "hard", smoothing: float = 0.1, text: str = "text") -> tuple[Student, list[dict]]:
    """Distil teacher columns into a Student; returns it with each epoch's task losses and eta.

    The features are staged once. Each epoch is one pass: tasks sum gradients over their rows, and only sums of
    WIDTH x classes numbers go to the driver. ``hard``: the teacher's class; ``smooth``: ``smoothing`` of it spread over all classes;
    ``soft``: the teacher's distribution, from the column soft_<task> where there is one (classes 0, 1, ... in order).
    """
    soft = {t for t in tasks if loss == "soft" and f"soft_{t}" in df.columns}
    first = df.select(*[F.size(f"soft_{t}").alias(t) for t in soft]).first() if soft else None
    values = {t: list(range(first[t])) if t in soft and first else [r[0] for r in df.select(t).distinct().orderBy(t).collect()] for t in tasks}  # classes of a task: few
    student = Student(values, weighting)
    place = {t: {v: i for i, v in enumerate(vs)} for t, vs in values.items()}

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = batch.to_pylist()
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([_hashed(r[text]).astype(np.float32).tobytes() for r in rows], pa.binary()), pa.array([[place[t][r[t]] for t in tasks] for r in rows], pa.list_(pa.int32())),
                    pa.array([[v for t in tasks if t in soft for v in r[f"soft_{t}"]] for r in rows], pa.list_(pa.float64())),
                ],
                ["x", "y", "z"],
            )

    data = stage(df.select(text, *tasks, *[f"soft_{t}" for t in tasks if t in soft]).mapInArrow(encode, "x binary, y array<int>, z array<double>"), "student")
    spans, at = {}, 0
    for t in tasks:
        if t in soft:
            spans[t] = slice(at, at + len(values[t]))
            at += len(values[t])
    history = []
    for _ in range(epochs):
        heads = student.heads

        def gradients(batches: Iterator[pa.RecordBatch], heads=heads) -> Iterator[pa.RecordBatch]:
            sums = {t: np.zeros_like(w) for t, w in heads.items()}
            total, n = dict.fromkeys(heads, 0.0), 0
            for batch in batches:
                x = np.stack([np.frombuffer(b, np.float32) for b in batch.column(0).to_pylist()]).astype(float) if batch.num_rows else np.zeros((0, WIDTH))
                y = np.array(batch.column(1).to_pylist()).reshape(-1, len(heads))
                z = np.array(batch.column(2).to_pylist(), float).reshape(len(x), -1) if len(x) else np.zeros((0, 0))
                n += len(x)
                for k, (t, w) in enumerate(heads.items()):
                    p, goal = _softmax(x @ w) if len(x) else np.zeros((0, w.shape[1])), np.eye(w.shape[1])[y[:, k]]
                    if t in spans and len(x):
                        goal = z[:, spans[t]]
                    elif loss == "smooth" and w.shape[1] > 1:
                        goal = (1 - smoothing) * goal + smoothing / w.shape[1]
                    sums[t] += x.T @ (p - goal)
                    total[t] -= (goal * np.log(p + 1e-12)).sum()
            yield pa.RecordBatch.from_pydict({"task": list(heads), "g": [sums[t].ravel().tolist() for t in heads], "loss": [float(total[t]) for t in heads], "n": [n] * len(heads)})

        parts = data.mapInArrow(gradients, "task string, g array<double>, loss double, n long")
        summed = parts.select("task", F.posexplode("g").alias("i", "g"), "loss", "n").groupBy("task", "i").agg(F.sum("g").alias("g"), F.sum("loss").alias("loss"), F.sum("n").alias("n")).toPandas()
        seen = {}
        for t, w in student.heads.items():
            own = summed[summed["task"] == t].sort_values("i")
            n = max(int(own["n"].iloc[0]), 1)
            seen[t] = float(own["loss"].iloc[0]) / n
            scale = np.exp(-student.eta[t]) if weighting == "uncertainty" else 1.0
            student.heads[t] = w - rate * scale * own["g"].to_numpy().reshape(w.shape) / n
            if weighting == "uncertainty":
                student.eta[t] -= 0.1 * (1 - seen[t] * np.exp(-student.eta[t]))
        history.append({"loss": seen, "eta": dict(student.eta)})
    return student, history


def score_student(df: DataFrame, student: Student, text: str = "text") -> DataFrame:
    """``df`` with a column student_<task> for each task, from one pass over the text."""
    schema = T.StructType([*df.schema.fields, *[T.StructField(f"student_{t}", T.StringType()) for t in student.tasks]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index(text)).to_pylist()
            x = np.stack([_hashed(t) for t in texts]) if texts else np.zeros((0, WIDTH))
            best = {t: p.argmax(1) for t, p in student.predict(x).items()} if texts else {t: [] for t in student.tasks}
            extra = [pa.array([str(student.tasks[t][i]) for i in best[t]], pa.string()) for t in student.tasks]
            yield pa.RecordBatch.from_arrays([*batch.columns, *extra], [*batch.schema.names, *[f"student_{t}" for t in student.tasks]])

    return df.mapInArrow(run, schema)


def agreement(df: DataFrame, truth: str, guess: str) -> DataFrame:
    """(class, support, precision, recall, f1) of each class of ``truth``; counts only, one shuffle."""
    cells = df.groupBy(F.col(truth).cast("string").alias("t"), F.col(guess).cast("string").alias("g")).agg(F.count("*").alias("n"))
    by_t = cells.groupBy(F.col("t").alias("class")).agg(F.sum("n").alias("support"), F.sum(F.when(F.col("t") == F.col("g"), F.col("n")).otherwise(0)).alias("hit"))
    by_g = cells.groupBy(F.col("g").alias("class")).agg(F.sum("n").alias("guessed"))
    both = by_t.join(by_g, "class", "left")
    precision, recall = ratio(F.col("hit"), F.coalesce("guessed", F.lit(0))), ratio(F.col("hit"), F.col("support"))
    return both.select("class", "support", precision.alias("precision"), recall.alias("recall"), ratio(2 * precision * recall, precision + recall).alias("f1"))
