"""Quality classifier: cumulative-link (ordinal logistic) regression on graded ratings.

One weight vector over hashed text features is shared by all grades; ordered thresholds split the score
into grades: P(grade >= k) = sigmoid(score - threshold_k). The expected grade and a tail probability
serve selection. Features are hashed byte trigrams of the whole text and hashed tokens of its shape
(how repetitive, how loud, how many symbols), all in one space.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column

#: Dimensions of the hashed space, and the bound on labelled rows that a fit uses.
DIMS, MOST_ROWS = 1 << 11, 6000
CHUNK = 1 << 20


def trigrams(data: bytes) -> np.ndarray:
    """Counts of hashed byte trigrams, over the whole text, chunk by chunk."""
    out = np.zeros(DIMS, np.int64)
    b = np.frombuffer(data, np.uint8)
    for at in range(0, max(0, len(b) - 2), CHUNK):
        x = b[at : at + CHUNK + 2].astype(np.uint32)
        code = ((x[:-2] << 16 | x[1:-1] << 8 | x[2:]) * np.uint32(2654435761)) >> np.uint32(32 - 11)
        out += np.bincount(code, minlength=DIMS)
    return out


def shape(text: str, data: bytes) -> list[tuple[str, int]]:
    """Binned shape of the text, as (name, bin)."""
    w = data.split()
    n = max(1, len(w))
    b = np.frombuffer(data, np.uint8)
    count = np.bincount(b, minlength=256) if len(b) else np.zeros(256, np.int64)
    upper, lower = int(count[65:91].sum()), int(count[97:123].sum())
    marks = int(sum(count[ord(c)] for c in "#*$%&|<>{}[]=/\\"))
    step = lambda x, cuts: int(np.searchsorted(cuts, x))
    runs = sum(a == c for a, c in zip(w, w[1:]))
    return [
        ("words", step(len(w), [1, 5, 10, 20, 50, 100, 500, 2000])),
        ("distinct", step(len(set(w)) / n, [0.05, 0.1, 0.2, 0.35, 0.5, 0.7, 0.9])),
        ("runs", step(runs / n, [0.01, 0.05, 0.1, 0.3, 0.6])),
        ("upper", step(upper / max(1, upper + lower), [0.05, 0.1, 0.2, 0.4, 0.7])),
        ("marks", step(marks / n, [0.01, 0.05, 0.1, 0.3, 1.0])),
        ("shouts", step(int(count[33]) / n, [0.01, 0.05, 0.2, 0.5])),
        ("digits", step(int(count[48:58].sum()) / max(1, len(b)), [0.01, 0.05, 0.1, 0.3])),
        ("lines", step(len(set(lines := text.split("\n"))) / len(lines), [0.3, 0.5, 0.7, 0.9])),
    ]


def _slot(name: str, k: int) -> int:
    h = 2166136261
    for c in f"{name}={k}".encode():
        h = (h ^ c) * 16777619 & 0xFFFFFFFF
    return DIMS + h % 256


def features(text: str) -> np.ndarray:
    """Dense vector: unit-length square roots of the trigram counts, then the shape's slots."""
    data = text.encode("utf-8", "replace")
    out = np.zeros(DIMS + 256, np.float32)
    out[:DIMS] = np.sqrt(trigrams(data))
    out[:DIMS] /= max(1e-9, float(np.linalg.norm(out[:DIMS])))
    for name, k in shape(text, data):
        out[_slot(name, k)] += 0.5
    return out


def descend(loss, v: np.ndarray, steps: int, memory: int = 10, small: float = 1e-5) -> np.ndarray:
    """Quasi-Newton descent with the curvature of the last ``memory`` steps and halving of a step that does
    not go down. loss: v -> (value, slope)."""
    value, slope = loss(v)
    past: list[tuple[np.ndarray, np.ndarray, float]] = []
    for _ in range(steps):
        way, a = slope.copy(), []
        for s, g, r in reversed(past):
            a.append(r * float(s @ way))
            way -= a[-1] * g
        if past:
            s, g, r = past[-1]
            way /= r * float(g @ g)
        for (s, g, r), k in zip(past, reversed(a), strict=True):
            way += (k - r * float(g @ way)) * s
        fall, size = float(slope @ way), 1.0 if past else min(1.0, 1 / max(1e-12, float(np.abs(slope).sum())))
        for _ in range(30):
            new = v - size * way
            new_value, new_slope = loss(new)
            if new_value <= value - 1e-4 * size * fall:
                break
            size /= 2
        else:
            return v
        s, g = new - v, new_slope - slope
        if (curve := float(s @ g)) > 1e-12:
            past = [*past[1 - memory :], (s, g, 1 / curve)]
        v, value, slope = new, new_value, new_slope
        if np.abs(slope).max() < small:
            break
    return v


class CumulativeLink:
    """Ordinal logistic regression with shared weights and increasing thresholds."""

    def __init__(self, weights: np.ndarray, thresholds: np.ndarray, grades: list[int]):
        self.weights, self.thresholds, self.grades = weights, thresholds, grades

    @classmethod
    def fit(cls, x: np.ndarray, y: np.ndarray, steps: int = 100, l2: float = 1e-3) -> CumulativeLink:
        grades = sorted(set(y.tolist()))
        if len(grades) < 2:
            return cls(np.zeros(x.shape[1], np.float32), np.zeros(0), grades or [0])
        above = np.stack([y > g for g in grades[:-1]], 1).astype(np.float32)  # (rows, grades - 1)
        share = above.mean(0).clip(1e-3, 1 - 1e-3)
        first, d = np.sort(-np.log(share / (1 - share))), x.shape[1]

        def cuts(raw: np.ndarray) -> np.ndarray:
            """Thresholds: the first, then the (positive) steps between them, given by their logarithms."""
            return raw[0] + np.concatenate([[0], np.cumsum(np.exp(raw[1:]))])

        def loss(v: np.ndarray) -> tuple[float, np.ndarray]:
            w, raw = v[:d], v[d:]
            m = (x @ w.astype(np.float32)).astype(float)[:, None] - cuts(raw)[None, :]
            value = (np.logaddexp(0, m) - above * m).sum() / len(x) + l2 / 2 * float(w @ w)
            err = (1 / (1 + np.exp(-np.clip(m, -50, 50))) - above) / len(x)
            gt = -err.sum(0)
            raw_slope = np.concatenate([[gt.sum()], [gt[k:].sum() * np.exp(raw[k]) for k in range(1, len(gt))]])
            return value, np.concatenate([x.T @ err.sum(1).astype(np.float32) + l2 * w, raw_slope])

        v = np.concatenate([np.zeros(d), first[:1], np.log(np.maximum(1e-2, np.diff(first)))])
        v = descend(loss, v, steps)
        return cls(v[:d].astype(np.float32), cuts(v[d:]), grades)

    def tails(self, score: np.ndarray) -> np.ndarray:
        """P(grade > g) for each grade g but the last, per row; falls from left to right."""
        return 1 / (1 + np.exp(-np.clip(np.asarray(score)[:, None] - self.thresholds[None, :], -50, 50)))

    def expected(self, tails: np.ndarray) -> np.ndarray:
        return self.grades[0] + (tails * np.diff(self.grades)[None, :]).sum(1) if len(self.grades) > 1 else np.full(len(tails), float(self.grades[0]))


def training_rows(df: DataFrame, ratings: DataFrame, id_col: str, text_col: str, grade_col: str, most_rows: int) -> tuple[np.ndarray, np.ndarray]:
    """Features and grades of at most ``most_rows`` rated rows, those with the least hash of the id. Of
    documents that repeat an id, the text with the least hash is rated; of ratings, the least."""
    rated = ratings.where(column(grade_col).isNotNull() & column(id_col).isNotNull()).groupBy(column(id_col).alias("id")).agg(F.min(column(grade_col).cast("int")).alias("g"))
    few = rated.orderBy(F.xxhash64("id"), "id").limit(most_rows)
    texts = df.select(column(id_col).alias("id"), F.coalesce(column(text_col), F.lit("")).alias("t")).join(F.broadcast(few), "id")
    joined = texts.groupBy("id", "g").agg(F.min_by("t", F.struct(F.xxhash64("t"), "t")).alias("t")).select("g", "t")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for g, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array([g], pa.int32()), pa.array([features(t).astype(np.float16).tobytes()])], names=["g", "x"])

    got = joined.mapInArrow(run, "g int, x binary").toArrow()
    if not got.num_rows:
        return np.zeros((0, DIMS + 256), np.float32), np.zeros(0, np.int64)
    x = np.frombuffer(b"".join(got["x"].to_pylist()), np.float16).reshape(got.num_rows, -1).astype(np.float32)
    return x, np.array(got["g"].to_pylist())


def fit(df: DataFrame, ratings: DataFrame, id_col: str = "doc_id", text_col: str = "text", grade_col: str = "grade", most_rows: int = MOST_ROWS) -> CumulativeLink:
    """Learns from at most ``most_rows`` rated rows. Null ids and null grades are left out, a null text is rated
    as the empty one; with no ratings, or all of one grade, the model knows that grade only (0 without any).
    Other columns are not read."""
    return CumulativeLink.fit(*training_rows(df, ratings, id_col, text_col, grade_col, most_rows))


def classify(df: DataFrame, model: CumulativeLink, at_least: int, cut: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, expected_grade, tail (P(grade >= at_least)) and kept (tail >= cut).

    Null and empty texts are scored as the empty text; without ratings all get the only grade known
    and tail 0.5; repeated rows come back as often; an empty table gives an empty result. Other
    columns are not read.
    """
    k = next((i for i, g in enumerate(model.grades[1:]) if g >= at_least), None)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            score = np.array([float(features(t) @ model.weights) for t in b.column(1).to_pylist()])
            tails = model.tails(score)
            tail = tails[:, k] if k is not None else np.full(len(score), 0.5)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(model.expected(tails)), pa.array(tail), pa.array(tail >= cut)], names=["i", "expected_grade", "tail", "kept"])

    rows = df.select(column(id_col).cast("bigint").alias("i"), F.coalesce(column(text_col), F.lit("")).alias("t"))
    return rows.mapInArrow(run, "i bigint, expected_grade double, tail double, kept boolean").withColumnRenamed("i", id_col)


def graded(labels: DataFrame) -> DataFrame:
    """Ratings of three grades from the two labels: 0 poor, 1 sound but toxic, 2 sound."""
    return labels.where("quality is not null").select("doc_id", F.when(F.col("quality") == 0, 0).when(F.coalesce(F.col("toxic"), F.lit(0)) == 1, 1).otherwise(2).alias("grade"))
