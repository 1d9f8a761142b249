"""Toxicity: a support vector machine on a gapped-subsequence string kernel with Nyström landmarks.

k(u, v) sums, over the subsequences of P characters that two words share, decay to the number of
characters skipped in both; at most GAP are skipped at a step, so an insult with characters put in or left out
still matches. Documents are compared as sets of words: K(d, e) is the sum of k(u, v) ** POWER over all words u of
d and v of e. A power of a kernel is one and so is the sum, and the power lets one close match outweigh
many slight ones, however long the text. Landmarks are documents of one word piece, which labelled sentences
show to be telling; K at the landmarks, whitened by their own kernel matrix, is the Nyström map of a
document, on which a linear machine is trained. A logistic curve turns its margin into a score.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import column, packed, unpacked

P, PIECE, DECAY, GAP, POWER = 4, 5, 0.5, 2, 3
#: Landmarks, bound on labelled rows that a fit uses, characters of a word looked at in one piece.
LANDMARKS, MOST_ROWS, WIDTH = 48, 8000, 40
CACHE = 1 << 19
EDGE = "^"
APART = re.compile(r"(?<!\S)(?:[^\W\d_]\s+){3,}[^\W\d_](?!\S)")


def units(text: str) -> set[str]:
    """Words, each with its start marked, and runs of letters that stand apart, joined."""
    low = text.lower()
    out = set(low.split())
    joined = ["".join(m.group().split()) for m in APART.finditer(low)]
    marked: set[str] = set()
    for w in (*out, *joined):
        if len(w) < WIDTH:
            marked.add(EDGE + w)
        else:  # a very long word in overlapping pieces
            marked.update((EDGE if i == 0 else "") + w[i : i + WIDTH - 1] for i in range(0, len(w), WIDTH // 2))
    return marked


def kernel(codes: np.ndarray, z: str) -> np.ndarray:
    """k(u, z) of each row u of a matrix of code points, padded by zeros."""
    n, width = codes.shape
    hit = [codes == ord(c) for c in z]
    spare = len(z) - P
    # state[j]: sums that end at this place with character j of z. Only those j count which leave
    # enough of z before and behind.
    state = {j: hit[j].astype(np.float32) for j in range(spare + 1)}
    for q in range(1, P):
        new = {}
        for j in range(q, q + spare + 1):
            total = np.zeros((n, width), np.float32)
            for back in range(1, GAP + 2):
                src = state.get(j - back)
                if src is None:
                    continue
                for step in range(1, GAP + 2):
                    total[:, step:] += src[:, :-step] * np.float32(DECAY ** (step - 1 + back - 1))
            new[j] = total * hit[j]
        state = new
    return sum(state.values()).sum(1)


def matrix(strings: list[str]) -> np.ndarray:
    out = np.zeros((len(strings), WIDTH + 1), np.uint32)
    for k, s in enumerate(strings):
        x = np.frombuffer(s.encode("utf-32-le", "surrogatepass"), np.uint32)
        out[k, : len(x)] = x[: WIDTH + 1]
    return out


#: k of a piece of unlike characters with itself.
UNIT = float(kernel(matrix(["abcdefghij"[:PIECE]]), "abcdefghij"[:PIECE])[0])


def letters(codes: np.ndarray) -> np.ndarray:
    """Set of the characters of each row, as bits of a hash."""
    bits = np.where(codes > 0, np.left_shift(np.uint64(1), (codes.astype(np.uint64) * np.uint64(7)) % np.uint64(64)), np.uint64(0))
    return np.bitwise_or.reduce(bits, axis=1)


@dataclass
class Model:
    landmarks: list[str]
    whiten: np.ndarray
    weights: np.ndarray
    bias: float
    slope: float
    shift: float

    def score(self, values: np.ndarray) -> np.ndarray:
        margin = (values @ self.whiten) @ self.weights + self.bias
        return 1 / (1 + np.exp(-np.clip(self.slope * margin + self.shift, -50, 50)))


class Embedder:
    """K of documents at the landmarks, with a cache of the words that have any. The unit of k is that of a
    piece of unlike characters with itself."""

    def __init__(self, landmarks: list[str]):
        self.landmarks = landmarks
        z = matrix(landmarks) if landmarks else np.zeros((0, WIDTH + 1), np.uint32)
        self.sets = letters(z)
        # A unit with fewer of a landmark's characters than its poorest subsequence has value 0.
        self.need = np.array([min(len(set(s[:k] + s[k + 1 :])) for k in range(len(s))) if len(s) > P else len(set(s)) for s in landmarks], np.int64)
        self.known: dict[str, int] = {}
        self.rows: list[np.ndarray] = []

    def _learn(self, new: list[str]) -> None:
        for at in range(0, len(new), 8192):
            part = new[at : at + 8192]
            codes = matrix(part)
            own = letters(codes)
            values = np.zeros((len(part), len(self.landmarks)), np.float32)
            for j, z in enumerate(self.landmarks):
                sel = np.flatnonzero(np.bitwise_count(own & self.sets[j]) >= min(self.need[j], int(np.bitwise_count(self.sets[j]))))
                if len(sel):
                    sub = codes[sel]
                    width = int((sub > 0).sum(1).max())
                    values[sel, j] = (kernel(sub[:, :width], z) / UNIT) ** POWER
            some = values.any(1)
            for w, s, v in zip(part, some.tolist(), values, strict=True):
                if s:
                    self.known[w] = len(self.rows)
                    self.rows.append(v)
                else:
                    self.known[w] = -1

    def values(self, texts: list[str]) -> np.ndarray:
        if len(self.known) > CACHE:
            self.known, self.rows = {}, []
        each = [units(t) for t in texts]
        new = list(set().union(*each).difference(self.known)) if each else []
        if new:
            self._learn(new)
        out = np.zeros((len(texts), len(self.landmarks)), np.float32)
        for k, u in enumerate(each):
            got = [self.rows[i] for i in map(self.known.__getitem__, u) if i >= 0]
            if got:
                out[k] = np.sum(got, axis=0)
        return out


def pieces(text: str) -> set[str]:
    return {w[i : i + PIECE] for w in units(text) for i in range(max(0, len(w) - PIECE + 1))}


def choose_landmarks(labelled: DataFrame, most: int = LANDMARKS) -> list[str]:
    """Word pieces that cover the toxic rows best, one after another, each by how many rows it adds
    less five times those it meets among the clean. labelled: (y, t), a bounded sample."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tox: Counter = Counter()
        clean: Counter = Counter()
        for b in batches:
            for y, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                (tox if y else clean).update(pieces(t))
        # Pieces that no toxic row of this task has still count against those of other tasks.
        keys = list(tox | clean)
        for at in range(0, len(keys), 50_000):
            k = keys[at : at + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array(k, pa.string()), pa.array([tox[x] for x in k], pa.int64()), pa.array([clean[x] for x in k], pa.int64())], names=["z", "a", "b"])

    counts = labelled.mapInArrow(run, "z string, a bigint, b bigint").groupBy("z").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    total = labelled.agg(F.sum("y").alias("a"), F.sum(1 - F.col("y")).alias("b")).first()
    na, nb = max(1, total["a"] or 0), max(1, total["b"] or 0)
    gain = F.col("a") / F.lit(na) - 5 * F.col("b") / F.lit(nb)
    top = [r["z"] for r in counts.where(F.col("a") >= 2).orderBy(gain.desc(), "z").limit(20 * most).collect()]
    if not top:
        return []
    index = {z: i for i, z in enumerate(top)}

    def meet(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for y, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                own = sorted(index[z] for z in pieces(t) & index.keys())
                yield pa.RecordBatch.from_arrays([pa.array([y], pa.int32()), pa.array([own], pa.list_(pa.int32()))], names=["y", "z"])

    rows = labelled.mapInArrow(meet, "y int, z array<int>").toArrow()
    has = np.zeros((rows.num_rows, len(top)), bool)
    for k, own in enumerate(rows["z"].to_pylist()):
        has[k, own] = True
    y = np.array(rows["y"].to_pylist(), bool)
    against = 5 * has[~y].sum(0) / nb
    times, chosen = np.zeros(int(y.sum())), []
    for _ in range(most):
        worth = (has[y] * (0.25 ** times)[:, None]).sum(0) / na - against
        if worth.max() <= 0.02 / na:
            break
        chosen.append(int(worth.argmax()))
        times += has[y][:, chosen[-1]]
        against[chosen[-1]] = np.inf
    return [top[i] for i in chosen]


def fit_margin(x: np.ndarray, y: np.ndarray, steps: int = 1500, cost: float = 30.0) -> tuple[np.ndarray, float]:
    """Linear machine with squared hinge loss, classes weighing alike, by accelerated gradient steps."""
    sign = np.where(y, 1.0, -1.0)
    weigh = np.where(y, 0.5 / max(1, y.sum()), 0.5 / max(1, (~y).sum()))
    a = np.concatenate([x, np.ones((len(x), 1))], 1)
    step = 1 / (1 / cost + 2 * np.linalg.eigvalsh((a * weigh[:, None]).T @ a)[-1])
    w = v = np.zeros(a.shape[1])
    for t in range(1, steps + 1):
        slack = np.maximum(0, 1 - sign * (a @ v))
        g = -2 * a.T @ (weigh * sign * slack) + np.append(v[:-1], 0) / cost
        new = v - step * g
        v, w = new + (t - 1) / (t + 2) * (new - w), new
    return w[:-1], float(w[-1])


def calibrate(margin: np.ndarray, y: np.ndarray, steps: int = 100) -> tuple[float, float]:
    """Slope (positive) and shift of the logistic curve over the margins, by Newton steps, with targets
    drawn in from 0 and 1 so that separable data stay finite."""
    n1, n0 = int(y.sum()), int((~y).sum())
    t = np.where(y, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    a, b = 1.0, 0.0
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -50, 50)))
        r, h = p - t, p * (1 - p) + 1e-9
        g = np.array([(r * margin).sum() + 1e-3 * (a - 1), r.sum()])
        m = np.array([[(h * margin**2).sum() + 1e-3, (h * margin).sum()], [(h * margin).sum(), h.sum()]])
        d = np.linalg.solve(m + 1e-9 * np.eye(2), g)
        a, b = a - float(np.clip(d[0], -1, 1)), b - float(np.clip(d[1], -1, 1))
    return max(a, 1e-3), b


def landmark_matrix(landmarks: list[str]) -> np.ndarray:
    """K among the landmarks."""
    return (np.stack([kernel(matrix(landmarks), z) for z in landmarks], 1).astype(np.float64) / UNIT) ** POWER


def held_out(id_col: str = "doc_id") -> Column:
    return F.crc32(column(id_col).cast("string").cast("binary")) % 4 == 2


def fit(df: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", most_rows: int = MOST_ROWS, landmarks: int = LANDMARKS) -> Model:
    """Learns from at most ``most_rows`` labelled rows that are not held out, those with the least hash
    of the id (toxic rows fill up to a third of them). Null ids and labels are left out; of documents that repeat
    an id the text with the least hash counts, of labels the largest; null texts count as empty. Without
    rows of both labels every score is next to 0. Other columns are not read."""
    rows = labels.where(column(label_col).isNotNull() & column(id_col).isNotNull() & ~held_out(id_col)).groupBy(column(id_col).alias("id")).agg(F.max(column(label_col).cast("int")).alias("y"))
    pick = lambda y, n: rows.where(F.col("y") == y).orderBy(F.xxhash64("id"), "id").limit(n)
    few = pick(1, most_rows // 3).union(pick(0, most_rows - most_rows // 3))
    texts = df.select(column(id_col).alias("id"), F.coalesce(column(text_col), F.lit("")).alias("t")).join(F.broadcast(few), "id")
    sample = texts.groupBy("id", "y").agg(F.min_by("t", F.struct(F.xxhash64("t"), "t")).alias("t")).select("y", "t").checkpoint()
    chosen = choose_landmarks(sample, landmarks)
    if not chosen:
        return Model([], np.zeros((0, 0), np.float32), np.zeros(0), -1.0, 1.0, -10.0)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = Embedder(chosen)
        for b in batches:
            v = e.values(b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r.tobytes() for r in v])], names=["y", "v"])

    got = sample.mapInArrow(run, "y int, v binary").toArrow()
    y = np.array(got["y"].to_pylist(), bool)
    x = np.frombuffer(b"".join(got["v"].to_pylist()), np.float32).reshape(len(y), -1).astype(np.float64)
    own = landmark_matrix(chosen)
    val, vec = np.linalg.eigh((own + own.T) / 2)
    good = val > 1e-6 * val.max()
    whiten = vec[:, good] / np.sqrt(val[good])
    w, bias = fit_margin(x @ whiten, y)
    slope, shift = calibrate((x @ whiten) @ w + bias, y)
    return Model(chosen, whiten.astype(np.float32), w, bias, slope, shift)


def scorer(model: Model):
    """Column function text -> score. Null and empty texts get the score of no match."""

    def run(it: Iterator[pa.Array]) -> Iterator[pa.Array]:
        e = Embedder(model.landmarks)
        for texts in it:
            parts = [model.score(e.values([x or "" for x in texts.slice(i, 256).to_pylist()])) for i in range(0, len(texts), 256)]
            yield pa.array(np.concatenate(parts) if parts else np.zeros(0), pa.float64())

    run.__annotations__ = {"it": Iterator[pa.Array], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, "double")


def score(df: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", cut: float = 0.3) -> DataFrame:
    """One row per document: id, held_out, score, predicted (int, score >= cut).

    Null and empty texts are scored as texts without a match; repeated rows come back as often; an
    empty table gives an empty result. Other columns are not read.
    """
    rows = df.select(column(id_col).alias(id_col), F.coalesce(held_out(id_col), F.lit(False)).alias("held_out"), scorer(model)(column(text_col)).alias("score"))
    return rows.withColumn("predicted", (F.col("score") >= cut).cast("int"))


def drop_toxic(df: DataFrame, model: Model, text_col: str = "text", cut: float = 0.3) -> DataFrame:
    """The rows scored below ``cut``, with all their columns, whatever their names and types. Null and empty
    texts stay, repeated rows stay as often as they came; an empty table gives an empty result."""
    return unpacked(packed(df, toxic=scorer(model)(column(text_col))).where(F.col("toxic") < cut), df)
