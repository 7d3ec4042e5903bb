"""Document quality by a factorisation machine.

Inputs: hashed words (log counts, unit length) and structure statistics of the text. The pairwise part of
w0 + w.x + sum over i<j of <v_i, v_j> x_i x_j costs one pass over the non-zeros: half of the sum over factors of
(sum v x)^2 - sum (v x)^2. Trained by mini-batch Adam on the logistic loss over a bounded sample of labelled rows
(``most_examples``, in digest order of doc_id), so the model has one size whatever the corpus.

Defined results: null and empty texts score by their (all-zero) statistics; without labels of both classes the
score is the smoothed base rate; repeated rows score alike; doc_id, lang, source and labels are never inputs.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Shared
from .words import held_out, labelled

BUCKETS = 1 << 13
STATISTICS = ("words", "mean_length", "distinct", "repeats", "bars", "upper", "digits", "symbols", "lines", "same_lines", "line_words", "long_words", "stops", "short", "top_word")
WIDTH = BUCKETS + len(STATISTICS)


class Hasher(dict):
    def __missing__(self, word: str) -> int:
        h = zlib.crc32(word.encode("utf-8", "replace")) % BUCKETS
        if len(self) < 300_000:
            self[word] = h
        return h


def features(text: str | None, hasher: Hasher) -> tuple[np.ndarray, np.ndarray]:
    """Sorted feature numbers and values."""
    text = text or ""
    words = text.split()
    n = len(words)
    if not n:
        return np.array([BUCKETS + STATISTICS.index("short")], np.int32), np.array([1.0], np.float32)
    counts = Counter(words)
    rows = text.split("\n")
    chars = max(1, len(text))
    letters = text.count
    number = sum(map(letters, "0123456789"))
    symbol = sum(map(letters, "!#$%&*=<>{}[]~^\\"))
    upper = sum(1 for w in words if w.isupper() and len(w) > 1)
    repeats = sum(map(str.__eq__, words, words[1:]))
    stats = np.array(
        [
            np.log1p(n) / 10, min(3.0, chars / n / 8), len(counts) / n, repeats / n, letters("|") / n, upper / n, number / chars * 4, symbol / chars * 10,
            np.log1p(len(rows)) / 6, 1 - len(set(rows)) / len(rows), np.log1p(n / len(rows)) / 6, sum(1 for w in words if len(w) > 12) / n, letters(".") / n, 1.0 if n < 8 else 0.0, max(counts.values()) / n,
        ],
        np.float32,
    )
    at = np.fromiter(map(hasher.__getitem__, counts.keys()), np.int32, len(counts))
    bag = np.bincount(at, weights=np.log1p(np.fromiter(counts.values(), np.float64, len(counts))), minlength=0)
    hit = np.flatnonzero(bag)
    value = bag[hit]
    value /= np.sqrt((value * value).sum())
    return np.r_[hit, np.arange(BUCKETS, WIDTH)].astype(np.int32), np.r_[value, stats].astype(np.float32)


class Machine:
    def __init__(self, factors: int = 8, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.w0, self.w, self.v = 0.0, np.zeros(WIDTH), rng.normal(0, 0.02, (WIDTH, factors))

    def logits(self, at: np.ndarray, x: np.ndarray, cuts: np.ndarray) -> np.ndarray:
        """Rows are the slices of (at, x) that start at cuts."""
        vx = self.v[at] * x[:, None]
        sums = np.add.reduceat(vx, cuts)
        squares = np.add.reduceat(vx * vx, cuts)
        return self.w0 + np.add.reduceat(self.w[at] * x, cuts) + 0.5 * (sums**2 - squares).sum(1)

    def train(self, rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, epochs: int = 6, rate: float = 0.02, batch: int = 256, least_steps: int = 600, shrink: float = 1e-3, seed: int = 7) -> Machine:
        """Small samples take smaller batches and more epochs, so that the parameters move far enough."""
        batch = max(16, min(batch, len(rows) // 16))
        epochs = max(epochs, -(-least_steps * batch // len(rows)))
        rng = np.random.default_rng(seed)
        rate_of_ones = np.clip(labels.mean(), 1e-3, 1 - 1e-3)
        self.w0 = float(np.log(rate_of_ones / (1 - rate_of_ones)))
        moments = [[np.zeros_like(p), np.zeros_like(p)] for p in (self.w, self.v)]
        step, first0, second0 = 0, 0.0, 0.0
        for _ in range(epochs):
            order = rng.permutation(len(rows))
            for low in range(0, len(order), batch):
                part = order[low : low + batch]
                at = np.concatenate([rows[i][0] for i in part])
                x = np.concatenate([rows[i][1] for i in part]).astype(float)
                sizes = np.array([len(rows[i][0]) for i in part])
                cuts = np.r_[0, np.cumsum(sizes)[:-1]]
                error = 1 / (1 + np.exp(-np.clip(self.logits(at, x, cuts), -30, 30))) - labels[part]
                error /= len(part)
                each = np.repeat(error, sizes)
                sums = np.repeat(np.add.reduceat(self.v[at] * x[:, None], cuts), sizes, axis=0)
                used, back = np.unique(at, return_inverse=True)
                grad_w = np.bincount(back, each * x) + shrink * self.w[used]
                slope = (each * x)[:, None] * (sums - self.v[at] * x[:, None])
                grad_v = np.stack([np.bincount(back, slope[:, f]) for f in range(self.v.shape[1])], 1) + shrink * self.v[used]
                step += 1
                lift = rate * np.sqrt(1 - 0.999**step) / (1 - 0.9**step)
                first0, second0 = 0.9 * first0 + 0.1 * error.sum(), 0.999 * second0 + 0.001 * error.sum() ** 2
                self.w0 -= lift * first0 / (np.sqrt(second0) + 1e-8)
                for value, grad, (m1, m2) in ((self.w, grad_w, moments[0]), (self.v, grad_v, moments[1])):
                    m1[used] = 0.9 * m1[used] + 0.1 * grad
                    m2[used] = 0.999 * m2[used] + 0.001 * grad**2
                    value[used] -= lift * m1[used] / (np.sqrt(m2[used]) + 1e-8)
        return self

    def score(self, rows: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
        if not rows:
            return np.empty(0)
        cuts = np.r_[0, np.cumsum([len(a) for a, _ in rows])[:-1]]
        z = self.logits(np.concatenate([a for a, _ in rows]), np.concatenate([x for _, x in rows]).astype(float), cuts)
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", most_examples: int = 10_000, **options) -> Machine:
    hasher = Hasher()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            found = [features(t, hasher) for t in batch["text"]]
            yield pd.DataFrame({"doc_id": batch["doc_id"], "label": batch["label"], "at": [a.tobytes() for a, _ in found], "x": [x.tobytes() for _, x in found]})

    rows = labelled(docs, labels, label, most_examples).mapInPandas(run, "doc_id long, label int, at binary, x binary").toPandas()
    rows = rows.sort_values(["doc_id", "at", "x"])
    marks = rows["label"].to_numpy(float)
    machine = Machine()
    if len(set(marks)) < 2:
        rate = (marks.sum() + 1) / (len(marks) + 2)
        machine.w0, machine.v[:] = float(np.log(rate / (1 - rate))), 0.0
        return machine
    return machine.train([(np.frombuffer(a, np.int32), np.frombuffer(x, np.float32)) for a, x in zip(rows["at"], rows["x"], strict=True)], marks, **options)


def quality(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, **options) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    shared, hasher = Shared(docs.sparkSession, fit(docs, labels, **options)), Hasher()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, out = batch.column(1).to_pylist(), []
            for low in range(0, len(texts), 128):
                out.append(shared.value.score([features(t, hasher) for t in texts[low : low + 128]]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.concatenate(out) if out else np.empty(0), pa.float64())], ["doc_id", "score"])

    scored = docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
