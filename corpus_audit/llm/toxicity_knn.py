"""Toxicity from the nearest labelled examples by exact TF-IDF cosine over a block-max inverted index.

Teaching rows: at most ``most_examples`` labelled documents, every one of them in the index with every word it holds.
A word weighs (1 + ln tf) * idf * relevance^2. idf is counted over all documents. Relevance is log2(2 + ratio), the
ratio of the word's rate among toxic examples to its rate among the others: 1 to 1.6 for words that say nothing, more
for words of toxic examples; no word is left out. With plain TF-IDF (relevance 1) the neighbours follow the language
and topic of a text instead (held-out figures in the README), which is why the factor is there.

The index cuts the examples into blocks of neighbours that share their heaviest word. Per word it holds the greatest
weight in each block; a query adds these maxima, visits blocks from the highest bound down and stops when the k-th best
cosine is out of reach, so the k nearest are exact. Neighbours vote with their similarity; votes of the teaching rows,
each without itself, calibrate the score by a logistic curve. The nearest are returned as evidence.

Defined results: null and empty texts, and texts without any known word, score the smoothed base rate; equal
similarities go to the smaller example number; repeated rows score alike; empty tables give no rows, no labels or one
label only give that constant score; other columns are ignored; very long texts count whole.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Shared, written
from .words import _WORD, held_out, labelled, word_counts

BLOCK = 32


class BlockMaxIndex:
    """Unit TF-IDF vectors of the examples in blocks, with the greatest weight of every term in each block."""

    def __init__(self, vectors: list, labels: np.ndarray, ids: np.ndarray, n_terms: int):
        """vectors: dicts, or (terms ascending, weights)."""
        vectors = [_arrays(v) if isinstance(v, dict) else v for v in vectors]
        # examples with the same heaviest term become neighbours, so that blocks differ in their bounds
        heaviest = [int(t[np.argmax(w)]) if len(t) else -1 for t, w in vectors]
        self.order = np.array(sorted(range(len(vectors)), key=lambda i: (heaviest[i], i)), np.int64)
        self.place = np.argsort(self.order)
        self.labels, self.ids = labels, ids
        self.n_blocks = -(-len(vectors) // BLOCK)
        sizes = np.array([len(vectors[i][0]) for i in self.order], np.int64)
        self.rows = np.r_[0, np.cumsum(sizes)]
        self.terms = np.concatenate([np.empty(0, np.int32), *(vectors[i][0] for i in self.order)]).astype(np.int32)
        self.weights = np.concatenate([np.empty(0), *(vectors[i][1] for i in self.order)])
        block = (np.repeat(np.arange(len(vectors)), sizes) // BLOCK).astype(np.int64)
        at = np.lexsort((block, self.terms))
        term, block, weight = self.terms[at].astype(np.int64), block[at], self.weights[at]
        first = np.flatnonzero(np.r_[len(at) > 0, (term[1:] != term[:-1]) | (block[1:] != block[:-1])])
        self.max_block = block[first].astype(np.int32)
        self.max_weight = np.maximum.reduceat(weight, first) if len(first) else np.empty(0)
        self.max_cut = np.searchsorted(term[first], np.arange(n_terms + 1))
        # the same weights by term, for queries that leave most blocks open
        self.post_cut = np.searchsorted(term, np.arange(n_terms + 1))
        self.post_row = np.repeat(np.arange(len(vectors)), sizes)[at].astype(np.int32)
        self.post_weight = weight
        self.query = np.zeros(n_terms)
        self.visited = self.asked = 0

    def vector(self, number: int) -> tuple[np.ndarray, np.ndarray]:
        """The terms and weights of an example."""
        at = slice(self.rows[self.place[number]], self.rows[self.place[number] + 1])
        return self.terms[at].astype(np.int64), self.weights[at]

    def nearest(self, query: dict[int, float], k: int, without: int = -1) -> list[tuple[float, int]]:
        """The k highest (cosine, example number), ties to the smaller number; only positive cosines."""
        scores, numbers = self.search(*_arrays(query), k, without)
        return list(zip(scores.tolist(), numbers.tolist(), strict=True))

    def search(self, terms: np.ndarray, weights: np.ndarray, k: int, without: int = -1) -> tuple[np.ndarray, np.ndarray]:
        """As ``nearest``, with ascending terms and arrays."""
        if not len(terms) or not self.n_blocks:
            return np.empty(0), np.empty(0, np.int64)
        flat, size = _ranges(self.max_cut[terms], self.max_cut[terms + 1])
        bound = np.bincount(self.max_block[flat], np.repeat(weights, size) * self.max_weight[flat], self.n_blocks)
        self.query[terms] = weights
        ranked = np.argsort(-bound, kind="stable")
        scores, rows, floor = np.empty(0), np.empty(0, np.int64), 0.0
        # where many bounds are close to the highest, two blocks settle little: the lists are then read at once
        close = np.count_nonzero(bound > bound[ranked[0]] / 2) > self.n_blocks // 16
        for low, high in ((0, self.n_blocks),) if close else ((0, 2), (2, self.n_blocks)):
            part = ranked[low:high]
            part = part[bound[part] > max(0.0, floor - 1e-12)]
            if not len(part):
                break
            at = (part[:, None] * BLOCK + np.arange(BLOCK)).ravel()
            at = at[at < len(self.order)]
            found = np.concatenate([self._of_block(p) for p in part]) if len(part) <= self.n_blocks // 16 else self._by_term(terms, weights)[at]
            keep = (found > max(0.0, floor - 1e-12)) & (self.order[at] != without)
            scores, rows = np.concatenate((scores, found[keep])), np.concatenate((rows, at[keep]))
            self.visited += len(part)
            if len(scores) >= k:
                floor = float(np.partition(scores, len(scores) - k)[len(scores) - k])
        self.asked += self.n_blocks
        self.query[terms] = 0.0
        # scores are compared after rounding, so what rounds like the k-th stays
        near = scores >= floor - 1e-11
        scores, numbers = np.round(scores[near], 12), self.order[rows[near]]
        best = np.lexsort((numbers, -scores))[:k]
        return scores[best], numbers[best]

    def _of_block(self, block: int) -> np.ndarray:
        """The cosines of the rows of a block, from their own weights."""
        cuts = self.rows[block * BLOCK : (block + 1) * BLOCK + 1]
        low, high = cuts[0], cuts[-1]
        each = self.weights[low:high] * self.query[self.terms[low:high]]
        found, full = np.zeros(len(cuts) - 1), cuts[1:] > cuts[:-1]
        if high > low:
            found[full] = np.add.reduceat(each, cuts[:-1][full] - low)
        return found

    def _by_term(self, terms: np.ndarray, weights: np.ndarray) -> np.ndarray:
        """The cosines of all rows, from the lists of the query's terms."""
        flat, size = _ranges(self.post_cut[terms], self.post_cut[terms + 1])
        return np.bincount(self.post_row[flat], np.repeat(weights, size) * self.post_weight[flat], len(self.order))


def _arrays(vector: dict[int, float]) -> tuple[np.ndarray, np.ndarray]:
    """The terms of a vector, ascending, and their weights."""
    terms = np.array(sorted(vector), np.int64)
    return terms, np.array([vector[t] for t in terms.tolist()], float)


def _ranges(low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of all ranges [low, high) one after the other, and the size of each range."""
    size = high - low
    end = np.cumsum(size)
    return np.repeat(low - end + size, size) + np.arange(end[-1] if len(end) else 0), size


def unit(counts: dict[int, int], weight: np.ndarray) -> dict[int, float]:
    """The unit vector of term counts, terms in ascending order."""
    terms, values = unit_arrays(*_arrays(counts), weight)
    return dict(zip(terms.tolist(), values.tolist(), strict=True))


def unit_arrays(terms: np.ndarray, counts: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """As ``unit``, with ascending terms and arrays."""
    values = (1 + np.log(counts)) * weight[terms]
    norm = float(np.sqrt(values @ values))
    return (terms, values / norm) if norm > 0 else (terms[:0], values[:0])


def known_terms(words, number: dict[str, int]) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of the known words, ascending, and how often each occurs."""
    counts = Counter(words)
    terms = np.fromiter(map(number.get, counts, repeat(-1)), np.int64, len(counts))
    times = np.fromiter(counts.values(), np.float64, len(counts))
    at = np.argsort(terms)[np.count_nonzero(terms < 0) :]
    return terms[at], times[at]


def _relevance(toxic: np.ndarray, df: np.ndarray, n_toxic: int, n: int) -> np.ndarray:
    """log2(2 + ratio of the rates among toxic and other examples); one other example at least."""
    rate = toxic * (n - n_toxic) / np.maximum(1, df - toxic) / max(1, n_toxic)
    return np.log2(2 + rate)


def document_frequencies(docs: DataFrame, number: dict[str, int], chunk: int = 8_192) -> tuple[np.ndarray, int]:
    """In how many of all documents each known term occurs, and the number of documents.

    Every task sends one packed array a chunk of terms; sums go over groups of tasks first."""
    shared = Shared(docs.sparkSession, number)
    size = len(number)

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known, df, n = shared.value, np.zeros(size + 1, np.int64), 0
        for batch in batches:
            for text in batch["text"]:
                n += 1
                if text:
                    words = set(_WORD.findall(text.lower()))
                    # a word that is not known counts in the last place, which is overwritten
                    df[np.fromiter(map(known.get, words, repeat(size)), np.int64, len(words))] += 1
        df[size] = n
        group = TaskContext.get().partitionId() // 64
        rows = [(group, low // chunk, df[low : low + chunk].tobytes()) for low in range(0, size + 1, chunk)]
        yield pd.DataFrame(rows, columns=["grp", "chunk", "counts"])

    def total(frame: pd.DataFrame) -> pd.DataFrame:
        summed = np.sum([np.frombuffer(x, np.int64) for x in frame["counts"]], axis=0)
        return pd.DataFrame({"grp": [0], "chunk": [frame["chunk"].iloc[0]], "counts": [summed.astype(np.int64).tobytes()]})

    kind = "grp long, chunk long, counts binary"
    parts = docs.select("text").mapInPandas(count, kind).groupBy("grp", "chunk").applyInPandas(total, kind)
    rows = sorted(parts.groupBy("chunk").applyInPandas(total, kind).collect(), key=lambda r: r["chunk"])
    shared.done()
    if not rows:
        return np.zeros(size, np.int64), 0
    found = np.concatenate([np.frombuffer(r["counts"], np.int64) for r in rows])
    return found[:size], int(found[size])


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", most_examples: int = 2_500, k: int = 25) -> dict:
    """terms, weight of each, index, base rate, k and the calibration; bounded by ``most_examples``."""
    spark = docs.sparkSession
    sample = labelled(docs, labels, label, most_examples)

    def counted(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            counts = [word_counts(t) for t in batch["text"]]
            yield pd.DataFrame({"doc_id": batch["doc_id"], "label": batch["label"], "terms": [list(c.keys()) for c in counts], "times": [list(c.values()) for c in counts]})

    chosen = written(sample.mapInPandas(counted, "doc_id long, label int, terms array<string>, times array<int>"), "toxic-sample")
    marks, ids, rows, words, times = _flat(chosen)
    flat = words.dictionary_encode()
    found = flat.dictionary.to_pylist()
    # numbers follow the order of the words
    order = sorted(range(len(found)), key=found.__getitem__)
    number: dict[str, int] = {found[i]: n for n, i in enumerate(order)}
    terms = np.argsort(np.array(order, np.int64))[flat.indices.to_numpy(zero_copy_only=False)] if found else np.empty(0, np.int64)
    df, n_docs = document_frequencies(docs, number)
    n, n_toxic = len(marks), int(marks.sum())
    own = np.bincount(terms, minlength=len(number))
    toxic = np.bincount(terms, np.repeat(marks, np.diff(rows)), len(number))
    weight = (np.log((1 + n_docs) / (1 + df)) + 1) * _relevance(toxic, own, n_toxic, n) ** 2 if n else np.zeros(0)
    vectors = []
    for low, high in zip(rows[:-1], rows[1:], strict=True):
        at = low + np.argsort(terms[low:high])
        vectors.append(unit_arrays(terms[at], times[at].astype(float), weight))
    index = BlockMaxIndex(vectors, marks.astype(float), ids, len(number))
    # a text without known words is as toxic as texts are on the whole
    base = n_toxic / (n + 1)
    model = {"number": number, "weight": weight, "index": index, "base": base, "k": k, "curve": None}
    if 0 < n_toxic < n:
        model["curve"] = calibrated(spark, model)
    return model


def _flat(chosen: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, pa.Array, np.ndarray]:
    """(labels, ids, cuts, words, times) of the examples by doc_id (equal ones by words and times), end to end: as
    buffers, for lists of words would take many times their size on the driver."""
    got = chosen.toArrow().combine_chunks()
    if not got.num_rows:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.zeros(1, np.int64), pa.array([], pa.string()), np.empty(0, np.int64)
    ids = got["doc_id"].to_numpy()
    order = np.argsort(ids, kind="stable")
    run = np.flatnonzero(np.r_[True, np.diff(ids[order]) != 0])
    for low, high in zip(run, np.r_[run[1:], len(order)], strict=True):
        if high - low > 1:
            order[low:high] = sorted(order[low:high], key=lambda i: (got["terms"][int(i)].as_py(), got["times"][int(i)].as_py()))
    got = got.take(pa.array(order)).combine_chunks()
    terms, times = got["terms"].combine_chunks(), got["times"].combine_chunks()
    sizes = np.asarray(terms.value_lengths(), np.int64)
    return got["label"].to_numpy().astype(np.int64), ids[order], np.r_[0, np.cumsum(sizes)], terms.flatten(), times.flatten().to_numpy()


def vote(index: BlockMaxIndex, near: tuple[np.ndarray, np.ndarray], base: float, prior: float = 0.1) -> float:
    """Toxic share of the neighbours' similarity, drawn to the base rate where they are far."""
    scores, numbers = near
    return float((scores @ index.labels[numbers] + prior * base) / (scores.sum() + prior))


def calibrated(spark, model: dict, rounds: int = 50) -> tuple[float, float]:
    """(slope, shift) of a logistic curve over the logit of the vote, fitted on the examples, each without itself.

    Targets are smoothed by the class sizes, so separable votes give finite curves."""
    shared = Shared(spark, model)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            fitted = shared.value
            index = fitted["index"]
            votes = [vote(index, index.search(*index.vector(i), fitted["k"], without=i), fitted["base"]) for i in batch["id"]]
            yield pd.DataFrame({"id": batch["id"], "vote": votes})

    rows = spark.range(len(model["index"].labels)).mapInPandas(run, "id long, vote double").collect()
    shared.done()
    x, y = np.zeros(len(model["index"].labels)), model["index"].labels
    for r in rows:
        x[r["id"]] = _logit(r["vote"])
    n1, n0 = y.sum(), len(y) - y.sum()
    target = np.where(y == 1, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    a, b = 1.0, 0.0
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a * x + b, -30, 30)))
        w = np.maximum(p * (1 - p), 1e-9)
        design = np.stack((x, np.ones_like(x)), 1)
        step = np.linalg.solve(design.T @ (design * w[:, None]) + 1e-3 * np.eye(2), design.T @ (target - p))
        a, b = a + step[0], b + step[1]
        if np.abs(step).max() < 1e-9:
            break
    return (float(a), float(b)) if a > 0 else (1.0, 0.0)


def _logit(p: float) -> float:
    p = min(max(p, 1e-6), 1 - 1e-6)
    return float(np.log(p / (1 - p)))


class Scorer:
    """Scores texts; remembers a bounded number of them, as copies are frequent."""

    def __init__(self, most: int = 50_000):
        self.most, self.known = most, {}

    def __call__(self, model: dict, texts) -> tuple[list[float], list[list[int]]]:
        scores, evidence = [], []
        for text in texts:
            found = self._one(model, text or "")
            scores.append(found[0])
            evidence.append(found[1])
        return scores, evidence

    def _one(self, model: dict, text: str) -> tuple[float, list[int]]:
        key = hashlib.md5(text.encode("utf-8", "replace")).digest()
        if (out := self.known.get(key)) is None:
            out = self._score(model, text)
            if len(self.known) < self.most:
                self.known[key] = out
        return out

    def _score(self, model: dict, text: str) -> tuple[float, list[int]]:
        number, index = model["number"], model["index"]
        near = index.search(*unit_arrays(*known_terms(_WORD.findall(text.lower()), number), model["weight"]), model["k"])
        if not len(near[0]):
            return model["base"], []
        share = vote(index, near, model["base"])
        if model["curve"] is not None:
            a, b = model["curve"]
            share = float(1 / (1 + np.exp(-np.clip(a * _logit(share) + b, -30, 30))))
        return share, index.ids[near[1][:3]].tolist()


def score(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, score, evidence (nearest example ids, at most 3)."""
    shared = Shared(docs.sparkSession, (Scorer(), model))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            scorer, fitted = shared.value
            scores, evidence = scorer(fitted, batch["text"])
            yield pd.DataFrame({"doc_id": batch["doc_id"], "score": scores, "evidence": evidence})

    return docs.select("doc_id", "text").mapInPandas(run, "doc_id long, score double, evidence array<long>")


def toxicity(docs: DataFrame, labels: DataFrame, threshold: float = 0.5, **options) -> DataFrame:
    found = score(docs, fit(docs, labels, **options))
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "evidence")


def keep_clean(docs: DataFrame, labels: DataFrame, threshold: float = 0.5, **options) -> DataFrame:
    """docs without the rows that score at or above the threshold; columns as they came."""
    schema = docs.schema
    shared = Shared(docs.sparkSession, (Scorer(), fit(docs, labels, **options)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            scorer, model = shared.value
            scores, _ = scorer(model, batch.column(batch.schema.names.index("text")).to_pylist())
            yield batch.filter(pa.array([s < threshold for s in scores], pa.bool_()))

    return docs.mapInArrow(run, schema)
