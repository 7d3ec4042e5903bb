"""Exact top-k inner products with multi-resolution segment statistics.

A vector is described per segment by mean m and deviation s; over a segment of length l two vectors' inner product
lies within l (m m' +- s s'), so sums over segments bound the whole from coarse (one segment) to fine. For each
query, candidates whose upper bound falls below the current k-th best leave at the coarsest level that rules them
out, pair by pair; surviving pairs get exact integer products. (Inner products and squared distances bound each other
through the norms, so this is the lower bound on distance in another form.) What the bounds save depends on the data:
components that vary along a vector like noise leave nearly every pair open, whatever the level below the whole.

Queries travel in broadcast chunks of at most ``chunk`` vectors, each chunk against all rows where they lie; every
partition returns at most k rows a query. Components and scores beyond 64 bits stay at the end of the range.

Defined results: vectors null, or with null or non-finite components, take no part; neither do candidates of
another length than the query; ties go to the smaller vec_id; repeated vec_ids are rows of their own, but never
candidates of a query with the same vec_id, and ask once, with the smallest vector; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Shared

LEVELS = (1, 4, 16, 32)
FURTHEST = float(2**62)


def usable(vector: Column) -> Column:
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce(vector.isNotNull() & (F.size(vector) > 0) & fine, F.lit(False))


def quantised(vectors: DataFrame, scale: int = 1024) -> DataFrame:
    """vec_id, vector array<long>: floor(scale * x) of the usable rows."""
    taken = vectors.where(usable(F.col("embedding")) & F.col("vec_id").isNotNull())
    # what no 64-bit number holds stays at the end of the range
    number = lambda x: F.floor(F.least(F.greatest(F.lit(scale) * x.cast("double"), F.lit(-FURTHEST)), F.lit(FURTHEST)))
    return taken.select("vec_id", F.transform("embedding", number).alias("vector"))


def segment_bounds(block: np.ndarray, segments: int) -> np.ndarray:
    """Rows such that the product of two vectors' rows bounds their inner product from above (row-wise stacking)."""
    parts = np.array_split(np.arange(block.shape[1]), min(segments, block.shape[1]))
    mean = np.stack([block[:, p].mean(1) * np.sqrt(len(p)) for p in parts], 1)
    dev = np.stack([block[:, p].std(1) * np.sqrt(len(p)) for p in parts], 1)
    return np.concatenate((mean, dev), 1)


def _products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact integer inner products: by float64 where all sums stay below 2^53, else in Python's integers."""
    if float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * a.shape[1] < 2**53:
        return np.rint(a.astype(float) @ b.astype(float).T).astype(np.int64)
    exact = a.astype(object) @ b.astype(object).T
    return np.clip(exact, -(2**63) + 1, 2**63 - 1).astype(np.int64)


def _paired(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact integer inner products of row i with row i."""
    if float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * a.shape[1] < 2**53:
        return np.rint(np.einsum("ij,ij->i", a.astype(float), b.astype(float))).astype(np.int64)
    exact = (a.astype(object) * b.astype(object)).sum(1)
    return np.clip(exact, -(2**63) + 1, 2**63 - 1).astype(np.int64)


class Search:
    """Best k per query over the candidates seen so far; tested and survived count pairs."""

    def __init__(self, ids: np.ndarray, queries: np.ndarray, k: int):
        self.ids, self.queries, self.k = ids, queries, k
        self.bounds = [segment_bounds(queries.astype(float), n) for n in LEVELS]
        self.best_id = np.zeros((len(ids), 0), np.int64)
        self.best = np.zeros((len(ids), 0), np.int64)
        self.tested = self.survived = 0

    def add(self, ids: np.ndarray, block: np.ndarray) -> None:
        lowest = np.iinfo(np.int64).min
        floor = self.best[:, -1] if self.best.shape[1] == self.k else np.full(len(self.ids), lowest)
        self.tested += len(ids) * len(self.ids)
        open_queries, candidates = np.arange(len(self.ids)), np.arange(len(ids))
        alive = np.ones((len(self.ids), len(ids)), bool)
        for level, n in enumerate(LEVELS):
            if n > block.shape[1]:
                break
            upper = self.bounds[level][open_queries] @ segment_bounds(block[candidates].astype(float), n).T
            slack = 1e-6 * np.abs(upper) + 1e-3
            alive &= upper + slack >= floor[open_queries][:, None]
            rows, columns = alive.any(1), alive.any(0)
            open_queries, candidates, alive = open_queries[rows], candidates[columns], alive[np.ix_(rows, columns)]
            if not alive.size:
                return
        pairs = int(alive.sum())
        self.survived += pairs
        if pairs * 8 < alive.size:  # few pairs: each on its own
            q_at, c_at = np.nonzero(alive)
            scores = np.full(alive.shape, lowest)
            for low in range(0, pairs, 65_536):
                q, c = q_at[low : low + 65_536], c_at[low : low + 65_536]
                scores[q, c] = _paired(self.queries[open_queries[q]], block[candidates[c]])
        else:
            scores = np.where(alive, _products(self.queries[open_queries], block[candidates]), lowest)
        found = ids[candidates]
        width = min(self.k, self.best.shape[1] + len(candidates))
        best_id, best = np.zeros((len(self.ids), width), np.int64), np.full((len(self.ids), width), lowest)
        old = self.best.shape[1]
        best[:, : min(old, width)], best_id[:, : min(old, width)] = self.best[:, :width], self.best_id[:, :width]
        for row, q in enumerate(open_queries):
            hit = np.flatnonzero((scores[row] >= floor[q]) & (scores[row] > lowest) & (found != self.ids[q]))
            real = self.best[q] > lowest
            all_scores = np.r_[self.best[q][real], scores[row][hit]]
            all_ids = np.r_[self.best_id[q][real], found[hit]]
            order = np.lexsort((all_ids, -all_scores))[:width]
            best[q] = lowest
            best[q, : len(order)], best_id[q, : len(order)] = all_scores[order], all_ids[order]
        self.best, self.best_id = best, best_id

    def rows(self) -> pd.DataFrame:
        q, c = np.nonzero(self.best > np.iinfo(np.int64).min)
        return pd.DataFrame({"query_id": self.ids[q], "vec_id": self.best_id[q, c], "score": self.best[q, c]})


def _chunks(queries: DataFrame, chunk: int) -> Iterator[pd.DataFrame]:
    """The queries in vec_id order, a bounded number at a time."""
    last, shape = None, ["vec_id", "vector"]
    while True:
        rest = queries if last is None else queries.where(F.col("vec_id") > last)
        part = rest.orderBy("vec_id").limit(chunk).toPandas()[shape]
        if not len(part):
            return
        yield part
        last = int(part["vec_id"].iloc[-1])


def top_k(vectors: DataFrame, k: int = 10, query_step: int = 100, chunk: int = 32_768, scale: int = 1024) -> DataFrame:
    """query_id, rank, vec_id, score for the queries vec_id % query_step == 0."""
    spark = vectors.sparkSession
    numbers = quantised(vectors, scale)
    found = None
    queries = numbers.where(F.col("vec_id") % query_step == 0).groupBy("vec_id").agg(F.min("vector").alias("vector"))
    for part in _chunks(queries, chunk):
        shared = Shared(spark, [(int(i), np.array(v, np.int64)) for i, v in zip(part["vec_id"], part["vector"], strict=True)])

        def run(batches: Iterator[pd.DataFrame], shared=shared) -> Iterator[pd.DataFrame]:
            searches: dict[int, list[Search]] = {}
            for width in {len(v) for _, v in shared.value}:
                own = [(i, v) for i, v in shared.value if len(v) == width]
                turns = [own[low : low + 2048] for low in range(0, len(own), 2048)]
                searches[width] = [Search(np.array([i for i, _ in turn], np.int64), np.stack([v for _, v in turn]), k) for turn in turns]
            for batch in batches:
                widths = batch["vector"].map(len)
                for width, turns in searches.items():
                    own = batch[widths == width]
                    for low in range(0, len(own), 2048):
                        rows = own.iloc[low : low + 2048]
                        ids, block = rows["vec_id"].to_numpy(np.int64), np.stack(rows["vector"].to_list()).astype(np.int64)
                        for search in turns:
                            search.add(ids, block)
            for turns in searches.values():
                for search in turns:
                    yield search.rows()

        rows = numbers.mapInPandas(run, "query_id long, vec_id long, score long")
        found = rows if found is None else found.unionByName(rows)
    if found is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
