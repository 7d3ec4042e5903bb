"""Approximate nearest neighbours with balanced posting lists.

Centroids come from a bounded sample (k-means with a size penalty, so lists stay even); their number grows with the
square root of the rows, up to an eighth of the sample. Every vector goes to its nearest list and, when it lies near a
boundary, also to the lists whose centroid is at most ``replicate`` times as far, up to ``copies``. A query walks an
in-memory graph over the centroids and searches the lists within ``prune`` times the nearest centroid's distance: at
least ``least_lists`` and at most the share ``probe`` of all. On clustered vectors the distance ratio decides; on
vectors without clusters all centroids are about equally far, and the share does. ``shelf`` lists make a shelf, to which
a query is sent once, with the lists it searches there; shelves of more than ``shelf_rows`` rows or ``shelf_queries``
queries are met in parts. A list meets all its queries in one product. Cosines of what is found are exact, on the
original vectors.

Defined results: vectors null, zero or with null or non-finite components take no part, nor candidates of another
length; ties go to the smaller vec_id; a query is never its own candidate; repeated vec_ids
count once, with their best score, and ask once; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Shared, written
from .exact_topk import usable


RUN = 1_024  # rows a product takes at once


def balanced_centroids(sample: np.ndarray, n: int, rounds: int = 12, seed: int = 3) -> np.ndarray:
    """Unit centroids by k-means whose assignment pays for crowded lists."""
    rng = np.random.default_rng(seed)
    unit = np.unique(sample, axis=0)
    n = min(n, len(unit))
    centroids = unit[rng.permutation(len(unit))[:n]].copy()
    fee = np.zeros(n)
    for _ in range(rounds):
        # in runs of rows: the whole product would not fit the driver
        own = np.concatenate([np.argmax(unit[i : i + RUN] @ centroids.T - fee, axis=1) for i in range(0, len(unit), RUN)])
        sizes = np.bincount(own, minlength=n)
        fee += 0.02 * (sizes / max(1.0, len(unit) / n) - 1)
        sums = np.zeros_like(centroids)
        np.add.at(sums, own, unit)
        norms = np.linalg.norm(sums, axis=1, keepdims=True)
        centroids = np.where(norms > 1e-9, sums / np.maximum(norms, 1e-9), centroids)
    return centroids


class CentroidGraph:
    """k-nearest-neighbour graph over the centroids, searched best first, ``stride`` nodes at a time."""

    def __init__(self, centroids: np.ndarray, degree: int = 16, seed: int = 5):
        self.centroids = centroids
        near = np.argsort(-(centroids @ centroids.T), axis=1, kind="stable")[:, 1 : degree + 1]
        # a few far links keep the graph connected
        far = np.random.default_rng(seed).integers(0, len(centroids), (len(centroids), 2))
        links = [np.unique(np.r_[a, b]) for a, b in zip(near, far, strict=True)]
        source = np.repeat(np.arange(len(links)), [len(x) for x in links])
        both = np.unique(np.c_[np.r_[source, np.concatenate(links)], np.r_[np.concatenate(links), source]], axis=0)
        # the links of node i are the run from starts[i] to starts[i + 1]
        self.targets, self.starts = both[:, 1], np.searchsorted(both[:, 0], np.arange(len(centroids) + 1))

    def search(self, query: np.ndarray, width: int, stride: int = 16) -> tuple[np.ndarray, np.ndarray]:
        """About the ``width`` nearest centroids: (distances, numbers), nearest first."""
        seen, done = np.zeros(len(self.centroids), bool), np.zeros(len(self.centroids), bool)
        seen[0] = True
        numbers, distances = np.array([0]), self._distance(query, np.array([0]))
        while True:
            open_ones = numbers[~done[numbers]][:stride]  # of the best so far, nearest first
            if not len(open_ones):
                return distances, numbers
            done[open_ones] = True
            linked = np.unique(np.concatenate([self.targets[self.starts[x] : self.starts[x + 1]] for x in open_ones.tolist()]))
            fresh = linked[~seen[linked]]
            seen[fresh] = True
            numbers, distances = np.r_[numbers, fresh], np.r_[distances, self._distance(query, fresh)]
            order = np.lexsort((numbers, distances))[:width]
            numbers, distances = numbers[order], distances[order]

    def _distance(self, query: np.ndarray, nodes: np.ndarray) -> np.ndarray:
        return np.sqrt(np.maximum(0.0, 2 - 2 * (self.centroids[nodes] @ query)))


def build(vectors: DataFrame, width: int, n_lists: int, most_sample: int = 20_000) -> CentroidGraph:
    """Graph over centroids fitted on the first ``most_sample`` usable vectors in digest order."""
    sample = vectors.where(F.size("embedding") == width).orderBy(F.md5(F.col("vec_id").cast("string")), "embedding").limit(most_sample).toPandas()
    block = np.stack(sample["embedding"].to_list()).astype(float)
    unit = block / np.linalg.norm(block, axis=1, keepdims=True)
    return CentroidGraph(balanced_centroids(unit, max(1, min(n_lists, len(unit) // 8))))


def nearest(vectors: DataFrame, k: int = 5, query_step: int = 50, **options) -> DataFrame:
    """query_id, rank, vec_id, score for the queries vec_id % query_step == 0; options as in ``_nearest``."""
    spark = vectors.sparkSession
    norm = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    rows = vectors.where(usable(F.col("embedding")) & F.col("vec_id").isNotNull()).where(norm > 0).select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("embedding"))
    # vectors of one length meet each other only: an index for every length that the table has
    sizes = {r["width"]: r["n"] for r in rows.groupBy(F.size("embedding").alias("width")).agg(F.count(F.lit(1)).alias("n")).collect()}
    out = None
    for width, n in sorted(sizes.items()):
        found = _nearest(rows.where(F.size("embedding") == width), width, n, k, query_step, **options)
        out = found if out is None else out.unionByName(found)
    if out is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    return out


FOUND = "query_id long, vec_id long, score double"


def _nearest(
    rows: DataFrame, width: int, n: int, k: int, query_step: int, lists: float = 4.0, copies: int = 3, replicate: float = 1.25, prune: float = 2.0, probe: float = 0.3,
    least_lists: int = 8, shelf: int = 32, shelf_rows: int = 20_000, shelf_queries: int = 5_000,
) -> DataFrame:
    spark = rows.sparkSession
    graph = Shared(spark, build(rows, width, math.ceil(lists * math.sqrt(n))))

    def place(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        centroids = graph.value.centroids
        for batch in batches:
            for i in range(0, len(batch), RUN):
                block = np.stack(batch["embedding"].iloc[i : i + RUN].to_list())
                unit = block / np.linalg.norm(block, axis=1, keepdims=True)
                distance = np.sqrt(np.maximum(0.0, 2 - 2 * unit @ centroids.T))
                some = min(copies, len(centroids))
                order = np.argpartition(distance, some - 1, axis=1)[:, :some]
                near = np.take_along_axis(distance, order, 1)
                row, rank = np.nonzero(near <= near.min(axis=1, keepdims=True) * replicate + 1e-12)
                ids = batch["vec_id"].to_numpy(np.int64)[i : i + RUN]
                yield pd.DataFrame({"list": order[row, rank].astype("int32"), "vec_id": ids[row], "vector": [block[r].tobytes() for r in row]})

    placed = written(rows.mapInPandas(place, "list int, vec_id long, vector binary"), "ann-lists")

    def choose(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for vec_id, vector in zip(batch["vec_id"], batch["embedding"], strict=True):
                block = np.asarray(vector, float)
                distance, number = graph.value.search(block / np.linalg.norm(block), max(least_lists, math.ceil(probe * len(graph.value.centroids))))
                chosen = np.sort(number[(np.arange(len(number)) < least_lists) | (distance <= distance[0] * prune)]).astype(np.int32)
                packed = block.tobytes()
                cuts = np.flatnonzero(np.diff(chosen // shelf)) + 1
                out += [(int(lists[0]) // shelf, vec_id, packed, lists.tobytes()) for lists in np.split(chosen, cuts)]
            yield pd.DataFrame(out, columns=["shelf", "query_id", "query", "lists"]).astype({"shelf": "int32", "query_id": "int64"})

    asked = rows.where(F.col("vec_id") % query_step == 0).groupBy("vec_id").agg(F.min("embedding").alias("embedding"))
    # dealt out by count: a few queries are small as rows and long as work
    asked = asked.repartition(max(1, min(2_000, math.ceil(n / query_step / 64))), "vec_id")
    probes = written(asked.mapInPandas(choose, "shelf int, query_id long, query binary, lists binary"), "ann-probes")
    # a row per shelf: parts of its vectors and of its queries meet each other, so no task grows with either
    shelved = placed.withColumn("shelf", F.floor(F.col("list") / shelf).cast("int"))
    sides = shelved.groupBy("shelf").agg(F.ceil(F.count(F.lit(1)) / shelf_rows).cast("int").alias("parts"))
    sides = sides.join(probes.groupBy("shelf").agg(F.ceil(F.count(F.lit(1)) / shelf_queries).cast("int").alias("turns")), "shelf")
    sides = written(sides, "ann-sides")
    part = lambda key, n: F.pmod(F.xxhash64(key), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    stored = shelved.join(sides, "shelf").select("shelf", part("vec_id", "parts").alias("part"), every("turns").alias("turn"), "list", "vec_id", "vector")
    asking = probes.join(sides, "shelf").select("shelf", part("query_id", "turns").alias("turn"), every("parts").alias("part"), "query_id", "query", "lists")

    def search(key, queries: pd.DataFrame, block: pd.DataFrame) -> pd.DataFrame:
        return search_shelf(queries, block, k)

    met = asking.groupBy("shelf", "part", "turn").cogroup(stored.groupBy("shelf", "part", "turn")).applyInPandas(search, FOUND)
    first = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    distinct = met.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    return distinct.withColumn("rank", F.row_number().over(first)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def search_shelf(queries: pd.DataFrame, block: pd.DataFrame, k: int) -> pd.DataFrame:
    """query_id, vec_id, score: the k nearest of each query in the lists it names, of one shelf. A list meets its queries
    in one product; what cannot be among the k nearest by it goes, and the rest gets exact cosines."""
    none = pd.DataFrame({"query_id": np.empty(0, np.int64), "vec_id": np.empty(0, np.int64), "score": np.empty(0)})
    if not len(queries) or not len(block):
        return none
    block = block.sort_values("list", kind="stable")
    lists, ids = block["list"].to_numpy(np.int64), block["vec_id"].to_numpy(np.int64)
    vectors = np.frombuffer(b"".join(block["vector"]), float).reshape(len(block), -1)
    asked = np.frombuffer(b"".join(queries["query"]), float).reshape(len(queries), -1)
    unit, unit_asked = (x / np.linalg.norm(x, axis=1, keepdims=True) for x in (vectors, asked))
    own = queries["query_id"].to_numpy(np.int64)
    named = [np.frombuffer(x, np.int32) for x in queries["lists"]]
    who, where = np.repeat(np.arange(len(named)), [len(x) for x in named]), np.concatenate(named)
    order = np.argsort(where, kind="stable")
    who, where = who[order], where[order]
    floor = np.full(len(queries), -np.inf)  # no row below it is among the k nearest
    hits = []
    for number in np.unique(where).tolist():
        low, high = np.searchsorted(lists, [number, number + 1])
        begin, end = np.searchsorted(where, [number, number + 1])
        if low == high:
            continue
        here = ids[low:high]
        least, place = np.unique(here, return_inverse=True)
        turn = max(1, 1_000_000 // (high - low))
        for i in range(begin, end, turn):
            asking = who[i : min(i + turn, end)]
            rough = unit_asked[asking] @ unit[low:high].T
            rough[own[asking][:, None] == here[None, :]] = -np.inf
            best = rough
            if len(least) < len(here):  # repeated ids fill one place
                best = np.full((len(asking), len(least)), -np.inf)
                np.maximum.at(best, (slice(None), place), rough)
            if len(least) > k:
                floor[asking] = np.maximum(floor[asking], np.partition(best, -k, axis=1)[:, -k])
            q, r = np.nonzero((rough >= floor[asking][:, None] - 1e-9) & (rough > -np.inf))
            hits.append((asking[q], r + low, rough[q, r]))
    if not hits:
        return none
    q, r, rough = (np.concatenate(x) for x in zip(*hits, strict=True))
    keep = rough >= floor[q] - 1e-9
    q, r, rough = q[keep], r[keep], rough[keep]
    # one floor more, over the lists: of the best row of every id, the k-th
    by_id = np.lexsort((-rough, ids[r], q))
    fresh = np.r_[True, (np.diff(q[by_id]) != 0) | (np.diff(ids[r[by_id]]) != 0)][: len(q)]
    one = by_id[fresh]
    one = one[np.lexsort((-rough[one], q[one]))]
    at = np.arange(len(one)) - np.searchsorted(q[one], q[one])
    floor[q[one[at == k - 1]]] = rough[one[at == k - 1]]
    keep = rough >= floor[q] - 1e-9
    q, r = q[keep], r[keep]
    found = pd.DataFrame({"q": q, "vec_id": ids[r], "score": cosines(asked[q], vectors[r])})
    found = found.groupby(["q", "vec_id"], as_index=False)["score"].max().sort_values(["q", "score", "vec_id"], ascending=[True, False, True]).groupby("q").head(k)
    return pd.DataFrame({"query_id": own[found["q"].to_numpy()], "vec_id": found["vec_id"].to_numpy(), "score": found["score"].to_numpy()})


def cosines(queries: np.ndarray, block: np.ndarray) -> np.ndarray:
    """Cosines of the rows of both in double precision, each by the same sequence of operations whatever the block."""
    dots = [float(np.dot(q, v)) for q, v in zip(queries, block, strict=True)]
    lengths = [math.sqrt(float(np.dot(q, q))) * math.sqrt(float(np.dot(v, v))) for q, v in zip(queries, block, strict=True)]
    return np.array(dots, float) / np.array(lengths, float)
