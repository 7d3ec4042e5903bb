"""Exact n-gram Jaccard self join with adaptive multi-match prefixes, for near-duplicate classes.

Sets: distinct word n-grams of a document, as 64-bit digests. Two sets link when the intersection is at least
``percent``/100 of the union. With n members and a = ceil(percent * n / 100), the first n - a + l members in a
global order (frequent members last) hold the l smallest shared members of any linked pair. So every document may
choose its own l: a linked pair shares at least min(l, l') prefix members. Documents whose prefix looks expensive
(frequent members in it) lengthen it and ask for more matches before a candidate is verified.

Work on classes of equal sets. Per posting list only stars go out first: every class against the list's most
typical class. Verified stars give components; after that only lists with several components produce further
candidates, members of the smaller components against the rest, packed per member and verified block by block. So
copies that one pivot joins cost stars, no row is made for a pair, and no link between components is lost.

Defined results: null and empty texts have no members, link with nothing and are their own class; fewer words
than n make one member of the whole sequence; repeated rows get a row each; columns other than doc_id and text
are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Shared, written
from .components import components

_MULTIPLIERS = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3], dtype=np.uint64)


class WordDigests(dict):
    """bytes -> 64-bit digest; remembers a bounded number of words."""

    def __init__(self, most: int = 300_000):
        super().__init__()
        self.most = most

    def __missing__(self, word: bytes) -> int:
        digest = xxhash.xxh3_64_intdigest(word)
        if len(self) < self.most:
            self[word] = digest
        return digest


def _mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(31))
    h = h * np.uint64(0x7FB5D329728EA185)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x81DADEF4BC2DD44D)
    return h ^ (h >> np.uint64(33))


def members(text: str | None, n: int, digests: WordDigests) -> np.ndarray:
    """Sorted distinct digests of the word n-grams; bytes.lower and bytes.split act on ASCII only."""
    words = text.encode("utf-8", "replace").lower().split() if text else []
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(digests.__getitem__, words), np.uint64, len(words))
    if len(words) < n:
        total = (h * _MULTIPLIERS[: len(h)]).sum(dtype=np.uint64, keepdims=True) + np.uint64(len(words))
        return _mix(total)
    total = h[: len(h) - n + 1] * _MULTIPLIERS[0]
    for i in range(1, n):
        total += h[i : len(h) - n + 1 + i] * _MULTIPLIERS[i]
    return np.unique(_mix(total))


def _class_key(found: np.ndarray) -> int:
    """One digest for a whole set."""
    total = _mix(found ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64, keepdims=True)
    return int(_mix(total + np.uint64(len(found))).astype(np.int64)[0])


def _short(found: np.ndarray) -> np.ndarray:
    """40 bits of each digest; the global order needs frequencies only roughly."""
    return found >> np.uint64(24)


def frequent_members(docs: DataFrame, n: int, least: int, most: int) -> tuple[np.ndarray, np.ndarray]:
    """(40-bit digests, frequencies), sorted, of the members in at least ``least`` documents.

    Counted exactly over all documents: blocks of sorted digests travel as byte planes of their differences, by
    digest range; ranges follow the number of documents. Should more than ``most`` qualify, the bar rises (only the
    order changes with it, never the result)."""
    bits = max(6, math.ceil(math.log2(max(1, docs.count()) / 20_000 + 1)) + 2)
    low = 40 - bits

    def blocks(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        digests, held, size = WordDigests(), [], 0

        def flush() -> pd.DataFrame:
            keys, counts = np.unique(np.concatenate(held), return_counts=True)
            part = (keys >> np.uint64(low)).astype(np.int64)
            cuts = np.flatnonzero(np.diff(part)) + 1
            rows = []
            for k, c, p in zip(np.split(keys, cuts), np.split(counts, cuts), np.split(part, cuts), strict=True):
                gaps = np.diff(k, prepend=k[:1]).astype(np.uint64)
                gaps[0] = k[0] & np.uint64((1 << low) - 1)
                planes = gaps.view(np.uint8).reshape(-1, 8)[:, :5].T.tobytes()
                rows.append((int(p[0]), len(k), planes, np.minimum(c, 65535).astype(np.uint16).view(np.uint8).reshape(-1, 2).T.tobytes()))
            return pd.DataFrame(rows, columns=["part", "n", "gaps", "counts"])

        for batch in batches:
            for text in batch["text"]:
                found = members(text, n, digests)
                if len(found):
                    held.append(_short(found))
                    size += len(found)
                if size > 2_000_000:
                    yield flush()
                    held, size = [], 0
        if size:
            yield flush()

    def totals(frame: pd.DataFrame) -> pd.DataFrame:
        keys, counts = [], []
        for size, gaps, times in zip(frame["n"], frame["gaps"], frame["counts"], strict=True):
            planes = np.zeros((size, 8), np.uint8)
            planes[:, :5] = np.frombuffer(gaps, np.uint8).reshape(5, size).T
            keys.append(np.cumsum(planes.view(np.uint64).ravel()))
            counts.append(np.ascontiguousarray(np.frombuffer(times, np.uint8).reshape(2, size).T).view(np.uint16).ravel().astype(np.int64))
        key, count = np.concatenate(keys), np.concatenate(counts)
        order = np.argsort(key, kind="stable")
        key, count = key[order], count[order]
        first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        sums = np.add.reduceat(count, first)
        keep = sums >= least
        base = np.uint64(int(frame["part"].iloc[0]) << low)
        return pd.DataFrame({"member": (key[first][keep] | base).astype(np.int64), "n": sums[keep]})

    counted = docs.select("text").mapInPandas(blocks, "part long, n int, gaps binary, counts binary")
    heavy = written(counted.groupBy("part").applyInPandas(totals, "member long, n long"), "ngram-frequent")
    total = heavy.count()
    if total > most:
        bar = heavy.select(F.percentile_approx("n", 1 - most / total, 100_000)).first()[0]
        heavy = heavy.where(F.col("n") > bar)
    found = heavy.toPandas().sort_values("member")
    return found["member"].to_numpy(np.uint64), found["n"].to_numpy(np.int64)


def prefixes(docs: DataFrame, n: int, percent: int, heavy: tuple[np.ndarray, np.ndarray], most_matches: int = 8) -> DataFrame:
    """doc_id, class_key, size, matches (the document's own l), typical, prefix."""
    shared = Shared(docs.sparkSession, heavy)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        keys, counts = shared.value
        digests = WordDigests()
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch["doc_id"], batch["text"], strict=True):
                found = members(text, n, digests)
                size = len(found)
                if not size:
                    rows.append((doc_id, 0, 0, 1, 0.0, []))
                    continue
                times = np.zeros(size, np.int64)
                if len(keys):
                    short = _short(found)
                    at = np.minimum(np.searchsorted(keys, short), len(keys) - 1)
                    times = np.where(keys[at] == short, counts[at], 0)
                spread = _mix(found)
                order = np.lexsort((spread, times))
                need = -(-percent * size // 100)
                plain = order[: size - need + 1]
                cost = int(times[plain].sum())
                matches = min(need, most_matches, 2 + int(math.log2(1 + cost / 64)))
                rows.append((doc_id, _class_key(found), size, matches, float(np.log1p(times).mean()), found[order[: size - need + matches]].astype(np.int64)))
            yield pd.DataFrame(rows, columns=["doc_id", "class_key", "size", "matches", "typical", "prefix"])

    return docs.select("doc_id", "text").mapInPandas(run, "doc_id long, class_key long, size long, matches int, typical double, prefix array<long>")


def full_sets(docs: DataFrame, wanted: DataFrame, n: int, most_ids: int = 1_000_000) -> DataFrame:
    """(class_key, members binary) of the documents in ``wanted`` (doc_id, class_key).

    Up to ``most_ids`` ids travel to the scan, so texts are not shuffled; beyond that it is a semi join."""
    if wanted.count() <= most_ids:
        ids = Shared(docs.sparkSession, np.sort(wanted.select("doc_id").toPandas()["doc_id"].to_numpy(np.int64)))
        source = docs.select("doc_id", "text")
    else:
        ids = None
        source = docs.select("doc_id", "text").join(wanted.select("doc_id"), "doc_id", "left_semi")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        digests = WordDigests()
        for batch in batches:
            if ids is not None:
                known = ids.value
                if not len(known):
                    continue
                batch = batch[batch["doc_id"].notna()]
                doc = batch["doc_id"].to_numpy(np.int64)
                batch = batch[known[np.minimum(np.searchsorted(known, doc), len(known) - 1)] == doc]
            rows = []
            for text in batch["text"]:
                found = members(text, n, digests)
                if len(found):
                    rows.append((_class_key(found), found.tobytes()))
            yield pd.DataFrame(rows, columns=["class_key", "members"])

    sets = source.mapInPandas(run, "class_key long, members binary")
    # a document id may be repeated with other texts, and a text with other ids
    return sets.join(wanted.select("class_key"), "class_key", "left_semi").groupBy("class_key").agg(F.first("members").alias("members"))


def verified(docs: DataFrame, pairs: DataFrame, classes: DataFrame, n: int, percent: int) -> DataFrame:
    """The pairs (a, b) of class keys that link, exactly."""
    pairs = written(pairs.select("a", "b"), "ngram-pairs")
    ends = pairs.select(F.col("a").alias("class_key")).unionByName(pairs.select(F.col("b").alias("class_key"))).distinct()
    wanted = written(classes.join(ends, "class_key", "left_semi").select(F.col("rep").alias("doc_id"), "class_key"), "ngram-wanted")
    sets = written(full_sets(docs, wanted, n), "ngram-sets")

    def linked(a: pd.Series, b: pd.Series) -> pd.Series:
        out = []
        for x, y in zip(a, b, strict=True):
            x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
            both = np.concatenate((x, y))
            both.sort()
            common = int((both[1:] == both[:-1]).sum())
            out.append(100 * common >= percent * (len(x) + len(y) - common))
        return pd.Series(out, dtype=bool)

    test = F.pandas_udf(linked, "boolean")
    joined = pairs.join(sets.select(F.col("class_key").alias("a"), F.col("members").alias("set_a")), "a").join(sets.select(F.col("class_key").alias("b"), F.col("members").alias("set_b")), "b")
    return written(joined.where(test("set_a", "set_b")).select("a", "b"), "ngram-linked")


def _candidates(raw: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """raw (a, b, one row per shared prefix member) -> (a, b) with enough matches and fitting sizes."""
    side = lambda c: classes.select(F.col("class_key").alias(c), F.col("size").alias(f"size_{c}"), F.col("matches").alias(f"matches_{c}"))
    counted = raw.groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"))
    joined = counted.join(side("a"), "a").join(side("b"), "b")
    fits = F.least("size_a", "size_b") * 100 >= F.greatest("size_a", "size_b") * percent
    return joined.where((F.col("shared") >= F.least("matches_a", "matches_b")) & fits).select("a", "b")


def _between_parts(docs: DataFrame, ruled: DataFrame, classes: DataFrame, n: int, percent: int, list_part: int = 2_000, per_block: int = 1_500_000, per_chunk: int = 1_500_000) -> DataFrame:
    """Links (a, b) between classes of different parts, exactly, without a row for each pair.

    Parts are ranked (``rank``: classes in the part, then its label), and in every list the class of the lower part
    asks, so all shared lists of a pair count for the same asker. Askers meet the list as packed runs of members;
    those of the list's largest part meet only the runs outside it. Per asker x the matches over all its lists are
    counted; candidates that reach the asked matches and fit in size go, packed by block of classes, to
    the blocks' sets for verification. Blocks hold about ``per_block`` members of sets; the askers of a block are cut
    into chunks of about ``per_chunk`` members, each of which meets its own copy of the block, so no task's memory
    grows with the number of askers."""
    packed = ruled.withColumn("inner", F.col("part") == F.col("major"))
    packed = packed.withColumn("run", F.pmod(F.xxhash64("class_key"), F.ceil(F.count(F.lit(1)).over(Window.partitionBy("member")) / list_part)))
    packed = packed.groupBy("member", "run", "inner").agg(F.max("rank").alias("top"), F.collect_list(F.struct("class_key", "rank", "size", "matches")).alias("others"))
    last = F.max("rank").over(Window.partitionBy("member"))
    asking = ruled.withColumn("last", last).where(F.col("rank") < F.col("last"))
    asking = asking.select("member", F.col("class_key").alias("x"), (F.col("part") == F.col("major")).alias("inner_x"), F.col("rank").alias("rank_x"), F.col("size").alias("size_x"), F.col("matches").alias("matches_x"))
    met = asking.join(packed, "member").where(~(F.col("inner") & F.col("inner_x")) & (F.col("rank_x") < F.col("top"))).select(
        "x",
        "matches_x",
        F.filter("others", lambda y: (F.col("rank_x") < y["rank"]) & (F.least(F.col("size_x"), y["size"]) * 100 >= F.greatest(F.col("size_x"), y["size"]) * percent)).alias("others"),
    )
    met = met.where(F.size("others") > 0).select("x", "matches_x", F.transform("others", lambda y: y["class_key"]).alias("y"), F.transform("others", lambda y: y["matches"]).alias("need"))
    blocks = max(1, math.ceil((classes.agg(F.sum("size")).first()[0] or 0) / per_block))

    def candidates(x: int, matches: int, ys: np.ndarray, need: np.ndarray) -> list[tuple[int, int, np.ndarray]]:
        ys, first, times = np.unique(ys, return_index=True, return_counts=True)
        ys = ys[times >= np.minimum(need[first], matches)]
        block = ys % blocks
        order = np.argsort(block, kind="stable")
        ys, block = ys[order], block[order]
        return [(x, int(p[0] % blocks), p) for p in np.split(ys, np.flatnonzero(np.diff(block)) + 1) if len(p)]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Batches come sorted by x; an x that a batch does not finish waits for the next one."""
        waiting: tuple[int, int, list, list] | None = None

        def packed_rows(rows: list[tuple[int, int, np.ndarray]]) -> pa.RecordBatch:
            cuts = np.r_[0, np.cumsum([len(r[2]) for r in rows])].astype(np.int32)
            flat = pa.array(np.concatenate([r[2] for r in rows]), pa.int64())
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int32()), pa.ListArray.from_arrays(pa.array(cuts), flat)], ["x", "block", "ys"])

        for batch in batches:
            if not batch.num_rows:
                continue
            xs, matches = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            offsets = batch.column(2).offsets.to_numpy()
            ys, need = batch.column(2).flatten().to_numpy(), batch.column(3).flatten().to_numpy()
            offsets = offsets - offsets[0]
            starts = np.r_[0, np.flatnonzero(np.diff(xs)) + 1]
            rows = []
            for low, high in zip(starts, np.r_[starts[1:], len(xs)], strict=True):
                x, part = int(xs[low]), slice(offsets[low], offsets[high])
                if waiting is not None and waiting[0] != x:
                    rows += candidates(waiting[0], waiting[1], np.concatenate(waiting[2]), np.concatenate(waiting[3]))
                    waiting = None
                if waiting is not None:
                    waiting[2].append(ys[part])
                    waiting[3].append(need[part])
                elif high == len(xs):
                    waiting = (x, int(matches[low]), [ys[part]], [need[part]])
                else:
                    rows += candidates(x, int(matches[low]), ys[part], need[part])
            if rows:
                yield packed_rows(rows)
        if waiting is not None and (rows := candidates(waiting[0], waiting[1], np.concatenate(waiting[2]), np.concatenate(waiting[3]))):
            yield packed_rows(rows)

    asked = met.repartition("x").sortWithinPartitions("x").mapInArrow(count, "x long, block int, ys array<long>")
    asked = written(asked, "ngram-asked")

    def named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            both = np.concatenate((batch.column(0).to_numpy(), batch.column(1).flatten().to_numpy()))
            yield pa.RecordBatch.from_arrays([pa.array(np.unique(both), pa.int64())], ["class_key"])

    ends = asked.select("x", "ys").mapInArrow(named, "class_key long").distinct()
    wanted = written(classes.join(ends, "class_key", "left_semi").select(F.col("rep").alias("doc_id"), "class_key"), "ngram-wanted")
    sets = written(full_sets(docs, wanted, n), "ngram-sets")
    left = asked.join(sets.select(F.col("class_key").alias("x"), F.col("members").alias("set_x")), "x")
    sizes = asked.join(classes.select(F.col("class_key").alias("x"), "size"), "x").groupBy("block").agg(F.ceil(F.sum("size") / per_chunk).cast("int").alias("chunks"))
    sizes = written(sizes, "ngram-chunks")
    left = left.join(sizes, "block").withColumn("chunk", F.pmod(F.xxhash64("x"), F.col("chunks")).cast("int")).drop("chunks")
    right = sets.withColumn("block", F.pmod("class_key", F.lit(blocks)).cast("int")).join(sizes, "block")
    right = right.withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1))).drop("chunks")

    def verify(key, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        known = {k: np.frombuffer(m, np.uint64) for k, m in zip(right["class_key"], right["members"], strict=True)}
        out = []
        for x, set_x, ys in zip(left["x"], left["set_x"], left["ys"], strict=True):
            mine = np.frombuffer(set_x, np.uint64)
            sizes = np.array([len(known[y]) for y in ys])
            every = np.concatenate([known[y] for y in ys])
            hit = mine[np.minimum(np.searchsorted(mine, every), len(mine) - 1)] == every
            common = np.add.reduceat(hit.astype(np.int64), np.r_[0, np.cumsum(sizes)[:-1]])
            for i in np.flatnonzero(100 * common >= percent * (len(mine) + sizes - common)):
                out.append((min(x, ys[i]), max(x, ys[i])))
        return pd.DataFrame(out, columns=["a", "b"]).astype("int64")

    return written(left.groupBy("block", "chunk").cogroup(right.groupBy("block", "chunk")).applyInPandas(verify, "a long, b long"), "ngram-more")


def near_duplicates(docs: DataFrame, n: int = 4, percent: int = 85, frequent_from: int = 16, most_frequent: int = 2_000_000) -> DataFrame:
    """doc_id, n_shingles, class_key, component_id (smallest doc_id reachable by links, itself included)."""
    heavy = frequent_members(docs, n, frequent_from, most_frequent)
    base = written(prefixes(docs, n, percent, heavy), "ngram-prefixes")
    filled = base.where("size > 0")
    classes = filled.groupBy("class_key").agg(F.min("doc_id").alias("rep"), F.max("size").alias("size"), F.max("matches").alias("matches"), F.max("typical").alias("typical"))
    classes = written(classes, "ngram-classes")
    one = filled.join(classes.select("class_key", F.col("rep").alias("doc_id")), ["class_key", "doc_id"], "left_semi").dropDuplicates(["class_key"])
    posted = one.select("class_key", "typical", F.explode("prefix").alias("member"))
    whole = Window.partitionBy("member")
    lists = posted.select("member", "class_key", F.count(F.lit(1)).over(whole).alias("n"), F.max(F.struct("typical", "class_key")).over(whole)["class_key"].alias("pivot")).where("n > 1")
    lists = written(lists.select("member", "class_key", "pivot"), "ngram-lists")

    stars = written(_candidates(lists.where("class_key <> pivot").select(F.least("class_key", "pivot").alias("a"), F.greatest("class_key", "pivot").alias("b")), classes, percent), "ngram-stars")
    links = verified(docs, stars, classes, n, percent)
    labels = components(links)

    # every pair that is left joins two components; the largest component of a list meets only the others
    sizes = labels.groupBy("label").agg(F.count(F.lit(1)).alias("n_label"))
    parts = labels.join(sizes, "label").select(F.col("node").alias("class_key"), "label", "n_label")
    part = F.coalesce("label", "class_key")
    placed = lists.join(parts, "class_key", "left").select("member", "class_key", part.alias("part"), F.struct(F.coalesce("n_label", F.lit(1)).alias("n"), part.alias("part")).alias("rank"))
    sized = placed.withColumn("n_part", F.count(F.lit(1)).over(Window.partitionBy("member", "part")))
    ruled = sized.withColumn("major", F.max(F.struct("n_part", "part")).over(whole)["part"]).withColumn("mixed", F.min("part").over(whole) != F.max("part").over(whole))
    # whole parts of a list keep to what they need: sizes let most pairs go before they are made
    ruled = ruled.where("mixed").join(classes.select("class_key", "size", "matches"), "class_key")
    ruled = written(ruled.select("member", "class_key", "part", "rank", "major", "size", "matches"), "ngram-mixed")
    more = _between_parts(docs, ruled, classes, n, percent)
    labels = components(links.unionByName(more))

    joined = classes.join(labels.withColumnRenamed("node", "class_key"), "class_key", "left").select("class_key", "rep", F.coalesce("label", "class_key").alias("part"))
    smallest = joined.groupBy("part").agg(F.min("rep").alias("component_id"))
    by_class = joined.join(smallest, "part").select(F.col("class_key").alias("k"), "component_id")
    out = base.select("doc_id", "size", "class_key").join(by_class, (F.col("class_key") == F.col("k")) & (F.col("size") > 0), "left")
    return out.select("doc_id", F.col("size").alias("n_shingles"), "class_key", F.when(F.col("size") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """docs with one document of each component (the smallest doc_id); documents without words stay."""
    found = near_duplicates(docs, **options)
    kept = found.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("kept_id")).distinct()
    return docs.join(kept, F.col("doc_id").eqNullSafe(F.col("kept_id")), "left_semi")


def digest(found: DataFrame) -> DataFrame:
    return found.select("doc_id", "n_shingles", "component_id")
