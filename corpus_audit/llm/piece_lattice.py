"""SentencePiece encoding and decoding over a relational lattice.

The bounded-length substrings of a word join the piece table; the matches are the edges of the word's lattice and a
higher-order aggregate folds them from left to right. For unigram models the fold keeps the best score sum per
position. For BPE models it keeps the one edge per position that merging would leave there: two neighbouring pieces
stand iff no third piece across their border merges earlier than both sides grew past it (each piece carries the
growth of its left and right flank), which gives exactly the merge result without replaying merges.

The lattices of the corpus' most frequent words are built relationally once (``dictionary``, a bounded number of
words) and travel to the workers; a word outside it runs through the same lattice and fold (``Lattice``) where it
is met, since joining every rare word back to its places would move the text twice. The dictionary only saves time.

Words are maximal runs between blanks with the blank mark in front; line ends stand alone (no piece holds one, which
``load`` checks). Characters without a piece become byte pieces.

Defined results: null text is the empty text and gives no ids; the blank mark itself reads back as a blank;
repeated rows encode alike; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from array import array
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Shared, written

BLANK = "▁"
NEVER = float("inf")
_RUNS = re.compile(f"{BLANK}*[^{BLANK}\\n]+|{BLANK}+|\\n")


@dataclass
class Pieces:
    """A model's table. spine maps a piece to (right flank, left flank): (length, rank of the merge that ends it)."""

    kind: str
    ids: dict[str, int]
    ranks: dict[str, float]
    bytes_: list[int]
    table: list[str]
    unknown: int
    spine: dict[str, tuple[list[tuple[int, float]], list[tuple[int, float]]]] = field(default_factory=dict)
    longest: int = 1


def load(path: str, kind: str = "bpe") -> Pieces:
    """The piece table of a model file. The file is read on the driver only; the table travels."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    table = [model.id_to_piece(i) for i in range(model.vocab_size())]
    bytes_ = [0] * 256
    ids = {}
    for i, piece in enumerate(table):
        if model.is_byte(i):
            bytes_[int(piece[3:5], 16)] = i
        elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)):
            ids[piece] = i
    if any(BLANK in p.lstrip(BLANK) or "\n" in p for p in ids):
        raise ValueError("pieces reach across words")
    out = Pieces(kind, ids, {p: -model.get_score(i) for p, i in ids.items()}, bytes_, table, model.unk_id(), longest=max(map(len, ids)))
    if kind == "bpe":
        for piece in list(ids):
            tree = _merge_tree(piece, out.ranks)
            if tree is not None:
                out.spine[piece] = _flanks(tree, out.ranks)
    return out


def _merge_tree(piece: str, ranks: dict[str, float]):
    """Nested pairs by which merging builds a piece from its characters, or None if it ends otherwise."""
    nodes = [(c, None, None) for c in piece]
    while len(nodes) > 1:
        options = [(ranks[a[0] + b[0]], i) for i, (a, b) in enumerate(zip(nodes, nodes[1:], strict=False)) if a[0] + b[0] in ranks]
        if not options:
            return None
        i = min(options)[1]
        nodes[i : i + 2] = [(nodes[i][0] + nodes[i + 1][0], nodes[i], nodes[i + 1])]
    return nodes[0]


def _flanks(tree, ranks: dict[str, float]):
    sides = []
    for child in (2, 1):
        out, node, ended = [], tree, NEVER
        while node is not None:
            out.append((len(node[0]), ended))
            ended, node = ranks.get(node[0], NEVER), node[child]
        sides.append(out)
    return sides[0], sides[1]


class Lattice:
    """The lattice and the fold for one word at a time, inside a worker."""

    def __init__(self, pieces: Pieces, most_pairs: int = 500_000):
        self.p, self.most, self.pairs = pieces, most_pairs, {}
        # the lengths from 3 on that pieces with these three characters in front have
        reach: dict[str, set[int]] = {}
        for piece in pieces.spine:
            if len(piece) >= 3:
                reach.setdefault(piece[:3], set()).add(len(piece))
        self.reach = {start: tuple(sorted(lengths)) for start, lengths in reach.items()}

    def stands(self, left: str, right: str) -> bool:
        key = (left, right)
        known = self.pairs.get(key)
        if known is None:
            known = self._stands(left, right)
            if len(self.pairs) < self.most:
                self.pairs[key] = known
        return known

    def _stands(self, left: str, right: str) -> bool:
        ranks = self.p.ranks
        for n, ends_left in self.p.spine[left][0] if left in self.p.spine else [(1, NEVER)]:
            for m, ends_right in self.p.spine[right][1] if right in self.p.spine else [(1, NEVER)]:
                rank = ranks.get(left[-n:] + right[:m])
                if rank is not None and rank < ends_left and rank <= ends_right:
                    return False
        return True

    def _edges(self, word: str, start: int) -> list[str]:
        """The pieces of the lattice that start here, shortest first; a cut beyond the word's end repeats the longest."""
        usable, out = self.p.spine, [word[start]]
        two = word[start : start + 2]
        if two in usable:
            out.append(two)
        for length in self.reach.get(word[start : start + 3], ()):
            piece = word[start : start + length]
            if piece in usable:
                out.append(piece)
        return out

    def _walk(self, word: str) -> list[str] | None:
        """The one path whose neighbours all stand, depth first over the edges, longest first; for short words."""
        path, end, n, pairs = [], 0, len(word), self.pairs
        open_edges = [self._edges(word, 0)]
        last = None
        while True:
            options = open_edges[-1]
            while options:
                piece = options.pop()
                if last is None:
                    break
                stands = pairs.get((last, piece))
                if stands is None:
                    stands = self.stands(last, piece)
                if stands:
                    break
            else:
                open_edges.pop()
                if last is None:
                    return None
                end -= len(path.pop())
                last = path[-1] if path else None
                continue
            path.append(piece)
            last = piece
            end += len(piece)
            if end == n:
                return path
            open_edges.append(self._edges(word, end))

    def encode(self, word: str) -> list[int]:
        ids, longest, n = self.p.ids, self.p.longest, len(word)
        usable = self.p.spine if self.p.kind == "bpe" else ids
        if self.p.kind == "bpe":
            if n <= 24 and (path := self._walk(word)) is not None:
                try:
                    return [ids[piece] for piece in path]
                except KeyError:  # a character without a piece
                    return [i for piece in path for i in self.of(piece)]
            at: list[str | None] = [None] * (n + 1)
            for end in range(1, n + 1):
                for start in range(max(0, end - longest), end):
                    piece = word[start:end]
                    if (piece in usable or end - start == 1) and (not start or at[start] is not None and self.stands(at[start], piece)):
                        at[end] = piece
                        break
            out, end = [], n
            while end:
                out.append(at[end])
                end -= len(at[end])
        else:
            best = [(0.0, "")] + [(-NEVER, "")] * n
            floor = -max(self.p.ranks.values()) - 10
            for end in range(1, n + 1):
                for start in range(max(0, end - longest), end):  # of equal sums the longest last piece wins
                    piece = word[start:end]
                    if piece in ids or end - start == 1:
                        total = best[start][0] + (-self.p.ranks[piece] if piece in ids else floor)
                        if total > best[end][0]:
                            best[end] = (total, piece)
            out, end = [], n
            while end:
                out.append(best[end][1])
                end -= len(best[end][1])
        return [i for piece in reversed(out) for i in self.of(piece)]

    def of(self, piece: str) -> list[int]:
        if piece in self.p.ids:
            return [self.p.ids[piece]]
        return [self.p.bytes_[b] for b in piece.encode("utf-8", "replace")] if any(self.p.bytes_) else [self.p.unknown]


def words_of(text: str | None) -> list[str]:
    """The words of a text with their blank marks; line ends stand alone."""
    return _RUNS.findall(BLANK + text.replace(" ", BLANK)) if text else []


# --- the relational lattice -------------------------------------------------------------------------------------------


def piece_frame(spark: SparkSession, pieces: Pieces) -> DataFrame:
    """piece, id, rank, right, left: as many rows as the model has pieces."""
    flank = lambda side: [{"len": n, "ends": e} for n, e in side]
    usable = pieces.spine if pieces.kind == "bpe" else pieces.ids
    rows = [(p, pieces.ids[p], pieces.ranks[p], *([flank(s) for s in pieces.spine[p]] if pieces.kind == "bpe" else ([], []))) for p in usable]
    side = "array<struct<len:int,ends:double>>"
    return spark.createDataFrame(rows, f"piece string, id int, rank double, right {side}, left {side}")


def edges(words: DataFrame, pieces: DataFrame, longest: int) -> DataFrame:
    """word, edges array<struct<s,e,id,rank,right,left>>: explode bounded substrings, equi-join, group by word."""
    starts = words.select("word", F.explode(F.sequence(F.lit(0), F.length("word") - 1)).alias("s"))
    spans = starts.select("word", "s", F.explode(F.sequence(F.col("s") + 1, F.least(F.length("word"), F.col("s") + longest))).alias("e"))
    cut = spans.withColumn("piece", F.substr("word", F.col("s") + 1, F.col("e") - F.col("s")))
    single = F.expr("array(named_struct('len', 1, 'ends', cast('Infinity' as double)))")
    met = cut.join(F.broadcast(pieces), "piece", "left").where(F.col("id").isNotNull() | (F.col("e") - F.col("s") == 1))
    edge = F.struct(
        "s", "e", F.coalesce("id", F.lit(-1)).alias("id"), F.coalesce("rank", F.lit(NEVER)).alias("rank"), F.coalesce("right", single).alias("right"), F.coalesce("left", single).alias("left")
    )
    return met.groupBy("word").agg(F.sort_array(F.collect_list(edge)).alias("edges"))


EDGE = "struct<s:int,e:int,id:int,rank:double,right:array<struct<len:int,ends:double>>,left:array<struct<len:int,ends:double>>>"
STEP = "struct<s:int,e:int,id:int>"


def fold_bpe(lattice: DataFrame) -> DataFrame:
    """word, path array<struct<s,e,id>>: the merge result. One fold forward, one back over what it chose."""
    length = F.length("word")

    def blocked(crossing: Column, left: Column, right: Column) -> Column:
        at = right["s"]
        return F.exists(
            crossing,
            lambda m: F.exists(left["right"], lambda x: (x["len"] == at - m["s"]) & (m["rank"] < x["ends"]))
            & F.exists(right["left"], lambda x: (x["len"] == m["e"] - at) & (m["rank"] <= x["ends"])),
        )

    def fits(acc: Column, x: Column, row: Column) -> Column:
        before = F.element_at(acc, x["s"] + 1)
        crossing = F.element_at(F.col("crossing"), x["s"] + 1)
        return (x["s"] == 0) | (before.isNotNull() & ~blocked(crossing, before, x))

    def step(acc: Column, row: Column) -> Column:
        return F.concat(acc, F.array(F.try_element_at(F.filter(row, lambda x: fits(acc, x, row)), F.lit(1))))

    # edges by their end, and by the borders they cross
    positions = F.sequence(F.lit(0), length)
    sorted_out = lattice.select(
        "word",
        F.transform(F.sequence(F.lit(1), length), lambda p: F.filter("edges", lambda x: x["e"] == p)).alias("ending"),
        F.transform(positions, lambda p: F.filter("edges", lambda x: (x["s"] < p) & (x["e"] > p))).alias("crossing"),
    )
    forward = sorted_out.select("word", F.aggregate("ending", F.array(F.lit(None).cast(EDGE)), step).alias("chosen"))
    slim = forward.select("word", F.transform("chosen", lambda x: F.when(x.isNotNull(), F.struct(x["s"].alias("s"), x["e"].alias("e"), x["id"].alias("id")))).alias("chosen"))
    start = F.struct(length.alias("at"), F.array().cast(f"array<{STEP}>").alias("path"))

    def walk(acc: Column, _: Column) -> Column:
        here = F.element_at(F.col("chosen"), acc["at"] + 1)
        return F.when(acc["at"] > 0, F.struct(here["s"].alias("at"), F.concat(F.array(here), acc["path"]).alias("path"))).otherwise(acc)

    return slim.select("word", F.aggregate("chosen", start, walk, lambda acc: acc["path"]).alias("path"))


def fold_unigram(lattice: DataFrame, unknown_score: float) -> DataFrame:
    """word, path array<struct<s,e,id>>: the greatest score sum (rank is the negative score)."""
    kind = f"array<struct<total:double,path:array<{STEP}>>>"
    first = F.expr(f"cast(array(named_struct('total', 0d, 'path', cast(array() as array<{STEP}>))) as {kind})")

    def step(acc: Column, row: Column) -> Column:
        def grown(x: Column) -> Column:
            before = F.element_at(acc, x["s"] + 1)
            score = F.when(x["id"] < 0, F.lit(unknown_score)).otherwise(-x["rank"])
            return F.struct((before["total"] + score).alias("total"), F.concat(before["path"], F.array(F.struct(x["s"].alias("s"), x["e"].alias("e"), x["id"].alias("id")))).alias("path"))

        best = F.array_max(F.transform(row, lambda x: F.struct(grown(x)["total"].alias("total"), (-x["s"]).alias("tie"), grown(x)["path"].alias("path"))))
        return F.concat(acc, F.array(F.struct(best["total"].alias("total"), best["path"].alias("path"))))

    by_end = lattice.select("word", F.transform(F.sequence(F.lit(1), F.length("word")), lambda p: F.filter("edges", lambda x: x["e"] == p)).alias("ending"))
    return by_end.select("word", F.aggregate("ending", first, step, lambda acc: F.element_at(acc, -1)["path"]).alias("path"))


def encode_words(words: DataFrame, pieces: Pieces) -> DataFrame:
    """word (not empty) -> word, path array<struct<s,e,id>> (id -1: a character without a piece)."""
    lattice = edges(words, piece_frame(words.sparkSession, pieces), pieces.longest)
    if pieces.kind == "bpe":
        return fold_bpe(lattice)
    return fold_unigram(lattice, -max(pieces.ranks.values()) - 10)


def frequent_words(docs: DataFrame, most: int, longest: int = 40) -> DataFrame:
    """About the ``most`` most frequent words between blanks; each partition leaves out what it saw once. It only fills a
    cache: what is missing here is encoded where it is met."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: Counter = Counter()
        for batch in batches:
            for text in batch["text"]:
                if text:
                    seen.update(text.split(" "))
            if len(seen) > 1_000_000:
                yield rows(seen)
                seen = Counter()
        yield rows(seen)

    def rows(seen: Counter) -> pd.DataFrame:
        kept = [(BLANK + w, n) for w, n in seen.items() if n > 1 and w and len(w) < longest and "\n" not in w and BLANK not in w]
        return pd.DataFrame(kept, columns=["word", "n"]).astype({"word": object, "n": "int64"})

    counted = docs.select("text").mapInPandas(count, "word string, n long")
    return counted.groupBy("word").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "word").limit(most).select("word")


def dictionary(docs: DataFrame, pieces: Pieces, most: int) -> dict[str, bytes]:
    """word -> ids as 16-bit or 32-bit numbers, for at most ``most`` words."""
    lattice, kind = Lattice(pieces), _kind(pieces)
    words = written(frequent_words(docs, most), "piece-words")
    coded = encode_words(words.repartition(2 * docs.sparkSession.sparkContext.defaultParallelism, "word"), pieces)
    return _packed(coded.select("word", "path").toArrow(), lattice, kind)


def _packed(coded: pa.Table, lattice, kind) -> dict[str, bytes]:
    """The dictionary from word and path; paths stay buffers, as a row object a piece would take many times their size."""
    out = {}
    for batch in coded.to_batches(max_chunksize=4_096):
        path, flat = batch.column("path"), batch.column("path").flatten()
        cuts = np.r_[0, np.cumsum(np.asarray(path.value_lengths(), np.int64))].tolist()
        ids, starts, ends = (flat.field(c).to_pylist() for c in ("id", "s", "e"))
        for word, low, high in zip(batch.column("word").to_pylist(), cuts[:-1], cuts[1:], strict=True):
            got = [i for n in range(low, high) for i in ([ids[n]] if ids[n] >= 0 else lattice.of(word[starts[n] : ends[n]]))]
            out[word] = np.array(got, kind).tobytes()
    return out


def _kind(pieces: Pieces):
    return np.uint16 if len(pieces.table) <= 65_536 else np.uint32


class Encoder(dict):
    """word -> packed ids; starts from the dictionary and remembers a bounded number of further words."""

    def __init__(self, pieces: Pieces, known: dict[str, bytes], most: int = 300_000):
        super().__init__(known)
        self.lattice, self.kind, self.room = Lattice(pieces), _kind(pieces), most + len(known)
        self.code = "H" if self.kind is np.uint16 else "I"

    def __missing__(self, word: str) -> bytes:
        ids = array(self.code, self.lattice.encode(word)).tobytes()
        if len(self) < self.room:
            self[word] = ids
        return ids

    def encode(self, text: str | None) -> np.ndarray:
        return np.frombuffer(b"".join(map(self.__getitem__, words_of(text))), self.kind)


class Decoder:
    def __init__(self, pieces: Pieces):
        self.bytes_ = [p.replace(BLANK, " ").encode() for p in pieces.table]
        for value, number in enumerate(pieces.bytes_):
            if number:
                self.bytes_[number] = bytes([value])

    def decode(self, ids) -> str:
        text = b"".join(map(self.bytes_.__getitem__, ids)).decode("utf-8", "replace")
        return text[1:] if text.startswith(" ") else text


def encode(docs: DataFrame, pieces: Pieces, most_words: int = 50_000) -> DataFrame:
    """doc_id, n_tokens, ids, ids_sha256 (of the ids as 4-byte little-endian numbers), intact (decoding gives the text back)."""
    shared = Shared(docs.sparkSession, (Encoder(pieces, dictionary(docs, pieces, most_words)), Decoder(pieces)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, decoder = shared.value
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for low in range(0, len(texts), 256):
                part = texts[low : low + 256]
                found = [encoder.encode(t) for t in part]
                offsets = np.r_[0, np.cumsum([len(x) for x in found])].astype(np.int32)
                flat = (np.concatenate(found) if found else np.empty(0)).astype(np.int32)
                digests = [hashlib.sha256(x.astype("<i4").tobytes()).hexdigest() for x in found]
                intact = [decoder.decode(x.tolist()) == (t or "") for x, t in zip(found, part, strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(low, len(part)), pa.array([len(x) for x in found], pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat)), pa.array(digests, pa.string()), pa.array(intact, pa.bool_())],
                    ["doc_id", "n_tokens", "ids", "ids_sha256", "intact"],
                )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids array<int>, ids_sha256 string, intact boolean")


def decode(encoded: DataFrame, pieces: Pieces) -> DataFrame:
    """encoded with text: the decoding of ids (null ids give the empty text)."""
    shared = Shared(encoded.sparkSession, pieces)

    @F.pandas_udf("string")
    def text_of(ids: pd.Series) -> pd.Series:
        decoder = Decoder(shared.value)
        return ids.map(lambda x: decoder.decode(list(x)) if x is not None else "")

    return encoded.withColumn("text", text_of("ids"))
