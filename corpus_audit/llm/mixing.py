"""Mixing sources to target weights with a low-discrepancy schedule (DataFrame functions only).

Slot s of the schedule draws the golden-ratio point u(s) = (s * GOLD mod 2^32) / 2^32; the source whose
cumulative share interval holds u(s) gets the slot. The r-th slot of a source takes the r-th block of its
shuffled word stream: its documents in digest order, laid end to end, walked twice at most, cut into blocks of
``block`` words. Blocks that a source's points did not reach fill slots after the drawn ones, the sources spread
evenly by a golden stride, so every source takes its whole target. Slots beyond a source's target are void; the last block ends at the target.

All running sums are two-level (sum per hash bucket, sum over buckets, sum inside a bucket), so neither a hot
source nor the whole schedule ever meets in one task.

Defined results: null text has size 0 and takes nothing; a null source is a source of its own, last in order;
repeated rows count each; an empty table gives no rows. Reruns agree: the order is a digest of doc_id and text.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_GAP, n_words, written

GOLD, CYCLE = 2654435769, 4294967296  # fixed values: 2^32 over the golden ratio, and 2^32
BLOCK = 128
SLOT_CHUNK = 65_536


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share: float = 1.5, cap: int = 2) -> DataFrame:
    """source, source_size, target, low, high (its interval of the unit line).

    Targets fill like water: proportional to the weights until cap * size stops one, the rest reshared."""
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    cycle = F.array(*[F.lit(w) for w in weights])
    named = per.withColumn("weight", F.element_at(cycle, ((F.row_number().over(order) - 1) % len(weights)) + 1).cast("long"))
    by_ratio = Window.orderBy(F.col("source_size") / F.col("weight"), F.col("source").asc_nulls_last())
    before, after = by_ratio.rowsBetween(Window.unboundedPreceding, -1), by_ratio.rowsBetween(0, Window.unboundedFollowing)
    everything = Window.partitionBy().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    level = named.select(
        "*",
        ((F.sum("source_size").over(everything) * F.lit(share) - F.coalesce(F.sum(F.col("source_size") * cap).over(before), F.lit(0))) / F.sum("weight").over(after)).alias("level"),
    )
    # the water level is the first one that no remaining source's cap stops
    reached = F.min(F.when(F.col("level") * F.col("weight") <= F.col("source_size") * cap, F.struct(F.col("source_size") / F.col("weight"), F.col("level").alias("level")))).over(everything)["level"]
    target = F.least((F.col("source_size") * cap).cast("double"), F.col("weight") * reached)
    filled = level.withColumn("target", F.coalesce(target, (F.col("source_size") * cap).cast("double")))
    running = F.sum("target").over(order.rowsBetween(Window.unboundedPreceding, 0))
    total = F.sum("target").over(everything)
    share_of = lambda c: F.when(total > 0, c / total).otherwise(F.lit(0.0))
    return filled.select("source", "source_size", "target", share_of(running - F.col("target")).alias("low"), share_of(running).alias("high"))


def schedule(spark, targets: DataFrame, block: int = BLOCK, spare: float = 1.02) -> DataFrame:
    """slot, source, block_no: which block of which source fills each slot. void slots are left out."""
    total = targets.agg(F.coalesce(F.sum("target"), F.lit(0.0))).first()[0]
    slots = int(total * spare / block) + 64 if total > 0 else 0
    point = ((F.col("id") % 2147483648) * GOLD % CYCLE) / CYCLE
    drawn = spark.range(slots).select(F.col("id").alias("slot"), point.alias("u"))
    # the sources' table has a row per source: the size of the catalogue, not of the data
    owned = drawn.join(F.broadcast(targets), (F.col("u") >= F.col("low")) & (F.col("u") < F.col("high")))
    owned = owned.select("slot", "source", "target", F.floor(F.col("slot") / SLOT_CHUNK).alias("chunk"))
    counts = written(owned.groupBy("source", "chunk").agg(F.count(F.lit(1)).alias("n")), "mix-counts")
    ahead = Window.partitionBy("source").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(F.col("source").alias("s"), F.col("chunk").alias("c"), F.coalesce(F.sum("n").over(ahead), F.lit(0)).alias("before"))
    inside = Window.partitionBy("source", "chunk").orderBy("slot")
    ranked = owned.withColumn("rank", F.row_number().over(inside) - 1)
    joined = ranked.join(offsets, F.col("source").eqNullSafe(F.col("s")) & (F.col("chunk") == F.col("c")))
    numbered = joined.select("slot", "source", "target", (F.col("before") + F.col("rank")).alias("block_no"))
    numbered = numbered.unionByName(_made_up(spark, targets, counts, slots, block))
    return numbered.where(F.col("block_no") * block < F.floor("target")).select("slot", "source", "block_no", F.least((F.col("block_no") + 1) * block, F.floor("target")).alias("ends"))


def _made_up(spark, targets: DataFrame, counts: DataFrame, slots: int, block: int) -> DataFrame:
    """slot, source, target, block_no of the blocks that the drawn slots lack, on the slots after them."""
    drawn = counts.groupBy(F.col("source").alias("s")).agg(F.sum("n").alias("drawn"))
    joined = targets.join(drawn, F.col("source").eqNullSafe(F.col("s")), "left").withColumn("drawn", F.coalesce("drawn", F.lit(0)))
    lacking = joined.withColumn("lacks", F.greatest(F.lit(0), F.ceil(F.floor("target") / block) - F.col("drawn"))).where("lacks > 0")
    # a row per source, as above
    upto = F.sum("lacks").over(Window.orderBy(F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0))
    lacking = written(lacking.select("source", "target", "drawn", (upto - F.col("lacks")).alias("first"), upto.alias("upto")), "mix-lacking")
    total = lacking.agg(F.coalesce(F.max("upto"), F.lit(0))).first()[0]
    stride = max(1, total * GOLD // CYCLE)
    while math.gcd(stride, total) > 1:
        stride += 1
    met = spark.range(total).join(F.broadcast(lacking), (F.col("id") >= F.col("first")) & (F.col("id") < F.col("upto")))
    # the stride shares no divisor with the total, so every slot is used once
    slot = (slots + (F.col("id").cast("decimal(20,0)") * stride % max(1, total))).cast("long")
    return met.select(slot.alias("slot"), "source", "target", (F.col("drawn") + F.col("id") - F.col("first")).alias("block_no"))


def placed(docs: DataFrame) -> DataFrame:
    """docs with size, and begin: the offset of each document in its source's shuffled word stream."""
    keyed = docs.withColumn("mix_key", F.md5(F.concat_ws("\n", F.col("doc_id").cast("string"), F.coalesce("text", F.lit("")))))
    return keyed.withColumn("size", n_words(F.col("text"))).withColumn("mix_bucket", F.substr("mix_key", F.lit(1), F.lit(3)))


def offsets(rows: DataFrame) -> DataFrame:
    """rows (source, doc_id, size, mix_key, mix_bucket) with begin."""
    sums = rows.groupBy("source", "mix_bucket").agg(F.sum("size").alias("n"))
    ahead = Window.partitionBy("source").orderBy("mix_bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select(F.col("source").alias("s"), F.col("mix_bucket").alias("b"), F.coalesce(F.sum("n").over(ahead), F.lit(0)).alias("before"))
    inside = Window.partitionBy("source", "mix_bucket").orderBy("mix_key", "copy").rowsBetween(Window.unboundedPreceding, -1)
    # equal keys are repeated rows; numbering them keeps the order total
    numbered = rows.withColumn("copy", F.row_number().over(Window.partitionBy("source", "mix_bucket").orderBy("mix_key", "size")))
    ranked = numbered.withColumn("within", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    joined = ranked.join(sums, F.col("source").eqNullSafe(F.col("s")) & (F.col("mix_bucket") == F.col("b")))
    return joined.select("source", "doc_id", "size", "mix_key", "copy", (F.col("before") + F.col("within")).alias("begin"))


def mix(docs: DataFrame, block: int = BLOCK, **options) -> DataFrame:
    """doc_id, mix_key, copy, source, size, source_size, target, taken (words, repeats counted)."""
    spark = docs.sparkSession
    rows = written(placed(docs).select("source", "doc_id", "size", "mix_key", "mix_bucket"), "mix-sizes")
    targets = written(source_targets(rows, **options), "mix-targets")
    at = offsets(rows)
    at = at.join(F.broadcast(targets.select(F.col("source").alias("s"), "source_size", "target")), F.col("source").eqNullSafe(F.col("s"))).drop("s")
    at = written(at, "mix-offsets")
    # each document lies in the blocks of its first and of its second walk
    walks = at.where(F.col("size") > 0).select("source", "mix_key", "copy", "size", "source_size", "begin", F.explode(F.array(F.lit(0), F.lit(1))).alias("walk"))
    walks = walks.withColumn("from", F.col("begin") + F.col("walk") * F.col("source_size")).withColumn("to", F.col("from") + F.col("size"))
    pieces = walks.withColumn("block_no", F.explode(F.sequence(F.floor(F.col("from") / block), F.floor((F.col("to") - 1) / block))))
    plan = schedule(spark, targets, block).select(F.col("source").alias("s"), F.col("block_no").alias("b"), "ends")
    met = pieces.join(plan, F.col("source").eqNullSafe(F.col("s")) & (F.col("block_no") == F.col("b")))
    words = F.greatest(F.lit(0), F.least("to", "ends") - F.greatest("from", F.col("block_no") * block))
    taken = met.groupBy("source", "mix_key", "copy").agg(F.sum(words).alias("taken"))
    taken = taken.select(F.col("source").alias("s"), F.col("mix_key").alias("k"), F.col("copy").alias("c"), "taken")
    joined = at.join(taken, F.col("source").eqNullSafe(F.col("s")) & (F.col("mix_key") == F.col("k")) & (F.col("copy") == F.col("c")), "left")
    return joined.select("doc_id", "mix_key", "copy", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"))


def digest(mixed: DataFrame) -> DataFrame:
    return mixed.select("doc_id", "size", "source_size", "target", "taken")


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The mix as documents: a row for each walk of a document, the last cut to the words taken.

    Rows repeated in the input (same doc_id and text) all take what the first of them takes."""
    taken = mix(docs, **options).where(F.col("taken") > 0).groupBy("mix_key").agg(F.max("taken").alias("_taken"), F.max("size").alias("_size"))
    keyed = docs.withColumn("_mix_key", F.md5(F.concat_ws("\n", F.col("doc_id").cast("string"), F.coalesce("text", F.lit("")))))
    both = keyed.join(taken.withColumnRenamed("mix_key", "_mix_key"), "_mix_key")
    both = both.withColumn("_walk", F.explode(F.sequence(F.lit(0), F.floor((F.col("_taken") - 1) / F.col("_size")).cast("int"))))
    left = F.col("_taken") - F.col("_walk") * F.col("_size")
    words = F.filter(F.split("text", WORD_GAP), lambda w: w != "")
    text = F.when(left >= F.col("_size"), F.col("text")).otherwise(F.array_join(F.slice(words, 1, left.cast("int")), " "))
    out = both.withColumn("text", text)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast("long"))
    return out.select(*docs.columns)
