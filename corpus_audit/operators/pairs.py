"""Look-alike pairs: a flawed function and its fix."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.edit import long_edit_similarity
from ..functions.text import similarity
from .near import by_smallest_ids, near_links

FLOOR = 0.8  # fixed value


def gated_versions(versions: DataFrame, min_similarity: float = FLOOR, metric: str = "edit", long_from: int = 200) -> DataFrame:
    """Text versions with both sides and their similarity. Once per distinct version; texts from ``long_from``
    characters take the bit-parallel distance in Arrow batches, which stops at the floor; shorter ones stay in the JVM."""
    both = versions.where("pre_text IS NOT NULL AND post_text IS NOT NULL")
    longer, shorter = F.greatest(F.length("pre_text"), F.length("post_text")), F.least(F.length("pre_text"), F.length("post_text"))
    if metric != "edit":
        return both.withColumn("similarity", similarity(F.col("pre_text"), F.col("post_text"), metric)).where(F.col("similarity") >= min_similarity)
    # the distance is at least the difference of the lengths
    possible = both.where(shorter >= longer * min_similarity)
    short = possible.where(longer < long_from).withColumn("similarity", similarity(F.col("pre_text"), F.col("post_text"), "edit"))
    long = possible.where(longer >= long_from).withColumn("similarity", long_edit_similarity("pre_text", "post_text", min_similarity))
    return short.unionByName(long).where(F.col("similarity") >= min_similarity)


def build_pairs(flawed: DataFrame, versions: DataFrame, min_similarity: float = FLOOR, metric: str = "edit") -> DataFrame:
    """pair_id, flawed_id, benign_id, variant, similarity of the flawed functions whose fix is similar enough."""
    key = ["function_id", "revision", "variant"]
    close = gated_versions(versions, min_similarity, metric).select(*key, "similarity")
    joined = flawed.join(close, key)
    name = F.concat_ws(":", F.col("commit_id").cast("string"), F.col("function_id").cast("string"))
    return joined.select(name.alias("pair_id"), F.concat(name, F.lit(":pre")).alias("flawed_id"), F.concat(name, F.lit(":post")).alias("benign_id"), "commit_id", "commit_ts", "variant", F.round("similarity", 6).alias("similarity"))


def pair_split_stats(pairs: DataFrame) -> DataFrame:
    """Pairs per split; both sides follow their commit, so each split is balanced."""
    return pairs.groupBy("split").agg(F.count(F.lit(1)).alias("n_pairs"), F.count_distinct("commit_id").alias("n_commits"))


def unpaired_reasons(flawed: DataFrame, pairs: DataFrame, samples: DataFrame) -> DataFrame:
    """Why flawed functions have no pair: deleted, fix de-duplicated, or too different."""
    name = F.concat_ws(":", F.col("commit_id").cast("string"), F.col("function_id").cast("string"))
    alone = flawed.withColumn("pair_id", name).join(pairs.select("pair_id"), "pair_id", "left_anti")
    kept = samples.where("side = 'post'").select(F.col("sample_id").alias("benign_id"), F.lit(1).alias("kept"))
    joined = alone.withColumn("benign_id", F.concat("pair_id", F.lit(":post"))).join(kept, "benign_id", "left")
    reason = F.when(F.col("post_digest").isNull(), "deleted").when(F.col("kept").isNull(), "fix de-duplicated").otherwise("too different")
    return joined.groupBy(reason.alias("reason")).agg(F.count(F.lit(1)).alias("n"))


def natural_pairs(documents: DataFrame, min_similarity: float = FLOOR, min_jaccard: float = 0.5, k: int = 3) -> DataFrame:
    """id_a, id_b, similarity, kind of natural pairs: near copies whose edit similarity passes the floor, long texts included.

    kind "link": two different texts, each named by its smallest id; "copy": that smallest id and another one with the
    equal text. Copies are not paired with each other."""
    members, links = near_links(documents, min_jaccard=min_jaccard, k=k, floor=min_similarity)
    return by_smallest_ids(members, links, "similarity")
