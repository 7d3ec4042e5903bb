"""Label-accuracy audits by human votes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

Z = 1.959963984540054  # fixed value: two-sided 95 % normal quantile


def audit_sample(flawed: DataFrame, per: str = "corpus", n: int = 50, seed: str = "audit", key: str = "sample_id") -> DataFrame:
    """Exactly n rows of each corpus (all, if fewer) in hash order."""
    order = Window.partitionBy(per).orderBy(F.md5(F.concat(F.lit(seed), F.col(key).cast("string"))), key)
    return flawed.withColumn("_n", F.row_number().over(order)).where(F.col("_n") <= n).drop("_n")


def audit_sheet(sample: DataFrame, history: DataFrame, advisories: DataFrame) -> DataFrame:
    """The sample with what an annotator looks at: both versions' digests and the advisory text."""
    versions = history.select("commit_id", "function_id", "function_name", "pre_digest", "post_digest")
    return sample.join(versions, ["commit_id", "function_id"], "left").join(advisories.select("commit_id", "advisory_id", "description"), "commit_id", "left")


def two_step(votes: DataFrame) -> DataFrame:
    """verdict from the two judgements is_fix (the commit fixes a flaw) and is_flawed (this function held it)."""
    both = F.when(F.col("is_fix").isNull() | F.col("is_flawed").isNull(), "unsure").when(F.col("is_fix") & F.col("is_flawed"), "flawed").otherwise("benign")
    return votes.withColumn("verdict", both)


def majority_vote(votes: DataFrame, revised: DataFrame | None = None, quorum: int = 2, expected: int = 3) -> DataFrame:
    """sample_id, verdict. A triple with an unsure vote is replaced by its revised round as a whole; without one, with
    another unsure vote or with another number of votes it stays needs_review."""

    def tally(frame: DataFrame) -> DataFrame:
        counts = frame.groupBy("sample_id").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("verdict") == "flawed").alias("yes"), F.count_if(F.col("verdict") == "unsure").alias("unsure"))
        decided = F.when((F.col("n") != expected) | (F.col("unsure") > 0), "needs_review").when(F.col("yes") >= quorum, "flawed").otherwise("benign")
        return counts.select("sample_id", decided.alias("verdict"))

    first = tally(votes)
    if revised is None:
        return first
    second = tally(revised).withColumnRenamed("verdict", "second")
    joined = first.join(second, "sample_id", "left")
    return joined.select("sample_id", F.when(F.col("verdict") == "needs_review", F.coalesce("second", "verdict")).otherwise(F.col("verdict")).alias("verdict"))


def label_accuracy(audited: DataFrame, per: str = "corpus") -> DataFrame:
    """corpus, n, n_correct, correct_pct with a 95 % Wilson interval over the decided samples."""
    decided = audited.where("verdict <> 'needs_review'").groupBy(per).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("verdict") == "flawed").alias("n_correct"))
    p, n = F.col("n_correct") / F.col("n"), F.col("n")
    half = Z * F.sqrt(p * (1 - p) / n + Z * Z / (4 * n * n))
    bound = lambda sign: F.round(100 * (p + Z * Z / (2 * n) + sign * half) / (1 + Z * Z / n), 4)
    return decided.select(per, "n", "n_correct", F.round(100 * p, 4).alias("correct_pct"), bound(-1).alias("low_pct"), bound(1).alias("high_pct"))


def error_breakdown(votes: DataFrame, per: str = "corpus") -> DataFrame:
    """Share of each reason among the samples that most voters call benign, by their most frequent reason (ties by name)."""
    benign = votes.where("verdict = 'benign'").groupBy(per, "sample_id", "category").agg(F.count(F.lit(1)).alias("n"))
    of_sample = benign.groupBy(per, "sample_id").agg(F.sum("n").alias("votes"), F.max(F.struct("n", (-F.ascii("category")).alias("_a"), "category"))["category"].alias("category"))
    counts = of_sample.where("votes >= 2").groupBy(per, "category").agg(F.count(F.lit(1)).alias("n"))
    total = Window.partitionBy(per)
    return counts.select(per, "category", "n", F.round(100.0 * F.col("n") / F.sum("n").over(total), 4).alias("pct"))
