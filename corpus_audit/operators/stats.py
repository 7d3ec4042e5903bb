"""Corpus statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def corpus_stats(samples: DataFrame, approximate: bool = False) -> DataFrame:
    """One row: flawed, benign, projects, commits, weaknesses, benign per flawed."""
    distinct = F.approx_count_distinct if approximate else F.count_distinct
    flawed, benign = F.count_if(F.col("label") == 1), F.count_if(F.col("label") == 0)
    return samples.agg(
        flawed.alias("n_flawed"), benign.alias("n_benign"), distinct("project_id").alias("n_projects"), distinct("commit_id").alias("n_commits"),
        distinct(F.when(F.col("label") == 1, F.col("weakness"))).alias("n_weaknesses"), F.round(F.try_divide(benign, flawed), 6).alias("benign_per_flawed"),
    )


def split_stats(samples: DataFrame) -> DataFrame:
    """Counts per split and label with totals (rollup)."""
    return samples.rollup("split", "label").agg(F.count(F.lit(1)).alias("n_samples"), F.count_distinct("commit_id").alias("n_commits"))


def imbalance(df: DataFrame, label: str = "label") -> DataFrame:
    positive, negative = F.count_if(F.col(label) == 1), F.count_if(F.col(label) == 0)
    return df.agg(positive.alias("n_pos"), negative.alias("n_neg"), F.round(F.try_divide(negative, positive), 6).alias("neg_per_pos"))
