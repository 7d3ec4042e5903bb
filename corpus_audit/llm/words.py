"""Text features shared by the two classifiers."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_WORD = re.compile(r"\w+")


def word_counts(text: str | None) -> Counter:
    return Counter(_WORD.findall(text.lower())) if text else Counter()


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def labelled(docs: DataFrame, labels: DataFrame, label: str, most: int) -> DataFrame:
    """(doc_id, text, label) of a bounded sample of the rows that may teach: the first ``most`` in digest order of doc_id.

    Null labels and held-out rows never teach; of repeated labels the greatest counts."""
    pool = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    pool = pool.groupBy("doc_id").agg(F.max(label).cast("int").alias("label"))
    sample = pool.orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(most)
    # the sample has a fixed most rows of two numbers
    return docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(sample), "doc_id")
