"""Four-way outcomes of predictions on pairs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import bucket

# The outcomes in their order; (prediction of the flawed side, prediction of the fixed side).
OUTCOMES = {"P-C": (1, 0), "P-V": (1, 1), "P-B": (0, 0), "P-R": (0, 1)}


def attach(pairs: DataFrame, predictions: DataFrame) -> DataFrame:
    """pair_id, pred_flawed, pred_fixed: pairs are melted to sides, so predictions are shuffled once."""
    sides = pairs.select("pair_id", F.explode(F.array(F.struct(F.lit("a").alias("s"), F.col("flawed_id").alias("sample_id")), F.struct(F.lit("b").alias("s"), F.col("benign_id").alias("sample_id")))).alias("x"))
    joined = sides.select("pair_id", "x.*").join(predictions.select("sample_id", "pred"), "sample_id", "left")
    return joined.groupBy("pair_id").agg(F.max(F.when(F.col("s") == "a", F.col("pred"))).alias("pred_flawed"), F.max(F.when(F.col("s") == "b", F.col("pred"))).alias("pred_fixed"))


def outcome(flawed: Column, fixed: Column) -> Column:
    out = None
    for name, (a, b) in OUTCOMES.items():
        test = (flawed == a) & (fixed == b)
        out = F.when(test, name) if out is None else out.when(test, name)
    return out


def pair_outcomes(attached: DataFrame, by: tuple[str, ...] = (), on_missing: str = "report") -> DataFrame:
    """n_pairs, n_missing, and share in percent of each outcome over the evaluated pairs (they sum to 100)."""
    o = outcome(F.col("pred_flawed"), F.col("pred_fixed"))
    if on_missing == "error":
        o = F.when(o.isNull(), F.raise_error(F.lit("pair without predictions"))).otherwise(o)
    named = attached.withColumn("_o", o)
    counts = named.groupBy(*by).agg(F.count("_o").alias("n_pairs"), F.count_if(F.col("_o").isNull()).alias("n_missing"), *[F.count_if(F.col("_o") == name).alias(name) for name in OUTCOMES])
    share = [F.round(F.try_divide(100.0 * F.col(f"`{name}`"), F.col("n_pairs")), 6).alias(name.replace("-", "_").lower()) for name in OUTCOMES]
    return counts.select(*by, "n_pairs", "n_missing", *share)


def predict_random(ids: DataFrame, p: float = 0.5, seed: str = "coin", key: str = "sample_id") -> DataFrame:
    """Baseline: a reproducible biased coin for each sample. Expected shares are p(1-p), p^2, (1-p)^2, p(1-p)."""
    return ids.withColumn("pred", (bucket(F.col(key), seed) < round(p * 10_000)).cast("int"))
