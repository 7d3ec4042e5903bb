"""Detector measures. Frames have label (1 flawed, 0 benign), score or pred, and optional group columns.

A sample is called flawed if its score is at least the threshold; tied scores are taken whole or not at all.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.prefix import running_before

CAP_PPM = 5_000  # fixed value: false alarms per million benign samples (0.5 %)


def confusion(df: DataFrame, threshold: float | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """tp, fp, tn, fn from pred, or from score at a threshold."""
    called = F.col("pred") == 1 if threshold is None else F.col("score") >= threshold
    flawed, benign = F.col("label") == 1, F.col("label") == 0
    return df.groupBy(*by).agg(F.count_if(flawed & called).alias("tp"), F.count_if(benign & called).alias("fp"), F.count_if(benign & ~called).alias("tn"), F.count_if(flawed & ~called).alias("fn"))


def rates(counts: DataFrame, digits: int = 6) -> DataFrame:
    """accuracy, precision, recall, f1, fpr, fnr; undefined f1, precision and recall are 0, other undefined rates null."""
    tp, fp, tn, fn = (F.col(c) for c in ("tp", "fp", "tn", "fn"))
    ratio = lambda a, b: F.round(F.try_divide(a, b), digits)
    return counts.select(
        "*", ratio(tp + tn, tp + fp + tn + fn).alias("accuracy"), F.coalesce(ratio(tp, tp + fp), F.lit(0.0)).alias("precision"), F.coalesce(ratio(tp, tp + fn), F.lit(0.0)).alias("recall"),
        F.coalesce(ratio(2 * tp, 2 * tp + fp + fn), F.lit(0.0)).alias("f1"), ratio(fp, fp + tn).alias("fpr"), ratio(fn, fn + tp).alias("fnr"),
    )


def score_histogram(df: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """A row per (group, score): pos, neg. Null and NaN scores are an error."""
    score = F.when(F.col("score").isNull() | F.isnan("score"), F.raise_error(F.lit("score is null or NaN"))).otherwise(F.col("score").cast("double"))
    return df.withColumn("score", score).groupBy(*by, "score").agg(F.count_if(F.col("label") == 1).alias("pos"), F.count_if(F.col("label") == 0).alias("neg"))


def error_curve(df: DataFrame, by: tuple[str, ...] = (), cells: int = 4096) -> DataFrame:
    """threshold, tp, fp, n_pos, n_neg for every distinct score, per group. Running counts are two-level over equal
    score ranges, so one group may hold all rows."""
    histogram = score_histogram(df, by)
    ends = histogram.groupBy(*by).agg(F.min("score").alias("_lo"), F.max("score").alias("_hi"), F.sum("pos").alias("n_pos"), F.sum("neg").alias("n_neg"))
    joined = histogram.join(F.broadcast(ends) if not by else ends, list(by)) if by else histogram.crossJoin(F.broadcast(ends))
    width = F.col("_hi") - F.col("_lo")
    cell = F.when(width > 0, -F.floor((F.col("score") - F.col("_lo")) / width * cells)).otherwise(F.lit(0).cast("long"))
    down = [F.desc("score")]
    tp = running_before(joined, F.col("pos"), cell, down, by, "_tp")
    both = running_before(tp, F.col("neg"), cell, down, by, "_fp")
    return both.select(*by, F.col("score").alias("threshold"), (F.col("_tp") + F.col("pos")).alias("tp"), (F.col("_fp") + F.col("neg")).alias("fp"), "n_pos", "n_neg")


def miss_rate_at_fpr(df: DataFrame, r_ppm: int | list[int] = CAP_PPM, by: tuple[str, ...] = (), tune_on: DataFrame | None = None) -> DataFrame:
    """The capped miss rate: the least FNR over thresholds whose FPR is at most r, per group and cap.

    Columns: r_ppm, threshold (null: nothing is called flawed), tp, fp, n_pos, n_neg, fpr, fnr. Among equal FNR the
    smaller FPR, then the larger threshold. No positives: fnr null; no negatives: any threshold passes. With
    ``tune_on`` the threshold comes from that frame and the counts from df; ``exceeds`` flags an FPR above the cap."""
    caps = df.sparkSession.createDataFrame([(int(x),) for x in (r_ppm if isinstance(r_ppm, list) else [r_ppm])], "r_ppm long")
    curve = error_curve(df if tune_on is None else tune_on, by)
    totals = (df if tune_on is None else tune_on).groupBy(*by).agg(F.count_if(F.col("label") == 1).alias("n_pos"), F.count_if(F.col("label") == 0).alias("n_neg"))
    none = totals.select(*by, F.lit(None).cast("double").alias("threshold"), F.lit(0).cast("long").alias("tp"), F.lit(0).cast("long").alias("fp"), "n_pos", "n_neg")
    points = curve.unionByName(none).crossJoin(F.broadcast(caps)).where(F.col("fp") * 1_000_000 <= F.col("r_ppm") * F.col("n_neg"))
    better = F.struct("tp", -F.col("fp"), F.coalesce("threshold", F.lit(float("inf"))).alias("t"))
    best = points.groupBy(*by, "r_ppm").agg(F.max_by(F.struct("threshold", "tp", "fp", "n_pos", "n_neg"), better).alias("b")).select(*by, "r_ppm", "b.*")
    if tune_on is not None:
        cuts = best.select(*by, "r_ppm", "threshold")
        rows = df.join(F.broadcast(cuts), list(by)) if by else df.crossJoin(F.broadcast(cuts))
        called = F.coalesce(F.col("score") >= F.col("threshold"), F.lit(False))
        best = rows.groupBy(*by, "r_ppm", "threshold").agg(
            F.count_if((F.col("label") == 1) & called).alias("tp"), F.count_if((F.col("label") == 0) & called).alias("fp"), F.count_if(F.col("label") == 1).alias("n_pos"), F.count_if(F.col("label") == 0).alias("n_neg")
        )
        best = best.withColumn("exceeds", F.col("fp") * 1_000_000 > F.col("r_ppm") * F.col("n_neg"))
    fpr, fnr = F.round(F.try_divide(F.col("fp"), F.col("n_neg")), 8), F.round(F.try_divide(F.col("n_pos") - F.col("tp"), F.col("n_pos")), 8)
    return best.withColumn("fpr", fpr).withColumn("fnr", fnr)


def miss_rate_approximate(df: DataFrame, r: float = 0.005, accuracy: int = 100_000) -> DataFrame:
    """threshold, fpr, fnr from an approximate quantile of the benign scores: one sketch pass, one counting pass."""
    cut = df.where("label = 0").agg(F.percentile_approx("score", 1 - r, accuracy).alias("threshold"))
    called = F.col("score") > F.col("threshold")
    flawed, benign = F.col("label") == 1, F.col("label") == 0
    rows = df.crossJoin(F.broadcast(cut)).groupBy("threshold").agg(F.count_if(benign & called).alias("fp"), F.count_if(benign).alias("n_neg"), F.count_if(flawed & ~called).alias("fn"), F.count_if(flawed).alias("n_pos"))
    return rows.select("threshold", F.try_divide("fp", "n_neg").alias("fpr"), F.try_divide("fn", "n_pos").alias("fnr"))


def det_curve(df: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """threshold, fpr, fnr along the whole trade-off."""
    fpr, fnr = F.round(F.try_divide(F.col("fp"), F.col("n_neg")), 8), F.round(F.try_divide(F.col("n_pos") - F.col("tp"), F.col("n_pos")), 8)
    return error_curve(df, by).select(*by, "threshold", fpr.alias("fpr"), fnr.alias("fnr"))


def predict_constant(df: DataFrame, value: int = 0) -> DataFrame:
    return df.withColumn("pred", F.lit(value))


def metric_correlation(results: DataFrame, pairs: list[tuple[str, str]]) -> DataFrame:
    """Pearson and Spearman correlation of metric columns over runs (a small frame of results)."""
    out = None
    for a, b in pairs:
        ranked = results.select(F.col(a).alias("a"), F.col(b).alias("b"))
        rank = lambda c: F.rank().over(Window.orderBy(c)) + (F.count(F.lit(1)).over(Window.partitionBy(c)) - 1) / 2
        ranked = ranked.withColumn("ra", rank("a")).withColumn("rb", rank("b"))
        row = ranked.agg(F.lit(f"{a}~{b}").alias("metrics"), F.round(F.corr("a", "b"), 6).alias("pearson"), F.round(F.corr("ra", "rb"), 6).alias("spearman"), F.count(F.lit(1)).alias("n_runs"))
        out = row if out is None else out.unionByName(row)
    return out


def compare_runs(results: DataFrame, key: str, setting: str, metric: str) -> DataFrame:
    """Every pair of settings of the same key with the difference of a metric."""
    a = results.select(F.col(key).alias("k"), F.col(setting).alias("setting_a"), F.col(metric).alias("value_a"))
    b = results.select(F.col(key).alias("k"), F.col(setting).alias("setting_b"), F.col(metric).alias("value_b"))
    return a.join(b, "k").where("setting_a < setting_b").select(F.col("k").alias(key), "setting_a", "setting_b", F.round(F.col("value_b") - F.col("value_a"), 6).alias("delta"))


def leaderboard(results: DataFrame, metric: str, descending: bool = True) -> DataFrame:
    return results.withColumn("place", F.rank().over(Window.orderBy(F.desc(metric) if descending else F.asc(metric))))
