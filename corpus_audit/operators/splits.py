"""Train / dev / test splits and training subsets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import bucket
from ..plans.prefix import first_by_digest, running_before

PARTS = ("train", "dev", "test")


def _cuts(fractions: tuple[float, ...]) -> list[int]:
    """Cumulative bounds in ten-thousandths."""
    out, total = [], 0
    for f in fractions[:-1]:
        total += round(f * 10_000)
        out.append(total)
    return out


def split_random(df: DataFrame, fractions: tuple[float, ...] = (0.8, 0.1, 0.1), seed: str = "s", key: str = "sample_id") -> DataFrame:
    """Baseline: by a hash of the key, so rows keep their split under any partitioning. key="commit_id" keeps commits whole."""
    train, dev = _cuts(fractions)
    b = bucket(F.col(key), seed)
    return df.withColumn("split", F.when(b < train, PARTS[0]).when(b < dev, PARTS[1]).otherwise(PARTS[2]))


def split_given(df: DataFrame, mapping: DataFrame, key: str = "sample_id") -> DataFrame:
    return df.join(mapping.select(key, "split"), key)


def split_chronological(df: DataFrame, fractions: tuple[float, ...] = (0.8, 0.1, 0.1), unit: str = "sample", embargo_days: int = 0) -> DataFrame:
    """By commit time, whole commits: a commit goes where its first unit falls in (commit_ts, commit_id) order.

    unit counts samples, commits or flawed samples. Running counts are two-level (per day, then inside a day). With
    an embargo, dev and test commits within that many days of the part before them are left out. Null dates are an
    error."""
    units = {"sample": F.count(F.lit(1)), "commit": F.lit(1), "flawed": F.count_if(F.col("label") == 1)}[unit]
    dated = F.when(F.col("commit_ts").isNull(), F.raise_error(F.lit("commit without a date"))).otherwise(F.col("commit_ts"))
    commits = df.withColumn("commit_ts", dated).groupBy("commit_id").agg(F.min("commit_ts").alias("_ts"), units.cast("long").alias("_n"))
    begun = running_before(commits, F.col("_n"), F.to_date("_ts"), ["_ts", "commit_id"], name="_begin")
    total = commits.agg(F.sum("_n").alias("_total"))
    train, dev = _cuts(fractions)
    at = F.col("_begin") * 10_000
    placed = begun.crossJoin(F.broadcast(total)).withColumn("split", F.when(at < F.col("_total") * train, PARTS[0]).when(at < F.col("_total") * dev, PARTS[1]).otherwise(PARTS[2]))
    if embargo_days:
        ends = placed.groupBy().agg(*[F.max(F.when(F.col("split") == p, F.col("_ts"))).alias(f"_{p}") for p in PARTS[:2]])
        gap = F.make_dt_interval(F.lit(embargo_days))
        placed = placed.crossJoin(F.broadcast(ends)).where(
            (F.col("split") == "train") | ((F.col("split") == "dev") & (F.col("_ts") > F.col("_train") + gap)) | ((F.col("split") == "test") & (F.col("_ts") > F.coalesce("_dev", "_train") + gap))
        )
    return df.join(placed.select("commit_id", "split"), "commit_id")


def split_by_quantile(df: DataFrame, fractions: tuple[float, ...] = (0.8, 0.1, 0.1)) -> DataFrame:
    """Variant: cut dates at approximate quantiles of the samples' dates, day-aligned."""
    day = F.unix_date(F.to_date("commit_ts"))
    train, dev = (c / 10_000 for c in _cuts(fractions))
    cuts = df.agg(F.percentile_approx(day, [train, dev], 10_000).alias("_cuts"))
    joined = df.crossJoin(F.broadcast(cuts))
    return joined.withColumn("split", F.when(day <= F.col("_cuts")[0], PARTS[0]).when(day <= F.col("_cuts")[1], PARTS[1]).otherwise(PARTS[2])).drop("_cuts")


def check_split(df: DataFrame) -> DataFrame:
    """One row: commits in several splits, and the order violations between neighbouring splits (0 or 1 each)."""
    straddling = df.groupBy("commit_id").agg((F.min("split") != F.max("split")).alias("x")).agg(F.count_if("x").alias("straddling_commits"))
    ends = df.agg(*[f(F.when(F.col("split") == p, F.col("commit_ts"))).alias(f"{n}_{p}") for p in PARTS for n, f in (("first", F.min), ("last", F.max))])
    late = lambda a, b: F.coalesce((F.col(f"last_{a}") > F.col(f"first_{b}")).cast("int"), F.lit(0)).alias(f"{a}_after_{b}")
    return straddling.crossJoin(ends.select(late("train", "dev"), late("dev", "test"), late("train", "test")))


def downsample_benign(train: DataFrame, ratio: int = 3, seed: str = "d", key: str = "sample_id") -> DataFrame:
    """All flawed rows and exactly ratio times as many benign ones (or all), drawn by hash."""
    flawed, benign = train.where("label = 1"), train.where("label = 0")
    wanted = flawed.agg((F.count(F.lit(1)) * ratio).alias("_wanted"))
    drawn = first_by_digest(benign.crossJoin(F.broadcast(wanted)), F.col("_wanted"), F.col(key), seed)
    return flawed.unionByName(drawn.select(*train.columns))
