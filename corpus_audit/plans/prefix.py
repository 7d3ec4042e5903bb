"""Running sums and exact samples without a global one-partition window."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def running_before(df: DataFrame, value: Column, coarse: Column, order: list, by: tuple[str, ...] = (), name: str = "before") -> DataFrame:
    """df with ``name``: the sum of ``value`` over all rows ahead in (coarse, order), per group ``by``.

    Two levels: sums per coarse cell are accumulated over the (few) cells, then inside each cell. ``coarse`` must
    not fall along ``order``."""
    cells = df.withColumn("_cell", coarse).withColumn("_value", value)
    sums = cells.groupBy(*by, "_cell").agg(F.sum("_value").alias("_sum"))
    ahead = Window.partitionBy(*by).orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select(*[F.col(c).alias(f"_by_{c}") for c in by], F.col("_cell").alias("_cell_2"), F.coalesce(F.sum("_sum").over(ahead), F.lit(0)).alias("_offset"))
    on = F.col("_cell").eqNullSafe(F.col("_cell_2"))
    for c in by:
        on = on & F.col(c).eqNullSafe(F.col(f"_by_{c}"))
    inside = Window.partitionBy(*by, "_cell").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    within = cells.withColumn("_within", F.coalesce(F.sum("_value").over(inside), F.lit(0)))
    return within.join(offsets, on).withColumn(name, F.col("_offset") + F.col("_within")).drop("_cell", "_cell_2", "_value", "_offset", "_within", *[f"_by_{c}" for c in by])


def first_by_digest(df: DataFrame, n: Column, key: Column, seed: str, digits: int = 3) -> DataFrame:
    """Exactly n rows (n: a scalar column over df) in order of md5(seed, key): counts per digest prefix find the
    threshold cell, and only ranks inside cells are computed."""
    keyed = df.withColumn("_hash", F.md5(F.concat(F.lit(seed), key.cast("string"))))
    ranked = running_before(keyed, F.lit(1), F.substring("_hash", 1, digits), ["_hash", key], name="_rank")
    return ranked.where(F.col("_rank") < n).drop("_rank", "_hash")


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().toString()


def plan_problems(df: DataFrame) -> list[str]:
    """What a plan at scale must not hold: Cartesian products, one-partition windows over data, Python rows."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return [x for x in ("CartesianProduct", "BatchEvalPython") if x in text]
