"""The experiment workloads by name, each as (run, metric, value, support)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import catalogue


def _long(df: DataFrame, run: str, keys: tuple[str, ...] = (), support: str | None = None) -> DataFrame:
    """Numeric columns of a result as rows."""
    numeric = [c for c, t in df.dtypes if t in ("bigint", "int", "double") and c not in keys]
    name = F.concat_ws("/", F.lit(run), *[F.coalesce(F.col(k).cast("string"), F.lit("all")) for k in keys])
    each = F.array(*[F.struct(F.lit(c).alias("metric"), F.col(c).cast("double").alias("value")) for c in numeric])
    size = F.col(support).cast("long") if support else F.lit(None).cast("long")
    return df.select(name.alias("run"), F.explode(each).alias("x"), size.alias("support")).select("run", "x.metric", "x.value", "support")


# workload -> [(query, key columns, support column)]
PLAN = {
    "label_audit": [("label_accuracy", ("corpus",), "n"), ("error_breakdown", ("corpus", "category"), "n")],
    "copy_audit": [("copy_rate_random", ("corpus",), "n_test"), ("copy_rate_by_id", ("corpus",), "n_test"), ("copy_rate_deduped", ("corpus",), "n_test")],
    "format_twins": [("raw_vs_normalized_dedup", ("kind",), "n_rows")],
    "time_audit": [("time_travel", (), "n_test"), ("time_travel_chronological", (), "n_test"), ("straddling_commits", (), "n_commits"), ("fix_leak", (), None)],
    "corpus_build": [("corpus_stats", (), None), ("split_stats_rollup", ("split", "label"), "n_samples")],
    "labeler_contrast": [("labeler_overlap", ("labeler",), "n_flawed")],
    "pair_build": [("pair_split_stats", ("split",), "n_pairs"), ("unpaired_reasons", ("reason",), "n")],
    "detector_grid": [("cross_corpus", ("run", "setting", "metric"), None), ("miss_rate_by_group", ("grp",), "n_pos")],
    "weight_grid": [("class_weight_loss", ("weight",), None), ("class_weight_sweep", ("run", "setting", "metric"), None), ("detector_pair_outcomes", ("run", "setting", "metric"), None)],
    "contrast_grid": [("contrastive_any", ("batch_id",), "n"), ("contrastive_class_aware", ("batch_id",), "n"), ("joint_fit", ("run", "setting", "metric"), None)],
    "prompt_grid": [("prompted_pair_outcomes", ("run", "setting", "metric"), None), ("pair_outcomes", ("variant",), "n_pairs"), ("pair_outcomes_random", (), "n_pairs")],
    "cap_sweep": [("miss_rate_sweep", ("r_ppm",), "n_pos"), ("miss_rate_ties", ("r_ppm",), "n_pos")],
    "metric_agreement": [("metric_correlation", ("metrics",), "n_runs")],
    "published_counts": [("published_reconstruction", ("run",), None)],
}


def run(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    found = catalogue.queries()
    out = None
    for query, keys, support in PLAN[name]:
        part = _long(found[query](spark, sf_dir), query, keys, support)
        out = part if out is None else out.unionByName(part)
    return out
