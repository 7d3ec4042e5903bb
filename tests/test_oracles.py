"""Every query with SQL against DuckDB, and the others for rows, at the smallest scale."""

import pytest

from corpus_audit import catalogue, workloads

from .oracle import differences

SF = "/root/testdata/sf0.001"
QUICK = [
    "normalize_digest", "raw_vs_normalized_dedup", "merge_sources", "dedup_cross_side", "near_copy_pairs", "label_merged", "corpus_stats", "split_stats_rollup", "label_accuracy", "error_breakdown",
    "copy_rate_deduped", "benchmark_contamination", "split_chronological", "downsample_benign", "miss_rate_by_group", "det_curve", "pair_outcomes", "metric_correlation", "contrastive_class_aware", "verdict_parse", "stream_sessions",
]


@pytest.mark.parametrize("name", QUICK)
def test_query_against_sql(spark, name):
    assert differences(catalogue.queries()[name](spark, SF), catalogue.oracle_sql()[name], SF) == ""


def test_workload_shape(spark):
    got = workloads.run("format_twins", spark, SF)
    assert got.columns == ["run", "metric", "value", "support"]
    kept = {r["run"]: r["value"] for r in got.where("metric = 'n_kept'").collect()}
    assert kept["raw_vs_normalized_dedup/raw"] > kept["raw_vs_normalized_dedup/normalised"]
