import itertools
import re
from datetime import datetime

import pytest
from pyspark.sql import functions as F

from corpus_audit import catalogue, published
from corpus_audit.functions.edit import edit_distance
from corpus_audit.operators import annotate, contrast, dedup, history, labelers, leakage, metrics, pairwise, splits
from corpus_audit.plans.prefix import plan_problems, running_before
from corpus_audit.sources.tables import load

from .oracle import differences

CHANGE = "commit_id long, commit_ts timestamp_ntz, project_id long, weakness string, file_name string, function_id long, function_name string, pre_digest string, post_digest string"


def changes(spark, rows):
    full = [(c, datetime(2020, 1, 1 + c), 1, "w", f, n, f"fn_{n}", a, b) for c, f, n, a, b in rows]
    return spark.createDataFrame(full, CHANGE)


def ids(df):
    return {(r["commit_id"], r["function_id"]) for r in df.collect()}


def test_sole_change_counts_before_duplicates_go(spark):
    rows = changes(spark, [(1, "a.c", 1, "x", "y"), (2, "a.c", 1, "p", "q"), (2, "a.c", 2, "r", "s"), (3, "a.c", 1, "m", "n"), (3, "a.c", 2, "k", "k"), (4, "a.c", 5, "x", "z"), (4, "a.c", 6, "u", None)])
    changed, unchanged = dedup.split_changed(rows)
    assert ids(unchanged) == {(3, 2)}
    survivors = dedup.dedup(changed, key="pre_digest")
    assert ids(survivors) == {(1, 1), (2, 1), (2, 2), (3, 1), (4, 6)}
    assert ids(labelers.label_sole_change(changed, survivors)) == {(1, 1), (3, 1)}
    assert ids(labelers.label_sole_change(changed, survivors, count_on="survivors")) == {(1, 1), (3, 1), (4, 6)}


def test_advisory_rules(spark):
    changed = changes(spark, [(1, "mod1.c", 1, "a", "b"), (1, "mod1.c", 12, "c", "d"), (2, "mod1.c", 3, "e", "f"), (2, "mod2.c", 4, "g", "h"), (3, "mod1.c", 5, "i", "j"), (3, "mod1.c", 6, "k", "l")])
    adv = spark.createDataFrame([("A", 1, "fn_12 and fn_1_legacy"), ("B", 2, "see src/mod1.c there"), ("C", 3, "in mod1.c and FN_5")], "advisory_id string, commit_id long, description string")
    linked = labelers.link_advisories(changed, adv)
    assert ids(labelers.label_advisory(changed, linked, rules=("function",))) == {(1, 12)}
    assert ids(labelers.label_advisory(changed, linked, rules=("function",), match="substring")) == {(1, 1), (1, 12)}
    assert ids(labelers.label_advisory(changed, linked, rules=("file",))) == {(2, 3)}
    assert (3, 5) in ids(labelers.label_advisory(changed, linked, rules=("function",), case=False))


def test_benign_samples_come_from_kept_commits(spark):
    rows = changes(spark, [(1, "a.c", 1, "x", "y"), (1, "a.c", 2, "k", "k"), (2, "a.c", 3, "p", "q"), (2, "a.c", 4, "r", "s"), (2, "a.c", 5, "t", "t"), (3, "b.c", 6, "u", None)])
    none = spark.createDataFrame([], "advisory_id string, commit_id long, description string")
    got = {(r["sample_id"], r["label"]) for r in labelers.build_corpus(rows, none).collect()}
    assert got == {("1:1:pre", 1), ("1:1:post", 0), ("1:2:same", 0), ("3:6:pre", 1)}


@pytest.mark.parametrize(("policy", "kept"), [("first", {"b"}), ("flawed_wins", {"a"}), ("drop", set())])
def test_conflicting_labels(spark, policy, kept):
    df = spark.createDataFrame([("a", "d", 1, 2), ("b", "d", 0, 1)], "id string, digest string, label int, at int")
    out = dedup.dedup(df, order_by=("at",), on_conflict=policy)
    assert {r["id"] for r in out.collect()} == kept


def test_dedup_is_idempotent_and_equals_the_window_form(spark):
    df = spark.range(300).select("id", (F.col("id") % 37).cast("string").alias("digest"), ((F.col("id") * 7919) % 101).alias("at"))
    once = dedup.dedup(df, order_by=("at", "id"))
    twice = dedup.dedup(once, order_by=("at", "id"))
    window = dedup.dedup_by_window(df.repartition(7), order_by=("at", "id"))
    assert sorted(once.collect()) == sorted(twice.collect()) == sorted(window.collect())


def test_copy_rate_equals_brute_force(spark):
    df = spark.range(200).select(F.col("id").cast("string").alias("sample_id"), F.concat(F.lit("t "), (F.col("id") % 60).cast("string")).alias("text"), (F.col("id") % 3 == 0).cast("int").alias("label"))
    df = splits.split_random(df).withColumn("digest", F.md5(F.translate("text", " \t\n\r", "")))
    fast, slow = leakage.copy_rate(df).first(), leakage.copy_rate_bruteforce(df).first()
    assert (fast["n_test"], fast["n_copied"]) == (slow["n_test"], slow["n_copied"])
    unique = dedup.dedup(df, order_by=("sample_id",))
    assert leakage.copy_rate(unique, only_flawed=False).first()["n_copied"] == 0


def test_chronological_split_keeps_commits_whole(spark):
    days = [1, 2, 2, 3, 4, 5]
    rows = [(f"s{i}", c, datetime(2020, 1, days[c]), int(i % 2)) for i, c in enumerate([0, 0, 1, 1, 2, 3, 4, 4, 4, 5])]
    df = spark.createDataFrame(rows, "sample_id string, commit_id long, commit_ts timestamp_ntz, label int")
    got = splits.split_chronological(df)
    of = {r["commit_id"]: r["split"] for r in got.collect()}
    assert of == {0: "train", 1: "train", 2: "train", 3: "train", 4: "train", 5: "test"}
    check = splits.check_split(got).first()
    assert (check["straddling_commits"], check["train_after_dev"], check["dev_after_test"]) == (0, 0, 0)


def test_downsampling_is_exact(spark):
    df = spark.range(1000).select(F.col("id").cast("string").alias("sample_id"), (F.col("id") % 10 == 0).cast("int").alias("label"))
    got = splits.downsample_benign(df, ratio=3)
    assert (got.where("label = 1").count(), got.where("label = 0").count()) == (100, 300)
    assert sorted(got.collect()) == sorted(splits.downsample_benign(df.repartition(5), ratio=3).collect())


def test_running_sums(spark):
    df = spark.range(500).select("id", (F.col("id") % 7).alias("v"))
    got = running_before(df, F.col("v"), F.floor(F.col("id") / 50), ["id"]).orderBy("id").collect()
    total = 0
    for r in got:
        assert r["before"] == total
        total += r["v"]


def test_majority_of_all_triples(spark):
    kinds = ("flawed", "benign", "unsure")
    triples = list(itertools.product(kinds, repeat=3))
    rows = [(f"t{i}", n, v) for i, t in enumerate(triples) for n, v in enumerate(t)]
    votes = spark.createDataFrame(rows, "sample_id string, annotator int, verdict string")
    got = {r["sample_id"]: r["verdict"] for r in annotate.majority_vote(votes).collect()}
    for i, t in enumerate(triples):
        assert got[f"t{i}"] == ("needs_review" if "unsure" in t else "flawed" if t.count("flawed") >= 2 else "benign")
    revised = votes.withColumn("verdict", F.when(F.col("annotator") == 0, "flawed").otherwise("benign"))
    assert "needs_review" not in {r["verdict"] for r in annotate.majority_vote(votes, revised).collect()}


def scored(spark, rows):
    return spark.createDataFrame(rows, "label int, score double")


@pytest.mark.parametrize(
    ("rows", "ppm", "fnr"),
    [
        ([(1, 1.0), (0, 1.0), (0, 1.0)], 5_000, 1.0),
        ([(1, 0.9), (0, 0.1)], 0, 0.0),
        ([(1, 0.1), (0, 0.9)], 5_000, 1.0),
        ([(1, 0.1), (0, 0.9)], 1_000_000, 0.0),
        ([(0, 0.5)], 5_000, None),
        ([(1, 0.5)], 5_000, 0.0),
    ],
)
def test_capped_miss_rate_edges(spark, rows, ppm, fnr):
    assert metrics.miss_rate_at_fpr(scored(spark, rows), ppm).first()["fnr"] == fnr


def test_capped_miss_rate_falls_with_the_cap_and_ignores_monotone_maps(spark):
    df = spark.range(2000).select((F.col("id") % 5 == 0).cast("int").alias("label"), ((F.col("id") * 7919) % 1009).cast("double").alias("score"))
    caps = [0, 1_000, 5_000, 50_000, 500_000, 1_000_000]
    got = {r["r_ppm"]: r["fnr"] for r in metrics.miss_rate_at_fpr(df, caps).collect()}
    assert [got[c] for c in caps] == sorted(got.values(), reverse=True)
    assert got[1_000_000] == 0
    mapped = df.withColumn("score", F.exp(F.col("score") / 300))
    assert got == {r["r_ppm"]: r["fnr"] for r in metrics.miss_rate_at_fpr(mapped, caps).collect()}


def test_pairs_cover_long_texts(spark):
    sf = "/root/testdata/sf0.001"
    flawed = catalogue.History(spark, sf).flawed()
    key = ["function_id", "revision", "variant"]
    wanted = {}
    for r in flawed.join(history.text_versions(spark, sf, flawed), key).collect():
        a, b = r["pre_text"], r["post_text"]
        if a is not None and b is not None and min(len(a), len(b)) >= 0.8 * max(len(a), len(b)):
            near = 1 - edit_distance(a, b) / max(len(a), len(b))
            if near >= 0.8:
                wanted[f"{r['commit_id']}:{r['function_id']}"] = (len(a), near)
    got = {r["pair_id"]: r["similarity"] for r in catalogue.build_pairs(spark, sf).collect()}
    assert got == {k: pytest.approx(near, abs=1e-6) for k, (_, near) in wanted.items()}
    assert any(n > 1_500 for n, _ in wanted.values())
    assert any(n >= 4_000 for n, _ in wanted.values())


def test_pair_outcomes_and_swapping(spark):
    rows = spark.createDataFrame([("a", 1, 0), ("b", 1, 1), ("c", 0, 0), ("d", 0, 1), ("e", 1, 0), ("f", None, 1)], "pair_id string, pred_flawed int, pred_fixed int")
    got = pairwise.pair_outcomes(rows).first()
    assert (got["n_pairs"], got["n_missing"], got["p_c"], got["p_v"], got["p_b"], got["p_r"]) == (5, 1, 40.0, 20.0, 20.0, 20.0)
    back = pairwise.pair_outcomes(rows.select("pair_id", F.col("pred_fixed").alias("pred_flawed"), F.col("pred_flawed").alias("pred_fixed"))).first()
    assert (back["p_c"], back["p_r"]) == (got["p_r"], got["p_c"])


def test_published_figures_return_from_counts(spark):
    from corpus_audit import catalogue

    sizes = [F.lit(n).alias(name) for n, name in zip(published.TEST_SIDE, ("flawed", "benign", "n_pairs"), strict=True)]
    got = {r["run"]: r for r in catalogue.measures_of_counts(published.counts(spark).select("*", *sizes)).collect()}
    printed = {f"{m} fit {fit}": row for m, fit, on, *row in published.DETECTORS if on == "new"} | {s: row for s, *row in published.SETTINGS if s != "weight 1"}
    for run, row in printed.items():
        assert [got[run][c] for c in ("accuracy", "f1", "miss", "p_c", "p_v", "p_b", "p_r")] == pytest.approx(row, abs=0.0051), run


def test_reported_findings():
    new = [r for r in published.DETECTORS if r[2] == "new"]
    wide = {r[0]: r[4] for r in published.DETECTORS if r[2] == "wide"}
    assert all(wide[r[0]] - r[4] > 40 for r in new)
    assert all(round(r[7] + r[8], 2) >= 95.04 for r in new)
    assert all(r[3] < published.TEST_BENIGN_SHARE for r in new)
    weights = published.SETTINGS[:5]
    assert all(r[2] > weights[0][2] for r in weights[1:])
    assert max(r[3] for r in weights) - min(r[3] for r in weights) < 2.2
    assert all(r[2] < 22.70 for r in published.PROMPTED if r[0] != "random")


def test_contrast_properties(spark):
    rows = [(i, 0, [float((i * 7 + k) % 5 - 2) for k in range(8)], i % 2) for i in range(6)]
    df = spark.createDataFrame(rows, "vec_id long, batch_id long, embedding array<float>, label int")
    both = [contrast.contrastive_loss(df, mode, p=0.0).first()["loss"] for mode in ("any", "class_aware")]
    assert both[1] <= both[0] + 1e-9
    same = contrast.contrastive_loss(df.withColumn("label", F.lit(1)), "class_aware", p=0.0).first()
    assert same["loss"] == pytest.approx(0.0)


def test_joint_fit_without_contrast_is_plain(spark):
    rows = [(i, i // 8, [float((i * 13 + k) % 7 - 3) / 3 for k in range(6)], int(i % 3 == 0)) for i in range(32)]
    df = spark.createDataFrame(rows, "vec_id long, batch_id long, embedding array<float>, label int")
    plain, zero = contrast.fit_joint(df, "none", epochs=2), contrast.fit_joint(df, "any", lam=0.0, epochs=2)
    assert (plain["w"] == zero["w"]).all()
    aware = contrast.fit_joint(df, "class_aware", epochs=3)
    assert aware["history"][0][2] > 0


def test_plans_have_no_cartesian_product(spark):
    df = spark.range(100).select(F.col("id").cast("string").alias("sample_id"), "id", (F.col("id") % 2).cast("int").alias("label"), F.col("id").cast("double").alias("score"))
    assert plan_problems(metrics.error_curve(df)) == []
    assert plan_problems(splits.downsample_benign(df)) == []


def test_compare_runs_follows_the_tables(spark, tmp_path):
    """A part of the rows gives other results; the SQL agrees."""
    for name in ("events", "lineitem"):
        load(spark, "/root/testdata/sf0.001", name).where(f"{'event_id' if name == 'events' else 'l_orderkey'} % 3 > 0").write.parquet(f"{tmp_path}/{name}.parquet")
    part, whole = catalogue.compare_runs(spark, str(tmp_path)), catalogue.compare_runs(spark, "/root/testdata/sf0.001")
    assert sorted(map(str, part.collect())) != sorted(map(str, whole.collect()))
    assert differences(whole, catalogue.oracle_sql()["compare_runs"], "/root/testdata/sf0.001") == ""


def test_leaderboard_follows_the_tables(spark, tmp_path):
    """A part of the rows gives other results; the SQL agrees."""
    for name in ("events", "lineitem"):
        load(spark, "/root/testdata/sf0.001", name).where(f"{'event_id' if name == 'events' else 'l_orderkey'} % 3 > 0").write.parquet(f"{tmp_path}/{name}.parquet")
    part, whole = catalogue.leaderboard(spark, str(tmp_path)), catalogue.leaderboard(spark, "/root/testdata/sf0.001")
    assert sorted(map(str, part.collect())) != sorted(map(str, whole.collect()))
    assert differences(whole, catalogue.oracle_sql()["leaderboard"], "/root/testdata/sf0.001") == ""


def test_metric_correlation_follows_the_tables(spark, tmp_path):
    """A part of the rows gives other results; the SQL agrees."""
    for name in ("events", "lineitem"):
        load(spark, "/root/testdata/sf0.001", name).where(f"{'event_id' if name == 'events' else 'l_orderkey'} % 3 > 0").write.parquet(f"{tmp_path}/{name}.parquet")
    part, whole = catalogue.metric_correlation(spark, str(tmp_path)), catalogue.metric_correlation(spark, "/root/testdata/sf0.001")
    assert sorted(map(str, part.collect())) != sorted(map(str, whole.collect()))
    assert differences(whole, catalogue.oracle_sql()["metric_correlation"], "/root/testdata/sf0.001") == ""


def test_published_reconstruction_follows_the_tables(spark, tmp_path):
    """A part of the rows gives other results; the SQL agrees."""
    for name in ("events", "lineitem"):
        load(spark, "/root/testdata/sf0.001", name).where(f"{'event_id' if name == 'events' else 'l_orderkey'} % 3 > 0").write.parquet(f"{tmp_path}/{name}.parquet")
    part, whole = catalogue.published_reconstruction(spark, str(tmp_path)), catalogue.published_reconstruction(spark, "/root/testdata/sf0.001")
    assert sorted(map(str, part.collect())) != sorted(map(str, whole.collect()))
    assert differences(whole, catalogue.oracle_sql()["published_reconstruction"], "/root/testdata/sf0.001") == ""
