"""Labelers and the corpus built from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import file_names, identifiers
from ..plans.materialise import written
from .dedup import dedup, split_changed

SAMPLE = ["sample_id", "commit_id", "commit_ts", "project_id", "weakness", "file_name", "function_id", "side", "digest", "label"]


def as_samples(changes: DataFrame, side: str, label: int) -> DataFrame:
    """Rows of one side of changes in the shape of samples; a missing text gives none."""
    value = F.col("post_digest" if side == "post" else "pre_digest")
    named = changes.select(
        F.concat_ws(":", F.col("commit_id").cast("string"), F.col("function_id").cast("string"), F.lit(side)).alias("sample_id"),
        "commit_id", "commit_ts", "project_id", "weakness", "file_name", "function_id", F.lit(side).alias("side"), value.alias("digest"), F.lit(label).alias("label"),
    )
    return named.where("digest IS NOT NULL")


def label_blanket(changed: DataFrame, unchanged: DataFrame | None = None) -> DataFrame:
    """Baseline: every changed function's pre version is flawed; post versions and unchanged functions are benign."""
    out = as_samples(changed, "pre", 1).unionByName(as_samples(changed, "post", 0))
    return out if unchanged is None else out.unionByName(as_samples(unchanged, "same", 0))


def only_change_of(changed: DataFrame, key: list[str]) -> DataFrame:
    """The keys in which one function changes: least and greatest agree, an algebraic test without distinct counts."""
    place = F.struct("file_name", "function_id")
    return changed.groupBy(*key).agg(F.min(place).alias("_a"), F.max(place).alias("_b")).where("_a = _b").drop("_a", "_b")


def label_sole_change(changed: DataFrame, survivors: DataFrame | None = None, count_on: str = "all") -> DataFrame:
    """Flawed: the only function that its commit changes. Counted before duplicates go, unless count_on="survivors"."""
    survivors = changed if survivors is None else survivors
    counted = survivors if count_on == "survivors" else changed
    return survivors.join(only_change_of(counted, ["commit_id"]), "commit_id", "left_semi").withColumn("rule", F.lit("sole"))


def link_advisories(commits: DataFrame, advisories: DataFrame) -> DataFrame:
    """commit_id, advisory_id, description; several advisories a commit stay several rows."""
    return advisories.join(commits.select("commit_id").distinct(), "commit_id", "left_semi").select("commit_id", "advisory_id", "description")


def mentions(linked: DataFrame, names: Column, case: bool = True) -> DataFrame:
    """(commit_id, name): what the advisories of each commit name."""
    found = linked.select("commit_id", F.explode(names).alias("name"))
    return (found if case else found.withColumn("name", F.lower("name"))).distinct()


def label_advisory(changed: DataFrame, linked: DataFrame, survivors: DataFrame | None = None, rules: tuple[str, ...] = ("function", "file"), match: str = "word", case: bool = True) -> DataFrame:
    """Flawed: named by an advisory of the commit (rule "function"), or the only change of a file that it names
    (rule "file"). match="substring" takes a name anywhere in the text, as a contrast to whole identifiers."""
    survivors = changed if survivors is None else survivors
    fold = (lambda c: c) if case else F.lower
    out = []
    if "function" in rules:
        if match == "word":
            named = mentions(linked, identifiers(F.col("description")), case).withColumnRenamed("name", "_name")
            hit = survivors.join(named, (survivors["commit_id"] == named["commit_id"]) & (fold(F.col("function_name")) == F.col("_name")), "left_semi")
        else:
            texts = linked.select(F.col("commit_id").alias("_commit"), "description")
            hit = survivors.join(texts, (F.col("commit_id") == F.col("_commit")) & F.contains(fold(F.col("description")), fold(F.col("function_name"))), "left_semi")
        out.append(hit.withColumn("rule", F.lit("function")))
    if "file" in rules:
        named = mentions(linked, file_names(F.col("description")), case).withColumnRenamed("name", "_name")
        alone = survivors.join(only_change_of(changed, ["commit_id", "file_name"]), ["commit_id", "file_name"], "left_semi")
        base = F.element_at(F.split("file_name", "/"), -1)
        hit = alone.join(named, (alone["commit_id"] == named["commit_id"]) & (fold(base) == F.col("_name")), "left_semi")
        out.append(hit.select(*survivors.columns).withColumn("rule", F.lit("file")))
    merged = out[0]
    for x in out[1:]:
        merged = merged.unionByName(x)
    return merged


def merge_labels(*labelled: DataFrame) -> DataFrame:
    """(commit_id, file_name, function_id, rules): which labelers fired, sorted."""
    rows = [x.select("commit_id", "file_name", "function_id", "rule") for x in labelled]
    merged = rows[0]
    for x in rows[1:]:
        merged = merged.unionByName(x)
    return merged.groupBy("commit_id", "file_name", "function_id").agg(F.array_join(F.sort_array(F.collect_set("rule")), "+").alias("rules"))


def label_flawed(changed: DataFrame, advisories: DataFrame, survivors: DataFrame | None = None) -> DataFrame:
    """Survivors that either labeler marks, with the rules that fired, once per digest."""
    survivors = dedup(changed, key="pre_digest") if survivors is None else survivors
    linked = link_advisories(changed, advisories)
    fired = merge_labels(label_sole_change(changed, survivors), label_advisory(changed, linked, survivors))
    return dedup(survivors.join(fired, ["commit_id", "file_name", "function_id"]), key="pre_digest")


def keep_labelled_commits(df: DataFrame, flawed: DataFrame) -> DataFrame:
    return df.join(flawed.select("commit_id").distinct(), "commit_id", "left_semi")


def derive_benign(flawed: DataFrame, unchanged: DataFrame) -> DataFrame:
    """Fixed versions of the flawed, and unchanged functions of their commits."""
    return as_samples(flawed, "post", 0).unionByName(as_samples(keep_labelled_commits(unchanged, flawed), "same", 0))


def samples_of(flawed: DataFrame, unchanged: DataFrame) -> DataFrame:
    """Samples of both labels: the flawed, their fixes and the unchanged functions of their commits, each text once,
    no benign copy of a flawed one. flawed is used several times; give it as a table."""
    marked = as_samples(flawed, "pre", 1).join(flawed.select("commit_id", "file_name", "function_id", "rules"), ["commit_id", "file_name", "function_id"])
    benign = dedup(derive_benign(flawed, unchanged), key="digest", order_by=("commit_ts", "commit_id", "file_name", "function_id", "side"))
    benign = benign.join(marked.select("digest"), "digest", "left_anti").withColumn("rules", F.lit(""))
    return marked.select(*SAMPLE, "rules").unionByName(benign.select(*SAMPLE, "rules"))


def build_corpus(changes: DataFrame, advisories: DataFrame) -> DataFrame:
    """The whole construction: no-op removal, first de-duplication, labelers, second de-duplication, benign samples,
    removal of benign copies of flawed ones. changes need digests; the result has samples with rules.

    Both labelers branch from the survivors, and the benign side from the flawed, so those two are written."""
    changed, unchanged = split_changed(changes)
    survivors = written(dedup(changed, key="pre_digest"), "survivors")
    return samples_of(written(label_flawed(changed, advisories, survivors), "flawed"), unchanged)


def compare_labelers(labelled: dict[str, DataFrame], reference: str) -> DataFrame:
    """labeler, n_flawed, n_overlap (with the reference), pct_in_reference; frames need commit_id, function_id."""
    keys = ["commit_id", "function_id"]
    base = labelled[reference].select(*keys).distinct().withColumn("in_reference", F.lit(1))
    out = None
    for name, df in labelled.items():
        joined = df.select(*keys).distinct().join(base, keys, "left")
        row = joined.agg(F.lit(name).alias("labeler"), F.count(F.lit(1)).alias("n_flawed"), F.count("in_reference").alias("n_overlap"))
        row = row.withColumn("pct_in_reference", F.round(F.try_divide(100.0 * F.col("n_overlap"), F.col("n_flawed")), 4))
        out = row if out is None else out.unionByName(row)
    return out
