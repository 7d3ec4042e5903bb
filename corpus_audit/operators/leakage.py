"""Leakage between training and test data."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import runs, strip_format, tokens


def copy_rate(samples: DataFrame, only_flawed: bool = True, key: str = "digest") -> DataFrame:
    """n_test, n_copied, pct: test samples (flawed ones by default) whose digest occurs anywhere in train."""
    test = samples.where("split = 'test'")
    if only_flawed:
        test = test.where("label = 1")
    train = samples.where("split = 'train'").select(F.col(key).alias("_train")).distinct()
    joined = test.join(train, F.col(key) == F.col("_train"), "left")
    out = joined.agg(F.count(F.lit(1)).alias("n_test"), F.count("_train").alias("n_copied"))
    return out.withColumn("pct", F.round(F.try_divide(100.0 * F.col("n_copied"), F.col("n_test")), 6))


def copy_rate_by_twin(samples: DataFrame, key: str = "digest") -> DataFrame:
    """Copied test samples by their own label and the label of the train twin."""
    test = samples.where("split = 'test'").select(F.col(key).alias("k"), F.col("label").alias("test_label"))
    twin = samples.where("split = 'train'").groupBy(F.col(key).alias("k")).agg(F.when(F.min("label") != F.max("label"), "both").when(F.max("label") == 1, "flawed").otherwise("benign").alias("train_label"))
    return test.join(twin, "k").groupBy("test_label", "train_label").agg(F.count(F.lit(1)).alias("n"))


def copy_rate_bruteforce(samples: DataFrame, text: str = "text") -> DataFrame:
    """The exhaustive comparison that hashing replaces; for tests on small frames only."""
    test = samples.where("split = 'test' AND label = 1").select("sample_id", strip_format(F.col(text)).alias("a"))
    train = samples.where("split = 'train'").select(strip_format(F.col(text)).alias("b"))
    hit = test.crossJoin(train).where("a = b").select("sample_id").distinct()
    return test.join(hit.withColumn("hit", F.lit(1)), "sample_id", "left").agg(F.count(F.lit(1)).alias("n_test"), F.count("hit").alias("n_copied"))


def copy_report(samples: DataFrame) -> DataFrame:
    """Digests with several rows: counts, splits, first and last commit, and the likely cause."""
    per = samples.groupBy("digest").agg(
        F.count(F.lit(1)).alias("n"), F.min("commit_id").alias("first_commit"), F.max("commit_id").alias("last_commit"),
        F.array_join(F.sort_array(F.collect_set("split")), "+").alias("splits"), F.min("label").alias("_lo"), F.max("label").alias("_hi"), F.min("side").alias("_s0"), F.max("side").alias("_s1"),
    )
    cause = F.when((F.col("_lo") != F.col("_hi")) & (F.col("_s0") != F.col("_s1")), "before and after").when(F.col("_lo") != F.col("_hi"), "contradictory labels").when(F.col("first_commit") == F.col("last_commit"), "same commit").otherwise("repeated across commits")
    return per.where("n > 1").select("digest", "n", "first_commit", "last_commit", "splits", cause.alias("cause"))


def time_travel(samples: DataFrame) -> DataFrame:
    """n_test, n_past_test (test rows older than the newest train row), n_train, n_future_train (train rows later
    than the oldest test row), pct_past_test."""
    ends = samples.agg(F.max(F.when(F.col("split") == "train", F.col("commit_ts"))).alias("_newest"), F.min(F.when(F.col("split") == "test", F.col("commit_ts"))).alias("_oldest"))
    rows = samples.select("split", "commit_ts").crossJoin(F.broadcast(ends))
    is_test, is_train = F.col("split") == "test", F.col("split") == "train"
    out = rows.agg(
        F.count_if(is_test).alias("n_test"), F.count_if(is_test & (F.col("commit_ts") < F.col("_newest"))).alias("n_past_test"),
        F.count_if(is_train).alias("n_train"), F.count_if(is_train & (F.col("commit_ts") > F.col("_oldest"))).alias("n_future_train"),
    )
    return out.withColumn("pct_past_test", F.round(F.try_divide(100.0 * F.col("n_past_test"), F.col("n_test")), 6))


def fix_leak(samples: DataFrame) -> DataFrame:
    """Functions whose fixed version trains while a flawed version of the same text is tested, counted over test rows."""
    fixed = samples.where("split = 'train' AND side = 'post'").select("function_id", F.col("commit_id").alias("fix_commit")).distinct()
    tested = samples.where("split = 'test' AND label = 1").select("function_id", "sample_id")
    hit = tested.join(fixed, "function_id", "left_semi")
    return hit.agg(F.count(F.lit(1)).alias("n_leaked"))


def straddling_commits(samples: DataFrame) -> DataFrame:
    per = samples.groupBy("commit_id").agg((F.min("split") != F.max("split")).alias("x"))
    return per.agg(F.count(F.lit(1)).alias("n_commits"), F.count_if("x").alias("n_straddling"))


def contained_in(train: DataFrame, items: DataFrame, k: int = 5, broadcast_items: int = 200_000) -> DataFrame:
    """(item_id, doc_id) where a train text holds a test passage.

    The second to (k+1)-th words of a passage are whole words wherever it stands, so their digest probes the k-grams
    of the train texts; hits are verified on the texts. Passages with fewer than k + 2 words compare directly."""
    words = tokens(F.col("text"))
    long_enough = F.size(words) >= k + 2
    probes = items.where(long_enough).select("item_id", F.col("text").alias("passage"), F.xxhash64(F.array_join(F.slice(words, 2, k), " ")).alias("gram"))
    grams_of = F.transform(runs(words, k), lambda x: F.xxhash64(x))
    if items.count() <= broadcast_items:
        # the sorted probe digests go to the scan as one array: a gram that probes nothing is never a row
        wanted = probes.agg(F.array_sort(F.collect_set("gram")).alias("wanted"))
        near = train.select("doc_id", grams_of.alias("own")).crossJoin(F.broadcast(wanted))
        grams = near.select("doc_id", F.explode(F.array_intersect("own", "wanted")).alias("gram"))
        probes = F.broadcast(probes)
    else:
        # texts stay behind while grams meet probes
        grams = train.select("doc_id", F.explode(F.array_distinct(grams_of)).alias("gram"))
    met = grams.join(probes, "gram").select("item_id", "doc_id", "passage").distinct()
    hits = met.join(train.select("doc_id", "text"), "doc_id").where(F.contains("text", "passage")).select("item_id", "doc_id")
    short = items.where(~long_enough).select("item_id", F.col("text").alias("passage"))
    rest = train.select("doc_id", "text").join(short, F.contains("text", "passage")).select("item_id", "doc_id")
    return hits.unionByName(rest).distinct()
