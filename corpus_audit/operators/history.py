"""Change histories: bindings of the given tables to commits, function changes and advisories; merging of sources."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import digest
from ..sources.tables import load

# How a (returnflag, linestatus) pair derives the post version.
GUARD = " if (checked) return;"
VARIANTS = {"N/F": "reformatted", "N/O": "deleted", "R": "guard appended", "A/F": "first half", "A/O": "substituted"}


def pre_text(text: Column, revision: Column) -> Column:
    return F.concat(text, F.lit(" // rev "), revision.cast("string"))


def post_text(pre: Column, variant: Column) -> Column:
    return (
        F.when(variant == "reformatted", F.replace(pre, F.lit(" "), F.lit("\t\n")))
        .when(variant == "guard appended", F.concat(pre, F.lit(GUARD)))
        .when(variant == "first half", F.substr(pre, F.lit(1), F.floor(F.length(pre) / 2).cast("int")))
        .when(variant == "substituted", F.replace(pre, F.lit("e"), F.lit("a")))
    )


def variant_of(flag: Column, status: Column) -> Column:
    return (
        F.when(flag == "R", "guard appended")
        .when((flag == "N") & (status == "F"), "reformatted")
        .when((flag == "N") & (status == "O"), "deleted")
        .when((flag == "A") & (status == "F"), "first half")
        .when((flag == "A") & (status == "O"), "substituted")
    )


def change_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per (commit, function), no texts: the keys, dates and the variant."""
    line = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", F.struct("l_linenumber", "l_suppkey", "l_returnflag", "l_linestatus").alias("x"))
    one = line.groupBy("l_orderkey", "l_partkey").agg(F.min("x").alias("x"))
    docs = load(spark, sf_dir, "documents").select("doc_id")
    part = load(spark, sf_dir, "part").select("p_partkey", "p_brand")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority")
    joined = one.join(docs, F.col("l_partkey") == F.col("doc_id"), "left_semi").join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(part, F.col("l_partkey") == F.col("p_partkey"))
    return joined.select(
        F.col("l_orderkey").alias("commit_id"),
        F.col("o_orderdate").alias("commit_ts"),
        F.col("o_custkey").alias("project_id"),
        F.col("p_brand").alias("weakness"),
        F.col("o_orderpriority").isin("1-URGENT", "2-HIGH").alias("is_security"),
        F.concat(F.lit("mod"), (F.col("x.l_suppkey") % 5).cast("string"), F.lit(".c")).alias("file_name"),
        F.col("l_partkey").alias("function_id"),
        F.concat(F.lit("fn_"), F.col("l_partkey").cast("string")).alias("function_name"),
        (F.col("l_orderkey") % 16).alias("revision"),
        variant_of(F.col("x.l_returnflag"), F.col("x.l_linestatus")).alias("variant"),
    )


def text_versions(spark: SparkSession, sf_dir: str, keys: DataFrame) -> DataFrame:
    """function_id, revision, variant with both texts: work on texts happens once per distinct version."""
    wanted = keys.select("function_id", "revision", "variant").distinct()
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("function_id"), "text")
    both = wanted.join(docs, "function_id").withColumn("pre_text", pre_text(F.col("text"), F.col("revision")))
    return both.withColumn("post_text", post_text(F.col("pre_text"), F.col("variant"))).drop("text")


def change_history(spark: SparkSession, sf_dir: str, security_only: bool = True) -> DataFrame:
    """Changes with digests of both versions (texts stay behind, see ``with_texts``)."""
    keys = change_keys(spark, sf_dir)
    if security_only:
        keys = keys.where("is_security")
    versions = text_versions(spark, sf_dir, keys).select(
        "function_id", "revision", "variant", digest(F.col("pre_text")).alias("pre_digest"), digest(F.col("post_text")).alias("post_digest")
    )
    return keys.join(versions, ["function_id", "revision", "variant"])


def with_texts(spark: SparkSession, sf_dir: str, changes: DataFrame) -> DataFrame:
    return changes.join(text_versions(spark, sf_dir, changes), ["function_id", "revision", "variant"])


def with_digests(changes: DataFrame, algo: str = "md5") -> DataFrame:
    """Any frame of changes that has texts, with pre_digest and post_digest."""
    return changes.withColumn("pre_digest", digest(F.col("pre_text"), algo=algo)).withColumn("post_digest", digest(F.col("post_text"), algo=algo))


def source_slices(keys: DataFrame, n: int = 4) -> dict[str, DataFrame]:
    """Overlapping source corpora, and one more that plays the excluded source."""
    found = {f"corpus{k}": keys.where((F.col("commit_id") % n == k) | (F.col("commit_id") % 10 == 0)) for k in range(n)}
    return found | {"declared": keys.where(F.col("commit_id") % 7 == 3)}


def merge_corpora(corpora: dict[str, DataFrame], exclude: tuple[str, ...] = (), key: tuple[str, ...] = ("commit_id", "file_name", "function_id")) -> DataFrame:
    """All sources but the excluded: one row per change with the sorted names of the sources that hold it."""
    named = [df.withColumn("corpus", F.lit(name)) for name, df in corpora.items() if name not in exclude]
    merged = named[0]
    for df in named[1:]:
        merged = merged.unionByName(df, allowMissingColumns=True)
    rest = [c for c in merged.columns if c not in (*key, "corpus")]
    return merged.groupBy(*key).agg(*[F.min(c).alias(c) for c in rest], F.sort_array(F.collect_set("corpus")).alias("corpora"))


def advisories(keys: DataFrame) -> DataFrame:
    """One advisory per security commit. By commit: two functions named, a file named, or neither; a longer
    identifier always stands by as a decoy."""
    least = F.min_by(F.struct("file_name", "function_name"), F.struct("function_id", "file_name"))
    per = keys.where("is_security").groupBy("commit_id").agg(least.alias("least"), F.max_by("function_name", "function_id").alias("greatest"))
    decoy = F.concat(F.lit(" Not concerned: "), F.col("least.function_name"), F.lit("_legacy."))
    kind = F.col("commit_id") % 3
    body = (
        F.when(kind == 0, F.concat(F.lit("Overflow in "), F.col("least.function_name"), F.lit(" and "), F.col("greatest"), F.lit("().")))
        .when(kind == 1, F.concat(F.lit("Overflow in src/"), F.col("least.file_name"), F.lit(" found.")))
        .otherwise(F.lit("Overflow found."))
    )
    return per.select(F.concat(F.lit("ADV-"), F.col("commit_id").cast("string")).alias("advisory_id"), "commit_id", F.concat(body, decoy).alias("description"))


def conversation_changes(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Natural mention texts: turn 0 describes, each later turn is a function named by its first word."""
    rows = load(spark, sf_dir, "conversations")
    name = F.regexp_extract("text", r"^[^A-Za-z_]*([A-Za-z_][A-Za-z0-9_]*)", 1)
    changes = rows.where("turn > 0").select(F.col("conv_id").alias("commit_id"), F.col("turn").alias("function_id"), name.alias("function_name"), F.lit("talk").alias("file_name")).where("function_name <> ''")
    described = rows.where("turn = 0").select(F.concat(F.lit("TALK-"), F.col("conv_id").cast("string")).alias("advisory_id"), F.col("conv_id").alias("commit_id"), F.col("text").alias("description"))
    return changes, described


def natural_samples(spark: SparkSession, sf_dir: str, label: str = "quality") -> DataFrame:
    """Documents with a label as samples: quality 0 or toxic 1 counts as flawed; dates come from the order of that id,
    commits are runs of three ids with their earliest date."""
    docs, labels, orders = (load(spark, sf_dir, t) for t in ("documents", "labels", "orders"))
    flawed = (F.col("quality") == 0) if label == "quality" else (F.col("toxic") == 1)
    dated = orders.select(F.floor(F.col("o_orderkey") / 3).alias("commit_id"), "o_orderdate").groupBy("commit_id").agg(F.min("o_orderdate").alias("commit_ts"))
    rows = docs.join(labels, "doc_id").select("doc_id", "text", "source", flawed.cast("int").alias("label"), F.floor(F.col("doc_id") / 3).alias("commit_id"))
    return rows.join(dated, "commit_id", "left").select(F.col("doc_id").cast("string").alias("sample_id"), "doc_id", "text", "source", "label", "commit_id", "commit_ts")


def attach_context(samples: DataFrame, changes: DataFrame, scope: str = "commit", most: int | None = 20) -> DataFrame:
    """samples with context: up to ``most`` (None: all) other functions of the same commit (or file in it), by function id."""
    key = ["commit_id"] if scope == "commit" else ["commit_id", "file_name"]
    others = changes.select(*key, F.struct("function_id", "function_name", F.col("pre_digest").alias("digest")).alias("other"))
    joined = samples.select("sample_id", "function_id", *key).join(others, key).where(F.col("function_id") != F.col("other.function_id"))
    every = F.sort_array(F.collect_set("other"))
    context = joined.groupBy("sample_id").agg((every if most is None else F.slice(every, 1, most)).alias("context"))
    return samples.join(context, "sample_id", "left")
