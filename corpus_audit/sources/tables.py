"""Given tables with declared schemas, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.schema(TABLES[name]).parquet(f"{sf_dir}/{name}.parquet")


def read_json_lines(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """Votes, advisories or functions as JSON lines, with a declared schema."""
    return spark.read.schema(schema).json(path)


def read_csv(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).option("header", True).csv(path)


def read_source_tree(spark: SparkSession, path: str, glob: str = "*") -> DataFrame:
    """file_name, text of every file below a folder."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", True).option("pathGlobFilter", glob).load(path)
    return files.selectExpr("path AS file_name", "cast(content AS string) AS text")


def save_samples(samples: DataFrame, path: str) -> None:
    """Partitioned by split; a rerun replaces the splits that it writes."""
    samples.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("split").parquet(path)


def save_bucketed(samples: DataFrame, name: str, buckets: int = 64) -> None:
    """A table bucketed by commit: commit-local labelers, benign derivation and pairing then need no shuffle."""
    samples.write.mode("overwrite").bucketBy(buckets, "commit_id").sortBy("commit_id").saveAsTable(name)


def save_json_lines(df: DataFrame, column: str, path: str) -> None:
    """One JSON document a line, as fine-tuning services take them."""
    df.selectExpr(f"to_json({column}) AS value").write.mode("overwrite").text(path)
