"""The engine's functions and bindings for SQL users."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..sources.tables import TABLES, load


def register_functions(spark: SparkSession) -> None:
    """strip_format, norm_digest, hash_bucket as temporary SQL functions; mention_tokens as a table function."""
    spark.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION strip_format(t STRING) RETURNS STRING RETURN translate(t, ' \t\n\r', '')")
    spark.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION norm_digest(t STRING) RETURNS STRING RETURN md5(translate(t, ' \t\n\r', ''))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hash_bucket(seed STRING, k STRING) RETURNS BIGINT RETURN cast(conv(substr(md5(concat(seed, k)), 1, 8), 16, 10) AS BIGINT) % 10000")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION miss_rate(fn BIGINT, tp BIGINT) RETURNS DOUBLE RETURN try_divide(fn, fn + tp)")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION mention_tokens(t STRING) RETURNS TABLE(token STRING, pos INT) "
        "RETURN SELECT x.col, x.pos FROM (SELECT posexplode(regexp_extract_all(coalesce(mention_tokens.t, ''), '[A-Za-z_][A-Za-z0-9_]*', 0)) AS (pos, col)) x"
    )


def register_tables(spark: SparkSession, sf_dir: str) -> None:
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
