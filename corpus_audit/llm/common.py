"""Helpers shared by the training-data operators."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid

from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

WORD_GAP = "[\\x20\\x09-\\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share; a temporary one only where the session names none."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="shared-"))
    return spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()


def written(df: DataFrame, name: str, codec: str | None = None) -> DataFrame:
    """df as a Parquet table in the shared folder: cuts the lineage and survives lost executors."""
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path, compression=codec)
    tidied(df.sparkSession)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def tidied(spark: SparkSession, seconds: float = 2.0, last: list[float] = [0.0]) -> None:  # noqa: B006
    """Collects the driver's garbage, at most once in ``seconds``.

    Spark removes the shuffle files and broadcasts of finished queries only when the driver's JVM has collected what
    named them; left to itself it first fills its heap, and the disk meanwhile."""
    if time.monotonic() - last[0] >= seconds:
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        last[0] = time.monotonic()


class Shared:
    """A bounded object broadcast by value, with its classes, so executors need not have this package.

    A worker process unpacks it once; what the object remembers lasts over that process's tasks."""

    def __init__(self, spark: SparkSession, value: object):
        self._packed = spark.sparkContext.broadcast(cloudpickle.dumps(value))
        tidied(spark)

    @property
    def value(self):
        packed = self._packed
        if "_unpacked" not in packed.__dict__:
            packed._unpacked = cloudpickle.loads(packed.value)
        return packed._unpacked

    def done(self) -> None:
        """To be called when no job will need it any more."""
        self._packed.destroy()


def n_words(text: Column) -> Column:
    """Number of maximal runs of characters outside the six ASCII blanks; null counts 0."""
    gaps = F.regexp_replace(F.coalesce(text, F.lit("")), WORD_GAP, " ")
    trimmed = F.trim(gaps)
    return F.when(trimmed == "", 0).otherwise(F.length(trimmed) - F.length(F.translate(trimmed, " ", "")) + 1).cast("long")


def spans_of(text: Column, pattern: Column | str) -> Column:
    """array<struct<start,end,value>> of the leftmost non-overlapping matches, in code points.

    The pieces between matches and the matches themselves alternate, so running lengths give the offsets.
    The pattern must not match the empty string."""
    pattern = F.lit(pattern) if isinstance(pattern, str) else pattern
    values = F.regexp_extract_all(text, pattern, F.lit(0))
    gaps = F.split(text, pattern, -1)
    paired = F.arrays_zip(F.slice(gaps, F.lit(1), F.size(values)).alias("gap"), values.alias("value"))
    return F.flatten(_shifted(F.transform(chunks(paired), _laid_out)))


CHUNK = 256
SPANS = "array<struct<start:bigint,end:bigint,value:string>>"


def chunks(items: Column) -> Column:
    """items in runs of CHUNK: folds that append copy what they have, so they run over one run at a time."""

    def cut(whole: Column) -> Column:
        n = F.ceil(F.size(whole) / CHUNK).cast("int")
        return F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.slice(whole, (i - 1) * CHUNK + 1, F.lit(CHUNK)))

    return bound(items, cut)


def bound(value: Column, use) -> Column:
    """use(value) with value computed once: an expression that a lambda names is computed again for each element."""
    return F.transform(F.array(value), use)[0]


def _laid_out(run: Column) -> Column:
    """struct<at,found>: the spans of a run of (gap, value), counted from its begin, and its length."""
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast(SPANS).alias("found"))

    def step(acc: Column, x: Column) -> Column:
        begin = acc["at"] + F.length(x["gap"])
        end = begin + F.length(x["value"])
        span = F.struct(begin.cast("long").alias("start"), end.cast("long").alias("end"), x["value"].alias("value"))
        return F.struct(end.cast("long").alias("at"), F.concat(acc["found"], F.array(span)).alias("found"))

    return F.aggregate(run, start, step)


def _shifted(runs: Column) -> Column:
    """The spans of each run, counted from the begin of the first."""
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast(f"array<{SPANS}>").alias("found"))

    def step(acc: Column, run: Column) -> Column:
        moved = F.transform(run["found"], lambda s: F.struct((s["start"] + acc["at"]).alias("start"), (s["end"] + acc["at"]).alias("end"), s["value"].alias("value")))
        return F.struct((acc["at"] + run["at"]).alias("at"), F.concat(acc["found"], F.array(moved)).alias("found"))

    return F.aggregate(runs, start, step, lambda acc: acc["found"])
