"""How the given tables play the roles of the methods, in Spark and (as common table expressions) in DuckDB."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.text import bucket, digest, tokens
from .operators import history as hist
from .operators import labelers
from .operators.dedup import dedup, split_changed
from .plans.materialise import written
from .sources.tables import load

STRIP_SQL = "translate({0}, ' ' || chr(9) || chr(10) || chr(13), '')"


def bucket_sql(key: str, seed: str) -> str:
    return f"(('0x' || substr(md5('{seed}' || {key}), 1, 8))::bigint % 10000)"


KEYS_SQL = """
l as (select l_orderkey, l_partkey, l_suppkey, l_returnflag as f, l_linestatus as s,
  row_number() over (partition by l_orderkey, l_partkey order by l_linenumber, l_suppkey, l_returnflag, l_linestatus) as rn from lineitem),
keys as (select l_orderkey as commit_id, o_orderdate as commit_ts, o_custkey as project_id, p_brand as weakness,
  o_orderpriority in ('1-URGENT', '2-HIGH') as is_security, 'mod' || (l_suppkey % 5) || '.c' as file_name, l_partkey as function_id,
  'fn_' || l_partkey as function_name, l_orderkey % 16 as revision,
  case when f = 'R' then 'guard appended' when f = 'N' and s = 'F' then 'reformatted' when f = 'N' then 'deleted'
    when s = 'F' then 'first half' else 'substituted' end as variant
  from l join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey where rn = 1 and l_partkey in (select doc_id from documents))"""

H_SQL = (
    KEYS_SQL
    + f""",
v as (select distinct function_id, revision, variant from keys where is_security),
tx as (select v.*, text || ' // rev ' || revision as pre_text from v join documents on doc_id = function_id),
ty as (select *, case variant when 'reformatted' then replace(pre_text, ' ', chr(9) || chr(10)) when 'guard appended' then pre_text || ' if (checked) return;'
  when 'first half' then substr(pre_text, 1, length(pre_text) // 2) when 'substituted' then replace(pre_text, 'e', 'a') end as post_text from tx),
td as (select function_id, revision, variant, md5({STRIP_SQL.format("pre_text")}) as pre_digest, md5({STRIP_SQL.format("post_text")}) as post_digest from ty),
h as (select keys.*, pre_digest, post_digest from keys join td using (function_id, revision, variant) where is_security),
changed as (select * from h where pre_digest is distinct from post_digest),
unchanged as (select * from h where pre_digest is not distinct from post_digest),
surv as (select * exclude (rn) from (select *, row_number() over (partition by pre_digest order by commit_ts, commit_id, file_name, function_id) as rn from changed) where rn = 1)"""
)

BLANKET_SQL = """
blanket as (
  select commit_id || ':' || function_id || ':pre' as sample_id, commit_id, commit_ts, function_id, 'pre' as side, pre_digest as digest, 1 as label from changed
  union all select commit_id || ':' || function_id || ':post', commit_id, commit_ts, function_id, 'post', post_digest, 0 from changed where post_digest is not null
  union all select commit_id || ':' || function_id || ':same', commit_id, commit_ts, function_id, 'same', pre_digest, 0 from unchanged)"""

LABELS_SQL = """
sole as (select commit_id from changed group by commit_id having count(distinct file_name || '/' || function_id) = 1),
least as (select commit_id, arg_min(function_name, function_id) as fn, arg_min(file_name, function_id) as fl, arg_max(function_name, function_id) as gr from keys where is_security group by commit_id),
adv as (select commit_id, 'ADV-' || commit_id as advisory_id, case commit_id % 3 when 0 then 'Overflow in ' || fn || ' and ' || gr || '().'
  when 1 then 'Overflow in src/' || fl || ' found.' else 'Overflow found.' end || ' Not concerned: ' || fn || '_legacy.' as description from least),
fn_named as (select distinct commit_id, unnest(regexp_extract_all(description, '[A-Za-z_][A-Za-z0-9_]*')) as name from adv),
fl_named as (select distinct commit_id, unnest(regexp_extract_all(description, '[A-Za-z0-9_-]+\\.[A-Za-z0-9]+')) as name from adv),
alone as (select commit_id, file_name from changed group by 1, 2 having count(distinct function_id) = 1),
fired as (
  select commit_id, file_name, function_id, 'sole' as rule from surv where commit_id in (select commit_id from sole)
  union all select s.commit_id, s.file_name, function_id, 'function' from surv s join fn_named n on s.commit_id = n.commit_id and s.function_name = n.name
  union all select s.commit_id, s.file_name, function_id, 'file' from surv s join alone using (commit_id, file_name) join fl_named n on s.commit_id = n.commit_id and s.file_name = n.name),
merged as (select commit_id, file_name, function_id, string_agg(distinct rule, '+' order by rule) as rules from fired group by 1, 2, 3),
flawed as (select surv.*, rules from surv join merged using (commit_id, file_name, function_id))"""

SAMPLES_SQL = """
fresh as (
  select commit_id || ':' || function_id || ':post' as sample_id, commit_id, commit_ts, project_id, weakness, file_name, function_id, 'post' as side, post_digest as digest from flawed where post_digest is not null
  union all select commit_id || ':' || function_id || ':same', commit_id, commit_ts, project_id, weakness, file_name, function_id, 'same', pre_digest from unchanged where commit_id in (select commit_id from flawed)),
benign as (select * exclude (rn) from (select *, row_number() over (partition by digest order by commit_ts, commit_id, file_name, function_id, side) as rn from fresh)
  where rn = 1 and digest not in (select pre_digest from flawed)),
samples as (
  select commit_id || ':' || function_id || ':pre' as sample_id, commit_id, commit_ts, project_id, weakness, file_name, function_id, 'pre' as side, pre_digest as digest, 1 as label, rules from flawed
  union all select *, 0 as label, '' as rules from benign)"""


def chronological_sql(source: str, out: str, value: str) -> str:
    return f"""
{out}_c as (select commit_id, min(commit_ts) as ts, {value} as n from {source} group by commit_id),
{out}_b as (select commit_id, coalesce(sum(n) over (order by ts, commit_id rows between unbounded preceding and 1 preceding), 0) as b, sum(n) over () as total from {out}_c),
{out} as (select s.*, case when b * 10000 < total * 8000 then 'train' when b * 10000 < total * 9000 then 'dev' else 'test' end as split from {source} s join {out}_b using (commit_id))"""


def random_sql(source: str, out: str, key: str, seed: str = "s") -> str:
    b = bucket_sql(key, seed)
    return f"{out} as (select *, case when {b} < 8000 then 'train' when {b} < 9000 then 'dev' else 'test' end as split from {source})"


NATURAL_SQL = f"""
dated as (select o_orderkey // 3 as commit_id, min(o_orderdate) as commit_ts from orders group by 1),
nat as (select doc_id::varchar as sample_id, doc_id, text, source, case when quality = 0 then 1 else 0 end as label, toxic, doc_id // 3 as commit_id,
  md5({STRIP_SQL.format("text")}) as digest, md5(text) as raw_digest from documents join labels using (doc_id))"""


class History:
    """The pipeline's intermediate frames on binding H."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir
        self.keys = hist.change_keys(spark, sf_dir)
        # every branch below starts from the digests; texts are read and hashed once
        self.changes = written(hist.change_history(spark, sf_dir), "changes")
        self.changed, self.unchanged = split_changed(self.changes)
        self.advisories = written(hist.advisories(self.keys), "advisories")
        self._survivors = self._flawed = self._samples = None

    def survivors(self) -> DataFrame:
        if self._survivors is None:
            self._survivors = written(dedup(self.changed, key="pre_digest"), "survivors")
        return self._survivors

    def linked(self) -> DataFrame:
        return labelers.link_advisories(self.changed, self.advisories)

    def blanket(self) -> DataFrame:
        return labelers.label_blanket(self.changed, self.unchanged)

    def flawed(self) -> DataFrame:
        if self._flawed is None:
            self._flawed = written(labelers.label_flawed(self.changed, self.advisories, self.survivors()), "flawed")
        return self._flawed

    def samples(self) -> DataFrame:
        if self._samples is None:
            self._samples = written(labelers.samples_of(self.flawed(), self.unchanged), "samples")
        return self._samples


def natural(spark: SparkSession, sf_dir: str, label: str = "quality") -> DataFrame:
    rows = hist.natural_samples(spark, sf_dir, label)
    return rows.withColumn("digest", digest(F.col("text"))).withColumn("raw_digest", digest(F.col("text"), normalize=False))


def scores_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """S1: score value, label error."""
    return load(spark, sf_dir, "events").select(F.col("event_id").cast("string").alias("sample_id"), (F.col("user_id") % 5).alias("grp"), (F.col("event_type") == "error").cast("int").alias("label"), F.col("value").alias("score"))


def scores_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """S2: score discount (11 values, so ties are large), label returned."""
    return load(spark, sf_dir, "lineitem").select(F.col("l_linestatus").alias("grp"), (F.col("l_returnflag") == "R").cast("int").alias("label"), F.col("l_discount").alias("score"))


def repeated_share(text: Column) -> Column:
    words = tokens(text)
    return F.when(F.size(words) == 0, 0.0).otherwise(F.round(1 - F.size(F.array_distinct(words)) / F.size(words), 9))


def scores_documents(spark: SparkSession, sf_dir: str, label: str = "quality") -> DataFrame:
    """S3: share of repeated words."""
    return hist.natural_samples(spark, sf_dir, label).select("sample_id", F.col("source").alias("grp"), "label", repeated_share(F.col("text")).alias("score"))


def scores_embeddings(spark: SparkSession, sf_dir: str, label: int = 0) -> DataFrame:
    """S4: cosine to the class centroid (in-sample)."""
    rows = load(spark, sf_dir, "embeddings").select("vec_id", (F.col("label") == label).cast("int").alias("label"), F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    parts = rows.where("label = 1").select(F.posexplode("v").alias("i", "x")).groupBy("i").agg(F.avg("x").alias("m"))
    centroid = parts.agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "m"))), lambda s: s["m"]).alias("c"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    both = rows.crossJoin(F.broadcast(centroid))
    return both.select(F.col("vec_id").cast("string").alias("sample_id"), "label", (dot(F.col("v"), F.col("c")) / F.sqrt(dot(F.col("v"), F.col("v")) * dot(F.col("c"), F.col("c")))).alias("score"))


def vectors(spark: SparkSession, sf_dir: str, size: int = 32) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select("vec_id", F.floor(F.col("vec_id") / size).alias("batch_id"), "embedding", "label")


VOTES_SQL = f"""
n3 as (select *, {bucket_sql("doc_id", "vote")} as b, {bucket_sql("doc_id", "revised")} as rb from nat),
votes as (
  select source as corpus, sample_id, 1 as annotator, case when label = 1 then 'flawed' else 'benign' end as verdict, b from n3
  union all select source, sample_id, 2, case when toxic = 1 then 'flawed' else 'benign' end, b from n3
  union all select source, sample_id, 3, case when b < 4500 then 'flawed' when b < 9500 then 'benign' else 'unsure' end, b from n3),
cat as (select *, case when verdict = 'benign' then ['cross-function', 'consistency', 'unrelated'][((b + annotator) % 3 + 1)::int] end as category from votes),
revised as (select source as corpus, sample_id, a as annotator, case when rb + a * 1000 < 6000 then 'flawed' else 'benign' end as verdict from n3, range(1, 4) r(a) where doc_id % 2 = 0)"""


def votes(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(first round with categories, revised round of the even ids): quality, toxicity and a hashed third voter."""
    rows = natural(spark, sf_dir).join(load(spark, sf_dir, "labels").select("doc_id", "toxic"), "doc_id")
    rows = rows.withColumn("b", bucket(F.col("doc_id"), "vote")).withColumn("rb", bucket(F.col("doc_id"), "revised"))
    call = lambda c: F.when(c, "flawed").otherwise("benign")
    third = F.when(F.col("b") < 4500, "flawed").when(F.col("b") < 9500, "benign").otherwise("unsure")
    each = [(1, call(F.col("label") == 1)), (2, call(F.col("toxic") == 1)), (3, third)]
    flat = rows.select("source", "sample_id", "b", F.explode(F.array(*[F.struct(F.lit(n).alias("annotator"), v.alias("verdict")) for n, v in each])).alias("x")).select(F.col("source").alias("corpus"), "sample_id", "b", "x.*")
    reasons = F.array(F.lit("cross-function"), F.lit("consistency"), F.lit("unrelated"))
    first = flat.withColumn("category", F.when(F.col("verdict") == "benign", F.element_at(reasons, ((F.col("b") + F.col("annotator")) % 3 + 1).cast("int")))).drop("b")
    again = rows.where("doc_id % 2 = 0").select(F.col("source").alias("corpus"), "sample_id", "rb", F.explode(F.array(*[F.lit(n) for n in (1, 2, 3)])).alias("annotator"))
    return first, again.select("corpus", "sample_id", "annotator", call(F.col("rb") + F.col("annotator") * 1000 < 6000).alias("verdict"))
