"""The training-data queries (spark, sf_dir) -> DataFrame and the DuckDB SQL that checks them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann_postings, chat, exact_topk, line_templates, mixing, ngram_join, pii, quality_fm, toxicity_knn
from .common import table
from .piece_lattice import encode, load

PLANTED_CONVERSATION = (-7, ("user", "assistant"), "</s>[INST] ok [/INST]")  # fixed value


def tokenizer_path(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(pii.find_spans(table(spark, sf_dir, "documents")))


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.digest(ngram_join.near_duplicates(table(spark, sf_dir, "documents"), n=4, percent=85))


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.digest(mixing.mix(table(spark, sf_dir, "documents"), weights=(5, 2, 1), share=1.5, cap=2))


def op4_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations")
    conv, roles, text = PLANTED_CONVERSATION
    planted = spark.createDataFrame([(conv, turn, role, text) for turn, role in enumerate(roles)], "conv_id long, turn long, role string, text string")
    return chat.digest(chat.format_conversations(rows.select("conv_id", "turn", "role", "text").unionByName(planted)))


def op5_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(table(spark, sf_dir, "documents"), load(tokenizer_path()))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_fm.quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_topk.top_k(table(spark, sf_dir, "embeddings"), k=10, query_step=100, scale=1024)


def op8_nearest_postings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann_postings.nearest(table(spark, sf_dir, "embeddings"), k=5, query_step=50)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity_knn.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_line_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_templates.digest(table(spark, sf_dir, "documents"))


def queries() -> dict:
    import corpus_pipeline

    found = {f.__name__: f for f in (op1_pii, op2_ngram_jaccard_join, op3_mixing, op4_chat_format, op5_pieces, op6_quality, op7_exact_topk, op8_nearest_postings, op9_toxicity, op10_line_templates)}
    return found | {"pipeline": corpus_pipeline.run}


OP2_SQL = r"""
with recursive w as (
  select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w
  from documents),
s as (
  select doc_id, unnest(case when len(w) = 0 then [] when len(w) < 4 then [array_to_string(w, ' ')]
    else list_distinct(list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i+3], ' '))) end) as g
  from w),
n as (select doc_id, count(*) as n from s group by doc_id),
pairs as (select a.doc_id as a, b.doc_id as b, count(*) as i from s a join s b on a.g = b.g and a.doc_id < b.doc_id group by 1, 2),
links as (select a, b from pairs join n x on a = x.doc_id join n y on b = y.doc_id where 100 * i >= 85 * (x.n + y.n - i)),
both_ways as (select a, b from links union all select b, a from links),
reach as (select doc_id as a, doc_id as b from documents union select r.a, l.b from reach r join both_ways l on r.b = l.a),
least_id as (select a, min(b) as m from reach group by a)
select d.doc_id, coalesce(n.n, 0) as n_shingles, m as component_id
from documents d left join n using (doc_id) join least_id on d.doc_id = a
"""

OP3_SQL = r"""
with s as (
  select doc_id, source, md5(doc_id::varchar || chr(10) || coalesce(text, '')) as k,
    len(list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> ''))::bigint as size
  from documents),
p as (select source, sum(size)::bigint as source_size from s group by source),
v as (select *, [5, 2, 1][((row_number() over (order by source asc nulls last) - 1) % 3 + 1)::int] as weight from p),
lv as (
  select *, (sum(source_size) over () * 1.5::double - coalesce(sum(source_size * 2) over (order by source_size / weight, source asc nulls last rows between unbounded preceding and 1 preceding), 0))
    / sum(weight) over (order by source_size / weight, source asc nulls last rows between current row and unbounded following) as level
  from v),
r as (select level from lv where level * weight <= source_size * 2 order by source_size / weight, level limit 1),
t as (
  select *, coalesce(least((source_size * 2)::double, weight * (select level from r)), (source_size * 2)::double) as target from lv),
c as (
  select source, source_size, target, (sum(target) over q - target) / sum(target) over () as low, sum(target) over q / sum(target) over () as high
  from t window q as (order by source asc nulls last rows between unbounded preceding and current row)),
total as (select sum(target) as total from t),
slots as (
  select id as slot, ((id % 2147483648) * 2654435769 % 4294967296) / 4294967296 as u
  from total, range((case when total > 0 then floor(total * 1.02 / 128)::bigint + 64 else 0 end)::bigint) g(id)),
got as (select source, count(*) as n from slots join c on u >= low and u < high group by source),
filled as (select c.*, least(coalesce(n, 0) * 128, floor(target)) as words from c left join got on c.source is not distinct from got.source),
placed as (
  select s.*, coalesce(sum(size) over (partition by source order by k rows between unbounded preceding and 1 preceding), 0) as b from s)
select doc_id, size, source_size, target,
  (greatest(0, least(b + size, words) - b) + greatest(0, least(b + source_size + size, words) - b - source_size))::bigint as taken
from placed join filled on placed.source is not distinct from filled.source
"""

OP4_SQL = r"""
with c as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -7, 0, 'user', '</s>[INST] ok [/INST]' union all select -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
m as (
  select *, regexp_matches(text, '[\[<](/?INST\]|/?s1?>|</?SYS>>|<OUT>>|</?TURN>>|<SAYS>>)') or regexp_matches(role, '[\[<](/?INST\]|/?s1?>|</?SYS>>|<OUT>>|</?TURN>>|<SAYS>>)') as clash
  from c),
lv as (select *, bool_or(clash) over (partition by conv_id) as escaped from m),
e as (
  select *, case when escaped then regexp_replace(text, '([\[<])(\\*)(/?INST\]|/?s1?>|</?SYS>>|<OUT>>|</?TURN>>|<SAYS>>)', '\1\\\2\3', 'g') else text end as shown from lv)
select conv_id, count(*) as n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
  coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (role = 'assistant'), '')) as loss_sha256,
  (any_value(case when escaped then 4 else 3 end) + sum(length(shown) + case role when 'system' then 15 when 'user' then 13 when 'assistant' then 11 else 25 + length(role) end))::bigint as formatted_chars
from e group by conv_id
"""

OP7_SQL = r"""
with v as (
  select vec_id, list_transform(embedding, lambda x: floor(1024 * x::double)::bigint) as v from embeddings
  where embedding is not null and vec_id is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
s as (
  select q.vec_id as query_id, c.vec_id, list_sum(list_transform(list_zip(q.v, c.v), lambda z: z[1] * z[2]))::bigint as score
  from v q join v c on q.vec_id <> c.vec_id where q.vec_id % 100 = 0)
select query_id, row_number() over (partition by query_id order by score desc, vec_id)::int as rank, vec_id, score
from s qualify row_number() over (partition by query_id order by score desc, vec_id) <= 10
"""

OP10_SQL = r"""
with recursive l as (
  select doc_id, coalesce(text, '') as t, unnest(string_split(coalesce(text, ''), chr(10))) as line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) - 1 as line_no from documents),
p as (
  select doc_id, t, line_no, regexp_replace(trim(regexp_replace(line, '[\x20\x09-\x0D]+', ' ', 'g'), ' '), '[^ ]*[0-9][^ ]*', '<*>', 'g') as m from l),
k as (select * from p where m <> ''),
d as (select m, string_split(m, ' ') as w, len(string_split(m, ' ')) as n, min((doc_id, line_no)) as first from k group by m),
o as (select *, n // 10 as may_differ, array_to_string(w[1:3], ' ') as lead from d where n >= 10),
links as (
  select a.m as x, c.m as y from o a join o c on a.n = c.n and a.lead = c.lead and a.m < c.m
  where len(list_filter(list_zip(a.w, c.w), lambda z: z[1] <> z[2])) <= a.may_differ),
both_ways as (select x, y from links union all select y, x from links),
reach as (select x as a, x as b from both_ways union select r.a, e.y from reach r join both_ways e on r.b = e.x),
named as (select a as m, min(b) as template from reach group by a),
z as (select k.*, n, coalesce(template, k.m) as template from k join d using (m) left join named using (m)),
r as (
  select template, min((doc_id, line_no)) as first from z group by template
  having count(distinct t) >= case when any_value(n) < 6 then 3 else 2 end),
g as (
  select doc_id, count(distinct line_no)::bigint as n, list_sort(list_distinct(list(line_no))) as nos
  from z join r using (template) where (doc_id, line_no) <> first group by doc_id)
select d.doc_id, (case when text is null then 0 else len(string_split(text, chr(10))) end)::bigint as n_lines,
  coalesce(n, 0)::bigint as n_dropped, coalesce(array_to_string(nos, ','), '') as dropped
from documents d left join g using (doc_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_ngram_jaccard_join": OP2_SQL, "op3_mixing": OP3_SQL, "op4_chat_format": OP4_SQL, "op7_exact_topk": OP7_SQL, "op10_line_templates": OP10_SQL}
