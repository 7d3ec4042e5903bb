"""Personal-data spans and information-theoretic sanitisation (DataFrame functions only).

Base spans (email, ip, card, phone) come from fixed patterns and checks. The corpus then says which further terms
give a protected entity away. With N documents, n(e) of them holding entity e, n(t) holding term t and n(e,t) holding
t within ``WINDOW`` code points of e, the disclosure of e by t is PMI(e;t) / IC(e) =
log2(N n(e,t) / (n(e) n(t))) / log2(N / n(e)); it is 1 where t stands beside e only. Terms at or above
``generalise_at`` become a class mark, those at or above ``remove_at`` vanish, wherever they stand in a document that
holds the entity. A pair counts once ``min_documents`` documents hold it (copies are documents too): without that, every
rare word beside an entity would give it away.

Counting: occurrences are made distinct per text, then summed per pair; words of the whole corpus are counted per term
before they meet the pairs. disclosure >= x needs n(t) <= n(e,t) (N / n(e))^(1-x), and the texts in which t stands
beside any entity bound n(t) from below, so common words leave the pairs first.

Defined results: null text is the empty text; empty texts have no spans; repeated rows are handled row by
row, as texts they count once; an empty table gives no rows; very long texts cost time in proportion; other columns of
the input are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import chunks, spans_of, written

KINDS = ("email", "ip", "card", "phone", "term", "removed_term")
WINDOW = 120

# The base patterns. The look-behinds and possessive runs only stop retries inside a run that has
# already failed as a whole; \G lets a search resume right after a match.
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?:(?<![0-9])|\G)[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]+)"
CARD = r"[0-9](?:[\x20-]?[0-9])++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
PATTERNS = {"email": EMAIL, "ip": IP, "card": CARD, "phone": PHONE}
NEEDS = {"email": "@", "phone": "+"}
TERM = r"(?<![\p{L}\p{N}_])\p{L}[\p{L}\p{N}_]{3,}(?![\p{L}\p{N}_])"


def _luhn(value: Column) -> Column:
    digits = F.reverse(F.regexp_replace(value, "[^0-9]", ""))
    doubled = F.transform(
        F.sequence(F.lit(1), F.length(digits)),
        lambda i: F.when(i % 2 == 1, F.substr(digits, i, F.lit(1)).cast("int")).otherwise(
            F.element_at(F.array(*[F.lit(x) for x in (0, 2, 4, 6, 8, 1, 3, 5, 7, 9)]), F.substr(digits, i, F.lit(1)).cast("int") + 1)
        ),
    )
    n = F.length(digits)
    return (n >= 13) & (n <= 19) & (F.aggregate(doubled, F.lit(0), lambda a, x: a + x) % 10 == 0)


def _valid(kind: str, value: Column) -> Column:
    if kind == "ip":
        part = r"0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])"
        return value.rlike(rf"^{part}\.{part}\.{part}\.{part}$")
    if kind == "card":
        # length first: the check sum is evaluated for plausible lengths only
        return F.when(F.length(value) > 40, False).otherwise(_luhn(value))
    if kind == "phone":
        return F.length(F.regexp_replace(value, "[^0-9]", "")).between(9, 15)
    return F.lit(True)


SPAN = "struct<kind:int,start:bigint,end:bigint,value:string>"


def _tagged(found: Column, number: int, kind: str | None = None) -> Column:
    valid = F.filter(found, lambda s: _valid(kind, s["value"])) if kind else found
    return F.transform(valid, lambda s: F.struct(F.lit(number).alias("kind"), s["start"].alias("start"), s["end"].alias("end"), s["value"].alias("value")))


def _candidate(text: Column, kind: str) -> Column:
    return F.contains(text, F.lit(NEEDS[kind])) if kind in NEEDS else text.rlike(r"[0-9][.\x20-]?[0-9]")


def base_spans(text: Column) -> Column:
    """array<struct<kind,start,end,value>> ordered by kind (email, ip, card, phone), then start."""
    none = F.array().cast(f"array<{SPAN}>")
    parts = []
    for number, (kind, pattern) in enumerate(PATTERNS.items()):
        parts.append(F.when(_candidate(text, kind), _tagged(spans_of(text, pattern), number, kind)).otherwise(none))
    return F.concat(*parts)


def _name(kind: Column, value: Column) -> Column:
    """One name for the spellings of an entity."""
    digits = F.regexp_replace(value, "[^0-9]", "")
    return F.concat_ws(":", kind.cast("string"), F.when(kind == 0, F.lower(value)).when(kind == 1, value).otherwise(digits))


def surroundings(text: Column) -> Column:
    """array<struct<entity,near>>: every base span with what stands within WINDOW code points before and after it.

    The pieces between two matches of a kind are cut from their ends, so the cost follows the text, not its spans."""
    none = F.array().cast("array<struct<entity:string,near:string>>")
    return F.concat(*[F.when(_candidate(text, kind), _around(text, number, kind)).otherwise(none) for number, kind in enumerate(PATTERNS)])


def _around(text: Column, number: int, kind: str) -> Column:
    values, gaps = F.regexp_extract_all(text, F.lit(PATTERNS[kind]), F.lit(0)), F.split(text, PATTERNS[kind], -1)
    met = F.arrays_zip(values.alias("value"), F.slice(gaps, F.lit(1), F.size(values)).alias("before"), F.slice(gaps, F.lit(2), F.size(values)).alias("after"))
    valid = F.filter(met, lambda x: _valid(kind, x["value"]))
    return F.transform(valid, lambda x: F.struct(_name(F.lit(number), x["value"]).alias("entity"), F.concat_ws(" . ", _end(x["before"]), _start(x["after"])).alias("near")))


def _end(gap: Column) -> Column:
    """The last WINDOW code points; a word that the cut may have halved goes."""
    return F.when(F.length(gap) > WINDOW, F.regexp_replace(F.right(gap, F.lit(WINDOW)), r"^[\p{L}\p{N}_]+", "")).otherwise(gap)


def _start(gap: Column) -> Column:
    return F.when(F.length(gap) > WINDOW, F.regexp_replace(F.left(gap, F.lit(WINDOW)), r"[\p{L}\p{N}_]+$", "")).otherwise(gap)


def terms_of(text: Column) -> Column:
    return F.array_distinct(F.regexp_extract_all(text, F.lit(TERM), F.lit(0)))


def _terms_near(near: Column) -> Column:
    """The words of a surrounding; of the kinds only addresses hold letters, and theirs are no words."""
    return terms_of(F.regexp_replace(near, EMAIL, " "))


def scanned(docs: DataFrame, carry_key: bool = False) -> DataFrame:
    """doc_id, row, spans, and of the rows with base spans text, text_key and around. One pass over the texts, written."""
    text = F.col("text")
    key = [F.xxhash64("doc_id", "text").alias("key")] if carry_key else []
    found = docs.select("doc_id", F.coalesce(text, F.lit("")).alias("text")).withColumn("spans", base_spans(text))
    hit = F.size("spans") > 0
    row = F.monotonically_increasing_id().alias("row")
    return written(found.select("doc_id", row, "spans", *key, *[F.when(hit, c).alias(n) for c, n in ((text, "text"), (F.xxhash64("text"), "text_key"), (surroundings(text), "around"))]), "pii-hits")


def revealing_terms(docs: DataFrame, generalise_at: float = 0.9, min_documents: int = 2, hits: DataFrame | None = None) -> DataFrame:
    """(entity, term, n_entity, n_term, n_both, disclosure) for every pair at or above ``generalise_at``. Counts are rows of ``docs``."""
    hits = (scanned(docs) if hits is None else hits).where("text IS NOT NULL")
    texts = hits.groupBy("text_key").agg(F.first("around").alias("around"), F.count(F.lit(1)).alias("copies"))
    met = texts.select("text_key", "copies", F.explode("around").alias("x")).select("text_key", "copies", "x.entity", _terms_near(F.col("x.near")).alias("terms"))
    # an entity of one document only cannot have a pair in two; hot entities are summed map-side
    per_entity = met.groupBy("entity", "text_key").agg(F.max("copies").alias("copies")).groupBy("entity").agg(F.sum("copies").alias("n_entity"))
    entities = written(per_entity.where(F.col("n_entity") >= min_documents), "pii-entities")
    met = written(met.join(entities, "entity").select("entity", "n_entity", "text_key", "copies", F.explode("terms").alias("term")).distinct(), "pii-near")
    pairs = met.groupBy("entity", "term", "n_entity").agg(F.sum("copies").alias("n_both")).where(F.col("n_both") >= min_documents)
    beside = met.groupBy("term", "text_key").agg(F.max("copies").alias("copies")).groupBy("term").agg(F.sum("copies").alias("at_least"))
    n_docs = docs.agg(F.count(F.lit(1)).alias("n_docs"))
    most = F.col("n_both") * F.pow(F.col("n_docs") / F.col("n_entity"), F.lit(1 - generalise_at)) * 1.000001
    pairs = written(pairs.crossJoin(F.broadcast(n_docs)).join(beside, "term").where(F.col("at_least") <= most).drop("at_least"), "pii-candidates")
    # pairs of a term and a text that holds it are summed before any join: the join sees each term once
    words = docs.select(F.explode(terms_of(F.coalesce(F.col("text"), F.lit("")))).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("n_term"))
    if pairs.isEmpty():
        return pairs.select("entity", "term", "n_entity", F.lit(0).cast("long").alias("n_term"), "n_both", F.lit(0.0).alias("disclosure"))
    pmi = F.log2(F.col("n_docs") * F.col("n_both") / (F.col("n_entity") * F.col("n_term")))
    content = F.log2(F.col("n_docs") / F.col("n_entity"))
    disclosure = F.when(content > 0, F.least(F.lit(1.0), pmi / content)).otherwise(F.lit(0.0))
    scored = pairs.join(words, "term").select("entity", "term", "n_entity", "n_term", "n_both", disclosure.alias("disclosure"))
    return scored.where(F.col("disclosure") >= generalise_at)


def find_spans(docs: DataFrame, carry_key: bool = False, remove_at: float = 0.98, **options) -> DataFrame:
    """doc_id, spans array<struct<kind,start,end,value>>; kinds 4 (generalise) and 5 (remove) are revealing terms of the
    document's own entities."""
    kept = scanned(docs, carry_key)
    hits = kept.where("text IS NOT NULL")
    reveal = written(revealing_terms(docs, hits=hits, **options).select("entity", "term", (F.col("disclosure") >= remove_at).alias("gone")), "pii-reveal")
    key = ["key"] if carry_key else []
    if reveal.isEmpty():
        return kept.select("doc_id", "spans", *key)
    # every word of a document with entities, against the terms that reveal one of them
    words = hits.select("row", F.transform("around", lambda x: x["entity"]).alias("own"), F.explode(terms_of(F.col("text"))).alias("term"))
    of_doc = words.join(reveal, "term").where(F.array_contains("own", F.col("entity"))).groupBy("row", "term").agg(F.max("gone").alias("gone"))
    of_doc = of_doc.groupBy("row").agg(F.sort_array(F.collect_list(F.when(~F.col("gone"), F.col("term")))).alias("mild"), F.sort_array(F.collect_list(F.when(F.col("gone"), F.col("term")))).alias("strong"))
    none = F.array().cast(f"array<{SPAN}>")

    def marked(terms: str, number: int) -> Column:
        pattern = F.concat(F.lit(r"(?<![\p{L}\p{N}_])(?:"), F.array_join(terms, "|"), F.lit(r")(?![\p{L}\p{N}_])"))
        return F.when(F.size(terms) > 0, _tagged(spans_of(F.col("text"), pattern), number)).otherwise(none)

    extra = F.concat(marked("mild", 4), marked("strong", 5))
    terms = hits.join(of_doc, "row").select("row", extra.alias("extra"))
    return kept.join(terms, "row", "left").select("doc_id", *key, F.concat("spans", F.coalesce("extra", none)).alias("spans"))


def sanitise(docs: DataFrame, **options) -> DataFrame:
    """doc_id and text with every span replaced by its class mark ([EMAIL] ...), terms by [TERM]; terms at or above
    ``remove_at`` vanish; overlaps merge."""
    marks = F.array(*[F.lit("" if k == "removed_term" else f"[{k.upper()}]") for k in KINDS])
    spans = F.array_sort(F.transform("spans", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))

    def run_text(acc: Column, run: Column) -> Column:
        """The text from where acc ends to the end of the run's last span, without the run's spans."""
        until = F.greatest(acc["at"], F.array_max(F.transform(run, lambda x: x["end"])))
        part = F.substr(F.col("text"), (acc["at"] + 1).cast("int"), (until - acc["at"]).cast("int"))
        begin = F.struct(acc["at"].alias("at"), F.lit("").alias("out"), acc["at"].alias("zero"), part.alias("part"))

        def step(a: Column, s: Column) -> Column:
            between = F.substr(a["part"], (a["at"] - a["zero"] + 1).cast("int"), (s["start"] - a["at"]).cast("int"))
            out = F.when(s["start"] >= a["at"], F.concat(a["out"], between, F.element_at(marks, s["kind"] + 1))).otherwise(a["out"])
            return F.struct(F.greatest(a["at"], s["end"]).alias("at"), out.alias("out"), a["zero"].alias("zero"), a["part"].alias("part"))

        done = F.aggregate(run, begin, step)
        return F.struct(done["at"].alias("at"), F.concat(acc["out"], F.array(done["out"])).alias("out"))

    rebuilt = F.aggregate(
        chunks(spans),
        F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<string>").alias("out")),
        run_text,
        lambda a: F.concat(F.array_join(a["out"], ""), F.substr(F.col("text"), (a["at"] + 1).cast("int"), F.length("text"))),
    )
    key = F.xxhash64("doc_id", "text")
    texts = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    # rows repeated as a whole have equal spans, so one of them serves all
    spans_by_row = find_spans(texts, carry_key=True, **options).dropDuplicates(["key"]).select("key", "spans")
    return texts.withColumn("key", key).join(spans_by_row, "key").select("doc_id", rebuilt.alias("text"))


def _of_kind(number: int) -> Column:
    return F.filter("spans", lambda s: s["kind"] == number)


def digest(found: DataFrame) -> DataFrame:
    names = F.array(*[F.lit(k) for k in KINDS])
    label = lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))
    base = F.filter("spans", lambda s: s["kind"] < 4)
    counts = [F.size(_of_kind(n)).cast("long").alias(f"n_{k}") for n, k in enumerate(KINDS)]
    return found.select(
        "doc_id",
        *counts,
        F.sha2(F.array_join(F.transform(base, label), ","), 256).alias("base_sha256"),
        F.array_join(F.transform("spans", label), ",").alias("spans"),
    )
