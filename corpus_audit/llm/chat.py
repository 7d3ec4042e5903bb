"""Chat formatting with a grammar round trip (DataFrame functions only).

A conversation renders to one string: a head, then each turn between an opening and a closing mark. The
deterministic parser cuts the string at every mark. Rendering starts without escapes; wherever the parsed
turns differ from the source, the conversation is rendered at level 1, where a backslash goes behind the
first character of every mark (or escaped mark) inside a text, so the text holds no mark and one backslash
less gives it back. Level 1 always round-trips, so two passes reach the fixed point.

Defined results: null text and null role are empty; roles other than system, user, assistant keep their
(escaped) name in the turn; ties in turn order by role, then text; repeated rows are repeated turns; a null
conv_id is a conversation of its own; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The marks of the format.
OPEN = {"system": "<<SYS>>", "user": "[INST]", "assistant": "<<OUT>>"}
CLOSE = {"system": "<</SYS>>", "user": "[/INST]", "assistant": "</s>"}
HEADS = ("<s>", "<s1>")
OTHER_OPEN, OTHER_NAME, OTHER_CLOSE = "<<TURN>>", "<<SAYS>>", "<</TURN>>"
_TAIL = r"(/?INST\]|/?s1?>|</?SYS>>|<OUT>>|</?TURN>>|<SAYS>>)"
MARK = r"[\[<]" + _TAIL
ESCAPE_FROM, ESCAPE_TO = r"([\[<])(\\*)" + _TAIL, r"$1\\$2$3"
UNESCAPE_FROM, UNESCAPE_TO = r"([\[<])\\(\\*)" + _TAIL, r"$1$2$3"
TURNS = "array<struct<role:string,text:string>>"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, ESCAPE_FROM, ESCAPE_TO)


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, UNESCAPE_FROM, UNESCAPE_TO)


def _pick(role: Column, marks: dict[str, str], other: Column) -> Column:
    out = None
    for name, mark in marks.items():
        out = F.when(role == name, F.lit(mark)) if out is None else out.when(role == name, F.lit(mark))
    return out.otherwise(other)


def render(turns: Column, level: int) -> Column:
    keep = escape if level else (lambda c: c)
    each = F.transform(
        turns,
        lambda t: F.concat(
            _pick(t["role"], OPEN, F.concat(F.lit(OTHER_OPEN), keep(t["role"]), F.lit(OTHER_NAME))),
            keep(t["text"]),
            _pick(t["role"], CLOSE, F.lit(OTHER_CLOSE)),
        ),
    )
    return F.concat(F.lit(HEADS[level]), F.array_join(each, ""))


def parse(df: DataFrame, rendered: str, out: str) -> DataFrame:
    """df with ``out``: the turns that the marks of a rendered string delimit; null entries mean not well formed.

    Marks and parts become columns first: inside the per-turn functions they would be searched again for each turn."""
    cut = df.withColumn("_marks", F.regexp_extract_all(rendered, F.lit(MARK), F.lit(0))).withColumn("_parts", F.split(rendered, MARK, -1))
    marks, parts = F.col("_marks"), F.col("_parts")
    n = F.size(marks)
    padded = F.concat(marks, F.array(F.lit(""), F.lit("")))
    zipped = F.arrays_zip(marks.alias("m"), F.slice(padded, F.lit(2), n).alias("m2"), F.slice(padded, F.lit(3), n).alias("m3"), F.slice(parts, F.lit(2), n).alias("p"), F.slice(F.concat(parts, F.array(F.lit(""))), F.lit(3), n).alias("p2"))
    cut = cut.withColumn("_zip", zipped).withColumn("_level", F.try_element_at(marks, F.lit(1)))
    plain = lambda c: F.when(F.col("_level") == HEADS[1], unescape(c)).otherwise(c)
    opens = F.filter("_zip", lambda x: x["m"].isin(*OPEN.values(), OTHER_OPEN))

    def turn(x: Column) -> Column:
        out = F.when((x["m"] == OTHER_OPEN) & (x["m2"] == OTHER_NAME) & (x["m3"] == OTHER_CLOSE), F.struct(plain(x["p"]).alias("role"), plain(x["p2"]).alias("text")))
        for role, sign in OPEN.items():
            out = out.when((x["m"] == sign) & (x["m2"] == CLOSE[role]), F.struct(F.lit(role).alias("role"), plain(x["p"]).alias("text")))
        return out

    return cut.withColumn(out, F.transform(opens, turn)).drop("_marks", "_parts", "_zip", "_level")


def format_conversations(conversations: DataFrame) -> DataFrame:
    """conv_id, formatted, level, turns (read back from formatted), intact (they equal the source)."""
    row = F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    source = (
        conversations.groupBy("conv_id")
        .agg(F.sort_array(F.collect_list(row)).alias("rows"))
        .select("conv_id", F.transform("rows", lambda r: F.struct(r["role"].alias("role"), r["text"].alias("text"))).alias("source"))
    )
    first = parse(source.withColumn("formatted", render(F.col("source"), 0)), "formatted", "turns")
    checked = first.withColumn("level", F.when(F.coalesce(F.col("turns") == F.col("source"), F.lit(False)), 0).otherwise(1))
    final = checked.withColumn("formatted", F.when(F.col("level") == 0, F.col("formatted")).otherwise(render(F.col("source"), 1)))
    read = parse(final.drop("turns"), "formatted", "turns")
    return read.select("conv_id", "formatted", "level", "turns", (F.col("turns") == F.col("source")).alias("intact"))


def loss_text(turns: Column) -> Column:
    """What the loss mask covers: each assistant text once, in order."""
    return F.array_join(F.transform(F.filter(turns, lambda t: t["role"] == "assistant"), lambda t: t["text"]), "")


def digest(formatted: DataFrame) -> DataFrame:
    turns = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = loss_text(F.col("turns"))
    return formatted.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(turns, 256).alias("turns_sha256"),
        F.length(loss).cast("long").alias("loss_chars"),
        F.sha2(loss, 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )
