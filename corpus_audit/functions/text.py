"""Column functions on texts: normalisation, digests, hash buckets, similarity, identifiers, verdicts."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

FORMATTING = " \t\n\r"  # fixed value: the characters that do not count as content


def strip_format(text: Column, unicode: bool = False) -> Column:
    """text without formatting characters; with ``unicode`` without any white space. Null stays null."""
    return F.regexp_replace(text, r"(?U)\s+", "") if unicode else F.translate(text, FORMATTING, "")


def digest(text: Column, normalize: bool = True, algo: str = "md5") -> Column:
    """Digest of the (normalised) text. xxhash64 is for prefilters only."""
    content = strip_format(text) if normalize else text
    if algo == "md5":
        return F.md5(content)
    if algo == "sha2":
        return F.sha2(content, 256)
    if algo == "xxhash64":
        return F.when(content.isNotNull(), F.xxhash64(content))
    raise ValueError(f"unknown digest {algo!r}")


def bucket(key: Column, seed: str = "", buckets: int = 10_000) -> Column:
    """A reproducible number in [0, buckets): the same in any engine, whatever the partitioning."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(seed), key.cast("string"))), 1, 8), 16, 10).cast("long") % buckets


def edit_similarity(a: Column, b: Column, floor: float | None = None) -> Column:
    """1 - distance / longer length. With ``floor`` null below it, and the distance stops early."""
    longer = F.greatest(F.length(a), F.length(b))
    if floor is None:
        return F.when(longer == 0, 1.0).otherwise(1 - F.levenshtein(a, b) / longer)
    # ANSI levenshtein wants a literal threshold, so the bound goes through a length test and a comparison
    close = F.least(F.length(a), F.length(b)) >= longer * floor
    value = F.when(longer == 0, 1.0).otherwise(1 - F.levenshtein(a, b) / longer)
    return F.when(close, F.when(value >= floor, value))


def _jaccard(a: Column, b: Column) -> Column:
    union = F.size(F.array_union(a, b))
    return F.when(union == 0, 1.0).otherwise(F.size(F.array_intersect(a, b)) / union)


def tokens(text: Column) -> Column:
    return F.filter(F.split(text, r"[ \t\n\r]+"), lambda w: w != "")


def token_similarity(a: Column, b: Column) -> Column:
    return _jaccard(F.array_distinct(tokens(a)), F.array_distinct(tokens(b)))


def runs(words: Column, k: int) -> Column:
    """The runs of k neighbouring words, joined by blanks. Shifted copies are zipped, so ``words`` is evaluated k times
    and not once a run."""
    n = F.greatest(F.size(words) - k + 1, F.lit(0))
    out = F.slice(words, F.lit(1), n)
    for shift in range(1, k):
        out = F.zip_with(out, F.slice(words, F.lit(shift + 1), n), lambda a, b: F.concat(a, F.lit(" "), b))
    return out


def shingles(text: Column, k: int = 3) -> Column:
    """Distinct runs of k words; a shorter text is one run."""
    words = tokens(text)
    return F.when(F.size(words) == 0, F.array().cast("array<string>")).when(F.size(words) < k, F.array(F.array_join(words, " "))).otherwise(F.array_distinct(runs(words, k)))


def shingle_similarity(a: Column, b: Column, k: int = 3) -> Column:
    return _jaccard(shingles(a, k), shingles(b, k))


def similarity(a: Column, b: Column, metric: str = "edit", floor: float | None = None) -> Column:
    if metric == "edit":
        return edit_similarity(a, b, floor)
    value = {"token": token_similarity, "shingle": shingle_similarity}[metric](a, b)
    return value if floor is None else F.when(value >= floor, value)


def identifiers(text: Column) -> Column:
    """Distinct whole identifiers of a text: runs of letters, digits and underscore that start with no digit."""
    return F.array_distinct(F.regexp_extract_all(text, F.lit("[A-Za-z_][A-Za-z0-9_]*"), F.lit(0)))


def file_names(text: Column) -> Column:
    """Distinct base names with an extension that a text mentions (directories in front are cut)."""
    return F.array_distinct(F.regexp_extract_all(text, F.lit(r"[A-Za-z0-9_\-]+\.[A-Za-z0-9]+(?![A-Za-z0-9_.\-/])"), F.lit(0)))


def parse_verdict(text: Column) -> Column:
    """1 (flawed), 0 (benign) or null from a free answer: the last clear statement decides, negation first."""
    low = F.lower(F.trim(text))
    last = F.element_at(F.concat(F.array(F.lit("")), F.regexp_extract_all(low, F.lit(r"\b(yes|no|not vulnerable|vulnerable|not flawed|flawed|benign)\b"), F.lit(1))), -1)
    return F.when(last.isin("yes", "vulnerable", "flawed"), 1).when(last.isin("no", "not vulnerable", "not flawed", "benign"), 0)
