import random
import time

import pytest
from pyspark.sql import functions as F

from corpus_audit.functions.edit import edit_distance
from corpus_audit.functions.text import digest, edit_similarity, identifiers, parse_verdict, shingle_similarity, token_similarity


def one(spark, column, *values):
    row = spark.createDataFrame([values], ", ".join(f"c{i} string" for i in range(len(values))))
    return row.select(column(*[F.col(f"c{i}") for i in range(len(values))])).first()[0]


def test_format_twins_share_a_digest(spark):
    rows = spark.createDataFrame([("a b",), ("a\tb",), ("a\r\nb",), ("ab",), ("A b",), ("",), (None,)], "t string")
    got = [r[0] for r in rows.select(digest(F.col("t"))).collect()]
    assert len(set(got[:4])) == 1
    assert got[4] != got[0]
    assert got[5] is not None
    assert got[6] is None


@pytest.mark.parametrize(("text", "verdict"), [("YES", 1), ("no.", 0), ("It is not vulnerable", 0), ("", None), (None, None), ("maybe", None), ("no... on reflection YES", 1)])
def test_verdicts(spark, text, verdict):
    assert one(spark, parse_verdict, text) == verdict


def test_mentions_are_whole_identifiers(spark):
    assert set(one(spark, identifiers, "fn_12 and fn_1()")) == {"fn_12", "and", "fn_1"}
    assert "fn_1" not in one(spark, identifiers, "fn_12 only")


def test_similarities(spark):
    assert one(spark, lambda a, b: edit_similarity(a, b), "abcd", "abce") == pytest.approx(0.75)
    assert one(spark, lambda a, b: edit_similarity(a, b, 0.8), "abcd", "abce") is None
    assert one(spark, token_similarity, "a b c", "b c d") == pytest.approx(0.5)
    assert one(spark, shingle_similarity, "a b c d", "a b c e") == pytest.approx(1 / 3)
    assert one(spark, lambda a, b: edit_similarity(a, b), "", "") == 1.0


def slow_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def test_edit_distance_against_table():
    rng = random.Random(1)
    for _ in range(300):
        a, b = ("".join(rng.choice("abcé") for _ in range(rng.randrange(14))) for _ in "ab")
        assert edit_distance(a, b) == slow_distance(a, b)


def test_edit_distance_of_one_letter_for_another_needs_no_table():
    rng = random.Random(4)
    a = "".join(rng.choice("abcdefghijklmno e") for _ in range(200_000))
    begin = time.process_time()
    assert edit_distance(a, a.replace("e", "a")) == a.count("e")
    assert edit_distance("b" * 50_000 + a, a + "c" * 50_000, 40_000) == 40_001
    assert time.process_time() - begin < 3  # 0.7 s for 40,000 characters by the table, growing with the square
    for _ in range(300):
        x, y = ("".join(rng.choice("abce") for _ in range(rng.randrange(1, 12))) for _ in range(2))
        for b in (y, x.replace("e", "a")):
            far = slow_distance(x, b)
            assert edit_distance(x, b) == far
            assert all(min(edit_distance(x, b, most), most + 1) == min(far, most + 1) for most in range(5))
