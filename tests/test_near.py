import itertools
import random

from pyspark.sql import functions as F

from corpus_audit.functions.edit import edit_distance, edit_distances
from corpus_audit.operators.dedup import near_copies_lsh
from corpus_audit.operators.pairs import natural_pairs


def shingles(text):
    words = [w for w in text.replace("\t", " ").replace("\n", " ").replace("\r", " ").split(" ") if w]
    return {tuple(words[i : i + 3]) for i in range(len(words) - 2)} if len(words) > 2 else {tuple(words)} - {()}


def expected(rows):
    """Every different pair of texts once, by smallest ids, and every other id with its text's smallest one."""
    ids = {}
    for i, text in sorted(rows):
        if text and shingles(text):
            ids.setdefault(text, []).append(i)
    out = {(v[0], i, 1.0, "copy") for v in ids.values() for i in v[1:]}
    for (x, i), (y, j) in itertools.combinations(ids.items(), 2):
        a, b = shingles(x), shingles(y)
        similarity = round(1 - edit_distance(x, y) / max(len(x), len(y)), 6)
        if len(a & b) / len(a | b) >= 0.5 and similarity >= 0.8:
            out.add((min(i[0], j[0]), max(i[0], j[0]), similarity, "link"))
    return out


def families(seed):
    draw, rows = random.Random(seed), []
    for family in range(12):
        base = [draw.choice(["if", "x", "=", "return", "Ä", "漢", f"v{family}", *map(str, range(40))]) for _ in range(draw.choice([1, 2, 3, 8, 60, 300]))]
        for _ in range(draw.randrange(1, 9)):
            words = list(base)
            for _ in range(draw.randrange(0, 1 + len(words) // 6)):
                at = draw.randrange(len(words))
                words[at : at + draw.randrange(2)] = draw.choice([[], ["new"], [f"w{draw.randrange(99)}"]])
            rows.append(draw.choice([" ", "\n", " \t"]).join(words))
    rows += [None, "", " \n", "a\x0bb c d", "a b c d", "a\x0cb c d"]
    return list(enumerate(rows + rows[:9], 100))


def test_natural_pairs_equal_brute_force(spark):
    for seed in (1, 2):
        rows = families(seed)
        got = natural_pairs(spark.createDataFrame(rows, "doc_id long, text string").repartition(5))
        found = [(r["id_a"], r["id_b"], r["similarity"], r["kind"]) for r in got.collect()]
        assert len(found) == len(set(found))
        assert set(found) == expected(rows)


def test_sketches_lose_no_link_and_expand_no_copies(spark):
    rows = families(3) + [(2000 + i, "a text of five words") for i in range(40)]
    ids = {}
    for i, text in sorted(rows):
        if text and shingles(text):
            ids.setdefault(text, []).append(i)
    wanted = {(v[0], i, 1.0, "copy") for v in ids.values() for i in v[1:]}
    for (x, i), (y, j) in itertools.combinations(ids.items(), 2):
        a, b = shingles(x), shingles(y)
        if len(a & b) / len(a | b) >= 0.5:
            wanted.add((min(i[0], j[0]), max(i[0], j[0]), round(len(a & b) / len(a | b), 6), "link"))
    got = near_copies_lsh(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    found = [(r["id_a"], r["id_b"], round(r["jaccard"], 6), r["kind"]) for r in got]
    assert len(found) == len(set(found))
    assert set(found) == wanted


def test_copies_make_a_row_each(spark):
    rows = [(i, "one two three four five") for i in range(300)] + [(1000 + i, f"a b c d e f g h i j k l m n o p q r s t u v w x {i % 2}") for i in range(300)]
    got = natural_pairs(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r["kind"]: r["n"] for r in got.groupBy("kind").agg(F.count("*").alias("n")).collect()} == {"copy": 299 + 298, "link": 1}


def test_distances_of_many_pairs_equal_those_of_each():
    draw, pairs, most = random.Random(5), [], []
    for _ in range(400):
        letters = "abcde é漢"[: draw.choice([2, 4, 8])]
        a = draw.choices(letters, k=draw.choice([0, 5, 40, 100, 300]))
        b = list(a)
        for _ in range(draw.choice([0, 1, 3, 20, 60])):
            at = draw.randrange(len(b) + 1)
            b[at : at + draw.randrange(3)] = draw.choices(letters, k=draw.randrange(3))
        pairs.append(("".join(a), "".join(b)))
        most.append(draw.choice([0, 3, 20, 400]))
    got = edit_distances(pairs, most, chars=5_000)
    assert [min(g, m + 1) for g, m in zip(got, most, strict=True)] == [min(edit_distance(*p), m + 1) for p, m in zip(pairs, most, strict=True)]
