"""Edge cases of the training-data operators, against brute force where SQL cannot say it."""

import hashlib
import itertools
import random
import re
import time

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from corpus_audit.llm import ann_postings, chat, exact_topk, line_templates, mixing, ngram_join, piece_lattice, pii, quality_fm, toxicity_knn
from corpus_audit.llm.queries import tokenizer_path

DOC = "doc_id long, text string, lang string, source string, n_chars long"


def documents(spark, texts, sources=None):
    rows = [(i, t, "en", (sources or {}).get(i, "s"), len(t or "")) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOC)


WORDS = [f"w{i}" for i in range(400)]


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


# --- personal data ----------------------------------------------------------------------------------------------------

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def luhn(v):
    digits = [int(c) for c in v if c.isdigit()][::-1]
    return 13 <= len(digits) <= 19 and sum(x if i % 2 == 0 else sum(divmod(2 * x, 10)) for i, x in enumerate(digits)) % 10 == 0


def base(text):
    out = []
    for kind, pattern, valid in (
        ("email", EMAIL, lambda v: True),
        ("ip", IP, lambda v: all(int(p) <= 255 for p in v.split("."))),
        ("card", CARD, luhn),
        ("phone", PHONE, lambda v: 9 <= sum(c.isdigit() for c in v) <= 15),
    ):
        out += [f"{kind}:{m.start()}:{m.end()}" for m in pattern.finditer(text) if valid(m[0])]
    return ",".join(out)


TRICKY = [
    None, "", "é a@b.co, x@y", "a@b.com@d.e x@y.z+q@r.s", "1.2.3.4 256.1.1.1 1.2.3.4.5.6.7.8 00001.2.3.255", "4785380592391141 4111 1111 1111 1111 4111-1111-1111-1112",
    "+49 (30) 123-456 +1 +12345678901234567", "a" * 3000 + "@x.y", "1" * 5000, "😀 mail😀 a@b.c 1.1.1.1 +4912345678901", "..@..", "x@y.z.", "%@a.b a@-.-",
]


def test_base_spans(spark):
    got = {r["doc_id"]: r["base_sha256"] for r in pii.digest(pii.find_spans(documents(spark, TRICKY))).collect()}
    for i, text in enumerate(TRICKY):
        assert got[i] == hashlib.sha256(base(text or "").encode()).hexdigest(), TRICKY[i]


def test_revealing_terms_and_sanitising(spark):
    rng = random.Random(3)
    texts = [f"{prose(rng, 5)} the Zorblax{'' if i % 2 else ' '} desk answers boss@corp.example today {i}" for i in range(8)] + [f"{prose(rng, 9)} the desk" for _ in range(40)]
    texts = [t.replace("Zorblax ", "Zorblax") for t in texts]
    docs = documents(spark, texts)
    found = {r["doc_id"]: r for r in pii.digest(pii.find_spans(docs)).collect()}
    assert all(found[i]["n_email"] == 1 and "term" in found[i]["spans"] for i in range(8))
    assert all(found[i]["spans"] == "" for i in range(8, 48))
    clean = {r["doc_id"]: r["text"] for r in pii.sanitise(docs).collect()}
    assert all("boss@corp" not in t and "Zorblax" not in t for t in clean.values())
    assert clean[10] == texts[10]


def test_disclosure_equals_brute_force(spark):
    import math

    rng = random.Random(11)
    rare = [f"rare{i:03}" for i in range(40)]
    mails = [f"person{i}@corp.example" for i in range(6)]
    texts = []
    for i in range(120):
        words = [rng.choice(WORDS[:60]) for _ in range(rng.randrange(3, 90))]
        if i % 3 == 0:
            who = rng.randrange(6)
            words[1:1] = [rng.choice(rare[who * 3 : who * 3 + 4]), mails[who], rng.choice(rare)]
        texts.append(" ".join(words))
    texts += texts[:9] + [None, ""]
    around, docs_of = {}, {}
    for i, t in enumerate(texts):
        for w in set(re.findall(r"(?<!\w)[a-z]\w{3,}(?!\w)", EMAIL.sub(" ", t or "")) + re.findall(r"(?<!\w)(?:person\d|corp|example)(?!\w)", t or "")):
            docs_of.setdefault(w, set()).add(i)
        for m in EMAIL.finditer(t or ""):
            before, after = t[: m.start()], t[m.end() :]
            before = re.sub(r"^\w+", "", before[-pii.WINDOW :]) if len(before) > pii.WINDOW else before
            after = re.sub(r"\w+$", "", after[: pii.WINDOW]) if len(after) > pii.WINDOW else after
            for w in set(re.findall(r"(?<!\w)[a-z]\w{3,}(?!\w)", before + " . " + after)):
                around.setdefault((f"0:{m[0]}", w), set()).add(i)
    holding = {f"0:{e}": {i for i, t in enumerate(texts) if e in (t or "")} for e in mails}
    expected = {}
    for (e, w), both in around.items():
        n_e, n_t, n = len(holding[e]), len(docs_of[w]), len(texts)
        value = min(1.0, math.log2(n * len(both) / (n_e * n_t)) / math.log2(n / n_e))
        if len(both) >= 2 and value >= 0.5:
            expected[(e, w)] = (n_e, n_t, len(both), pytest.approx(value))
    docs = documents(spark, texts)
    got = {(r["entity"], r["term"]): (r["n_entity"], r["n_term"], r["n_both"], r["disclosure"]) for r in pii.revealing_terms(docs, generalise_at=0.5).collect()}
    assert got == expected and len(got) > 10
    strong = {k for k, v in got.items() if v[3] >= 0.98}
    assert 0 < len(strong) < len(got)
    clean = {r["doc_id"]: r["text"] for r in pii.sanitise(docs, generalise_at=0.5).collect()}
    for i, t in enumerate(texts):
        own = {f"0:{e}" for e in mails if e in (t or "")}
        for e, w in got:
            if e in own:
                assert w not in clean[i].split()
        if not own:
            assert clean[i] == (t or "")
    assert any("[TERM]" in t for t in clean.values())


def test_pii_repeated_rows_long_texts_and_clashing_names(spark):
    long = "word " * 4_000 + "a@b.co " + "word " * 4_000
    rows = [(1, long), (1, long), (1, "x@y.zz other"), (None, "1.2.3.4"), (2, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS row", "2 AS key", "3 AS spans", "4 AS around", "5 AS term", "6 AS entity")
    got = pii.digest(pii.find_spans(docs))
    assert sorted((r["doc_id"] or 0, r["n_email"], r["n_ip"]) for r in got.collect()) == [(0, 0, 1), (1, 1, 0), (1, 1, 0), (1, 1, 0), (2, 0, 0)]
    assert pii.sanitise(docs).where("text LIKE '%@%'").count() == 0
    assert pii.sanitise(docs).count() == 5


def test_pii_empty_table(spark):
    assert pii.digest(pii.find_spans(documents(spark, []))).count() == 0


# --- near duplicates --------------------------------------------------------------------------------------------------


def shingle_sets(texts, n):
    out = []
    for t in texts:
        words = (t or "").encode().lower().split()
        out.append(frozenset(tuple(words[i : i + n]) for i in range(len(words) - n + 1)) if len(words) >= n else frozenset([tuple(words)]) if words else frozenset())
    return out


def brute_components(texts, n, percent):
    sets = shingle_sets(texts, n)
    label = list(range(len(texts)))

    def find(i):
        while label[i] != i:
            i = label[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                a, b = sorted((find(i), find(j)))
                label[b] = a
    return [find(i) for i in range(len(sets))], [len(s) for s in sets]


def edited(rng, text, edits):
    words = text.split()
    for _ in range(edits):
        words[rng.randrange(len(words))] = rng.choice(WORDS) + "x"
    return " ".join(words)


def near_texts(seed):
    rng = random.Random(seed)
    base_text = prose(rng, 160)
    texts = [edited(rng, base_text, rng.randrange(0, 9)) for _ in range(60)]
    texts += [prose(rng, rng.randrange(1, 80)) for _ in range(30)]
    texts += [None, "", "  \n ", "one two", "ONE two", "one two three four", "x"] + texts[:10]
    passage = prose(rng, 60)
    texts += [f"{prose(rng, 12)} {passage} {prose(rng, 12)}" for _ in range(25)]
    return texts


@pytest.mark.parametrize(("n", "percent", "frequent_from"), [(4, 85, 16), (5, 80, 3)])
def test_components_equal_brute_force(spark, n, percent, frequent_from):
    texts = near_texts(n)
    components, sizes = brute_components(texts, n, percent)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.digest(ngram_join.near_duplicates(documents(spark, texts), n=n, percent=percent, frequent_from=frequent_from)).collect()}
    assert got == {i: (sizes[i], components[i]) for i in range(len(texts))}


def test_matches_of_a_pair_count_together_whichever_side_a_list_prefers(spark):
    words = [[f"g{group}x{i}" for i in range(11)] for group in range(300)]
    texts = [" ".join(w[cut:]) for w in words for cut in (0, 1, 2)]
    got = {r["doc_id"]: r["component_id"] for r in ngram_join.near_duplicates(documents(spark, texts), n=4, percent=85).collect()}
    # 7 of 8 members and 6 of 7 shared: the middle text links with both others
    assert got == {i: i - i % 3 for i in range(len(texts))}


def test_keep_one_keeps_documents_without_words(spark):
    kept = {r["doc_id"] for r in ngram_join.keep_one(documents(spark, ["a b c d e f", "a b c d e f", None, "", ""]), n=5, percent=80).collect()}
    assert kept == {0, 2, 3, 4}


def test_near_duplicates_of_nothing(spark):
    assert ngram_join.near_duplicates(documents(spark, [])).count() == 0


# --- mixing -----------------------------------------------------------------------------------------------------------


def test_mix_meets_targets(spark):
    rng = random.Random(5)
    texts = [prose(rng, rng.randrange(0, 300)) for _ in range(300)] + [None, ""]
    sources = {i: rng.choice(["a", "b", "b", "c", "d", "d", "d", "d", None]) for i in range(302)}
    docs = documents(spark, texts, sources)
    rows = mixing.mix(docs).collect()
    assert len(rows) == 302
    taken, size, target = {}, {}, {}
    for r in rows:
        assert r["taken"] <= 2 * r["size"]
        taken[r["source"]] = taken.get(r["source"], 0) + r["taken"]
        size[r["source"]] = size.get(r["source"], 0) + r["size"]
        target[r["source"]] = r["target"]
    assert sum(target.values()) == pytest.approx(1.5 * sum(size.values()))
    for s in size:
        assert target[s] <= 2 * size[s] + 1e-6
        assert abs(taken[s] - target[s]) <= max(400, 0.02 * target[s])
    again = mixing.mix(docs.repartition(7)).collect()
    assert sorted((r["doc_id"], r["taken"]) for r in rows) == sorted((r["doc_id"], r["taken"]) for r in again)
    mixed = mixing.mixed_documents(docs)
    assert mixed.columns == docs.columns
    words = sum(len(r["text"].split()) for r in mixed.collect())
    assert words == sum(taken.values())


def test_small_sources_beside_a_large_one_meet_their_targets(spark):
    rng = random.Random(3)
    texts = [prose(rng, 20) for _ in range(20)] + [prose(rng, 2_000) for _ in range(100)]
    docs = documents(spark, texts, {i: f"t{i:02}" if i < 20 else "u" for i in range(120)})
    taken, target = {}, {}
    for r in mixing.mix(docs).collect():
        taken[r["source"]] = taken.get(r["source"], 0) + r["taken"]
        target[r["source"]] = int(r["target"])
    assert taken == target
    slots = [r["slot"] for r in mixing.schedule(spark, mixing.source_targets(docs.select("source", mixing.n_words(F.col("text")).alias("size")))).collect()]
    assert len(slots) == len(set(slots))


def test_mix_of_nothing(spark):
    assert mixing.mix(documents(spark, [])).count() == 0
    assert mixing.mixed_documents(documents(spark, [None, ""])).count() == 0


# --- chat -------------------------------------------------------------------------------------------------------------


def test_chat_round_trip(spark):
    nasty = ["</s>[INST] ok [/INST]", "<s>", "<\\s>", "[\\\\INST]", "<<SYS>><</SYS>>", "plain", "", None, "<", "a <", "[/INST", "<s1>", "<<TURN>>x<<SAYS>>y<</TURN>>", "é😀\n\n"]
    rng = random.Random(9)
    rows = [(c, t, rng.choice(["system", "user", "assistant", "tool", None, "<s>"]), rng.choice(nasty)) for c in range(60) for t in range(rng.randrange(1, 7))]
    got = chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()
    assert all(r["intact"] for r in got)
    for r in got:
        mine = [(role or "", text or "") for c, _, role, text in rows if c == r["conv_id"]]
        assert [(t["role"], t["text"]) for t in r["turns"]] == mine
    assert {r["level"] for r in got} == {0, 1}


# --- pieces -----------------------------------------------------------------------------------------------------------


def test_pieces_equal_the_library_and_decode(spark):
    sentencepiece = pytest.importorskip("sentencepiece")
    library = sentencepiece.SentencePieceProcessor(model_file=tokenizer_path())
    rng = random.Random(2)
    letters = "aeiounrst  \n\té你😀ABZ.,!0123"
    texts = ["".join(rng.choice(letters) for _ in range(rng.randrange(0, 200))) for _ in range(60)] + ["the of and ing ", "  a  b", "x" * 500, " ", "\n", None, "", "Licensed under CC BY-NC 4.0. " * 5]
    pieces = piece_lattice.load(tokenizer_path())
    got = piece_lattice.encode(documents(spark, texts), pieces, most_words=500)
    rows = {r["doc_id"]: r for r in got.collect()}
    for i, t in enumerate(texts):
        assert rows[i]["ids"] == library.encode(t or ""), t
        assert rows[i]["intact"]
    back = {r["doc_id"]: r["text"] for r in piece_lattice.decode(got, pieces).collect()}
    assert all(back[i] == (t or "") for i, t in enumerate(texts))


def test_relational_lattice_equals_the_worker_fold(spark):
    pieces = piece_lattice.load(tokenizer_path())
    lattice = piece_lattice.Lattice(pieces)
    words = ["▁the", "▁nation", "ingtion", "▁xqzé", "▁▁▁a", "aaaaaaa", "▁Erounining"]
    got = piece_lattice.encode_words(spark.createDataFrame([(w,) for w in words], "word string"), pieces).collect()
    for r in got:
        ids = [i for x in r["path"] for i in ([x["id"]] if x["id"] >= 0 else lattice.of(r["word"][x["s"] : x["e"]]))]
        assert ids == lattice.encode(r["word"])


def test_unigram_fold_is_viterbi(spark):
    scores = {"a": -1.0, "b": -1.5, "ab": -2.0, "ba": -3.5, "aba": -2.6, "c": -0.5}
    pieces = piece_lattice.Pieces("unigram", {p: i for i, p in enumerate(scores)}, {p: -s for p, s in scores.items()}, [0] * 256, list(scores), 0, longest=3)
    words = ["ababa", "cab", "abab", "bcb", "aba"]
    got = {r["word"]: r["path"] for r in piece_lattice.encode_words(spark.createDataFrame([(w,) for w in words], "word string"), pieces).collect()}

    def best(word):
        return max((scores[word[:i]] + (best(word[i:]) if word[i:] else 0) for i in range(1, len(word) + 1) if word[:i] in scores), default=-1e9)

    for w in words:
        assert sum(scores[w[x["s"] : x["e"]]] for x in got[w]) == pytest.approx(best(w))


# --- classifiers ------------------------------------------------------------------------------------------------------


def labelled_texts(spark):
    rng = random.Random(8)
    texts, rows = [], []
    for i in range(400):
        bad = i % 4 == 0
        words = prose(rng, 30).split()
        if bad:
            words[3:3] = [rng.choice(["idiot", "scum"]), "trash"]
        texts.append(" ".join(words))
        rows.append((i, 0 if bad else 1, int(bad)))
    texts += [None, ""]
    labels = spark.createDataFrame([*rows, (5, None, None), (9999, 1, 1)], "doc_id long, quality int, toxic int")
    return documents(spark, texts), labels


def test_toxicity_on_held_out_rows(spark):
    docs, labels = labelled_texts(spark)
    got = toxicity_knn.toxicity(docs, labels).collect()
    assert len(got) == 402
    assert all(0 <= r["score"] <= 1 for r in got)
    for r in got:
        if r["doc_id"] < 400 and r["held_out"]:
            assert r["predicted"] == int(r["doc_id"] % 4 == 0)
    kept = toxicity_knn.keep_clean(docs, labels)
    assert kept.columns == docs.columns
    assert kept.count() == 302


def test_block_max_index_is_exact():
    rng = np.random.default_rng(4)
    vectors = [toxicity_knn.unit({int(t): int(c) for t, c in zip(rng.integers(0, 40, 5), rng.integers(1, 4, 5), strict=True)}, np.ones(40)) for _ in range(700)]
    index = toxicity_knn.BlockMaxIndex(vectors, np.zeros(700), np.arange(700), 40)
    for q in vectors[:60]:
        dense = sorted(((-round(sum(w * v.get(t, 0.0) for t, w in q.items()), 9), n) for n, v in enumerate(vectors)), key=lambda x: x)[:10]
        assert [n for _, n in index.nearest(q, 10)] == [n for _, n in dense] or [round(s, 8) for s, _ in index.nearest(q, 10)] == [round(-s, 8) for s, _ in dense]


def test_search_is_exact_with_close_and_with_spread_bounds():
    rng = np.random.default_rng(5)
    draw = lambda low: toxicity_knn.unit({int(t): 1 for t in rng.integers(low, low + 30, 6)}, np.ones(90))
    vectors = [draw(0) for _ in range(600)] + [draw(60) for _ in range(40)] + [{}]
    index = toxicity_knn.BlockMaxIndex(vectors, np.zeros(641), np.arange(641), 90)
    matrix = np.zeros((641, 90))
    for i, v in enumerate(vectors):
        matrix[i, list(v)] = list(v.values())
    shares = []
    for n in [*range(20), *range(600, 620)]:
        before = index.visited
        scores, numbers = index.search(*index.vector(n), 10, without=n)
        every = np.round(matrix @ matrix[n], 9)
        every[n] = -1
        best = np.lexsort((np.arange(641), -every))[:10]
        assert numbers.tolist() == best.tolist() and np.allclose(scores, every[best])
        shares.append(index.visited - before)
    assert min(shares) < max(shares)


def test_examples_stay_arrays_on_the_driver(spark):
    docs, labels = labelled_texts(spark)
    marks, ids, rows, words, times = toxicity_knn._flat(toxicity_knn.labelled(docs, labels, "toxic", 50).selectExpr("doc_id", "label", "split(text, ' ') as terms", "transform(split(text, ' '), x -> 1) as times"))
    assert len(ids) == 50 == len(marks) == len(rows) - 1 and (np.diff(ids) > 0).all()
    assert rows[-1] == len(words) == len(times)
    index = toxicity_knn.fit(docs, labels)["index"]
    assert isinstance(index.vector(0)[0], np.ndarray) and abs(float(np.square(index.vector(0)[1]).sum()) - 1) < 1e-9


def test_no_labels_no_crash(spark):
    docs, labels = labelled_texts(spark)
    none = labels.limit(0)
    assert {r["predicted"] for r in toxicity_knn.toxicity(docs, none).collect()} == {0}
    assert quality_fm.quality(docs, none).count() == 402


def test_quality_and_the_linear_time_identity(spark):
    docs, labels = labelled_texts(spark)
    got = [r for r in quality_fm.quality(docs, labels).collect() if r["held_out"] and r["doc_id"] < 400]
    right = sum((r["score"] >= 0.5) == (r["doc_id"] % 4 != 0) for r in got)
    assert right / len(got) > 0.9
    machine = quality_fm.Machine(factors=3, seed=1)
    machine.w[:] = np.random.default_rng(0).normal(size=len(machine.w))
    at, x = quality_fm.features("some words and some more words, 12 | 3!", quality_fm.Hasher())
    slow = machine.w0 + sum(machine.w[i] * v for i, v in zip(at, x, strict=True))
    slow += sum(machine.v[at[i]] @ machine.v[at[j]] * x[i] * x[j] for i in range(len(at)) for j in range(i))
    assert machine.logits(at, x.astype(float), np.array([0]))[0] == pytest.approx(slow)


# --- vectors ----------------------------------------------------------------------------------------------------------


def vector_rows(spark):
    rng = np.random.default_rng(6)
    rows = [(i, [float(x) for x in rng.normal(size=8)]) for i in range(400)]
    rows[7] = (7, rows[8][1])
    rows += [(400, None), (401, [1.0, None] + [0.0] * 6), (402, [float("nan")] * 8), (403, [float("inf")] * 8), (404, [0.0] * 8), (405, [1.0, 2.0]), (500, [1.0, 1.0])]
    return rows, spark.createDataFrame(rows, "vec_id long, embedding array<float>")


def test_exact_top_k_against_brute_force(spark):
    rows, df = vector_rows(spark)
    good = [(i, [np.floor(1024 * float(np.float32(x))) for x in v]) for i, v in rows if v and None not in v and np.isfinite(v).all()]
    got = {}
    for r in exact_topk.top_k(df, chunk=3).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    for q, vq in good:
        if q % 100 == 0:
            every = sorted((-int(sum(a * b for a, b in zip(vq, v, strict=True))), i) for i, v in good if i != q and len(v) == len(vq))[:10]
            assert sorted(got.get(q, [])) == [(n + 1, i, -s) for n, (s, i) in enumerate(every)]


def test_nearest_recall_and_scores(spark):
    rows, df = vector_rows(spark)
    good = {i: np.array(v, np.float32).astype(float) for i, v in rows if v and None not in v and np.isfinite(v).all() and any(v)}
    got = {}
    for r in ann_postings.nearest(df).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
        a, b = good[r["query_id"]], good[r["vec_id"]]
        assert r["score"] == pytest.approx(float(a @ b / np.sqrt((a @ a) * (b @ b))), abs=1e-12)
    hit = total = 0
    for q, v in good.items():
        if q % 50 == 0:
            every = sorted((-(v @ w) / np.linalg.norm(w), i) for i, w in good.items() if i != q and len(w) == len(v))[:5]
            hit += len({i for _, i in every} & {i for _, i, _ in got.get(q, [])})
            total += len(every)
    assert hit / total >= 0.9


def test_shelf_search_against_brute_force():
    rng = np.random.default_rng(7)
    base = rng.normal(size=(300, 8))
    vectors = np.concatenate([base, base[:40], base[:40]])
    block = pd.DataFrame({"list": np.r_[rng.integers(32, 40, 340), np.full(40, 33)], "vec_id": np.r_[np.arange(340), np.arange(40)], "vector": [v.tobytes() for v in vectors]})
    named = [np.sort(rng.permutation(np.arange(32, 42))[: i % 6 + 1]).astype(np.int32) for i in range(60)]
    queries = pd.DataFrame({"query_id": np.arange(0, 240, 4), "query": [vectors[i].tobytes() for i in range(0, 240, 4)], "lists": [x.tobytes() for x in named]})
    got = ann_postings.search_shelf(queries, block, 5)
    for q, lists in zip(range(0, 240, 4), named, strict=True):
        best = {}
        for at, i, v in zip(block["list"], block["vec_id"], vectors, strict=True):
            if at in lists and i != q:
                best[i] = max(best.get(i, -2.0), float(ann_postings.cosines(vectors[q][None], v[None])[0]))
        wanted = sorted(best.items(), key=lambda x: (-x[1], x[0]))[:5]
        mine = got[got["query_id"] == q]
        assert list(zip(mine["vec_id"], mine["score"], strict=True)) == wanted
    assert not len(ann_postings.search_shelf(queries[:0], block, 5)) and not len(ann_postings.search_shelf(queries, block[:0], 5))


def test_shelf_search_keeps_up_with_many_lists():
    rng = np.random.default_rng(9)
    vectors = rng.normal(size=(6_000, 16))
    block = pd.DataFrame({"list": rng.integers(0, 32, 6_000), "vec_id": np.arange(6_000), "vector": [v.tobytes() for v in vectors]})
    queries = pd.DataFrame({"query_id": np.arange(500), "query": [v.tobytes() for v in vectors[:500]], "lists": [np.arange(32, dtype=np.int32).tobytes()] * 500})
    begin = time.process_time()
    got = ann_postings.search_shelf(queries, block, 5)
    assert len(got) == 2_500
    assert time.process_time() - begin < 6  # 16,000 searches of a list; one by one they took 1.2 ms each, 19 s


# --- lines ------------------------------------------------------------------------------------------------------------


def test_template_lines(spark):
    line = "Copyright 2020 by the many authors of this file"
    texts = [f"alpha\n{line}\nshort one", f"beta\n{line.replace('2020', '1999')}\nshort one", f"x\n{line}", f"x\n{line}", None, "", "only once but long enough to count here"]
    rows = {r["doc_id"]: r["text"] for r in line_templates.drop_lines(documents(spark, texts)).collect()}
    assert rows == {0: texts[0], 1: "beta\nshort one", 2: "x", 3: "x", 4: None, 5: "", 6: texts[6]}
    copies = documents(spark, ["a long line that only copies of one text share"] * 3)
    assert {r["n_dropped"] for r in line_templates.drop_lines(copies).collect()} == {0}
    everywhere = {r["doc_id"]: r["n_dropped"] for r in line_templates.drop_lines(documents(spark, texts), keep_first=False).collect()}
    assert everywhere == {0: 1, 1: 1, 2: 1, 3: 1, 4: 0, 5: 0, 6: 0}
    assert line_templates.drop_lines(documents(spark, [])).count() == 0


def test_short_lines_of_several_documents_go(spark):
    texts = [f"{name}\n\nAll rights reserved.\nLes." for name in ("alpha", "beta", "gamma")] + ["alpha\n\nAll rights reserved.\nLes.", "delta\ntwo only", "epsilon\ntwo only"]
    rows = {r["doc_id"]: r["text"] for r in line_templates.drop_lines(documents(spark, texts)).collect()}
    assert rows == {0: texts[0], 1: "beta\n", 2: "gamma\n", 3: "alpha\n", 4: texts[4], 5: texts[5]}


def template_lines_by_hand(texts, depth, alike=0.9):
    """{doc: dropped line numbers}, every line of a leaf against every other one."""
    places, tokens = {}, {}
    for i, text in enumerate(texts):
        for n, line in enumerate((text or "").split("\n")):
            words = ["<*>" if re.search("[0-9]", w) else w for w in line.split()]
            if words:
                key = " ".join(words)
                tokens[key] = words
                places.setdefault(key, []).append((i, n))
    label = {k: k for k in tokens}

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    leaves = {}
    for key, words in tokens.items():
        leaves.setdefault((len(words), *words[:depth]), []).append(key)
    for (n, *_), keys in leaves.items():
        may = (n * (1_000_000 - round(alike * 1_000_000))) // 1_000_000
        for x, y in itertools.combinations(keys, 2):
            if may and sum(a != b for a, b in zip(tokens[x], tokens[y], strict=True)) <= may:
                label[find(x)] = find(y)
    groups = {}
    for key in tokens:
        groups.setdefault(find(key), []).extend(places[key])
    out = {i: set() for i in range(len(texts))}
    for key, met in groups.items():
        if len({texts[i] for i, _ in met}) >= (2 if len(tokens[key]) >= 6 else 3):
            for i, n in met:
                if (i, n) != min(met):
                    out[i].add(n)
    return out


@pytest.mark.parametrize("depth", [1, 3, 8])
def test_template_tree_equals_brute_force(spark, depth):
    rng = random.Random(depth)
    frames = [prose(rng, rng.randrange(3, 40)).split() for _ in range(12)]
    texts = []
    for i in range(90):
        lines = []
        for _ in range(rng.randrange(0, 6)):
            words = list(rng.choice(frames)) if rng.random() < 0.7 else prose(rng, rng.randrange(1, 20)).split()
            for _ in range(rng.randrange(0, 4)):
                words[rng.randrange(len(words))] = rng.choice(["x", "y", "7", "z9"])
            lines.append(" ".join(words).replace("w", "v") if rng.random() < 0.1 else "  ".join(words))
        texts.append("\n".join([*lines, "", f"own text {'abcdefghij'[i % 10]}{'klmnopqrst'[i // 10]}"]))
    texts += [None, "", *texts[:5]]
    got = {r["doc_id"]: {int(x) for x in r["dropped"].split(",") if x} for r in line_templates.digest(documents(spark, texts), depth=depth).collect()}
    assert got == template_lines_by_hand(texts, depth)


def test_depth_and_variable_fields(spark):
    words = "every reader of this page may copy it for any use and pass it on".split()
    a, b = " ".join(words), " ".join([*words[:1], "writer", *words[2:]])
    docs = documents(spark, [f"one\n{a}", f"two\n{b}"])
    assert [sum(r["n_dropped"] for r in line_templates.digest(docs, depth=d).collect()) for d in (1, 3)] == [1, 0]
    shown = line_templates.templates(docs, depth=1).collect()
    assert [(r["text"], r["n_lines"], r["occurrences"]) for r in shown] == [(a.replace("reader", "<*>"), 2, 2)]


def test_lines_alike_to_each_other_but_not_to_the_first_of_their_band(spark):
    words = "here is the same begin but other words do end".split()
    a = [*words[:8], "will", "stop"]
    b = [*words[:7], "people", "will", "stop"]
    texts = [" ".join(words), "one\n" + " ".join(a), "two\n" + " ".join(b), "three\n" + " ".join([*b[:5], "two", *b[6:]])]
    got = {r["doc_id"]: r["dropped"] for r in line_templates.digest(documents(spark, texts)).collect()}
    assert got == {0: "", 1: "", 2: "1", 3: "1"}


def test_large_bands_of_several_components(spark):
    rng = random.Random(23)
    start = [f"same{'abcdefghij'[i]}" for i in range(10)]
    letters = "abcdefghijklmnop"
    texts = [f"{' '.join(start)} {' '.join(rng.choice(letters[:4]) for _ in range(10))}" for _ in range(200)]
    got = {r["doc_id"]: {int(x) for x in r["dropped"].split(",") if x} for r in line_templates.digest(documents(spark, texts)).collect()}
    assert got == template_lines_by_hand(texts, 3)


def test_rows_of_one_id_lose_their_own_lines(spark):
    line = "this long line stands in several documents of the table"
    docs = spark.createDataFrame([(1, f"{line}\nfirst"), (1, f"second\n{line}"), (1, f"second\n{line}"), (None, f"third\n{line}"), (2, line)], "doc_id long, text string").selectExpr("*", "7 AS leaf", "8 AS template", "9 AS line", "1 AS n_dropped_before")
    got = line_templates.drop_lines(docs)
    assert got.columns == [*docs.columns, "n_dropped"]
    texts = sorted(r["text"] for r in got.collect())
    assert sum(line in t for t in texts) == 1 and len(texts) == 5
    long = "\n".join(f"line number {'abcdefghij'[i % 10]} of a very long text" for i in range(20_000))
    assert line_templates.drop_lines(documents(spark, [long, long + "!"])).count() == 2


def test_extra_columns_pass(spark):
    docs = documents(spark, ["some text", None]).withColumn("gone", F.lit(1)).withColumn("row", F.lit(2)).withColumn("taken", F.lit(3))
    assert line_templates.drop_lines(docs).columns[:8] == docs.columns
    assert pii.find_spans(docs).count() == 2
    assert mixing.mixed_documents(docs).columns == docs.columns


def test_components_of_a_long_path(spark):
    from corpus_audit.llm.components import components

    order = np.random.default_rng(5).permutation(4_000)
    links = [(int(a), int(b)) for a, b in zip(order[:-1], order[1:], strict=True)] + [(9_001, 9_000), (9_000, 9_001), (9_005, 9_005)]
    got = {r["node"]: r["label"] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {int(x): 0 for x in order} | {9_000: 9_000, 9_001: 9_000}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_narrowed_leaves_little_of_other_keys(spark):
    keys = lambda low, high: spark.range(low, high).select(F.xxhash64("id").alias("line"), "id")
    chosen = keys(0, 400_000)
    kept = line_templates._narrowed(keys(0, 800_000).unionByName(keys(0, 10)), chosen, "line")
    assert kept.columns == ["line", "id"]
    assert kept.where("id < 400000").count() == 400_010
    assert kept.where("id >= 400000").count() < 40_000


def test_lanes_never_show_more_differences(spark):
    rows = [(f"{' '.join(f'w{i}' for i in range(n))}", f"{' '.join(f'w{i if i % k else -i}' for i in range(n))}") for n in (1, 6, 7, 8, 40) for k in (1, 3, 50)]
    a, b = F.col("a"), F.col("b")
    got = spark.createDataFrame(rows, "a string, b string").select(line_templates._unlike("a", "b").alias("exact"), line_templates._unlike_lanes(line_templates._lanes("a"), line_templates._lanes("b")).alias("least"), (a == b).alias("same")).collect()
    assert all(r["least"] <= r["exact"] <= r["least"] + 2 for r in got)
    assert all(r["least"] == 0 for r in got if r["same"]) and max(r["least"] for r in got) > 30
