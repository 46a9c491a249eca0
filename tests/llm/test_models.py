"""Operators 5 and 10: held-out accuracy on small made-up tables, and the defined cases."""

import random
import zlib

import numpy as np
import pytest

from saferoads.llm import language_crf, toxicity


def held(d, parts=4):
    return zlib.crc32(str(d).encode()) % parts == 2


def prose(rng, syllables, n):
    return " ".join("".join(rng.choice(syllables) for _ in range(rng.randint(1, 4))) for _ in range(n))


def test_toxicity_catches_misspellings(spark):
    rng = random.Random(1)
    calm = "th er on an re he in ed nd ha at en es or nt ea ti to it st io le is ou ar as de rt ve".split()
    bad = ["blockhead", "nitwitted", "scumbaggy"]
    odd = ["blockheaad", "nitw1tted", "scumbagggy"]
    docs, labels = [], []
    for i in range(500):
        toxic = i % 4 == 0
        words = prose(rng, calm, rng.randint(5, 120)).split()
        if toxic:
            words.insert(rng.randrange(len(words)), rng.choice(odd if held(i) else bad))
        docs.append((i, " ".join(words)))
        labels.append((i, int(toxic)))
    docs += [(900, None), (901, ""), (902, "###")]
    d = spark.createDataFrame(docs, "doc_id bigint, text string")
    trained = toxicity.train(d, spark.createDataFrame(labels, "doc_id bigint, toxic int"))
    rows = {r["doc_id"]: r for r in toxicity.score(d, trained).collect()}
    known = dict(labels)
    tried = [i for i in known if held(i)]
    ranked = sorted(tried, key=lambda i: rows[i]["score"])
    pairs = [(k, i) for k, i in enumerate(ranked) if known[i]]
    n = len(pairs)
    assert (sum(k for k, _ in pairs) - n * (n - 1) / 2) / n / (len(tried) - n) > 0.9  # area under the curve
    assert np.mean([rows[i]["predicted"] == known[i] for i in tried]) > 0.8
    assert all(0 <= r["score"] <= 1 for r in rows.values()) and rows[900]["score"] == rows[901]["score"] == rows[902]["score"] < 0.3
    kept = toxicity.drop_toxic(d, trained)
    assert kept.columns == d.columns and kept.count() == sum(not r["predicted"] for r in rows.values())


def test_toxicity_without_labels(spark):
    d = spark.createDataFrame([(1, "a b"), (2, None)], "doc_id bigint, text string")
    trained = toxicity.train(d, spark.createDataFrame([], "doc_id bigint, toxic int"))
    assert {r["score"] for r in toxicity.score(d, trained).collect()} == {0.0}
    assert toxicity.score(d.limit(0), trained).count() == 0


SYLLABLES = {"en": "th er on and re he ing ed".split(), "fr": "eau ou le ré que ment è".split(), "de": "sch ung ein ß keit ver".split()}


@pytest.fixture(scope="module")
def languages(spark):
    rng = random.Random(2)
    rows = [(i, prose(rng, SYLLABLES[lang], rng.randint(3, 150)), lang) for i, lang in ((i, rng.choice(list(SYLLABLES))) for i in range(300))]
    rows += [(900, None, "en"), (901, "", None), (902, "12 34 !!", "fr"), (903, prose(rng, SYLLABLES["en"], 60) + " " + prose(rng, SYLLABLES["fr"], 25), None)]
    d = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    return rows, d, language_crf.train(d)


def test_language(languages):
    rows, d, model = languages
    got = {r["doc_id"]: r for r in language_crf.predict(d, model).collect()}
    tried = [(i, lang) for i, _, lang in rows[:300] if held(i)]
    assert np.mean([got[i]["lang_pred"] == lang for i, lang in tried]) > 0.97
    assert [got[i]["lang_pred"] for i in (900, 901, 902)] == ["und"] * 3 and got[903]["lang_pred"] == "en"
    assert all(0 <= r["score"] <= 1 for r in got.values())
    assert language_crf.predict(d.limit(0), model).count() == 0


def test_words_of_mixed_text(languages):
    _, d, model = languages
    words = [r for r in language_crf.word_labels(d.where("doc_id = 903"), model).orderBy("word_index").collect()]
    assert np.mean([w["lang_pred"] == "en" for w in words[:60]]) > 0.9 and np.mean([w["lang_pred"] == "fr" for w in words[60:]]) > 0.8


def test_forward_backward_equals_enumeration():
    import itertools

    rng = np.random.default_rng(4)
    score, moves = rng.normal(size=(1, 4, 3)), rng.normal(size=(3, 3))
    there = np.array([[True, True, True, False]])
    post, pairs = language_crf.forward_backward(score, there, moves)
    weight = {p: np.exp(sum(score[0, t, p[t]] for t in range(3)) + sum(moves[p[t], p[t + 1]] for t in range(2))) for p in itertools.product(range(3), repeat=3)}
    total = sum(weight.values())
    for t in range(3):
        assert np.allclose(post[0, t], [sum(w for p, w in weight.items() if p[t] == k) / total for k in range(3)])
    assert np.allclose(pairs, [[sum(w * sum((p[t], p[t + 1]) == (a, b) for t in range(2)) for p, w in weight.items()) / total for b in range(3)] for a in range(3)])


def test_blocks_of_a_text_are_one_chain():
    """Texts of 200, 64, 65 and 1 words in blocks of 64 against a recursion over each whole text."""
    rng = np.random.default_rng(9)
    sizes, k = [200, 64, 65, 1, 130], 4
    doc = np.repeat(np.arange(len(sizes)), sizes)
    score, moves = rng.normal(size=(len(doc), k)) * 2, rng.normal(size=(k, k)) * 2
    cell, there = language_crf.chains(doc)
    table = score[cell]
    post, _ = language_crf.forward_backward(table, there, moves, with_moves=False, reached=language_crf.messages(table, there, moves, doc[cell[:, 0]]))
    got = np.empty((len(doc), k))
    got[cell[there]] = post[there]
    for i, n in enumerate(sizes):
        e, step = np.exp(score[doc == i]), np.exp(moves)
        ahead, behind = [e[0] / e[0].sum()], [np.ones(k)]
        for t in range(1, n):
            a = np.array([sum(ahead[-1][p] * step[p, q] for p in range(k)) * e[t, q] for q in range(k)])
            ahead.append(a / a.sum())
        for t in range(n - 2, -1, -1):
            b = np.array([sum(step[p, q] * e[t + 1, q] * behind[-1][q] for q in range(k)) for p in range(k)])
            behind.append(b / b.sum())
        want = np.array(ahead) * np.array(behind[::-1])
        assert np.allclose(got[doc == i], want / want.sum(1, keepdims=True))


def test_toxic_texts_without_words(spark):
    rows = [(i, "!!!" if i % 2 else f"calm words {i}") for i in range(40)]
    d = spark.createDataFrame(rows, "doc_id bigint, text string")
    trained = toxicity.train(d, spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id bigint, toxic int"))
    assert len({r["score"] for r in toxicity.score(d, trained).collect()}) == 1


def test_scored_text_repeated_long_and_with_clashing_columns(spark, languages):
    _, _, model = languages
    rng = random.Random(3)
    long = prose(rng, SYLLABLES["fr"], 60_000)
    d = spark.createDataFrame([(1, long, 0.5, "x"), (2, "th er on", 0.5, "x"), (2, "th er on", 0.5, "y"), (None, "ung keit sch", 0.5, "z")], "doc_id bigint, text string, score double, held_out string")
    got = sorted((str(r["doc_id"]), r["lang_pred"]) for r in language_crf.predict(d, model).collect())
    assert got == [("1", "fr"), ("2", "en"), ("2", "en"), ("None", "de")]
    trained = toxicity.train(d, spark.createDataFrame([(1, 0), (2, 1)], "doc_id bigint, toxic int"))
    assert toxicity.score(d, trained).count() == 4 and toxicity.drop_toxic(d, trained).columns == d.columns
