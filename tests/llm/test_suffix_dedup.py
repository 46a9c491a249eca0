"""Operator 1 against brute force over all windows."""

import hashlib
import random
from collections import Counter

import pytest

from saferoads.llm.suffix_dedup import remove_repeats

SCHEMA = "doc_id bigint, text string"


def brute(rows, depth):
    raws = [(d, (t or "").encode()) for d, t in rows]
    seen = Counter(r[i : i + depth] for _, r in raws for i in range(len(r) - depth + 1))
    out = []
    for d, r in raws:
        gone = [False] * (len(r) + 1)
        for i in range(len(r) - depth + 1):
            if seen[r[i : i + depth]] > 1:
                gone[i : i + depth] = [True] * depth
        spans = sum(gone[i] and not gone[i - 1] for i in range(len(r)))
        kept = bytes(b for b, g in zip(r, gone) if not g)
        out.append((d, len(r), len(r) - len(kept), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def made_up(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcé") for _ in range(rng.randint(1, 6)))
    passages = [" ".join(word() for _ in range(rng.randint(5, 60))) for _ in range(4)]
    rows = []
    for i in range(24):
        parts = []
        for _ in range(rng.randint(1, 5)):
            parts.append(rng.choice(passages) if rng.random() < 0.5 else " ".join(word() for _ in range(rng.randint(1, 40))))
        rows.append((i, " ".join(parts)))
    rows += [(30, rows[3][1]), (31, rows[5][1][7:]), (32, "ab" * 150), (33, "xyz " * 40), (34, "ab" * 40), (35, None), (36, ""), (37, "q" * 300)]
    rows += [rows[0], (None, rows[1][1][:90])]
    return rows


@pytest.mark.parametrize("seed, depth, gram", [(1, 40, 8), (2, 60, 16), (3, 33, 30)])
def test_equals_brute_force(spark, seed, depth, gram):
    rows = made_up(seed)
    got = remove_repeats(spark.createDataFrame(rows, SCHEMA), depth, gram).collect()
    assert sorted((tuple(r) for r in got), key=str) == brute(rows, depth)


def test_empty_table(spark):
    assert remove_repeats(spark.createDataFrame([], SCHEMA)).count() == 0


def test_text_is_replaced_and_other_columns_stay(spark):
    same = "lorem ipsum dolor " * 3 + "unique one sed do eiusmod"
    df = spark.createDataFrame([(1, same, "x", 5), (2, same, "y", 6), (3, "short", "z", 5)], "doc_id bigint, text string, digit string, n_chars bigint")
    got = {r["doc_id"]: r for r in remove_repeats(df, 40, 8, replace_text=True).collect()}
    assert got[1]["text"] == got[2]["text"] == "" and got[1]["n_chars"] == 0
    assert got[3]["text"] == "short" and got[3]["n_chars"] == 5 and got[2]["digit"] == "y"


@pytest.mark.parametrize("seed, segment", [(4, 300), (5, 97), (6, 64)])
def test_texts_cut_into_segments_equal_brute_force(spark, monkeypatch, seed, segment):
    from saferoads.llm import suffix_dedup

    monkeypatch.setattr(suffix_dedup, "SEGMENT", segment)
    rng = random.Random(seed)
    long = ["".join(rng.choice("abcdefgh ") for _ in range(5000)) for _ in range(3)]
    rows = made_up(seed) + [(50, long[0]), (51, long[1]), (52, long[2] + long[1][700:1400]), (53, long[0][:250] * 8), (54, "xy" + long[2][333:999])]
    got = remove_repeats(spark.createDataFrame(rows, SCHEMA), 40, 8).collect()
    assert sorted((tuple(r) for r in got), key=str) == brute(rows, 40)


def test_unique_long_text_stays(spark):
    rng = random.Random(7)
    rows = [(i, "".join(rng.choices("abcdefghijklmnopqrstuvwxyz ", k=900_000))) for i in range(2)]
    assert [r["n_removed"] for r in remove_repeats(spark.createDataFrame(rows, SCHEMA)).collect()] == [0, 0]


def brute_words(rows, depth):
    """doc_id, words covered by windows of `depth` words that start anywhere else, remaining text."""
    import re

    spans = [(d, t or "", [(m.start(), m.end()) for m in re.finditer(rb"[^\x20\x09-\x0D]+", (t or "").encode())]) for d, t in rows]
    parts = [(d, t.encode(), at, [t.encode()[a:b] for a, b in at]) for d, t, at in spans]
    seen = Counter(tuple(w[i : i + depth]) for _, _, _, w in parts for i in range(len(w) - depth + 1))
    out = []
    for d, raw, at, w in parts:
        gone = [False] * len(w)
        for i in range(len(w) - depth + 1):
            if seen[tuple(w[i : i + depth])] > 1:
                gone[i : i + depth] = [True] * depth
        kept, last = b"", 0
        for i, g in enumerate(gone):
            if g and (i == 0 or not gone[i - 1]):
                kept += raw[last : at[i][0]]
            if g:
                last = at[i][1]
        out.append((d, sum(gone), (kept + raw[last:]).decode()))
    return sorted(out, key=str)


def wordy(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcé") for _ in range(rng.randint(1, 3)))
    passages = [[word() for _ in range(n)] for n in (9, 10, 11, 14, 60)]
    rows = []
    for i in range(40):
        parts = []
        for _ in range(rng.randint(1, 6)):
            parts += rng.choice(passages) if rng.random() < 0.5 else [word() for _ in range(rng.randint(1, 30))]
        rows.append((i, "".join(w + rng.choice([" ", "\n", "  ", "\t"]) for w in parts)))
    return rows + [(50, rows[3][1]), (51, "x " * 70), (52, None), (53, ""), (54, "one"), rows[7], (55, " \n"), (None, rows[2][1])]


@pytest.mark.parametrize("seed, segment", [(1, 1 << 16), (2, 40), (3, 64)])
def test_windows_of_words_equal_brute_force(spark, seed, segment):
    from saferoads.llm.suffix_dedup import Unit

    rows = wordy(seed)
    unit = Unit(True, 10, 3, 4, segment)
    df = spark.createDataFrame(rows, SCHEMA)
    told = remove_repeats(df, passages=unit).collect()
    want = brute_words(rows, 10)
    assert sorted(((r["doc_id"], r["n_passage_words"]) for r in told), key=str) == sorted(((d, n) for d, n, _ in want), key=str)
    cut = remove_repeats(df, unit=unit, replace_text=True).collect()
    assert sorted(((r["doc_id"], r["text"] or "") for r in cut), key=str) == sorted(((d, t) for d, _, t in want), key=str)


def test_passages_at_their_least_length(spark):
    from saferoads.llm.suffix_dedup import word_unit

    rng = random.Random(3)
    word = lambda: "".join(rng.choices("abcdefghij", k=4))
    own = lambda n: " ".join(word() for _ in range(n))
    fifty, less = own(50), own(49)
    rows = [(1, own(30) + " " + fifty + " " + own(9)), (2, fifty + "\n" + own(80)), (3, own(60) + " " + less), (4, less + " " + own(5))]
    got = {r["doc_id"]: r["n_passage_words"] for r in remove_repeats(spark.createDataFrame(rows, SCHEMA), passages=word_unit()).collect()}
    assert got == {1: 50, 2: 50, 3: 0, 4: 0}


def test_columns_of_any_name_stay(spark):
    text = "ab cd ef gh " * 20
    df = spark.createDataFrame([(1, text, 7, "m", "x", "y", "z"), (2, text, 8, "n", "x", "y", "z")], "doc_id bigint, text string, _mark int, _doc string, _TH string, _cut string, _told string")
    got = remove_repeats(df, 40, 8, replace_text=True)
    assert got.columns == df.columns
    assert sorted((r["doc_id"], r["text"], r["_mark"], r["_doc"]) for r in got.collect()) == [(1, "", 7, "m"), (2, "", 8, "n")]


def test_a_long_word_and_a_long_text(spark):
    from saferoads.llm.suffix_dedup import pieces, word_unit

    raw = (b"a" * 700 + b" ") * 5 + b"b" * 5000 + b"\n" + b"cc " * 900
    assert b"".join(pieces(raw, 512)) == raw
    starts, ends = word_unit().byte_bounds(raw)
    assert [raw[a:b] for a, b in zip(starts, ends)] == raw.split()
