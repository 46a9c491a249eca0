"""Operator 3 against all pairs."""

import random

import pytest

from saferoads.llm.jaccard_join import allocate, components, keep_one, most_differences


def shingles(text, words):
    low = (text or "").translate({i: i + 32 for i in range(65, 91)})
    import re

    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    return {tuple(w[i : i + words]) for i in range(len(w) - words + 1)} or ({tuple(w)} if w else set())


def brute(rows, words, percent):
    sets = [shingles(t, words) for _, t in rows]
    ids = [d for d, _ in rows]
    up = {d: d for d in ids if d is not None}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if ids[i] is None or ids[j] is None or not sets[i] or not sets[j]:
                continue
            if 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                a, b = sorted((top(ids[i]), top(ids[j])))
                up[b] = a
    return sorted(((d, len(s), None if d is None else top(d)) for d, s in zip(ids, sets)), key=str)


def made_up(seed, longest):
    rng = random.Random(seed)
    vocabulary = ["w%d" % i for i in range(60)]
    rows, bases = [], []
    passage = [rng.choice(vocabulary) for _ in range(12)]
    for i in range(60):
        n = rng.randint(1, longest)
        w = [rng.choice(vocabulary) for _ in range(n)]
        if rng.random() < 0.4:
            w[rng.randrange(n + 1) : 0] = passage
        bases.append(w)
        rows.append((i, " ".join(w)))
    for i in range(60, 200):
        w = list(rng.choice(bases))
        for _ in range(rng.choice([0, 1, 1, 2, 4, max(1, len(w) // 25)])):
            k = rng.randrange(len(w) + 1)
            if rng.random() < 0.5 and len(w) > 1:
                del w[min(k, len(w) - 1)]
            else:
                w.insert(k, rng.choice(vocabulary))
        rows.append((i, " ".join(w).upper() if rng.random() < 0.2 else "\n".join(w)))
    rows += [(300, None), (301, ""), (302, "  \t"), (303, "one"), (304, "ONE"), (305, "one two"), (None, rows[0][1]), rows[5], (306, rows[5][1])]
    return rows


@pytest.mark.parametrize("seed, longest, words, percent", [(1, 12, 4, 85), (2, 40, 4, 85), (3, 160, 4, 85), (4, 90, 5, 80), (5, 16, 2, 80)])
def test_equals_all_pairs(spark, seed, longest, words, percent):
    rows = made_up(seed, longest)
    got = components(spark.createDataFrame(rows, "doc_id bigint, text string"), words, percent).collect()
    assert sorted((tuple(r) for r in got), key=str) == brute(rows, words, percent)


def test_large_buckets_in_blocks(spark, monkeypatch):
    from saferoads.llm import jaccard_join

    monkeypatch.setattr(jaccard_join, "HOT", 2)
    monkeypatch.setattr(jaccard_join, "BLOCK", 7)
    rows = made_up(6, 60)
    got = components(spark.createDataFrame(rows, "doc_id bigint, text string"), 4, 85).collect()
    assert sorted((tuple(r) for r in got), key=str) == brute(rows, 4, 85)


def test_one_of_each_group_stays(spark):
    rows = made_up(9, 60)
    kept = keep_one(spark.createDataFrame([(*r, "x") for r in rows], "doc_id bigint, text string, key string"), 5, 80).collect()
    want = sorted({c for d, _, c in brute(rows, 5, 80) if d is not None})
    assert sorted(r["doc_id"] for r in kept if r["doc_id"] is not None) == want and sum(r["doc_id"] is None for r in kept) == 1


def test_empty_table(spark):
    assert components(spark.createDataFrame([], "doc_id bigint, text string")).count() == 0


def test_allocation_covers_the_bound():
    for percent in (80, 85):
        for band in range(18):
            m, whole = allocate(band, percent)
            assert m > most_differences((2 << band) - 1, (2 << band) - 1, percent)
            assert whole == (band <= 3)


@pytest.mark.parametrize("words, percent", [(4, 85), (5, 80)])
def test_pairs_at_the_threshold_link(spark, words, percent):
    rng = random.Random(11)
    rows = []
    for i in range(400):
        a = rng.randint(33, 60)
        more = next(d for d in range(60, 0, -1) if 100 * a >= percent * (a + d))
        w = ["p%dx%d" % (i, k) for k in range(a + words - 1 + more)]
        rows += [(2 * i, " ".join(w[: a + words - 1])), (2 * i + 1, " ".join(w))]
    got = components(spark.createDataFrame(rows, "doc_id bigint, text string"), words, percent).collect()
    assert sorted(r["doc_id"] for r in got if r["component_id"] != r["doc_id"] // 2 * 2) == []


def test_pairs_whose_bounds_differ_link(spark):
    """Seven shingles more, at the threshold: found by search, one shared bucket at a spare of 0 on one side and 1 on the other."""
    rows = []
    for i in (546, 589, 1449, 2399, 3922):
        w = ["p%dx%d" % (i, k) for k in range(50 + i % 6)]
        rows += [(2 * i, " ".join(w[:-7])), (2 * i + 1, " ".join(w))]
    got = components(spark.createDataFrame(rows, "doc_id bigint, text string"), 4, 85).collect()
    assert [r["doc_id"] for r in got if r["component_id"] != r["doc_id"] // 2 * 2] == []


@pytest.mark.parametrize("words, percent", [(4, 85), (5, 80)])
def test_pairs_exactly_at_the_threshold_in_every_band(spark, words, percent):
    """For sizes from 2 to 300 the longest tail that still links, and one word more, which does not."""
    rng = random.Random(words)
    word = lambda: "".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=7))
    rows, links = [], []
    for i, n in enumerate([*range(2, 70), *range(70, 300, 3)] * 6):
        most = (100 - percent) * n // percent  # shingles that a longer text may add: 100 n >= percent (n + most)
        base = [word() for _ in range(n + words - 1)]
        rows += [(3 * i, " ".join(base)), (3 * i + 1, " ".join(base + [word() for _ in range(most)])), (3 * i + 2, " ".join([word() for _ in range(n)]))]
        links.append((3 * i, 3 * i + 1))
    lonely = [(10**6 + i, t + "".join(f" {word()}" for _ in range((100 - percent) * n // percent + 1))) for i, (n, t) in enumerate((len(t.split()) - words + 1, t) for _, t in rows[2::3] if len(t.split()) > words)]
    got = {r["doc_id"]: r["component_id"] for r in components(spark.createDataFrame(rows + lonely, "doc_id bigint, text string"), words, percent).collect()}
    assert [(a, b) for a, b in links if got[b] != a] == []
    assert all(got[d] == d for d, _ in lonely)


def test_a_leader_of_many_and_rows_of_one_id(spark, monkeypatch):
    from saferoads.llm import jaccard_join

    monkeypatch.setattr(jaccard_join, "FOLLOWERS", 3)
    rng = random.Random(8)
    base = ["".join(rng.choices("abcdefgh", k=5)) for _ in range(80)]
    rows = [(i, " ".join(base[:k] + [f"x{i}"] + base[k:])) for i in range(40) for k in [rng.randrange(80)]]
    rows += [(100, "own words that nobody shares at all here"), (100, rows[0][1] + " tail"), (101, "own words that nobody shares at all here too")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    assert sorted((tuple(r) for r in components(df).collect()), key=str) == brute(rows, 4, 85)


def test_a_clashing_column_stays(spark):
    df = spark.createDataFrame([(1, "a b c d e f g", 5, "k"), (2, "a b c d e f g", 6, "m"), (3, "z", 7, "n")], "doc_id bigint, text string, _mark int, doc string")
    got = keep_one(df)
    assert got.columns == df.columns and sorted((r["doc_id"], r["_mark"], r["doc"]) for r in got.collect()) == [(1, 5, "k"), (3, 7, "n")]
