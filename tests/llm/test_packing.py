"""Operator 9: every id once, windows within capacity, little padding."""

import random
import zlib

import numpy as np
import pytest

tokenizers = pytest.importorskip("tokenizers")
public = pytest.importorskip("public_tokenizers")

from saferoads.llm.packing import cut_points, difference, fill_windows, pack  # noqa: E402
from saferoads.llm.queries import byte_bpe  # noqa: E402


def test_difference_known_case():
    sets = difference([8, 7, 6, 5, 4], 2)
    assert sorted(s for s, _ in sets) == [14, 16] and sorted(i for _, m in sets for i in m) == list(range(5))


def test_windows_never_overflow():
    rng = random.Random(1)
    for _ in range(50):
        sizes = [rng.randint(1, 40) for _ in range(rng.randint(1, 60))]
        sets = fill_windows(sizes, 50)
        assert sorted(i for _, m in sets for i in m) == list(range(len(sizes)))
        assert all(sum(sizes[i] for i in m) == s <= 50 for s, m in sets)


def test_cut_points():
    for n in (1, 99, 100, 101, 250, 1000):
        p = cut_points(n, 100, 30)
        assert p[0] == 0 and p[-1] == n and all(0 < b - a <= 100 for a, b in zip(p, p[1:]))


def test_every_id_once(spark):
    rng = random.Random(2)
    texts = ["word " * rng.randint(1, 900) for _ in range(60)] + [None, "", "<|endoftext|> é͸ 日本", "a" * 30_000, "word "]
    rows = list(enumerate(texts)) + [(0, texts[0])]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = pack(df, byte_bpe(), with_ids=True).collect()
    exact = tokenizers.Tokenizer.from_file(public.path("byte_bpe_50k.json"))
    for doc, text in enumerate(texts):
        ids = exact.encode(text or "", add_special_tokens=False).ids + [1]
        pieces = sorted((r["start"], r["length"], r["ids_crc32"], r["doc_tokens"], tuple(r["ids"])) for r in got if r["doc_id"] == doc)
        times = 2 if doc == 0 else 1
        assert [i for p in pieces[::times] for i in p[4]] == ids
        assert all(n == len(ids) and crc == zlib.crc32(np.array(ids[s : s + k], "<u4").tobytes()) for s, k, crc, n, _ in pieces)
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in by.values():
        parts.sort()
        assert all(a + b == c for (a, b), (c, _) in zip(parts, parts[1:])) and parts[0][0] == 0 and sum(parts[-1]) <= 2048
    assert pack(df.limit(0), byte_bpe()).count() == 0
