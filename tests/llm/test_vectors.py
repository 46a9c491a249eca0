"""Operators 6 and 7 against all pairs."""

import math
import random

import numpy as np
from pyspark.sql import functions as F

from saferoads.llm.vectors import near_duplicates, tables_for, top_k

SCHEMA = "vec_id bigint, embedding array<float>, label int"


def made_up(seed=1):
    rng = np.random.default_rng(seed)
    rows = [(i, rng.normal(0, 1, 16).astype("f4").tolist(), int(rng.integers(0, 3))) for i in range(120)]
    for i in range(120, 200):
        base = rows[int(rng.integers(0, 120))]
        near = (np.array(base[1]) + rng.normal(0, rng.choice([0.0, 0.1, 0.3]), 16)).astype("f4").tolist()
        rows.append((i, near, base[2]))
    rows += [(300, None, 1), (301, [0.0] * 16, 1), (302, [float("nan")] * 16, 1), (303, [float("inf")] + [0.0] * 15, 1), (304, rows[0][1], None), (305, [1.0, 2.0], 1), (350, [2.0, 4.0], 1), (307, [None] * 16, 1), (308, [], 1)]
    return rows


def fine(v):
    return v is not None and all(x is not None and math.isfinite(x) for x in v)


def test_top_k(spark):
    rows = made_up()
    got = sorted(tuple(r) for r in top_k(spark.createDataFrame(rows, SCHEMA), F.col("vec_id") % 50 == 0).collect())
    ints = {i: [math.floor(256 * x) for x in v] for i, v, _ in rows if fine(v) and v}
    want = []
    for q in ints:
        if q % 50 == 0:
            ranked = sorted((-sum(a * b for a, b in zip(ints[q], v)), i) for i, v in ints.items() if i != q and len(v) == len(ints[q]))[:5]
            want += [(q, r + 1, i, -s) for r, (s, i) in enumerate(ranked)]
    assert got == sorted(want)
    assert top_k(spark.createDataFrame([], SCHEMA), F.col("vec_id") % 50 == 0).count() == 0


def test_near_duplicates(spark):
    rows = made_up(2)
    random.Random(3).shuffle(rows)
    got = sorted(tuple(r) for r in near_duplicates(spark.createDataFrame(rows, SCHEMA)).collect())
    part = {i: (np.array(v, "f8"), l) for i, v, l in rows if fine(v) and any(v) and l is not None}
    links = {i: [] for i, _, _ in rows}
    for i, (a, la) in part.items():
        for j, (b, lb) in part.items():
            if i < j and la == lb and len(a) == len(b) and a @ b / np.sqrt(a @ a) / np.sqrt(b @ b) >= 0.93:
                links[i].append(j)
                links[j].append(i)
    want = []
    for i in links:
        seen, todo = {i}, [i]
        while todo:
            for j in links[todo.pop()]:
                if j not in seen:
                    seen.add(j)
                    todo.append(j)
        want.append((i, len(links[i]), min(seen), min(seen) == i))
    assert got == sorted(want)
    assert near_duplicates(spark.createDataFrame([], SCHEMA)).count() == 0


def test_recall_is_planned():
    for bits in (8, 12, 20):
        same = (1 - math.acos(0.93) / math.pi) ** bits
        assert (1 - same) ** tables_for(bits, 0.93, 1e-4) <= 1e-4


def test_rows_that_share_an_id(spark):
    rows = [(1, [1.0, 0.0], 1), (1, [0.0, 1.0], 1), (2, [1.0, 0.01], 1), (3, [0.0, 1.0], 1), (3, [0.0, 1.0], 1), (4, [0.0, 1.0], 2)]
    got = sorted(tuple(r) for r in near_duplicates(spark.createDataFrame(rows, SCHEMA)).collect())
    assert got == sorted([(1, 1, 1, True), (1, 2, 1, True), (2, 1, 1, False), (3, 2, 1, False), (3, 2, 1, False), (4, 0, 4, True)])


def test_blocks_of_queries_and_what_the_pivots_spare(spark, monkeypatch):
    from saferoads.llm import vectors

    rng = np.random.default_rng(5)
    centers = rng.normal(0, 3, (12, 8))
    rows = [(i, (centers[i % 12] + rng.normal(0, 0.05, 8)).astype("f4").tolist(), 0, "x", 1.5) for i in range(3000)]
    df = spark.createDataFrame(rows, SCHEMA + ", score string, v double").repartition(2)
    asked = F.col("vec_id") % 50 == 0
    evaluated = spark.sparkContext.accumulator(0)
    want = sorted(tuple(r) for r in top_k(df, asked, evaluated=evaluated).collect())
    assert len(want) == 300 and evaluated.value < 0.5 * 60 * 2999
    monkeypatch.setattr(vectors, "QUERY_BLOCK", 14)
    assert sorted(tuple(r) for r in top_k(df, asked).collect()) == want
