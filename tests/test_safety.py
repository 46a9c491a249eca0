"""Path algebra: worked numbers and properties (A1-A13, W13)."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from saferoads.functions import safety

PATHS = {1: [0, 0, 0, 4, 5], 2: [1, 1, 0, 1, 2], 3: [1, 4, 0, 0, 4], 4: [0, 0, 0, 4, 3]}


@pytest.fixture(scope="module")
def vectors(spark):
    return spark.createDataFrame([(k, v) for k, v in PATHS.items()], "path_id int, sd array<bigint>")


def test_weights_and_scores(spark, vectors):
    assert spark.range(1).select(safety.level_weights(10.0, 5)).first()[0] == [1e4, 1e3, 100, 10, 1]
    got = {r[0]: r[1] for r in vectors.select("path_id", safety.pss("sd", 10.0, 5)).collect()}
    assert got == pytest.approx({1: 1 / 45, 2: 1 / 11012, 3: 1 / 14004, 4: 1 / 43})
    exact = {r[0]: int(r[1]) for r in vectors.select("path_id", safety.exact_cost("sd", 10, 5)).collect()}
    assert exact == {1: 45, 2: 11012, 3: 14004, 4: 43}
    assert [r[0] for r in vectors.orderBy("sd").collect()] == [4, 1, 2, 3]
    with pytest.raises(ValueError):
        safety.exact_cost("sd", 1000, 15)


def test_path_without_edges_is_safest(spark):
    zero = spark.range(1).select(safety.zeros(5).alias("sd"))
    assert zero.select(safety.pss("sd", 10.0, 5)).first()[0] == float("inf")
    assert zero.select(safety.min_ess("sd")).first()[0] is None


def test_vectors_from_edges(spark):
    edges = spark.createDataFrame([(1, 1, 4), (1, 3, 4), (1, 3, 5), (1, 2, 5)], "path_id int, len bigint, ess int")
    row = safety.s_vector(edges, 5).first()
    assert row["sd"] == [0, 0, 0, 4, 5] and row["dist"] == 9
    assert safety.s_distance(edges, 4).first()["d_s"] == 4
    grown = spark.createDataFrame([([0, 0, 0, 4, 3], 5, 2)], "sd array<bigint>, ess int, len bigint")
    assert grown.select(safety.add_edge("sd", "ess", "len")).first()[0] == [0, 0, 0, 4, 5]


def test_reciprocals_add(spark):
    row = spark.createDataFrame([([0, 1, 2], [3, 0, 1])], "a array<bigint>, b array<bigint>")
    whole, parts = row.select(safety.pss(safety.concat_paths("a", "b"), 20.0, 3), safety.pss_concat(safety.pss("a", 20.0, 3), safety.pss("b", 20.0, 3))).first()
    assert whole == pytest.approx(parts)


def test_order_does_not_depend_on_the_bound(spark):
    rng = random.Random(1)
    rows = [([rng.randint(0, 2) for _ in range(4)], [rng.randint(0, 2) for _ in range(4)]) for _ in range(200)]
    df = spark.createDataFrame(rows, "a array<bigint>, b array<bigint>")
    for base in (9.0, 50.0):
        assert safety.check_order(df, 4, base).count() == 0
    assert safety.check_bottleneck(df).count() == 0
    assert safety.check_subpath(spark.createDataFrame([([0, 1], [0, 2]), ([0, 1], [1, 1])], "before array<bigint>, after array<bigint>")).count() == 0


def test_pareto_keeps_undominated(spark):
    rng = random.Random(2)
    rows = [(1, rng.randint(0, 3), [rng.randint(0, 2), rng.randint(0, 3)], rng.randint(1, 6), [i]) for i in range(120)]
    got = {tuple(r["path"]) for r in safety.pareto(spark.createDataFrame(rows, "qid int, vid int, key array<bigint>, dist bigint, path array<bigint>")).collect()}
    want = set()
    for (_, v, k, d, p), _ in itertools.product(rows, [0]):
        beaten = any(v2 == v and (k2, d2) != (k, d) and k2 <= k and d2 <= d or (v2 == v and (k2, d2) == (k, d) and p2 < p) for _, v2, k2, d2, p2 in rows)
        if not beaten:
            want.add(tuple(p))
    assert got == want


def test_sql_functions(spark):
    from saferoads.functions.udfs import register, segment_distance

    register(spark)
    assert spark.sql("SELECT pss(array(0L, 0L, 0L, 4L, 5L), 10D), path_length(array(1L, 2L)), safer(array(0L, 9L), array(1L, 0L))").first()[:] == (pytest.approx(1 / 45), 3, True)
    assert spark.sql("SELECT u, w FROM path_edges(array(3L, 5L, 4L))").collect() == [(3, 5), (5, 4)]
    df = spark.createDataFrame([(5.0, 3.0, 0.0, 0.0, 10.0, 0.0), (-3.0, 4.0, 0.0, 0.0, 10.0, 0.0)], "x double, y double, xu double, yu double, xw double, yw double")
    assert [r[0] for r in df.select(segment_distance(*map(F.col, df.columns))).collect()] == [3.0, 5.0]
