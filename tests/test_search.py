"""Searches by rounds, indexes, updates and evaluation on small networks (M0-M3, I1-I12, W7, W12)."""

import random

import pytest
from pyspark.sql import functions as F
from test_kernel import brute

from saferoads.functions.safety import MinEss, ProductEss
from saferoads.operators import comptree, expand, safevor, update
from saferoads.operators.kernel import grouped_search
from saferoads.plans import evaluation
from saferoads.plans.components import connected_components
from saferoads.sources.networks import Network, scale_weights

SMAX = 3


def network(spark, edges, pois):
    vids = sorted({v for u, w, *_ in edges for v in (u, w)} | set(pois))
    return Network(
        spark.createDataFrame([(v, v % 5 * 10, v // 5 * 10) for v in vids], "vid bigint, x bigint, y bigint"),
        spark.createDataFrame([(u * 1000 + w, u, w, n, s) for u, w, n, s in edges], "eid bigint, u bigint, w bigint, len bigint, ess int"),
        spark.createDataFrame([(p,) for p in pois], "poi bigint"),
        SMAX,
    )


@pytest.fixture(scope="module")
def case(spark):
    rng = random.Random(5)
    edges = {}
    for v in range(25):
        for w in ((v + 1,) if v % 5 < 4 else ()) + ((v + 5,) if v < 20 else ()):
            if rng.random() < 0.8:
                edges[v, w] = (rng.randint(10, 20), rng.randint(1, SMAX))
    edges = [(u, w, *x) for (u, w), x in edges.items()]
    pois = {3, 11, 17, 20}
    net = network(spark, edges, pois)
    rows = [(i, v, 2, 45.0) for i, v in enumerate((0, 3, 7, 12, 18, 24))]
    return edges, pois, net, spark.createDataFrame(rows, "qid bigint, src bigint, k int, dc double"), rows


def found(df):
    out = {}
    for r in df.orderBy("qid", "rnk").collect():
        out.setdefault(r["qid"], []).append(tuple(r["key"]))
    return out


def test_all_methods_equal_enumeration(case):
    edges, pois, net, queries, rows = case
    want = {q: b for q, v, k, dc in rows if (b := brute(edges, pois, SMAX, v, k, dc))}
    tree, vor = comptree.build_comptree(net), safevor.build_safevor(net, listed=3)
    assert found(expand.expand(net, queries)) == want
    assert found(comptree.comptree_search(net, tree, queries)) == want
    assert found(safevor.safevor_search(net, vor, queries)) == want
    assert found(expand.euclid_baseline(net, queries)) == want
    for method in ("expand", "comptree", "safevor", "euclid"):
        assert found(grouped_search(net, queries, method, tree=tree).where("rnk > 0")) == want
    with pytest.raises(ValueError):
        comptree.comptree_search(net, tree, queries, measure=ProductEss)
    # The invariants of the tree: nested nodes, one cell for each POI.
    up = tree.pointers.alias("a").join(tree.pointers.alias("b"), (F.col("a.vid") == F.col("b.vid")) & (F.col("a.lvl") == F.col("b.lvl") + 1))
    assert up.groupBy("a.lvl", "a.comp").agg(F.count_distinct("b.comp").alias("n")).where("n > 1").count() == 0
    assert {r["cell"] for r in vor.cells.select("cell").distinct().collect()} == pois
    stats = evaluation.counters(grouped_search(net, queries, "comptree", tree=tree), "comptree", (1, 2)).first()
    assert stats["queries"] == 6 and stats["pushed"] >= stats["va"] - 1


def test_paths_are_paths(case):
    edges, _, net, queries, _ = case
    known = {(u, w): (n, s) for u, w, n, s in edges} | {(w, u): (n, s) for u, w, n, s in edges}
    for r in expand.expand(net, queries).collect():
        steps = [known[a, b] for a, b in zip(r["path"], r["path"][1:])]
        assert sum(n for n, _ in steps) == r["dist"] and [sum(n for n, s in steps if s == i) for i in range(1, SMAX + 1)] == list(r["key"])


def test_worst_edge_measure(case):
    edges, pois, net, queries, rows = case
    got = {(r["qid"], r["poi"]): r["key"][0] for r in expand.expand(net, queries, measure=MinEss).collect()}
    full = {(r["qid"], r["poi"]): r["key"] for r in expand.expand(net, queries).collect()}
    for q in got.keys() & full.keys():
        worst = next((i + 1 for i, x in enumerate(full[q]) if x), None)
        assert got[q] == (0 if worst is None else SMAX + 1 - worst)


def same(a, b):
    cols = sorted(a.columns)
    return sorted(map(str, a.select(cols).collect())) == sorted(map(str, b.select(cols).collect()))


def test_update_equals_rebuild(spark, case):
    edges, _, net, _, _ = case
    (u1, w1, _, s1), (u2, w2, *_), (u3, w3, _, s3) = edges[2], edges[9], edges[15]
    rows = [("ess", u1, w1, None, s1 % SMAX + 1, None, None), ("remove", u2, w2, None, None, None, None), ("add", 0, 12, 14, 2, None, None), ("ess", u3, w3, None, max(1, s3 - 1), None, None), ("add_poi", None, None, None, None, 8, None), ("remove_poi", None, None, None, None, 17, None)]
    for batch in (rows, rows[:1], rows[4:5]):
        changes = spark.createDataFrame(batch, update.CHANGES)
        fresh, tree = update.comptree_update(net, comptree.build_comptree(net), changes)
        built = comptree.build_comptree(fresh)
        assert same(tree.pointers, built.pointers) and same(tree.nodes, built.nodes) and same(tree.borders, built.borders)
    changes = spark.createDataFrame(rows, update.CHANGES)
    fresh, vor = update.safevor_update(net, safevor.build_safevor(net, listed=2), changes)
    built = safevor.build_safevor(fresh, listed=2)
    assert same(vor.cells, built.cells) and same(vor.borders, built.borders) and same(vor.adjacency, built.adjacency) and same(vor.border_distances, built.border_distances)


def test_local_build_equals_rounds(case):
    for height, reach in ((None, None), (2, 30.0)):
        a, b = comptree.build_comptree(case[2], height, reach), comptree.build_comptree_local(case[2], height, reach)
        assert same(a.pointers, b.pointers) and same(a.nodes, b.nodes) and same(a.borders, b.borders)


def test_index_round_trip(spark, case, tmp_path):
    tree = comptree.build_comptree(case[2], height=2)
    assert tree.cuts == (0, 1)
    update.save_index(tree, str(tmp_path))
    back = update.load_index(spark, str(tmp_path), tree)
    assert same(back.borders, tree.borders) and same(back.nodes, tree.nodes)


def test_border_places(spark):
    # Midpoint; shifted by a road of the same level; midpoint at a better level after equal worse levels.
    for edges, place in (
        ([(0, 1, 4, 2)], 4),
        ([(0, 1, 4, 2), (1, 2, 2, 2)], 6),
        ([(0, 3, 5, 1), (0, 1, 4, 2), (1, 2, 5, 1)], 4),
    ):
        ends = {0: 0, 1: 1} if len(edges) == 1 else {0: 0, 1: 2} if len(edges) == 2 else {0: 3, 1: 2}
        net = network(spark, edges, set(ends.values()))
        vor = safevor.build_safevor(net, listed=2)
        assert [r["pos2"] for r in vor.borders.where("u = 0 and w = 1").collect()] == [place]
        split = safevor.split_network(net, vor.borders)
        assert split.edges.agg(F.sum("len")).first()[0] == 2 * sum(n for _, _, n, _ in edges)


def test_effectiveness(spark, case):
    _, _, net, queries, _ = case
    nearest = expand.knn(net, queries, 2)
    queries = expand.set_dc(queries, nearest, 2.0)
    paths = evaluation.nearest_paths(net, queries, nearest)
    row = evaluation.effectiveness(expand.expand(net, queries.drop("few")), paths, SMAX, 100.0).first()
    assert 0 <= row["common"] <= 2 and row["length_ratio"] >= 1 and row["pss_ratio"] >= 1


def test_connected_components(spark):
    rng = random.Random(7)
    edges = [(rng.randrange(80), rng.randrange(80)) for _ in range(60)] + [(i, i + 1) for i in range(100, 180)]
    up = {v: v for e in edges for v in e}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        x, y = sorted((top(a), top(b)))
        up[y] = x
    touched = {v for a, b in edges if a != b for v in (a, b)}
    df = spark.createDataFrame([*edges, (None, 3)], "a bigint, b bigint")
    for last in (0, 20, 16_384):  # all by rounds, rounds and a last task, the task alone
        assert {r["id"]: r["comp"] for r in connected_components(df, last=last).collect()} == {v: top(v) for v in touched}
    assert connected_components(df.where("a < 0")).count() == 0


def test_weights_are_scaled(spark):
    got = scale_weights(spark.createDataFrame([(0.5,), (0.75,), (2.0,)], "len double")).collect()
    assert [r["len"] for r in got] == [1, 2, 4]


def test_table_function(spark, case):
    from saferoads.functions.udfs import register_safest_paths

    edges, pois, net, _, rows = case
    register_safest_paths(spark, net)
    for _, v, k, dc in rows[:2]:
        got = spark.sql(f"SELECT * FROM safest_paths({v}, {k}, {dc}D)").orderBy("rnk").collect()
        assert [tuple(r["sd"]) for r in got] == brute(edges, pois, SMAX, v, k, dc) and all(r["path"][0] == v for r in got)


def test_versioned_index(spark, case, tmp_path):
    from saferoads.streaming.incidents import VersionedIndex

    edges, _, net, _, _ = case
    u, w, _, s = edges[4]
    keeper = VersionedIndex(net, comptree.build_comptree_local(net), str(tmp_path))
    changes = spark.createDataFrame([("ess", u, w, None, s % SMAX + 1, None, None)], update.CHANGES)
    keeper(changes, 0)
    keeper(changes, 0)  # sent again
    built = comptree.build_comptree_local(keeper.net)
    assert same(keeper.tree.borders, built.borders)
    assert same(update.load_index(spark, f"{tmp_path}/version=0", keeper.tree).nodes, built.nodes)
    # A new driver goes on from the newest complete version; a version without its mark does not count.
    (tmp_path / "version=7").mkdir()
    again = VersionedIndex(net, comptree.build_comptree_local(net), str(tmp_path))
    assert again.applied == 0 and same(again.net.edges, keeper.net.edges) and same(again.tree.borders, built.borders)
    again(changes, 0)
    assert same(again.net.edges, keeper.net.edges)
    u, w, _, s = edges[6]
    again(spark.createDataFrame([("ess", u, w, None, s % SMAX + 1, None, None)], update.CHANGES), 1)
    assert VersionedIndex(net, keeper.tree, str(tmp_path)).applied == 1
    both = {(r["u"], r["w"]): r["ess"] for r in again.net.edges.collect()}
    assert all(both[e[0], e[1]] == e[3] % SMAX + 1 for e in (edges[4], edges[6]))


def test_one_entrance(spark, case):
    from saferoads.operators.topk import safest_topk

    _, _, net, queries, _ = case
    want = sorted((r["qid"], r["rnk"], r["poi"], r["dist"]) for r in expand.expand(net, queries).collect())
    for method, engine in (("expand", "kernel"), ("comptree", "rounds"), ("safevor", "kernel"), ("euclid", "rounds"), ("brute", "auto")):
        assert sorted((r["qid"], r["rnk"], r["poi"], r["dist"]) for r in safest_topk(net, queries, method, engine).collect()) == want, method
    with pytest.raises(ValueError):
        safest_topk(net, queries, "comptree", measure=ProductEss)
    with pytest.raises(ValueError):
        safest_topk(net, queries, "nearest")


def test_cell_tables_equal_cells_made_on_the_spot(case):
    import numpy as np

    from saferoads.operators import kernel

    _, _, net, _, _ = case
    built, rows = kernel.build_cells_local(net), net.arcs.collect()
    arrays = [np.array([r[c] for r in rows], np.int64) for c in ("src", "dst", "len", "ess")]
    pois = np.sort(np.array([r["poi"] for r in net.pois.collect()], np.int64))
    made, read = (kernel.Graph(*arrays, pois, net.smax) for _ in range(2))
    kernel.attach_cells(made)
    lists = lambda df, *names: [[r[n] for r in df.collect()] for n in names]
    kernel.attach_cell_tables(read, lists(built.cells, "vid", "cell"), lists(built.ways.where("direct"), "b1", "b2", "sd", "dist"), lists(built.ends, "cell", "b", "d_border", "d_poi"))
    for one, other in zip(made.cells, read.cells, strict=True):
        tidy = lambda x: {k: sorted(v) if isinstance(v, list) else v for k, v in x.items() if v != []}
        assert tidy(one) == tidy(other)


def test_long_roads_keep_their_order():
    """A level's length beyond 2^24 must not carry into the level above."""
    import numpy as np

    from saferoads.operators.kernel import Graph, expand_query

    far = 1 << 24
    edges = [(0, 1, far, 2), (1, 2, far, 2), (0, 2, 5, 1)]
    src, dst, length, ess = (np.array(c, np.int64) for c in zip(*(x for u, w, n, s in edges for x in ((u, w, n, s), (w, u, n, s)))))
    g = Graph(src, dst, length, ess, np.array([2]), 2, longest=4 * far)
    found, *_ = expand_query(g, 0, 1, 4 * far, {1, 2})
    (key, dist, _), = found.values()
    assert dist == 2 * far and g.vector(key) == [0, 2 * far]


def test_growth_of_cells_lists_the_safest(case):
    """The order by growing cells against the lists spread from all POIs, and the search that needs it."""
    edges, pois, net, queries, rows = case
    every = {(r["vid"], r["rnk"]): (r["poi"], list(r["sd"])) for r in safevor.safest_lists(net, len(pois)).collect()}
    vor = safevor.build_safevor(net, listed=2)
    tables = safevor.cell_tables(net, vor.cells.select("vid", "cell"))
    grown = safevor.safest_by_growth(net, tables, vor.adjacency, queries.withColumn("k", F.lit(9))).collect()
    at = {i: v for i, v, _, _ in rows}
    assert {(at[r["qid"]], r["rnk"]): (r["poi"], list(r["key"])) for r in grown} == {(v, n): x for (v, n), x in every.items() if v in at.values()}
    want = {q: b for q, v, k, dc in rows if (b := brute(edges, pois, SMAX, v, 3, dc))}
    assert found(safevor.safevor_search(net, vor, queries.withColumn("k", F.lit(3)))) == want


@pytest.mark.parametrize("rules", [(1, 2, 3), (1, 2, 4), (1, 2, 3, 4)])
def test_queries_carry_their_part_of_the_tree(case, rules):
    """The rows within the bound give the answers and the counters of the whole tree; no worker or driver holds it."""
    from saferoads.operators import kernel

    edges, _, net, queries, _ = case
    tree = comptree.build_comptree_local(net)
    held = kernel.tree_rows(net, queries, tree).selectExpr("size(tree) as n").collect()
    assert held and all(r["n"] <= tree.pointers.count() for r in held)
    arcs, pois = net.arcs.collect(), net.pois.collect()
    import numpy as np

    g = kernel.Graph(*(np.array([r[c] for r in arcs], np.int64) for c in ("src", "dst", "len", "ess")), np.array(sorted(r["poi"] for r in pois), np.int64), net.smax)
    lists = lambda df, *names: [[r[n] for r in df.collect()] for n in names]
    whole = lists(tree.pointers, "vid", "lvl", "comp"), lists(tree.borders, "lvl", "vid", "d_border", "d_poi")
    kernel.attach_tree(g, *whole)
    got = {r["qid"]: (r["va"], r["popped"], r["pushed"]) for r in grouped_search(net, queries, "comptree", rules, tree=tree).collect()}
    for r in queries.collect():
        start = g.index_of(r["src"])
        k = min(r["k"], len(kernel.within(g, start, r["dc"])[0]))
        if k:
            counts = kernel.comptree_query(g, start, k, r["dc"], set(rules))[2]
            assert got[r["qid"]] == tuple(counts[c] for c in ("va", "popped", "pushed"))


def test_packed_cells_equal_the_tables(case):
    import numpy as np

    from saferoads.operators import kernel

    _, _, net, _, _ = case
    built, rows = kernel.build_cells_local(net), net.arcs.collect()
    arrays = [np.array([r[c] for r in rows], np.int64) for c in ("src", "dst", "len", "ess")]
    pois = np.sort(np.array([r["poi"] for r in net.pois.collect()], np.int64))
    made, read = (kernel.Graph(*arrays, pois, net.smax) for _ in range(2))
    kernel.attach_cells(made)
    packed = kernel.packed_cells(built).collect()
    cells = built.cells.collect()
    kernel.StoredCells(read, [r["vid"] for r in cells], [r["cell"] for r in cells], [r["cell"] for r in packed], np.cumsum([0, *(len(r["data"]) for r in packed)]), b"".join(bytes(r["data"]) for r in packed))
    for v in range(len(made.vids)):
        assert made.cells[0].get(v) == read.cells[0].get(v)
        assert sorted(made.cells[2].get(v, ())) == sorted(read.cells[2].get(v, ()))
        assert made.cells[3].get(v) == read.cells[3].get(v) and made.cells[4].get(v) == read.cells[4].get(v)
        if v in made.pois:
            assert sorted(made.cells[1][v]) == sorted(read.cells[1][v])


def test_lists_by_blocks(case):
    """Blocks of three numbers of vertices hand the same lists on as one block."""
    _, pois, net, _, _ = case
    rows = lambda size: sorted((r["vid"], r["rnk"], r["poi"], tuple(r["sd"]), r["dist"]) for r in safevor.safest_lists(net, 2, size).collect())
    assert rows(3) == rows(1 << 40)


def test_safevor_without_the_plain_search(case, monkeypatch):
    """More POIs than the lists hold: the POIs within the bound are listed, arcs of other places are not searched."""
    edges, pois, net, queries, rows = case
    vor, seen, plain = safevor.build_safevor(net, listed=2), [], safevor.bounded
    monkeypatch.setattr(safevor, "bounded", lambda *a: seen.append(a[2].select("src").distinct().count()) or plain(*a))
    for k in (4, 9):
        want = {q: b for q, v, _, dc in rows if (b := brute(edges, pois, SMAX, v, k, dc))}
        assert found(safevor.safevor_search(net, vor, queries.withColumn("k", F.lit(k)))) == want
    one = queries.where(F.col("qid") == rows[0][0]).withColumn("dc", F.lit(1.0))
    safevor.safevor_search(net, vor, one).collect()
    assert len(seen) == 3 and seen[2] == 0
