"""Derived networks against the expected values of FIXTURES.md, plans, streams, sources."""

import shutil

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from saferoads.operators.ess import ess_asof, ess_from_counts
from saferoads.sources.networks import lattice_network, read_network, trade_network
from saferoads.streaming import incidents

SMALL, MIDDLE = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


def test_lattice(spark):
    net = lattice_network(spark, MIDDLE, rho=0.1)
    edges = net.edges.cache()
    assert net.vertices.count() == 2000 and edges.count() == 3462 and edges.agg(F.sum("len")).first()[0] == 51959
    levels = {r["ess"]: r["count"] for r in edges.groupBy("ess").count().collect()}
    assert [levels[s] for s in range(1, 11)] == [12, 117, 475, 1043, 1229, 420, 95, 46, 22, 3]
    assert net.pois.count() == 200 and [r[0] for r in net.pois.orderBy("poi").limit(5).collect()] == [0, 5, 18, 23, 36]
    small = lattice_network(spark, SMALL)
    assert small.edges.count() == 328 and small.pois.count() == 2


def test_plan_of_the_incident_join(spark):
    plan = lattice_network(spark, SMALL).edges._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    scan = next(x for x in plan.splitlines() if "FileScan" in x and "l_returnflag" in x)
    assert "EqualTo(l_returnflag,R)" in scan.replace(" ", "") and "l_extendedprice" not in scan


def test_score_inversion(spark):
    got = ess_from_counts(spark.createDataFrame([(i,) for i in range(10)], "n bigint"), 10).orderBy("n").collect()
    assert [r["ess"] for r in got] == list(range(10, 0, -1))


def test_as_of(spark):
    h = spark.createDataFrame([(1, 3, 10), (1, 4, 20), (2, 5, 15)], "eid int, ess int, valid_from int")
    a = spark.createDataFrame([(1, 9), (1, 10), (1, 25), (2, 20), (3, 1)], "eid int, at int")
    assert sorted(tuple(r) for r in ess_asof(a, h).collect() if r["ess"]) == [(1, 10, 3), (1, 25, 4), (2, 20, 5)]


def test_trade_network_has_hubs(spark):
    net = trade_network(spark, SMALL)
    assert net.edges.where("len < 1 or ess < 1 or ess > 5 or u >= w").count() == 0


def test_read_network(spark, tmp_path):
    spark.createDataFrame([(2, 1, 5, 3, True), (1, 2, 5, 3, False), (2, 3, 4, 1, None), (4, 4, 1, 1, None)], "u bigint, w bigint, len bigint, ess int, poi boolean").write.csv(str(tmp_path / "n"))
    net = read_network(spark, str(tmp_path / "n"), "csv", smax=3)
    assert sorted((r["u"], r["w"], r["len"], r["ess"]) for r in net.edges.collect()) == [(1, 2, 5, 3), (2, 3, 4, 1)] and net.pois.collect()[0][0] == 2


@pytest.fixture(scope="module")
def daily(spark, tmp_path_factory):
    """Events in files of three days, one of them late, some rows twice."""
    base = tmp_path_factory.mktemp("events")
    rows = spark.read.parquet(f"{SMALL}/events.parquet").withColumn("part", F.floor(F.dayofmonth("ts") / 3))
    extra = rows.where("event_id % 50 = 0")
    for part in range(11):
        out = rows.where(F.col("part") == part).unionAll(extra.where(F.col("part") == part)).drop("part").coalesce(1)
        out.write.parquet(str(base / f"w{part:02d}"))
    for part in range(11):
        for f in (base / f"w{part:02d}").glob("part-*.parquet"):
            f.rename(base / f"d{part:02d}.parquet")
        shutil.rmtree(base / f"w{part:02d}")
    return str(base)


def run(query):
    query.processAllAvailable()
    query.stop()


def test_windows_without_repeats(spark, daily):
    counted = incidents.window_counts(incidents.incident_stream(spark, daily, files=1))
    run(counted.writeStream.format("memory").queryName("weekly").outputMode("append").start())
    got = spark.table("weekly").agg(F.sum("n")).first()[0]
    closed = spark.table("weekly").agg(F.max("end")).first()[0]
    batch = spark.read.parquet(f"{SMALL}/events.parquet").where("event_type = 'error'")
    assert got == batch.where(F.col("ts").cast("timestamp") < F.lit(closed)).count()


def test_level_changes(spark, daily):
    moved = incidents.level_changes(incidents.incident_stream(spark, daily, files=3, edges=20), smax=5, per_level=3)
    run(moved.writeStream.format("memory").queryName("levels").outputMode("update").start())
    batch = spark.read.parquet(f"{SMALL}/events.parquet").where("event_type = 'error'").groupBy((F.col("event_id") * 611953 % 20).alias("eid")).count()
    want = {r["eid"]: max(1, 5 - r["count"] // 3) for r in batch.collect()}
    last = spark.table("levels").groupBy("eid").agg(F.max_by("ess", "n").alias("ess")).collect()
    assert {r["eid"]: r["ess"] for r in last} == {e: s for e, s in want.items() if s != 5}


def test_sessions_joins_and_batches(spark, daily, tmp_path):
    stream = incidents.incident_stream(spark, daily, files=11)
    run(incidents.session_counts(stream).writeStream.format("memory").queryName("sessions").outputMode("append").start())
    assert spark.table("sessions").count() > 0
    edges = spark.createDataFrame([(i, i, i + 1, 3) for i in range(500)], "eid bigint, u bigint, w bigint, ess int")
    seen = []
    query = incidents.apply_batches(incidents.with_edges(stream, edges), lambda df, n: seen.append(df.count()), str(tmp_path / "c"))
    run(query)
    assert sum(seen) == spark.read.parquet(f"{SMALL}/events.parquet").where("event_type = 'error'").count()
    opened = incidents.incident_stream(spark, daily, files=11, kinds=("signup",)).select("eid", F.col("ts").alias("opened"))
    run(incidents.near_openings(stream, opened, "30 days").writeStream.format("memory").queryName("openings").outputMode("append").start())


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["qid", "rnk", "poi", "dist", "sd"] and df.count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_text_source(spark, tmp_path):
    from saferoads.sources.text_source import RoadText

    (tmp_path / "a.txt").write_text("1 2 10 3\n# note\n\n2 3 11 4 # end\n")
    (tmp_path / "b.txt").write_text("3 4 12 5\n")
    spark.dataSource.register(RoadText)
    got = spark.read.format("roadtext").load(str(tmp_path / "*.txt")).collect()
    assert sorted(tuple(r) for r in got) == [(1, 2, 10, 3), (2, 3, 11, 4), (3, 4, 12, 5)]


def test_sweeps(spark):
    from saferoads.plans import workloads

    rows = workloads.sweep(spark, SMALL, "delta", (1.25, 2.0), n=6, rho=0.1, k=3).collect()
    pushed = {(r["method"], r["value"]): r["pushed"] for r in rows}
    assert all(pushed[m, 1.25] <= pushed[m, 2.0] for m in ("expand", "comptree"))
    by_k = workloads.sweep(spark, SMALL, "k", (1, 10), ("expand",), n=6, rho=0.1).collect()
    assert {r["value"]: r["pushed"] for r in by_k}[1.0] < {r["value"]: r["pushed"] for r in by_k}[10.0]
    e = workloads.effectiveness_by_delta(spark, SMALL, n=6, rho=0.1, k=3).orderBy("delta").collect()
    # Larger bounds: fewer common POIs, safer and longer paths.
    assert e[0]["common"] >= e[-1]["common"] and e[0]["pss_safest"] <= e[-1]["pss_safest"] and e[0]["length_ratio"] <= e[-1]["length_ratio"]
    stats = workloads.index_sweep(spark, SMALL, "comptree", "smax", (5,)).first()
    assert 0 < stats["border_share"] <= 1 and stats["seconds"] > 0


def test_level_weights_come_from_the_roads(spark):
    from saferoads.queries import level_weights, net_p

    want = {r["ess"]: r["n"] for r in net_p(spark, SMALL, smax=5).edges.groupBy("ess").agg(F.count("*").alias("n")).collect()}
    got = level_weights(spark, SMALL).collect()
    assert {r["s"]: r["n"] for r in got} == want and all(r["weight"] == 10.0 ** (5 - r["s"]) for r in got)


def test_index_sizes_need_no_rounds_over_the_network(spark, monkeypatch):
    from saferoads.plans import evaluation, workloads

    def fails(*_, **__):
        raise AssertionError("built by rounds")

    for name in ("build_comptree", "build_safevor"):
        monkeypatch.setattr(evaluation, name, fails)
    for which in ("comptree", "safevor"):
        stats = workloads.index_sweep(spark, SMALL, which, "rho", (0.1,)).first()
        assert stats["rows"] > 0 and stats["bytes"] > 0 and 0 < stats["border_share"] <= 1


def test_index_sizes_are_of_the_same_tables_at_any_size(spark, monkeypatch):
    """No size of the network changes what is measured; beyond the kernel's size it is refused."""
    from saferoads.operators import kernel
    from saferoads.plans import evaluation, workloads

    sizes = lambda: [tuple(workloads.index_sweep(spark, SMALL, which, "rho", (0.1,)).select("rows", "border_share").first()) for which in ("comptree", "safevor")]
    want = sizes()
    monkeypatch.setattr(evaluation, "MOST_ARCS", 2, raising=False)
    assert sizes() == want
    monkeypatch.setattr(kernel, "MOST_ARCS", 2)
    for which in ("comptree", "safevor"):
        with pytest.raises(ValueError):
            workloads.index_sweep(spark, SMALL, which, "rho", (0.1,))


@pytest.mark.parametrize("varies", ["delta", "k", "smax"])
def test_values_of_a_sweep_share_what_they_can(spark, monkeypatch, varies):
    """Incidents are counted once, indexes built once a network; counters are those of settings made one by one."""
    from saferoads.plans import evaluation, workloads

    made, values = [], {"delta": (1.25, 2.0), "k": (2, 4), "smax": (5, 8)}[varies]
    for name in ("lattice_counts", "build_comptree_local", "build_cells_local"):
        plain = getattr(workloads, name)
        monkeypatch.setattr(workloads, name, lambda *a, n=name, f=plain, **b: made.append(n) or f(*a, **b))
    got = workloads.sweep(spark, SMALL, varies, values, n=5, rho=0.1, **({} if varies == "k" else {"k": 3})).collect()
    networks = 2 if varies == "smax" else 1
    assert sorted(made) == ["build_cells_local"] * networks + ["build_comptree_local"] * networks + ["lattice_counts"]
    for value in values:
        net, queries, tree = workloads.setting(spark, SMALL, n=5, **({"rho": 0.1, "k": 3} | {varies: value}))
        for method in ("expand", "comptree", "safevor"):
            alone = evaluation.counters(evaluation.grouped_search(net, queries, method, tree=tree), method, ()).first()
            mine = next(r for r in got if r["value"] == value and r["method"] == method)
            assert all(mine[c] == alone[c] for c in ("queries", "va", "popped", "pushed", "extra", "parts"))


def proximity(path):
    import duckdb

    with duckdb.connect() as db:
        db.sql(f"CREATE VIEW embeddings AS SELECT * FROM '{path}/embeddings.parquet/*.parquet'")
        return sorted(db.sql(entry.oracle_sql()["proximity_edges"]).fetchall())


@pytest.mark.parametrize("kind", ["gaps", "copies"])
def test_proximity_on_odd_vectors(spark, tmp_path, monkeypatch, kind):
    """Missing components, vectors of other lengths, shared ids, ties and copies, in blocks of few rows; SQL passes over nulls."""
    import numpy as np

    from saferoads.operators import nearest

    monkeypatch.setattr(nearest, "BLOCK", 64 * 8)
    rng = np.random.default_rng(5)
    rows = []
    for i in range(300):
        v = [float(x) for x in rng.normal(size=8).astype(np.float32)] if kind == "gaps" or i % 3 else [1.0] * 8
        if kind == "gaps":
            v = [None] * 8 if i % 50 == 0 else [None if rng.random() < 0.05 else x for x in v] if i % 4 == 0 else v[: 1 + i % 8] if i % 7 == 0 else v
            v = [float(round(x)) if x is not None else None for x in v] if i % 5 == 0 else v
        rows.append((None if i == 17 else i // 2 if i % 20 == 0 else i, None if i == 18 else [] if i == 19 else v, None if i == 21 else int(rng.integers(0, 3)) if i % 2 else 1))
    spark.createDataFrame(rows, "vec_id bigint, embedding array<float>, label int").repartition(3).write.parquet(str(tmp_path / "embeddings.parquet"))
    assert sorted(tuple(r) for r in entry.queries()["proximity_edges"](spark, str(tmp_path)).collect()) == proximity(tmp_path)


def test_copies_are_not_all_paired():
    """What a block sums by the definition: a few pairs for each query, however many there are."""
    import numpy as np
    import pyarrow as pa

    from saferoads.operators import nearest

    rng, n = np.random.default_rng(6), 3000
    vectors = rng.normal(size=(2 * n, 16)).astype(np.float32)
    table = pa.table({"asked": [True] * n + [False] * n, "vec_id": pa.array(list(range(2 * n)), pa.int64()), "label": pa.array([1] * 2 * n, pa.int32()), "embedding": pa.array(list(vectors), pa.list_(pa.float32()))})
    summed, plain = [], nearest.gaps
    nearest.gaps = lambda a, *rest: summed.append(len(a)) or plain(a, *rest)
    try:
        found = nearest.nearest_in_block(table, 4)
    finally:
        nearest.gaps = plain
    assert found.num_rows == 4 * n and sum(summed) < 20 * n
    best = np.argsort(((vectors[0] - vectors[n:]) ** 2).sum(1), kind="stable")[:4] + n
    assert found.column("id2").to_pylist()[:4] == best.tolist()


def test_a_sweep_makes_its_roads_once(spark, monkeypatch):
    """Values of rho share the roads, their POIs are those of a network made for the value."""
    from saferoads.plans import workloads

    made, plain, roads = [], workloads.lattice_network, {}
    monkeypatch.setattr(workloads, "lattice_network", lambda *a, **b: made.append(b) or plain(*a, **b))
    for rho in (0.05, 0.2):
        net, *_ = workloads.setting(spark, SMALL, n=4, roads=roads, rho=rho)
        want = plain(spark, SMALL, rho=rho)
        assert sorted(r[0] for r in net.pois.collect()) == sorted(r[0] for r in want.pois.collect())
    assert len(made) == 1 and net.edges.count() == want.edges.count()
