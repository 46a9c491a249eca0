"""The experiments as sweeps: one parameter varies, the others keep their defaults (W1-W10).

Rows come from the exact kernel, so times are those of a worker core and counters those of the queue-ordered search.
"""

from __future__ import annotations

from collections.abc import Iterable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from saferoads.operators.comptree import build_comptree_local
from saferoads.operators.kernel import build_cells_local, grouped_search
from saferoads.plans import evaluation
from saferoads.plans.runtime import durable
from saferoads.sources.networks import Network, lattice_counts, lattice_network, sample_pois

#: The defaults and the values of each sweep.
DEFAULTS = {"k": 10, "delta": 2.0, "smax": 10, "rho": 0.01}
SWEEPS = {"delta": (1.25, 1.5, 1.75, 2.0), "k": (1, 5, 10, 25, 50), "smax": (5, 10, 15), "rho": (0.00001, 0.0001, 0.001, 0.01, 0.1)}


def network(spark: SparkSession, sf_dir: str, smax: int, rho: float, clustered: bool, roads: dict) -> Network:
    """The network of one setting. roads: what was made before of the same tables and clustering; counts of incidents serve all
    levels, vertices and edges all POIs, and the same values get the same network."""
    if (smax, rho) in roads:
        return roads[smax, rho]
    if smax not in roads:
        if not roads:
            vertices, counts, size = lattice_counts(spark, sf_dir, clustered=clustered)
            roads["counted"] = durable(vertices), durable(counts), size
        made = lattice_network(spark, sf_dir, smax=smax, rho=rho, clustered=clustered, counted=roads["counted"])
        roads[smax] = durable(made.edges)
    vertices, _, size = roads["counted"]
    roads[smax, rho] = Network(vertices, roads[smax], durable(sample_pois(vertices, rho, size)), smax)
    return roads[smax, rho]


def farthest(queries: DataFrame) -> float:
    return float(queries.agg(F.max("dc")).first()[0] or 0) + 1


def setting(spark: SparkSession, sf_dir: str, clustered: bool = False, n: int = 100, roads: dict | None = None, **changed):
    """Network, queries and component tree of one setting. roads: see network."""
    p = DEFAULTS | changed
    net = network(spark, sf_dir, p["smax"], p["rho"], clustered, {} if roads is None else roads)
    queries = evaluation.default_queries(net, p["k"], p["delta"], n, local=True)
    return net, queries.drop("few"), build_comptree_local(net, reach=farthest(queries))


def sweep(spark: SparkSession, sf_dir: str, varies: str, values: Iterable | None = None, methods: Iterable[str] = ("expand", "comptree", "safevor"), n: int = 100, clustered: bool = False, **fixed) -> DataFrame:
    """varies, value, method and the means of its counters; speed-ups over EXPAND where it is among the methods. Values of one
    network share its indexes: the tree is built for the largest bound, which changes no search of a smaller one."""
    out, roads, same = None, {}, {}
    for value in SWEEPS[varies] if values is None else values:
        p = DEFAULTS | fixed | {varies: value}
        same.setdefault((p["smax"], p["rho"]), []).append((value, p["k"], p["delta"]))
    for (smax, rho), settings in same.items():
        net = network(spark, sf_dir, smax, rho, clustered, roads)
        asked = [q.drop("few") for q in evaluation.all_queries(net, [(k, delta) for _, k, delta in settings], n, local=True)]
        with ThreadPoolExecutor(2) as both:  # one task assigns the vertices to cells, a task for each level builds the tree
            cells = both.submit(build_cells_local, net) if "safevor" in methods else None
            tree = both.submit(build_comptree_local, net, reach=max(map(farthest, asked))) if "comptree" in methods else None
            cells, tree = cells and cells.result(), tree and tree.result()
        for (value, *_), queries in zip(settings, asked, strict=True):
            for method in methods:
                row = evaluation.counters(grouped_search(net, queries, method, tree=tree, cells=cells), method, ())
                row = durable(row.drop("rules").select(F.lit(varies).alias("varies"), F.lit(float(value)).alias("value"), "*"))
                out = row if out is None else out.unionAll(row)
    base = out.where("method = 'expand'").select("value", F.col("ms").alias("base"))
    return out.join(base, "value", "left").withColumn("speed_up", F.col("base") / F.col("ms")).drop("base")


def effectiveness_by_delta(spark: SparkSession, sf_dir: str, n: int = 100, base: float = 1000.0, **fixed) -> DataFrame:
    """The comparison with nearest neighbours for every delta."""
    out = None
    for delta in SWEEPS["delta"]:
        net, queries, tree = setting(spark, sf_dir, n=n, **(fixed | {"delta": delta}))
        safest = durable(grouped_search(net, queries, "comptree", tree=tree).where("rnk > 0").select("qid", "rnk", "poi", "dist", "key"))
        nearest = durable(grouped_search(net, queries, "knn").where("rnk > 0"))
        row = evaluation.effectiveness(safest, path_keys(nearest, net), net.smax, base).withColumn("delta", F.lit(delta))
        out = row if out is None else out.unionAll(row)
    return out


def path_keys(found: DataFrame, net: Network) -> DataFrame:
    """found (qid, rnk, path, ...) with key, the s-vector of the path, by a join of its edges."""
    steps = found.select("qid", "rnk", F.explode(F.transform(F.sequence(F.lit(1), F.size("path")), lambda i: F.struct(F.get("path", i - 1).alias("src"), F.get("path", i).alias("dst")))).alias("s"))
    by_level = [F.coalesce(F.sum(F.when(F.col("ess") == s, F.col("len"))), F.lit(0)).cast("bigint") for s in range(1, net.smax + 1)]
    keys = steps.select("qid", "rnk", "s.*").join(net.arcs, ["src", "dst"], "left").groupBy("qid", "rnk").agg(F.array(*by_level).alias("key"))
    return found.drop("key").join(keys, ["qid", "rnk"])


def index_sweep(spark: SparkSession, sf_dir: str, which: str, varies: str, values: Iterable, reach: float = 60.0) -> DataFrame:
    """Build time, rows and border share of one index for values of smax or rho."""
    rows = []
    for value in values:
        p = DEFAULTS | {varies: value}
        net = lattice_network(spark, sf_dir, smax=p["smax"], rho=p["rho"])
        net = Network(durable(net.vertices), durable(net.edges), durable(net.pois), net.smax)  # read, not made again, in every round
        rows.append({"varies": varies, "value": float(value), **evaluation.index_stats(net, which, reach)})
    return spark.createDataFrame(rows)
