"""The registered queries of the safety engine, and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from saferoads.functions import safety
from saferoads.operators import comptree, ess, expand, safevor, topk
from saferoads.operators.kernel import build_cells_local, grouped_search
from saferoads.plans import evaluation, workloads
from saferoads.plans.runtime import durable, forget, read_table, shared_dir
from saferoads.sources import networks

K, DC, RHO, SMAX = 5, 60.0, 0.1, 10


def net_p(spark: SparkSession, sf_dir: str, **options) -> networks.Network:
    net = networks.lattice_network(spark, sf_dir, **({"smax": SMAX, "rho": RHO} | options))
    return networks.Network(durable(net.vertices), durable(net.edges), durable(net.pois), net.smax)


def asked(net: networks.Network, k: int = K, dc: float = DC, n: int = 100) -> DataFrame:
    return durable(networks.sample_queries(net, k, dc, n))


def shown(found: DataFrame) -> DataFrame:
    """Answers with the s-vector as text."""
    return found.select("qid", "rnk", "poi", "dist", F.array_join("key", ",").alias("sd"))


def edges_lattice(spark, sf_dir):
    return net_p(spark, sf_dir).edges


def incidents_per_edge(spark, sf_dir):
    vertices, _, width = networks.lattice_vertices(read_table(spark, sf_dir, "part"))
    edges = networks.lattice_edges(vertices, width)
    return ess.crime_counts(edges, networks.lattice_incidents(read_table(spark, sf_dir, "lineitem"), width), 10).select("eid", "u", "w", "n")


def incidents_clustered(spark, sf_dir):
    vertices, _, width = networks.lattice_vertices(read_table(spark, sf_dir, "part"))
    edges = networks.lattice_edges(vertices, width)
    return ess.crime_counts(edges, networks.lattice_incidents(read_table(spark, sf_dir, "lineitem"), width, True), 10).select("eid", "u", "w", "n")


def ess_histogram(spark, sf_dir):
    out = None
    for smax in (5, 10, 15):
        one = networks.lattice_network(spark, sf_dir, smax=smax).edges.groupBy("ess").agg(F.count("*").alias("n")).select(F.lit(smax).alias("smax"), "ess", "n")
        out = one if out is None else out.unionAll(one)
    return out


def poi_sample(spark, sf_dir):
    return net_p(spark, sf_dir).pois


def level_weights(spark, sf_dir):
    """The weights of the levels that roads have, with their numbers of roads."""
    roads = net_p(spark, sf_dir, smax=5).edges.groupBy("ess").agg(F.count("*").alias("n"))
    return roads.select(F.col("ess").alias("s"), F.element_at(safety.level_weights(10.0, 5), F.col("ess")).alias("weight"), "n")


def _sample_paths(spark, sf_dir):
    """Rows of the lattice as paths: the right edges of each row, as long as none is missing from the left."""
    net = net_p(spark, sf_dir)
    width = int(net.vertices.count() ** 0.5)
    right = net.edges.where(F.col("w") == F.col("u") + 1).withColumns({"path_id": F.floor(F.col("u") / width).cast("bigint"), "at": F.col("u") % width})
    order = Window.partitionBy("path_id").orderBy("at")
    return right.withColumn("i", F.row_number().over(order) - 1).where("i = at").select("path_id", "at", "len", "ess")


def s_vector_paths(spark, sf_dir):
    v = safety.s_vector(_sample_paths(spark, sf_dir), SMAX)
    return v.select("path_id", "dist", F.array_join("sd", ",").alias("sd"), safety.min_ess("sd").alias("bottleneck"))


def s_distance_paths(spark, sf_dir):
    return safety.s_distance(_sample_paths(spark, sf_dir), 4)


def pss_paths(spark, sf_dir):
    """Rank of the sample paths by safety, with the exact weighted length at base 1000 over five levels.

    Paths are ranked within ranges of the order; a range's first rank follows from the sizes of those before."""
    paths = _sample_paths(spark, sf_dir).withColumn("ess", F.least(F.col("ess"), F.lit(5)))
    v = durable(safety.s_vector(paths, 5))
    sizes = v.groupBy(F.col("sd")[0].alias("first")).agg(F.count("*").alias("n"))
    earlier = sizes.alias("a").join(sizes.alias("b"), F.col("b.first") < F.col("a.first"), "left").groupBy("a.first").agg(F.coalesce(F.sum("b.n"), F.lit(0)).alias("before"))
    within = F.rank().over(Window.partitionBy(F.col("sd")[0]).orderBy("sd"))
    ranked = v.withColumn("within", within).join(F.broadcast(earlier), v["sd"][0] == F.col("first"))  # as many rows as a path's length has values
    return ranked.select("path_id", safety.exact_cost("sd", 1000, 5).cast("bigint").alias("cost"), (F.col("before") + F.col("within")).cast("int").alias("rnk"))


def safest_expand(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return shown(expand.expand(net, asked(net)))


def safest_expand_clustered(spark, sf_dir):
    net = net_p(spark, sf_dir, clustered=True)
    return shown(expand.expand(net, asked(net)))


def safest_expand_smax5(spark, sf_dir):
    net = net_p(spark, sf_dir, smax=5)
    return shown(expand.expand(net, asked(net, 1, 80.0)))


def safest_brute(spark, sf_dir):
    """All simple paths of all queries, under a bound of 40."""
    net = net_p(spark, sf_dir)
    return shown(expand.brute_force(net, asked(net, K, 40.0)))


def safest_euclid(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return shown(expand.euclid_baseline(net, asked(net)))


def safest_comptree(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return shown(comptree.comptree_search(net, comptree.build_comptree(net, reach=DC), asked(net)))


def safest_comptree_height5(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return shown(comptree.comptree_search(net, comptree.build_comptree(net, height=5, reach=DC), asked(net)))


def safest_safevor(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return shown(safevor.safevor_search(net, safevor.build_safevor(net, reach=DC), asked(net)))


def _kernel(method):
    def query(spark, sf_dir):
        net = net_p(spark, sf_dir)
        tree = comptree.build_comptree_local(net, reach=DC) if method == "comptree" else None
        return shown(grouped_search(net, asked(net), method, tree=tree).where("rnk > 0"))

    return query


def safest_pairs(spark, sf_dir):
    """The safest path from each query vertex to the next one's nearest lattice neighbour two steps away."""
    net = net_p(spark, sf_dir)
    pairs = durable(asked(net).select("qid", "src", (F.col("src") + 2).alias("dst"), "dc"))
    found = expand.safest_path(net, pairs)
    return found.join(pairs.select("qid", F.col("dst").alias("poi")), ["qid", "poi"]).select("qid", "poi", "dist", F.array_join("key", ",").alias("sd"))


def safest_frontier(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return expand.safest_frontier(net, asked(net)).select("qid", "poi", "dist", F.array_join("key", ",").alias("sd"))


def euclid_candidates(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return expand.euclid_candidates(net, asked(net))


def knn_topk(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return expand.knn(net, asked(net), K)


def dc_by_delta(spark, sf_dir):
    net = net_p(spark, sf_dir)
    q = asked(net)
    nearest = durable(expand.knn(net, q, K))
    out = None
    for delta in (1.25, 1.5, 1.75, 2.0):
        one = expand.set_dc(q, nearest, delta).select(F.lit(delta).alias("delta"), "qid", "dc", "few")
        out = one if out is None else out.unionAll(one)
    return out


def comptree_pointers(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return comptree.pointers(net, comptree.cuts_of(SMAX, None))


def comptree_nodes(spark, sf_dir):
    net = net_p(spark, sf_dir)
    cuts = comptree.cuts_of(SMAX, None)
    return comptree.node_stats(net, durable(comptree.pointers(net, cuts)), cuts)


def comptree_borders(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return comptree.border_vertices(net, comptree.pointers(net, comptree.cuts_of(SMAX, None)))


def border_distance(spark, sf_dir):
    net = net_p(spark, sf_dir)
    cuts = comptree.cuts_of(SMAX, None)
    return comptree.border_distances(net, durable(comptree.pointers(net, cuts)), cuts, DC).select("lvl", "comp", "vid", "d_border", "d_poi")


def usn_assignment(spark, sf_dir):
    net = net_p(spark, sf_dir)
    lists = safevor.safest_lists(net, 1)
    return lists.select("vid", F.col("poi").alias("cell"), "dist", F.array_join("sd", ",").alias("sd"))


def _cells(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return net, durable(safevor.safest_lists(net, 1).select("vid", F.col("poi").alias("cell"), "sd", "dist"))


def cell_borders(spark, sf_dir):
    return safevor.cell_borders(*_cells(spark, sf_dir))


def cell_adjacency(spark, sf_dir):
    return safevor.adjacency_of(safevor.cell_borders(*_cells(spark, sf_dir)))


def cell_sizes(spark, sf_dir):
    _, cells = _cells(spark, sf_dir)
    return cells.groupBy("cell").agg(F.count("*").alias("n"), F.max("dist").alias("farthest"))


def effectiveness(spark, sf_dir):
    """Common POIs, lengths and mean scores (logarithms, at base 1000) of the safest and the nearest answers, by delta."""
    net = net_p(spark, sf_dir)
    q = asked(net)
    nearest = durable(expand.knn(net, q, K))
    known = durable(evaluation.nearest_paths(net, q, nearest))
    out = None
    for delta in workloads.SWEEPS["delta"]:
        bounded = durable(expand.set_dc(q, nearest, delta).drop("few"))
        safest = durable(topk.safest_topk(net, bounded, "expand"))
        row = evaluation.effectiveness(safest, known.join(safest.select("qid").distinct(), "qid", "left_semi"), SMAX, 1000.0)
        measures = [F.round(c, 6).alias(c) for c in ("common", "p_safest_in_knn", "length_knn", "length_safest", "length_ratio")]
        scores = [F.round(F.log10(c), 6).alias(f"log_{c}") for c in ("pss_knn", "pss_safest", "pss_ratio")]
        row = row.select(F.lit(delta).alias("delta"), *measures, *scores)
        out = row if out is None else out.unionAll(row)
    return out


def weight_choice_safest(spark, sf_dir):
    """Another weight of the roads: minutes at a speed that the level sets, rounded up."""
    net = net_p(spark, sf_dir).with_weight(F.ceil(F.col("len") * 6 / (F.col("ess") + 2)))
    return shown(expand.expand(net, asked(net)))


def daynight_safest(spark, sf_dir):
    """Answers by the levels of the daytime that the query names."""
    net = networks.daytime_network(spark, sf_dir)
    net = networks.Network(durable(net.vertices), durable(net.edges), durable(net.pois), net.smax)
    found = [shown(topk.safest_topk(net.for_key(key), asked(net), "expand")).select(F.lit(key).alias("daytime"), "*") for key in ("day", "night")]
    return found[0].unionAll(found[1])


def incidents_of_kinds(spark, sf_dir):
    """Events of two kinds for each edge number of the streams."""
    events = ess.of_kinds(read_table(spark, sf_dir, "events"), ("error", "signup"), "event_type")
    return events.groupBy((F.col("event_id") * 611953 % 500).alias("eid")).agg(F.count("*").alias("n"))


def cell_poi_paths(spark, sf_dir):
    """Stored safest ways inside the cells from their border ends to their POIs."""
    ways = build_cells_local(net_p(spark, sf_dir)).ways.where("b2 = cell and b1 <> cell")
    return ways.select("cell", "b1", "dist", F.array_join("sd", ",").alias("sd"))


def cell_ways(spark, sf_dir):
    """All stored ways inside the cells, border to border too, as counts and lengths by cell."""
    ways = build_cells_local(net_p(spark, sf_dir)).ways.where("direct")
    return ways.groupBy("cell").agg(F.count("*").alias("ways"), F.sum("dist").alias("length"))


def cells_kernel(spark, sf_dir):
    return build_cells_local(net_p(spark, sf_dir)).cells


def ablation_answers(spark, sf_dir):
    """Every rule set of every method over all queries: number of answers, their lengths and ranks. All sets agree."""
    net = net_p(spark, sf_dir)
    q, tree, cells = asked(net), comptree.build_comptree_local(net, reach=DC), build_cells_local(net)
    out = None
    for method, sets in evaluation.ABLATION.items():
        for rules in sets:
            found = grouped_search(net, q, method, rules, tree, cells=cells).where("rnk > 0")
            row = found.agg(F.count("*").alias("answers"), F.sum("dist").cast("bigint").alias("length"), F.sum(F.col("rnk") * F.col("poi")).cast("bigint").alias("ranks"))
            row = durable(row.select(F.lit(method).alias("method"), F.lit(",".join(map(str, rules))).alias("rules"), "*"))
            out = row if out is None else out.unionAll(row)
    return out


def _sweep(varies):
    n = 40 if varies in ("k", "rho") else 100  # a search for more POIs than there are visits the whole network

    def query(spark, sf_dir):
        return workloads.sweep(spark, sf_dir, varies, n=n)

    query.__name__ = f"sweep_{varies}"
    return query


def sweep_network(spark, sf_dir):
    """The defaults on the network with incidents in clusters."""
    return workloads.sweep(spark, sf_dir, "k", (10,), clustered=True)


def index_comparison(spark, sf_dir):
    """Build time, rows, bytes and border share of both indexes at the defaults."""
    return workloads.index_sweep(spark, sf_dir, "comptree", "rho", (0.01,)).withColumn("index", F.lit("comptree")).unionByName(workloads.index_sweep(spark, sf_dir, "safevor", "rho", (0.01,)))


def stream_window_counts(spark, sf_dir):
    """Incidents of every edge and week, by the stream; what the batch form counts."""
    from saferoads.streaming import incidents

    arriving = incidents.incident_stream(spark, sf_dir, delay="40 days", pattern="events.parquet")
    weekly = arriving.groupBy(F.window("ts", "7 days", startTime="4 days").alias("w"), "eid").agg(F.count("*").alias("n"))
    return _streamed(spark, weekly.select(F.to_date("w.start").cast("string").alias("week"), "eid", "n"), "complete")


def stream_level_changes(spark, sf_dir):
    """The last level of every edge whose incidents moved it, by the stream with state."""
    from saferoads.streaming import incidents

    arriving = incidents.incident_stream(spark, sf_dir, delay="40 days", pattern="events.parquet")
    moved = _streamed(spark, incidents.level_changes(arriving, 10, 2), "update")
    return moved.groupBy("eid").agg(F.max_by("ess", "n").alias("ess"))


def _streamed(spark, frame, mode):
    """Rows of a finished stream over the files that are there."""
    import uuid

    root, parts = f"{shared_dir(spark)}/saferoads-stream-{uuid.uuid4().hex}", []
    started = frame.writeStream.foreachBatch(lambda df, _: parts.append(durable(df))).outputMode(mode).option("checkpointLocation", root).trigger(availableNow=True).start()
    started.awaitTermination()
    forget(spark, root)
    if not parts:
        return spark.createDataFrame([], frame.schema)
    return parts[-1] if mode == "complete" else reduce(DataFrame.unionAll, parts)


def zone_safest(spark, sf_dir):
    net = networks.zone_network(spark, sf_dir)
    net = networks.Network(durable(net.vertices), durable(net.edges), durable(net.pois), net.smax)
    return shown(expand.expand(net, asked(net)))


def min_ess_safest(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return expand.expand(net, asked(net), measure=safety.MinEss).select("qid", "rnk", "poi", "dist", F.col("key")[0].alias("badness"))


def product_ess_safest(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return expand.expand(net, asked(net), measure=safety.ProductEss).select("qid", "rnk", "poi", "dist", F.col("key")[0].alias("badness"))


def daynight_ess(spark, sf_dir):
    edges = networks.daytime_network(spark, sf_dir).edges
    return edges.select("eid", F.col("ess_by")["day"].alias("day"), F.col("ess_by")["night"].alias("night"))


def trade_edges(spark, sf_dir):
    return networks.trade_network(spark, sf_dir).edges.select("u", "w", "len", "ess")


def trade_components(spark, sf_dir):
    net = networks.trade_network(spark, sf_dir)
    from saferoads.plans.components import connected_components

    comps = connected_components(net.edges.where("ess > 4"), "u", "w")
    return comps.groupBy("comp").agg(F.count("*").alias("n"))


def proximity_edges(spark, sf_dir):
    return networks.proximity_network(spark, sf_dir).edges.groupBy("ess").agg(F.count("*").alias("n"), F.min("len").alias("shortest"))


def _history(spark, sf_dir):
    """Versions of an edge's level: one for each error event at its number."""
    events = read_table(spark, sf_dir, "events").where("event_type = 'error'")
    return events.select((F.col("event_id") * 611953 % 500).alias("eid"), (1 + F.col("user_id") % 10).cast("int").alias("ess"), F.col("ts").alias("valid_from"))


def ess_asof(spark, sf_dir):
    asked_ = read_table(spark, sf_dir, "events").where("event_type = 'purchase'").select((F.col("event_id") * 611953 % 500).alias("eid"), F.col("ts").alias("at"))
    history = _history(spark, sf_dir).groupBy("eid", "valid_from").agg(F.max("ess").alias("ess"))
    return ess.ess_asof(asked_, history).groupBy("eid").agg(F.count("*").alias("asked"), F.sum("ess").alias("ess_sum"))


def ess_weekly_windows(spark, sf_dir):
    events = read_table(spark, sf_dir, "events").where("event_type = 'error'").withColumn("at", F.col("ts").cast("timestamp"))
    per = events.groupBy(F.window("at", "7 days", startTime="4 days").alias("w"), (F.col("event_id") * 611953 % 500).alias("eid")).agg(F.count("*").alias("n"))
    return per.select(F.to_date("w.start").cast("string").alias("week"), "eid", "n")


def incident_cube(spark, sf_dir):
    events = read_table(spark, sf_dir, "events")
    part = F.when((F.hour("ts") >= 6) & (F.hour("ts") < 18), "day").otherwise("night")
    return events.select("event_type", part.alias("part")).cube("event_type", "part").agg(F.count("*").alias("n"), F.grouping_id().cast("int").alias("grp"))


def answers_setops(spark, sf_dir):
    """Answers that the safest and the nearest search share, and those that only one has."""
    net = net_p(spark, sf_dir)
    q = asked(net)
    a = durable(expand.expand(net, q).select("qid", "poi"))
    b = durable(expand.knn(net, q, K, reach=DC).where(F.col("rnk") <= K).select("qid", "poi"))
    both, first, second = a.intersect(b), a.exceptAll(b), b.exceptAll(a)
    return both.withColumn("side", F.lit("both")).unionAll(first.withColumn("side", F.lit("safest"))).unionAll(second.withColumn("side", F.lit("nearest")))


def knn_kernel(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return grouped_search(net, asked(net), "knn").where("rnk > 0").select("qid", "rnk", "poi", "dist")


def border_distance_local(spark, sf_dir):
    return comptree.build_comptree_local(net_p(spark, sf_dir), reach=DC).borders


def comptree_nodes_local(spark, sf_dir):
    return comptree.build_comptree_local(net_p(spark, sf_dir), reach=DC).nodes


def ablation(spark, sf_dir):
    net = net_p(spark, sf_dir)
    return evaluation.ablation(net, asked(net), comptree.build_comptree_local(net, reach=DC))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (edges_lattice, incidents_per_edge, incidents_clustered, ess_histogram, poi_sample, level_weights, s_vector_paths, s_distance_paths, pss_paths, safest_expand, safest_expand_clustered, safest_expand_smax5, safest_brute, safest_euclid, safest_comptree, safest_comptree_height5, safest_safevor, safest_pairs, safest_frontier, euclid_candidates, knn_topk, dc_by_delta, comptree_pointers, comptree_nodes, comptree_borders, border_distance, usn_assignment, cell_borders, cell_adjacency, cell_sizes, effectiveness, zone_safest, min_ess_safest, product_ess_safest, daynight_ess, trade_edges, trade_components, proximity_edges, ess_asof, ess_weekly_windows, incident_cube, answers_setops, knn_kernel, border_distance_local, comptree_nodes_local, ablation, ablation_answers, weight_choice_safest, daynight_safest, incidents_of_kinds, cell_poi_paths, cell_ways, cells_kernel, index_comparison, sweep_network, stream_window_counts, stream_level_changes, *map(_sweep, workloads.SWEEPS))
} | {f"kernel_{m}": _kernel(m) for m in ("expand", "comptree", "safevor", "euclid")}
