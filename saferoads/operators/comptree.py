"""Hierarchy of connected components by safety threshold: build, statistics, search.

Level s holds the components of the roads with a level above s; level 0 is the whole network. All levels are built in one
run of the component search, over vertices coded as vid * LEVELS + level.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from saferoads.functions.safety import LexSafety, Measure
from saferoads.operators.expand import LABEL, answers, nearest_lists, seed_labels, settle
from saferoads.plans.components import connected_components
from saferoads.plans.runtime import durable, small_enough
from saferoads.sources.networks import Network

LEVELS = 64


@dataclass(frozen=True)
class CompTree:
    """pointers (vid, lvl, comp), nodes (lvl, comp, parent, n_vertices, n_edges, n_pois, is_leaf), borders (lvl, comp, vid,
    d_border, d_poi; null: none within reach). reach: the index serves bounds up to it (None: all)."""

    pointers: DataFrame
    nodes: DataFrame
    borders: DataFrame
    smax: int
    reach: float | None = None
    cuts: tuple[int, ...] = ()


def cuts_of(smax: int, height: int | None) -> tuple[int, ...]:
    """Thresholds of the levels: all, or `height` contiguous and complete ranges of about equal size."""
    height = smax if height is None else min(height, smax)
    return tuple(sorted({i * smax // height for i in range(height)}))


def levels_of(edges: DataFrame, cuts: tuple[int, ...]) -> DataFrame:
    """Edges once for each threshold below their level."""
    return edges.withColumn("lvl", F.explode(F.filter(F.array(*map(F.lit, cuts)), lambda c: c < F.col("ess"))))


def pointers(net: Network, cuts: tuple[int, ...]) -> DataFrame:
    coded = levels_of(net.edges, cuts).select((F.col("u") * LEVELS + F.col("lvl")).alias("a"), (F.col("w") * LEVELS + F.col("lvl")).alias("b"))
    comps = connected_components(coded)
    every = net.vertices.select("vid", F.explode(F.array(*map(F.lit, cuts))).alias("lvl")).withColumn("id", F.col("vid") * LEVELS + F.col("lvl"))
    comp = F.floor(F.coalesce("comp", "id") / LEVELS).cast("bigint")
    return every.join(comps, "id", "left").select("vid", "lvl", comp.alias("comp"))


def node_stats(net: Network, chain: DataFrame, cuts: tuple[int, ...]) -> DataFrame:
    at = chain.join(net.pois, chain.vid == net.pois.poi, "left").groupBy("lvl", "comp").agg(F.count("*").alias("n_vertices"), F.count("poi").alias("n_pois"))
    inside = levels_of(net.edges, cuts).join(chain.withColumnRenamed("vid", "u"), ["u", "lvl"]).groupBy("lvl", "comp").agg(F.count("*").alias("n_edges"), F.min("ess").alias("lo"), F.max("ess").alias("hi"))
    above = F.lit(None).cast("int")
    for c, p in zip(cuts[1:], cuts, strict=False):
        above = F.when(F.col("lvl") == c, F.lit(p)).otherwise(above)
    up = chain.select(F.col("vid").alias("comp"), F.col("lvl").alias("above"), F.col("comp").alias("parent"))
    nodes = at.join(inside, ["lvl", "comp"], "left").withColumn("above", above).join(up, ["comp", "above"], "left")
    leaf = (F.coalesce("n_edges", F.lit(0)) == 0) | (F.col("lo") == F.col("hi"))
    return nodes.select("lvl", "comp", "parent", "n_vertices", F.coalesce("n_edges", F.lit(0)).alias("n_edges"), "n_pois", leaf.alias("is_leaf"))


def border_vertices(net: Network, chain: DataFrame) -> DataFrame:
    """lvl, comp, vid of the vertices with an incident edge that their level leaves out."""
    least = net.arcs.groupBy("src").agg(F.min("ess").alias("least")).withColumnRenamed("src", "vid")
    return chain.join(least, "vid").where("least <= lvl").select("lvl", "comp", "vid")


def coded_arcs(net: Network, cuts: tuple[int, ...]) -> DataFrame:
    return levels_of(net.arcs, cuts).select((F.col("src") * LEVELS + F.col("lvl")).alias("src"), (F.col("dst") * LEVELS + F.col("lvl")).alias("dst"), "len")


def border_distances(net: Network, chain: DataFrame, cuts: tuple[int, ...], reach: float | None) -> DataFrame:
    """Borders with the distance, inside their node, to another border and to a POI: two runs serve all levels."""
    arcs = durable(coded_arcs(net, cuts))
    borders = durable(border_vertices(net, chain).withColumn("source", F.col("vid") * LEVELS + F.col("lvl")))
    two = nearest_lists(arcs, borders.select("source"), 2, reach)
    other = two.where("vid <> source").groupBy("vid").agg(F.min("dist").alias("d_border"))
    pois = chain.join(net.pois, chain.vid == net.pois.poi, "left_semi").select((F.col("vid") * LEVELS + F.col("lvl")).alias("source"))
    near = nearest_lists(arcs, pois, 1, reach).select("vid", F.col("dist").alias("d_poi"))
    coded = borders.withColumnRenamed("vid", "v")
    found = coded.join(other, coded.source == other.vid, "left").drop("vid").join(near, coded.source == near.vid, "left")
    return found.select("lvl", "comp", F.col("v").alias("vid"), "d_border", "d_poi")


def build_comptree(net: Network, height: int | None = None, reach: float | None = None) -> CompTree:
    cuts = cuts_of(net.smax, height)
    chain = durable(pointers(net, cuts))
    return CompTree(chain, durable(node_stats(net, chain, cuts)), durable(border_distances(net, chain, cuts, reach)), net.smax, reach, cuts)


def build_comptree_local(net: Network, height: int | None = None, reach: float | None = None) -> CompTree:
    """The same index for a network of a checked size: every level is a task that holds the arcs."""
    from saferoads.operators.kernel import MOST_ARCS

    if not small_enough(net.edges, MOST_ARCS // 2):
        raise ValueError("the network is too large for this build")
    cuts = cuts_of(net.smax, height)
    arcs = net.arcs.select("src", "dst", "len", "ess").toArrow()
    vids = np.sort(net.vertices.select("vid").toArrow().column("vid").to_numpy())
    pois = net.pois.toArrow().column("poi").to_numpy()
    spark = net.vertices.sparkSession
    sent = spark.sparkContext.broadcast((vids, [arcs.column(c).to_numpy() for c in ("src", "dst", "len", "ess")], pois))  # at most MOST_ARCS arcs

    def run(batches):
        for batch in batches:
            for level in batch.column("lvl").to_pylist():
                rows = level_rows(level, *sent.value, reach)
                kinds = (pa.int32(), pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, k) for c, k in zip(rows, kinds, strict=True)], ["lvl", "vid", "comp", "border", "d_border", "d_poi"])

    levels = spark.createDataFrame([(c,) for c in cuts], "lvl int").repartition(len(cuts), "lvl")
    found = durable(levels.mapInArrow(run, "lvl int, vid bigint, comp bigint, border boolean, d_border bigint, d_poi bigint"))
    chain = found.select("vid", "lvl", "comp")
    return CompTree(chain, durable(node_stats(net, chain, cuts)), found.where("border").select("lvl", "comp", "vid", "d_border", "d_poi"), net.smax, reach, cuts)


def level_rows(level: int, vids: np.ndarray, arcs: list, pois: np.ndarray, reach: float | None) -> tuple:
    """Components of one level, its borders, and their distances to another border and to a POI, all by arrays.

    Two borders nearest to each other meet at an arc between the vertices that are nearest to either (a way to the nearest
    other border leaves the own vertices by one arc, and from there no border is farther than the one it leads to)."""
    src, dst, length, ess = arcs
    s, d = np.searchsorted(vids, src), np.searchsorted(vids, dst)
    least = np.full(len(vids), 1 << 30)
    np.minimum.at(least, s, ess)
    keep = np.flatnonzero(ess > level)
    keep = keep[np.argsort(s[keep], kind="stable")]
    s, d, n = s[keep], d[keep], length[keep]
    first = np.searchsorted(s, np.arange(len(vids) + 1))
    border, far = least <= level, np.iinfo(np.int64).max
    dist, near = nearest_of(first, d, n, np.flatnonzero(border), reach)
    meet = np.flatnonzero((near[s] != near[d]) & (near[s] >= 0) & (near[d] >= 0))
    way = dist[s[meet]] + n[meet] + dist[d[meet]]
    other = np.full(len(vids), far)
    np.minimum.at(other, near[s[meet]], way)
    home, _ = nearest_of(first, d, n, np.searchsorted(vids, pois), reach)
    told = lambda x: pa.array(x, pa.int64(), mask=(x == far) | (x >= (far if reach is None else reach)))
    return np.full(len(vids), level, np.int32), vids, vids[least_reachable(len(vids), s, d)], border, told(other), told(home)


def least_reachable(n: int, s: np.ndarray, d: np.ndarray) -> np.ndarray:
    """The least number that each of n vertices reaches over the links s - d: roots join the least root next to them."""
    comp = np.arange(n)
    while True:
        a, b = comp[s], comp[d]
        open_ = a != b
        if not open_.any():
            return comp
        s, d = s[open_], d[open_]
        np.minimum.at(comp, a[open_], b[open_])
        np.minimum.at(comp, b[open_], a[open_])
        while not np.array_equal(comp, up := comp[comp]):
            comp = up


def nearest_of(first: np.ndarray, dst: np.ndarray, length: np.ndarray, sources: np.ndarray, reach: float | None) -> tuple[np.ndarray, np.ndarray]:
    """Distance of every vertex to its nearest source below reach, and that source (-1: none). first: where the arcs of a vertex begin."""
    far = np.iinfo(np.int64).max
    dist, near = np.full(len(first) - 1, far), np.full(len(first) - 1, -1)
    dist[sources], near[sources], new = 0, sources, sources
    while len(new):
        size = first[new + 1] - first[new]
        at = np.repeat(first[new] - np.cumsum(size) + size, size) + np.arange(size.sum())
        start, w = np.repeat(new, size), dst[at]
        d = dist[start] + length[at]
        better = (d < dist[w]) if reach is None else (d < dist[w]) & (d < reach)
        start, w, d = start[better], w[better], d[better]
        np.minimum.at(dist, w, d)
        won = d == dist[w]
        near[w[won]] = near[start[won]]
        new = np.unique(w[won])
    return dist, near


def start_levels(tree: CompTree, queries: DataFrame) -> DataFrame:
    """qid, start: the deepest level whose component around the query holds k POIs (the lowest one if none does)."""
    at = queries.join(tree.pointers, queries.src == tree.pointers.vid).join(tree.nodes.select("lvl", "comp", "n_pois"), ["lvl", "comp"])
    return at.groupBy("qid").agg(F.coalesce(F.max(F.when(F.col("n_pois") >= F.col("k"), F.col("lvl"))), F.min("lvl")).alias("start"))


def entering_limits(tree: CompTree, arcs: DataFrame, level: int) -> DataFrame:
    """src, ess, limit: the largest, over the nodes at `level` or deeper that an arc lies in and whose border its start is, of
    the way that any continuation needs (to another border or a POI of the node). A step with dist + limit >= dc is vain."""
    far = 1e18
    need = F.least(F.coalesce("d_border", F.lit(far)), F.coalesce("d_poi", F.lit(far)))
    steps = arcs.where(F.col("ess") > level).select("src", "ess").distinct()
    at = tree.borders.where(F.col("lvl") >= level).select(F.col("vid").alias("src"), "lvl", need.alias("need"))
    return steps.join(at, "src").where("lvl < ess").groupBy("src", "ess").agg(F.max("need").alias("limit"))


def comptree_search(net: Network, tree: CompTree, queries: DataFrame, rules: Iterable[int] = (1, 2, 3), measure: Measure = LexSafety) -> DataFrame:
    """All queries climb together, level by level; a query takes part from its start level until it has k answers.

    Labels of a finished level stay; at the next one they go on by the roads that it adds. Rule 3 is tested on the step
    that enters a node, never on the label. (Rule 4 needs the order of a queue: see kernel.py.)"""
    if not measure.bottleneck:
        raise ValueError("this search needs a measure whose worst edge decides first")
    if tree.reach is not None and (queries.agg(F.max("dc")).first()[0] or 0) > tree.reach:
        raise ValueError("the index was built for smaller bounds")
    asked = durable(queries.join(start_levels(tree, queries), "qid"))
    arcs, settled, done = durable(net.arcs), None, None
    for place in range(len(tree.cuts) - 1, -1, -1):
        level = tree.cuts[place]
        deeper = tree.cuts[place + 1] if place + 1 < len(tree.cuts) else net.smax
        seeds = seed_labels(asked.where(F.col("start") == level), measure, net.smax)
        if settled is None and seeds.isEmpty():
            continue
        open_arcs = arcs.where(F.col("ess") > level)
        if 3 in set(rules):
            open_arcs = open_arcs.join(entering_limits(tree, arcs, level), ["src", "ess"], "left")
            open_arcs = durable(open_arcs.withColumn("limit", F.coalesce("limit", F.lit(0.0))))
        else:
            open_arcs = open_arcs.withColumn("limit", F.lit(0.0))
        if settled is None:
            frontier, before = seeds, seeds
            first = None
        else:  # waiting labels go on by the added roads, seeds by all roads
            old = settled.withColumn("from", F.lit(deeper))
            frontier, before = old.select(LABEL).unionByName(seeds), settled.unionByName(seeds)
            fresh_at = durable(seeds.select("qid", F.lit(True).alias("seed")))
            first = fresh_at
        labels = level_fixpoint(before, frontier, open_arcs, first, deeper, net, measure)
        found = answers(labels, net.pois).groupBy("qid").agg(F.max("rnk").alias("n"))
        full = labels.select("qid", "k").distinct().join(found, "qid").where("n >= k").select("qid")
        full = durable(full)
        finished = labels.join(full, "qid", "left_semi")
        done = finished if done is None else done.unionByName(finished)
        settled = durable(labels.join(full, "qid", "left_anti"))
    whole = settled if done is None else done if settled is None else done.unionByName(settled)
    return answers(whole, net.pois)


def level_fixpoint(before: DataFrame, frontier: DataFrame, arcs: DataFrame, seeds: DataFrame | None, deeper: int, net: Network, measure: Measure) -> DataFrame:
    """Rounds inside one level; arcs carry the limit of the step."""
    settled, frontier, turn = durable(before.select(*LABEL, F.lit(-1).alias("turn"))), durable(frontier.select(LABEL)), 0
    while not frontier.isEmpty():
        step = frontier.join(arcs, (F.col("vid") == F.col("src")) & (F.col("dist") + F.col("len") < F.col("dc")) & (F.col("dist") + F.col("limit") < F.col("dc")))
        if turn == 0 and seeds is not None:
            step = step.join(seeds, "qid", "left").where(F.col("seed") | (F.col("ess") <= deeper))
        fresh = step.select("qid", F.col("dst").alias("vid"), measure.extend("key", "ess", "len", net.smax).alias("key"), (F.col("dist") + F.col("len")).alias("dist"), F.concat("path", F.array("dst")).alias("path"), "k", "dc")
        settled = settle(settled, fresh, turn)
        frontier = settled.where(F.col("turn") == turn).select(LABEL)
        turn += 1
    return settled.select(LABEL)
