"""Safest-path search by rounds of joins, for whole batches of queries.

A label is (qid, vid, key, dist, path, k, dc): a path from the query to vid. A round joins the new labels with the arcs,
drops what reaches the bound, and keeps the labels that no other of the same query and vertex beats in safety and
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from saferoads.functions.safety import LexSafety, Measure, pareto
from saferoads.plans.runtime import durable
from saferoads.sources.networks import Network

LABEL = ["qid", "vid", "key", "dist", "path", "k", "dc"]


def seed_labels(queries: DataFrame, measure: Measure, smax: int) -> DataFrame:
    return queries.select("qid", F.col("src").cast("bigint").alias("vid"), measure.start(smax).alias("key"), F.lit(0).cast("bigint").alias("dist"), F.array(F.col("src").cast("bigint")).alias("path"), "k", "dc")


def extend(frontier: DataFrame, arcs: DataFrame, measure: Measure, smax: int) -> DataFrame:
    """All extensions by one arc that stay below the bound (Rule 1 stands in the join's condition)."""
    step = frontier.join(arcs, (F.col("vid") == F.col("src")) & (F.col("dist") + F.col("len") < F.col("dc")))
    return step.select("qid", F.col("dst").alias("vid"), measure.extend("key", "ess", "len", smax).alias("key"), (F.col("dist") + F.col("len")).alias("dist"), F.concat("path", F.array("dst")).alias("path"), "k", "dc")


def settle(settled: DataFrame, fresh: DataFrame, turn: int) -> DataFrame:
    """settled with the labels of a round that none of the same query and vertex equals or beats; column turn tells the round.

    Known labels are read without their paths and never written again: a round writes what it adds. Labels that a later
    round beats stay and do no harm, since answers take the best."""
    known = settled.select(*(F.col(c).alias(f"_{c}") for c in ("qid", "vid", "key", "dist")))
    beaten = (F.col("qid") == F.col("_qid")) & (F.col("vid") == F.col("_vid")) & (F.col("_dist") <= F.col("dist")) & (F.col("_key") <= F.col("key"))
    return durable(pareto(fresh).join(known, beaten, "left_anti").select(*LABEL, F.lit(turn).alias("turn")), onto=settled)


def best_pois(labels: DataFrame, pois: DataFrame) -> DataFrame:
    """The safest label of each query and POI."""
    at = labels.join(pois, labels.vid == pois.poi)
    first = F.min(F.struct("key", "dist", "path"))
    return at.groupBy("qid", "poi").agg(first.alias("b"), F.first("k").alias("k")).select("qid", "poi", "b.key", "b.dist", "b.path", "k")


def answers(labels: DataFrame, pois: DataFrame) -> DataFrame:
    """qid, rnk, poi, dist, key, path: the k safest POIs, ties to the lesser POI; all of them if fewer are valid."""
    order = Window.partitionBy("qid").orderBy("key", "dist", "poi")
    ranked = best_pois(labels, pois).withColumn("rnk", F.row_number().over(order))
    return ranked.where(F.col("rnk") <= F.col("k")).select("qid", "rnk", "poi", "dist", "key", "path")


def kth_keys(labels: DataFrame, pois: DataFrame) -> DataFrame:
    """qid, worst: key of the k-th answer so far, of the queries that have k."""
    found = answers(labels, pois)
    counted = found.groupBy("qid").agg(F.max("key").alias("worst"), F.max("rnk").alias("n"))
    return counted.join(labels.select("qid", "k").distinct(), "qid").where(F.col("n") >= F.col("k")).select("qid", "worst")


def fixpoint(settled: DataFrame | None, frontier: DataFrame, arcs: DataFrame, net: Network, rules: Iterable[int], measure: Measure, pois: DataFrame, step_filter=None, first_arcs: DataFrame | None = None, most_labels: int = 20_000_000) -> DataFrame:
    """Labels at the end of all rounds. first_arcs: the arcs of the first round, where they differ."""
    rules, turn = set(rules), 0
    settled = frontier if settled is None else settled
    settled, frontier = durable(settled.select(*LABEL, F.lit(-1).alias("turn"))), durable(frontier.select(LABEL))
    while not frontier.isEmpty():
        used = first_arcs if first_arcs is not None and turn == 0 else arcs
        fresh = extend(frontier if step_filter is None else step_filter(frontier), used, measure, net.smax)
        if 2 in rules:
            if 7 in rules and turn % 3 == 2:
                bound = kth_keys(settled, pois)
                fresh = fresh.join(bound, "qid", "left").where(F.col("worst").isNull() | (F.col("key") <= F.col("worst"))).drop("worst")
            settled = settle(settled, fresh, turn)
        else:  # every simple valid path; the number of labels explodes with the bound
            settled = durable(fresh.where("size(path) = size(array_distinct(path))").select(*LABEL, F.lit(turn).alias("turn")), onto=settled)
            if settled.count() > most_labels:
                raise ValueError("too many paths without Rule 2; lower the bound")
        frontier = settled.where(F.col("turn") == turn).select(LABEL)
        turn += 1
    return settled.select(LABEL)


def expand(net: Network, queries: DataFrame, rules: Iterable[int] = (1, 2, 7), measure: Measure = LexSafety, pois: DataFrame | None = None) -> DataFrame:
    """Best-first network expansion, as a fixpoint."""
    pois = net.pois if pois is None else pois
    labels = fixpoint(None, seed_labels(queries, measure, net.smax), net.arcs, net, rules, measure, pois)
    return answers(labels, pois)


def safest_path(net: Network, pairs: DataFrame) -> DataFrame:
    """pairs (qid, src, dst, dc): the safest valid path of each pair."""
    queries = pairs.select("qid", "src", F.lit(1).alias("k"), "dc")
    labels = fixpoint(None, seed_labels(queries, LexSafety, net.smax), net.arcs, net, (1, 2), LexSafety, net.pois)
    return best_pois(labels.join(pairs.select("qid", F.col("dst").alias("vid")), ["qid", "vid"], "left_semi"), pairs.select(F.col("dst").alias("poi")).distinct()).drop("k")


def safest_frontier(net: Network, queries: DataFrame) -> DataFrame:
    """All paths to POIs that no other beats in both safety and length."""
    labels = fixpoint(None, seed_labels(queries, LexSafety, net.smax), net.arcs, net, (1, 2), LexSafety, net.pois)
    return pareto(labels.join(net.pois, labels.vid == net.pois.poi)).select("qid", "poi", "dist", "key", "path")


def brute_force(net: Network, queries: DataFrame) -> DataFrame:
    """All simple valid paths; tiny bounds only."""
    return expand(net, queries, rules=(1,))


def euclid_candidates(net: Network, queries: DataFrame) -> DataFrame:
    """(qid, poi) with a straight-line distance below the bound, by a join on grid cells as wide as the largest bound."""
    width = queries.agg(F.max("dc")).first()[0]
    at = net.vertices.select("vid", "x", "y")
    q = queries.join(at, queries.src == at.vid).select("qid", "dc", F.col("x").alias("qx"), F.col("y").alias("qy"))
    around = F.array(F.lit(-1), F.lit(0), F.lit(1))
    q = q.withColumns({"gx": F.floor(F.col("qx") / width), "gy": F.floor(F.col("qy") / width)}).withColumn("gx", F.explode(F.transform(around, lambda d: F.col("gx") + d))).withColumn("gy", F.explode(F.transform(around, lambda d: F.col("gy") + d)))
    p = net.pois.join(at, net.pois.poi == at.vid).select("poi", "x", "y", F.floor(F.col("x") / width).alias("gx"), F.floor(F.col("y") / width).alias("gy"))
    gap2 = (F.col("x") - F.col("qx")) * (F.col("x") - F.col("qx")) + (F.col("y") - F.col("qy")) * (F.col("y") - F.col("qy"))
    return q.join(p, ["gx", "gy"]).where(gap2 < F.col("dc") * F.col("dc")).select("qid", "poi")


def euclid_baseline(net: Network, queries: DataFrame, rules: Iterable[int] = (1, 2)) -> DataFrame:
    """One search for each query and straight-line candidate, without sharing labels; then the k best."""
    picked = euclid_candidates(net, queries).join(queries, "qid")
    numbered = durable(picked.withColumn("pair", F.struct("qid", "poi")))
    asked = numbered.select(F.col("pair").alias("qid"), "src", F.lit(1).alias("k"), "dc")
    labels = fixpoint(None, seed_labels(asked, LexSafety, net.smax), net.arcs, net, rules, LexSafety, net.pois)
    hits = labels.where("vid = qid.poi").groupBy("qid").agg(F.min(F.struct("key", "dist", "path")).alias("b"))
    best = hits.select(F.col("qid.qid").alias("qid"), F.col("qid.poi").alias("poi"), "b.key", "b.dist", "b.path").join(queries.select("qid", "k"), "qid")
    order = Window.partitionBy("qid").orderBy("key", "dist", "poi")
    return best.withColumn("rnk", F.row_number().over(order)).where("rnk <= k").select("qid", "rnk", "poi", "dist", "key", "path")


def nearest_lists(arcs: DataFrame, sources: DataFrame, k: int, reach: float | None = None) -> DataFrame:
    """vid, source, dist: the k nearest sources of every vertex (ties to the lesser source), below `reach` if given.

    All sources spread together; a vertex passes on only its own k, so one run serves every query."""
    state = durable(sources.select(F.col("source").alias("vid"), "source", F.lit(0).cast("bigint").alias("dist"), F.lit(1).alias("new")))
    order = Window.partitionBy("vid").orderBy("dist", "source")
    while not state.where("new = 1").isEmpty():
        moved = state.where("new = 1").join(arcs, F.col("vid") == F.col("src")).select(F.col("dst").alias("vid"), "source", (F.col("dist") + F.col("len")).alias("dist"), F.lit(1).alias("new"))
        if reach is not None:
            moved = moved.where(F.col("dist") < reach)
        best = state.withColumn("new", F.lit(0)).unionByName(moved).groupBy("vid", "source").agg(F.min(F.struct("dist", "new")).alias("b"))
        state = durable(best.select("vid", "source", "b.dist", "b.new").withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).drop("r"))
    return state.select("vid", "source", "dist")


def knn(net: Network, queries: DataFrame, k: int, reach: float | None = None) -> DataFrame:
    """qid, rnk, poi, dist: the k nearest POIs by network distance."""
    lists = nearest_lists(net.arcs, net.pois.select(F.col("poi").alias("source")), k, reach)
    order = Window.partitionBy("qid").orderBy("dist", "poi")
    return queries.join(lists, queries.src == lists.vid).select("qid", F.col("source").alias("poi"), "dist").withColumn("rnk", F.row_number().over(order)).select("qid", "rnk", "poi", "dist")


def set_dc(queries: DataFrame, nearest: DataFrame, delta: float) -> DataFrame:
    """Queries with dc = delta * distance of the k-th nearest POI; few: fewer than k are reachable."""
    far = nearest.join(queries.select("qid", "k"), "qid").where("rnk <= k").groupBy("qid").agg(F.max("dist").alias("far"), F.count("*").alias("n"))
    return queries.drop("dc").join(far, "qid").select("qid", "src", "k", (F.col("far") * delta).cast("double").alias("dc"), (F.col("n") < F.col("k")).alias("few"))
