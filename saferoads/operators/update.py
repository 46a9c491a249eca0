"""Index maintenance: changes of edges, levels and POIs, applied to the network and to both indexes.

A change list has op ('add', 'remove', 'ess', 'add_poi', 'remove_poi'), u, w, len, ess, poi. Only what a change can
reach is built again: for the tree the level-0 components with a changed end and the levels whose edge set changed,
for the cells the level-0 components with a changed end. Everything else is kept as it is.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from saferoads.operators.comptree import CompTree, border_distances, node_stats, pointers
from saferoads.operators.safevor import SafeVor, build_safevor
from saferoads.plans.components import connected_components
from saferoads.plans.runtime import durable
from saferoads.sources.networks import Network

CHANGES = "op string, u bigint, w bigint, len bigint, ess int, poi bigint, ts timestamp"


def apply_changes(net: Network, changes: DataFrame) -> Network:
    """The network after the changes; of several for one edge or POI the latest counts."""
    latest = Window.partitionBy("kind", "a", "b").orderBy(F.desc("ts"), "op")
    kind = F.when(F.col("op").isin("add_poi", "remove_poi"), "poi").otherwise("edge")
    a = F.when(F.col("op").isin("add_poi", "remove_poi"), F.col("poi")).otherwise(F.least("u", "w"))
    last = durable(changes.withColumns({"kind": kind, "a": a, "b": F.coalesce(F.greatest("u", "w"), F.lit(-1))}).withColumn("r", F.row_number().over(latest)).where("r = 1"))
    of_edges = last.where("kind = 'edge'").select(F.col("a").alias("u"), F.col("b").alias("w"), F.col("op"), F.col("len").alias("new_len"), F.col("ess").alias("new_ess"))
    kept = net.edges.join(of_edges, ["u", "w"], "left").where("op is null or op = 'ess'").select("eid", "u", "w", "len", F.coalesce("new_ess", "ess").cast("int").alias("ess"))
    added = of_edges.where("op = 'add'").select(F.xxhash64("u", "w").alias("eid"), "u", "w", F.col("new_len").alias("len"), F.col("new_ess").cast("int").alias("ess"))
    of_pois = last.where("kind = 'poi'")
    pois = net.pois.join(of_pois.select(F.col("a").alias("poi")), "poi", "left_anti").unionAll(of_pois.where("op = 'add_poi'").select("a")).distinct()
    return replace(net, edges=durable(kept.unionByName(added)), pois=durable(pois))


def touched_vertices(changes: DataFrame) -> DataFrame:
    return changes.select(F.explode(F.array("u", "w", "poi")).alias("vid")).where("vid is not null").distinct()


def touched_levels(net: Network, changes: DataFrame, cuts: tuple[int, ...]) -> list[int]:
    """Levels whose edge set changes: below the level of an added or removed edge, between old and new level of a changed
    one, all for a POI."""
    ends = changes.select("op", F.least("u", "w").alias("u"), F.greatest("u", "w").alias("w"), F.col("ess").alias("new"))
    known = ends.join(net.edges.select("u", "w", F.col("ess").alias("old")), ["u", "w"], "left")
    low = F.when(F.col("op") == "ess", F.least("old", "new")).otherwise(0)
    high = F.when(F.col("op") == "ess", F.greatest("old", "new")).when(F.col("op") == "remove", F.col("old")).when(F.col("op") == "add", F.col("new")).otherwise(net.smax)
    spans = known.select(low.alias("lo"), high.alias("hi")).distinct().collect()  # pairs of levels: at most smax squared
    return [c for c in cuts if any(s["lo"] is not None and s["hi"] is not None and s["lo"] <= c < s["hi"] for s in spans)]


def touched_part(old: Network, new: Network, changes: DataFrame) -> DataFrame:
    """vid of every vertex in a component, before or after, that holds a changed end."""
    both = old.edges.select("u", "w").unionAll(new.edges.select("u", "w"))
    comps = durable(connected_components(both, "u", "w"))
    every = old.vertices.select("vid").join(comps, F.col("vid") == F.col("id"), "left").select("vid", F.coalesce("comp", "vid").alias("comp"))
    hit = every.join(touched_vertices(changes), "vid", "left_semi").select("comp").distinct()
    return durable(every.join(hit, "comp", "left_semi").select("vid"))


def inside(net: Network, part: DataFrame) -> Network:
    return replace(net, vertices=durable(net.vertices.join(part, "vid", "left_semi")), edges=durable(net.edges.join(part, net.edges.u == part.vid, "left_semi")), pois=durable(net.pois.join(part, net.pois.poi == part.vid, "left_semi")))


def comptree_update(net: Network, tree: CompTree, changes: DataFrame) -> tuple[Network, CompTree]:
    fresh = apply_changes(net, changes)
    levels = touched_levels(net, changes, tree.cuts)
    # A border is a matter of the roads at or below its level, so a level change reaches the levels above it, too.
    levels = [c for c in tree.cuts if levels and c >= min(levels)]
    if not levels:
        return fresh, tree
    part = touched_part(net, fresh, changes)
    local = inside(fresh, part)
    cuts = tuple(levels)
    chain = durable(pointers(local, cuts))
    stats = durable(node_stats(local, chain, cuts)) if len(cuts) == len(tree.cuts) else None
    mine = lambda df: df.join(part, "vid", "left_semi").where(F.col("lvl").isin(*cuts))
    keep = lambda df: df.join(mine(df).select("vid", "lvl"), ["vid", "lvl"], "left_anti").select(df.columns)
    all_chain = durable(keep(tree.pointers).unionByName(chain.select(tree.pointers.columns)))
    borders = durable(keep(tree.borders).unionByName(border_distances(local, chain, cuts, tree.reach).select(tree.borders.columns)))
    if stats is None:
        stats = node_stats(local, all_chain.join(part, "vid", "left_semi"), tree.cuts)
    old_nodes = tree.pointers.join(part, "vid", "left_semi").select("lvl", "comp").distinct()
    nodes = durable(tree.nodes.join(old_nodes, ["lvl", "comp"], "left_anti").select(tree.nodes.columns).unionByName(stats.select(tree.nodes.columns)))
    return fresh, replace(tree, pointers=all_chain, nodes=nodes, borders=borders)


def safevor_update(net: Network, vor: SafeVor, changes: DataFrame, reach: float | None = None) -> tuple[Network, SafeVor]:
    fresh = apply_changes(net, changes)
    part = touched_part(net, fresh, changes)
    new = build_safevor(inside(fresh, part), vor.listed, reach)
    swap = lambda old, now, key: durable(old.join(part.withColumnRenamed("vid", key), key, "left_anti").select(old.columns).unionByName(now.select(old.columns)))
    return fresh, SafeVor(swap(vor.lists, new.lists, "vid"), swap(vor.cells, new.cells, "vid"), swap(vor.borders, new.borders, "u"), swap(vor.adjacency, new.adjacency, "cell"), swap(vor.border_distances, new.border_distances, "b"), vor.listed)


def save_index(index: CompTree | SafeVor, path: str) -> None:
    """One Parquet table for each part; those with levels are partitioned by level."""
    for name, table in vars(index).items():
        if isinstance(table, DataFrame):
            writer = table.write.mode("overwrite")
            (writer.partitionBy("lvl") if "lvl" in table.columns else writer).parquet(f"{path}/{name}")


def load_index(spark, path: str, like: CompTree | SafeVor) -> CompTree | SafeVor:
    tables = {name: spark.read.schema(t.schema).parquet(f"{path}/{name}") for name, t in vars(like).items() if isinstance(t, DataFrame)}
    return replace(like, **tables)
