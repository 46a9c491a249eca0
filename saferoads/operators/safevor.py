"""Network Voronoi cells whose metric is safety: build and search.

Every vertex belongs to the POI with the safest path, bound or no bound. A search lists a query's POIs in the order of
unconstrained safety until k of them have such a path within the bound; only the others listed before are searched
again under the bound.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterable
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from saferoads.functions.safety import LexSafety, add_edge, concat_paths, path_length, zeros
from saferoads.operators.expand import LABEL, nearest_lists, seed_labels, settle
from saferoads.operators.kernel import Cells, cell_tables  # noqa: F401
from saferoads.plans.runtime import drop, durable
from saferoads.sources.networks import Network

#: Numbers of vertices of a block; a block has to fit a task.
BLOCK = 8192


@dataclass(frozen=True)
class SafeVor:
    """lists (vid, rnk, poi, sd, dist): the safest POIs of every vertex, unconstrained; cells (vid, cell, sd, dist, tie);
    borders (u, w, cell_u, cell_w, ess, len, pos2); adjacency (cell, other); border_distances (cell, b, d_border, d_poi)."""

    lists: DataFrame
    cells: DataFrame
    borders: DataFrame
    adjacency: DataFrame
    border_distances: DataFrame
    listed: int


def lists_in_block(arcs: pa.Table, seeds: pa.Table, k: int, smax: int, bits: int, block: int, size: int) -> tuple[dict, dict]:
    """The k safest POIs of the vertices of one block, as {vid: {poi: key}} in their order, from the seeds (vid, poi, key); and
    what its arcs lead out of it, as {(vid, poi): key}. Keys are single integers, the worst level highest."""
    steps: dict = {}
    for v, w, length, e in zip(*(arcs.column(c).to_pylist() for c in ("src", "dst", "len", "ess")), strict=True):
        steps.setdefault(v, []).append((w, length << bits * (smax - e), w // size == block))
    heap, lists, leaving = [], {}, {}
    for v, p, vector in zip(*(seeds.column(c).to_pylist() for c in ("vid", "poi", "key")), strict=True):
        key = 0
        for x in vector:
            key = key << bits | x
        heap.append((key, p, v))
    heapq.heapify(heap)
    while heap:
        key, p, v = heapq.heappop(heap)
        known = lists.setdefault(v, {})
        if len(known) >= k or p in known:
            continue
        known[p] = key
        for w, more, inside in steps.get(v, ()):
            if not inside:
                leaving[w, p] = min(leaving.get((w, p), key + more), key + more)
            elif len(there := lists.get(w, ())) < k and p not in there:
                heapq.heappush(heap, (key + more, p, w))
    return lists, leaving


def safest_lists(net: Network, k: int, size: int = BLOCK) -> DataFrame:
    """vid, rnk, poi, sd, dist: the k safest POIs of each vertex without a bound, spread from all POIs together.

    A vertex on the safest path to a POI has that POI among its own k, so each vertex passes on k entries only. Blocks of
    vertices are searched whole; a round hands what leaves a block to the others, and only blocks that get something
    better are searched again."""
    smax = net.smax
    bits = max(24, int(net.edges.agg(F.sum("len")).first()[0] or 0).bit_length() + 1)
    block = lambda c: F.floor(F.col(c) / size).cast("bigint")
    arcs = durable(net.arcs.select(block("src").alias("block"), "src", "dst", "len", "ess"))
    pois = net.pois.select(block("poi").alias("block"), F.col("poi").alias("vid"), "poi", LexSafety.start(smax).alias("key"))
    vector = lambda key: [key >> bits * (smax - s) & (1 << bits) - 1 for s in range(1, smax + 1)]

    def searched(seeds: DataFrame, blocks: DataFrame | None, whole: bool) -> DataFrame:
        def run(group, a, b):
            at = group[0].as_py()
            lists, leaving = lists_in_block(a, b, k, smax, bits, at, size)
            rows = [(v, p, key, r) for v, known in lists.items() for r, (p, key) in enumerate(known.items(), 1)] if whole else [(v, p, key, 0) for (v, p), key in leaving.items()]
            columns = [pa.array([at] * len(rows), pa.int64()), *(pa.array([x[i] for x in rows], pa.int64()) for i in (0, 1)), pa.array([vector(x[2]) for x in rows], pa.list_(pa.int64())), pa.array([x[3] for x in rows], pa.int32())]
            return pa.Table.from_arrays(columns, ["block", "vid", "poi", "key", "rnk"])

        sides = [x if blocks is None else x.join(blocks, "block", "left_semi") for x in (arcs, seeds)]
        return sides[0].groupBy("block").cogroup(sides[1].groupBy("block")).applyInArrow(run, "block bigint, vid bigint, poi bigint, key array<bigint>, rnk int")

    offers, entering, todo, seeds = None, None, None, pois
    while True:
        found = searched(seeds, todo, False).drop("rnk")
        before, offers = offers, durable(found if offers is None else offers.join(todo, "block", "left_anti").unionByName(found))
        order = Window.partitionBy("vid").orderBy("key", "poi")
        best = offers.groupBy("vid", "poi").agg(F.min("key").alias("key")).withColumn("r", F.row_number().over(order)).where(F.col("r") <= k)
        last, entering = entering, durable(best.select(block("vid").alias("block"), "vid", "poi", "key"))
        better = entering if last is None else entering.join(last, ["vid", "poi", "key"], "left_anti")
        done, todo, seeds = todo, durable(better.select("block").distinct()), pois.unionByName(entering)
        drop(*(x for x in (before, last, done) if x is not None))
        if todo.isEmpty():
            break
    return searched(seeds, None, True).select("vid", "rnk", "poi", F.col("key").alias("sd"), path_length("key").alias("dist"))


def cell_borders(net: Network, cells: DataFrame) -> DataFrame:
    """Edges between cells; pos2: place, in half units from u, where both cells' POIs are equally safe."""
    a = cells.select(F.col("vid").alias("u"), F.col("cell").alias("cell_u"), F.col("sd").alias("sd_u"))
    b = cells.select(F.col("vid").alias("w"), F.col("cell").alias("cell_w"), F.col("sd").alias("sd_w"))
    across = net.edges.join(a, "u").join(b, "w").where("cell_u <> cell_w")
    at = F.col("ess") - 1
    return across.select("u", "w", "cell_u", "cell_w", "ess", "len", (F.col("sd_w")[at] - F.col("sd_u")[at] + F.col("len")).alias("pos2"))


def adjacency_of(borders: DataFrame) -> DataFrame:
    both = F.array(F.struct(F.col("cell_u").alias("cell"), F.col("cell_w").alias("other")), F.struct(F.col("cell_w").alias("cell"), F.col("cell_u").alias("other")))
    return borders.select(F.explode(both).alias("x")).select("x.cell", "x.other").distinct()


def split_network(net: Network, borders: DataFrame) -> Network:
    """The network with a vertex at every border place, all weights doubled so that they stay integers."""
    inner = borders.where("pos2 > 0 and pos2 < 2 * len")
    top = net.vertices.agg(F.max("vid")).first()[0] + 1
    numbered = inner.join(net.edges.select("u", "w", "eid"), ["u", "w"]).withColumn("mid", F.col("eid") + top)
    halves = F.array(F.struct(F.col("u").alias("u"), F.col("mid").alias("w"), F.col("pos2").alias("len")), F.struct(F.col("w").alias("u"), F.col("mid").alias("w"), (2 * F.col("len") - F.col("pos2")).alias("len")))
    parts = numbered.select(F.explode(halves).alias("h"), "ess", "eid").select("h.u", "h.w", "h.len", "ess", (F.col("eid") * 2).alias("eid"))
    rest = net.edges.join(inner.select("u", "w"), ["u", "w"], "left_anti").select("u", "w", (F.col("len") * 2).alias("len"), "ess", (F.col("eid") * 2 + 1).alias("eid"))
    vertices = net.vertices.select("vid").unionAll(numbered.select("mid")).withColumns({"x": F.lit(None).cast("bigint"), "y": F.lit(None).cast("bigint")})
    return Network(vertices, parts.unionByName(rest).select("eid", "u", "w", "len", "ess"), net.pois, net.smax)


def in_cell_distances(net: Network, cells: DataFrame, borders: DataFrame, reach: float | None) -> DataFrame:
    """cell, b, d_border, d_poi: for each end of a border edge, the way inside its cell to another such end and to the POI."""
    c = cells.select("vid", "cell")
    inside = durable(net.arcs.join(c.withColumnsRenamed({"vid": "src", "cell": "c1"}), "src").join(c.withColumnsRenamed({"vid": "dst", "cell": "c2"}), "dst").where("c1 = c2").select("src", "dst", "len"))
    ends = durable(borders.select(F.explode(F.array(F.struct(F.col("u").alias("b"), F.col("cell_u").alias("cell")), F.struct(F.col("w").alias("b"), F.col("cell_w").alias("cell")))).alias("x")).select("x.*").distinct())
    two = nearest_lists(inside, ends.select(F.col("b").alias("source")), 2, reach)
    other = two.where("vid <> source").groupBy("vid").agg(F.min("dist").alias("d_border")).withColumnRenamed("vid", "b")
    home = nearest_lists(inside, net.pois.select(F.col("poi").alias("source")), 1, reach).select(F.col("vid").alias("b"), F.col("dist").alias("d_poi"))
    return ends.join(other, "b", "left").join(home, "b", "left").select("cell", "b", "d_border", "d_poi")


def build_safevor(net: Network, listed: int = 2, reach: float | None = None) -> SafeVor:
    """listed: POIs kept for each vertex; queries whose k valid POIs need a longer list list the POIs within their bound."""
    lists = durable(safest_lists(net, max(listed, 2)))
    first, second = lists.where("rnk = 1"), lists.where("rnk = 2").select("vid", F.col("sd").alias("sd2"))
    cells = durable(first.join(second, "vid", "left").select("vid", F.col("poi").alias("cell"), "sd", "dist", F.coalesce(F.col("sd") == F.col("sd2"), F.lit(False)).alias("tie")))
    borders = durable(cell_borders(net, cells))
    return SafeVor(lists, cells, borders, durable(adjacency_of(borders)), durable(in_cell_distances(net, cells, borders, reach)), max(listed, 2))


def next_cells(adjacency: DataFrame, found: DataFrame) -> DataFrame:
    """found (qid, cell): the cells next to them that are not among them; the next safest POI is one of these."""
    return found.join(adjacency, "cell").select("qid", F.col("other").alias("cell")).distinct().join(found, ["qid", "cell"], "left_anti")


def relaxed(state: DataFrame, frontier: DataFrame, steps: DataFrame, allowed: DataFrame | None) -> DataFrame:
    """state (qid, vid, key) after steps (src, dst, sd, cell) from the frontier on, as long as any makes a vertex safer. Only
    steps into the allowed cells (qid, cell) count; without a bound one key for each vertex is enough."""
    while not frontier.isEmpty():
        moved = frontier.join(steps, frontier.vid == steps.src)
        if allowed is not None:
            moved = moved.join(allowed, ["qid", "cell"])
        tried = moved.select("qid", F.col("dst").alias("vid"), concat_paths("key", "sd").alias("key")).groupBy("qid", "vid").agg(F.min("key").alias("key"))
        known = state.select("qid", "vid", F.col("key").alias("had"))
        frontier = durable(tried.join(known, ["qid", "vid"], "left").where("had is null or key < had").drop("had"))
        before, state = state, durable(state.join(frontier, ["qid", "vid"], "left_anti").unionByName(frontier))
        drop(before)
    return state


def safest_by_growth(net: Network, tables: Cells, adjacency: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, rnk, poi, key, dist: every query's POIs in order of safety without a bound, until k of them have such a path
    within the bound or none is left.

    The first is the POI of the query's cell. The next one after any of them lies in a cell next to those found, and its
    path stays in these cells; so each turn adds the neighbours of the cell found last, lets the stored ways inside the
    cells and the roads between cells carry the keys into them, and takes the safest POI that is reached."""
    cells = tables.cells
    c1, c2 = cells.withColumnsRenamed({"vid": "src", "cell": "c1"}), cells.withColumnsRenamed({"vid": "dst", "cell": "cell"})
    roads = net.arcs.join(c1, "src").join(c2, "dst").select("src", "dst", add_edge(zeros(net.smax), "ess", "len").alias("sd"), "c1", "cell")
    roads = durable(roads)
    steps = durable(roads.where("c1 <> cell").drop("c1").unionByName(tables.ways.where("direct").select(F.col("b1").alias("src"), F.col("b2").alias("dst"), "sd", "cell")))
    home = durable(queries.join(cells, queries.src == cells.vid).select("qid", "src", "k", "dc", "cell"))
    # Inside its own cell a query may start at any vertex; from the ends on the stored ways do.
    seeds = durable(home.select("qid", F.col("src").alias("vid"), zeros(net.smax).alias("key")))
    state = relaxed(durable(seeds), seeds, roads.where("c1 = cell").drop("c1"), home.select("qid", "cell"))
    allowed = durable(home.select("qid", "cell"))
    found, open_, rank = None, home.select("qid", "k", "dc"), 1
    while True:
        at = state.join(net.pois, state.vid == net.pois.poi).select("qid", "poi", "key").join(open_, "qid")
        at = at if found is None else at.join(found.select("qid", "poi"), ["qid", "poi"], "left_anti")
        best = at.groupBy("qid").agg(F.min(F.struct("key", "poi")).alias("b")).select("qid", "b.poi", "b.key")
        fresh = durable(best.select("qid", F.lit(rank).alias("rnk"), "poi", "key", path_length("key").alias("dist")))
        if fresh.isEmpty():
            return fresh if found is None else found
        found = fresh if found is None else durable(fresh, onto=found)
        good = found.join(home.select("qid", "dc"), "qid").groupBy("qid").agg(F.count(F.when(F.col("dist") < F.col("dc"), 1)).alias("good"))
        open_ = durable(home.select("qid", "k", "dc").join(fresh.select("qid"), "qid", "left_semi").join(good, "qid").where("good < k").drop("good"))
        if open_.isEmpty():
            return found
        reached = found.select("qid", F.col("poi").alias("cell")).join(open_.select("qid"), "qid", "left_semi")
        news = durable(next_cells(adjacency, reached).join(allowed, ["qid", "cell"], "left_anti"))
        allowed = durable(news, onto=allowed)
        edge = steps.join(news, "cell").select("qid", F.col("src").alias("vid")).distinct()
        state = relaxed(state, durable(state.join(edge, ["qid", "vid"], "left_semi")), steps, allowed)
        rank += 1


def within_bounds(arcs: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, vid: the vertices on paths shorter than the bound, and the start."""
    frontier = durable(queries.select("qid", F.col("src").cast("bigint").alias("vid"), F.lit(0).cast("bigint").alias("dist"), "dc"))
    known = durable(frontier)
    while not frontier.isEmpty():
        moved = frontier.join(arcs, (F.col("vid") == F.col("src")) & (F.col("dist") + F.col("len") < F.col("dc"))).select("qid", F.col("dst").alias("vid"), (F.col("dist") + F.col("len")).alias("dist"), "dc")
        best = moved.groupBy("qid", "vid", "dc").agg(F.min("dist").alias("dist")).join(known.groupBy("qid", "vid").agg(F.min("dist").alias("had")), ["qid", "vid"], "left")
        before, frontier = frontier, durable(best.where("had is null or dist < had").select("qid", "vid", "dist", "dc"))
        drop(before)
        known = durable(frontier, onto=known)
    return durable(known.select("qid", "vid").distinct())


def listed_within(net: Network, arcs: DataFrame, near: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, src, k, dc, rnk, poi, key, dist: all POIs near the query in the order of safety of paths of any length over near
    vertices (qid, vid). A valid path meets only these, so the safest of them is the answer's where it is valid."""
    steps = durable(arcs.select("src", "dst", add_edge(zeros(net.smax), "ess", "len").alias("sd"), F.col("dst").alias("cell")))
    seeds = durable(queries.select("qid", F.col("src").cast("bigint").alias("vid"), zeros(net.smax).alias("key")))
    state = relaxed(durable(seeds), seeds, steps, near.withColumnRenamed("vid", "cell"))
    at = state.join(net.pois, F.col("vid") == F.col("poi")).select("qid", "poi", "key", path_length("key").alias("dist"))
    order = Window.partitionBy("qid").orderBy("key", "poi")
    return at.join(queries, "qid").select("qid", "src", "k", "dc", F.row_number().over(order).alias("rnk"), "poi", "key", "dist")


def safevor_search(net: Network, vor: SafeVor, queries: DataFrame, rules: Iterable[int] = (1, 2, 5, 6, 7)) -> DataFrame:
    """Candidates by the lists, then the bounded search for those whose unconstrained path is too long. Queries whose stored
    list ends before k valid ones get a list of all POIs within their bound."""
    rules = set(rules)
    before = Window.partitionBy("qid").orderBy("rnk").rowsBetween(Window.unboundedPreceding, -1)
    ok = (F.col("dist") < F.col("dc")).cast("int")
    cut_of = lambda listed: listed.withColumns({"ok": ok, "had": F.coalesce(F.sum(ok).over(before), F.lit(0))}).where("had < k")
    stored = durable(cut_of(queries.join(vor.lists, queries.src == vor.lists.vid).select("qid", "src", "k", "dc", "rnk", "poi", F.col("sd").alias("key"), "dist")))
    done = stored.groupBy("qid", "k").agg(F.sum("ok").alias("n")).where("n >= k").select("qid")
    near = within_bounds(net.arcs, queries)
    spots = durable(near.select("vid").distinct())
    arcs = net.arcs.join(spots.withColumnRenamed("vid", "src"), "src", "left_semi").join(spots.withColumnRenamed("vid", "dst"), "dst", "left_semi")
    arcs = durable(arcs.select("src", "dst", "len", "ess"))
    rest = durable(queries.select("qid", "src", "k", "dc").join(done, "qid", "left_anti"))
    good = durable(stored.join(done, "qid", "left_semi").unionByName(cut_of(listed_within(net, arcs, near, rest))))
    sure = good.where("ok = 1").select("qid", "poi", "key", "dist", F.lit(None).cast("array<bigint>").alias("path"), "k")
    worst = good.where("ok = 1").groupBy("qid").agg(F.max("key").alias("worst"), F.count("*").alias("n"))
    open_ = durable(good.where("ok = 0").select("qid", "poi", "src", "k", "dc"))
    labels = bounded(net, vor, arcs, open_, worst, rules)
    hits = labels.join(open_.select("qid", F.col("poi").alias("vid")), ["qid", "vid"]).groupBy("qid", "vid", "k").agg(F.min(F.struct("key", "dist", "path")).alias("b"))
    more = hits.select("qid", F.col("vid").alias("poi"), "b.key", "b.dist", "b.path", "k")
    order = Window.partitionBy("qid").orderBy("key", "dist", "poi")
    return sure.unionByName(more).withColumn("rnk", F.row_number().over(order)).where("rnk <= k").select("qid", "rnk", "poi", "dist", "key", "path")


def bounded(net: Network, vor: SafeVor, arcs: DataFrame, targets: DataFrame, worst: DataFrame, rules: set[int]) -> DataFrame:
    """Labels of the search under the bound for the targets (qid, poi, src, k, dc) of each query, over arcs (src, dst, len, ess)
    that hold all within the bounds.

    Rules 5 and 6 are tested on the step inside a cell from one of its border ends: it is vain if the way to another end
    breaks the bound and the cell's POI is no target, or is too far as well. Rule 7 drops labels beyond the k-th valid one."""
    far = 1e18
    c = vor.cells.select("vid", "cell")
    arcs = arcs.join(c.withColumnsRenamed({"vid": "src", "cell": "cell"}), "src", "left").join(c.withColumnsRenamed({"vid": "dst", "cell": "c2"}), "dst", "left")
    ends = vor.border_distances.select(F.col("b").alias("src"), F.coalesce("d_border", F.lit(far)).alias("db"), F.coalesce("d_poi", F.lit(far)).alias("dp"))
    arcs = arcs.join(ends, "src", "left").withColumn("inner", F.col("cell") == F.col("c2"))
    limit5 = F.when(F.col("inner"), F.coalesce("db", F.lit(0.0))).otherwise(0.0) if 5 in rules else F.lit(0.0)
    limit6 = F.when(F.col("inner"), F.least(F.coalesce("db", F.lit(0.0)), F.coalesce("dp", F.lit(0.0)))).otherwise(0.0) if 6 in rules else F.lit(0.0)
    arcs = durable(arcs.select("src", "dst", "len", "ess", "cell", limit5.alias("limit5"), limit6.alias("limit6")))
    queries = targets.select("qid", "src", "k", "dc").distinct()
    wanted = durable(targets.select("qid", F.col("poi").alias("cell"), F.lit(True).alias("target")))
    limit7 = durable(worst.join(queries.select("qid", "k"), "qid").where("n >= k").select("qid", "worst")) if 7 in rules else None
    frontier, turn = durable(seed_labels(queries, LexSafety, net.smax)), 0
    settled = durable(frontier.select(*LABEL, F.lit(-1).alias("turn")))
    while not frontier.isEmpty():
        step = frontier.join(arcs, (F.col("vid") == F.col("src")) & (F.col("dist") + F.col("len") < F.col("dc")))
        step = step.join(wanted, ["qid", "cell"], "left")
        step = step.where(F.when(F.col("target"), F.col("dist") + F.col("limit6") < F.col("dc")).otherwise(F.col("dist") + F.col("limit5") < F.col("dc")))
        fresh = step.select("qid", F.col("dst").alias("vid"), LexSafety.extend("key", "ess", "len", net.smax).alias("key"), (F.col("dist") + F.col("len")).alias("dist"), F.concat("path", F.array("dst")).alias("path"), "k", "dc")
        if limit7 is not None:
            fresh = fresh.join(limit7, "qid", "left").where(F.col("worst").isNull() | (F.col("key") <= F.col("worst"))).drop("worst")
        settled = settle(settled, fresh, turn)
        frontier = settled.where(F.col("turn") == turn).select(LABEL)
        turn += 1
    return settled.select(LABEL)
