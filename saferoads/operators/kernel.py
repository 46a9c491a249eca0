"""Exact best-first searches for one query at a time, inside the workers, with the counters of the experiments.

For networks whose arcs have a checked size (`MOST_ARCS`): the arcs go to the workers as arrays and the queries are
dealt out. Beyond that size the rounds of joins in expand.py, comptree.py and safevor.py do the same work.
Keys are single integers: as many bits for each level as the length of any path needs, the worst level highest, so that
their order is the safety order.

A pass by length alone tells the POIs within a query's bound first: no search goes on for more of them than there are.
Of an index, workers hold what their queries can meet: a query carries the rows of the tree within its bound, and the
tables of a cell travel packed and are opened when a search first enters the cell.
"""

from __future__ import annotations

import bisect
import heapq
import uuid
import zlib
from collections.abc import Iterable
from dataclasses import dataclass
from math import inf

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from saferoads.operators.comptree import CompTree
from saferoads.plans.runtime import durable, small_enough
from saferoads.sources.networks import Network

MOST_ARCS, MOST_PATHS = 5_000_000, 3_000_000
#: Vertices that SAFEVOR lists POIs over, as a multiple of those within the bound; cells open at once in a task.
LISTING, MOST_OPEN = 4, 20_000
#: Vertices whose arcs a worker holds as tuples.
MOST_ROWS = 200_000
OUT = "qid bigint, rnk int, poi bigint, dist bigint, key array<bigint>, path array<bigint>, va bigint, popped bigint, pushed bigint, extra bigint, parts bigint, ms double"


class Graph:
    """Arcs by start vertex, POIs, coordinates; and the parts of the indexes that a search asks for."""

    def __init__(self, src, dst, length, ess, pois, smax, xy=None, longest=0):
        vids = np.unique(np.concatenate([src, dst, pois]))
        self.vids, self.smax = vids, smax
        # No path that repeats no arc is longer than all arcs, none under a bound longer than the bound.
        self.bits = max(24, int(max(length.sum(), longest)).bit_length() + 1)
        order = np.argsort(src, kind="stable")
        s, d = np.searchsorted(vids, src[order]), np.searchsorted(vids, dst[order])
        length, ess = length[order], ess[order]
        self.out = Rows(np.searchsorted(s, np.arange(len(vids) + 1)), d, length, ess, [1 << self.bits * (smax - e) for e in range(smax + 1)])
        self.pois = set(np.searchsorted(vids, pois).tolist())
        worst = np.full(len(vids), smax + 1)
        np.minimum.at(worst, s, ess)
        self.worst_at = worst.tolist()
        self.xy = None if xy is None else {int(np.searchsorted(vids, v)): (x, y) for v, x, y in xy if v in set_of(vids)}
        self.tree = self.cells = None

    def index_of(self, vid):
        i = int(np.searchsorted(self.vids, vid))
        return i if i < len(self.vids) and self.vids[i] == vid else None

    def vector(self, key):
        return [key >> self.bits * (self.smax - s) & (1 << self.bits) - 1 for s in range(1, self.smax + 1)]

    def key_of(self, vector):
        key = 0
        for x in vector:
            key = key << self.bits | x
        return key


class Rows(dict):
    """The arcs of a vertex as tuples (to, length, level, unit of the key), made when a search first asks for them: searches
    meet a small part of a large network."""

    def __init__(self, first, dst, length, ess, units):
        self.first, self.dst, self.length, self.ess, self.units = first, dst, length, ess, units

    def made(self, v) -> list:
        a, b = self.first[v], self.first[v + 1]
        return [(w, n, e, self.units[e]) for w, n, e in zip(self.dst[a:b].tolist(), self.length[a:b].tolist(), self.ess[a:b].tolist(), strict=True)]

    def __missing__(self, v):
        if len(self) >= MOST_ROWS:
            self.clear()
        row = self[v] = self.made(v)
        return row


def kept_graph(name: tuple, make) -> Graph:
    """make(), or what the worker made last under the same name: tasks of one network follow each other."""
    if name not in _kept:
        _kept.clear()
        _kept[name] = make()
    return _kept[name]


_kept: dict[tuple, Graph] = {}


def set_of(vids, memory={}):  # noqa: B006  one entry, for the arrays of one task
    if memory.get("at") is not vids:
        memory["at"], memory["set"] = vids, set(vids.tolist())
    return memory["set"]


def within(g: Graph, start, dc):
    """POIs on paths shorter than dc (the start itself at any bound), and how many vertices are."""
    heap, done = [(0, start)], set()
    while heap:
        dist, v = heapq.heappop(heap)
        if v in done:
            continue
        done.add(v)
        for w, length, *_ in g.out[v]:
            if dist + length < dc and w not in done:
                heapq.heappush(heap, (dist + length, w))
    return g.pois & done, len(done)


def expand_query(g: Graph, start, k, dc, rules, targets=None, known=None, drop_step=None):
    """Pops paths, the safest first, until k POIs (or all targets) are popped. Returns answers {poi: (key, dist, label)},
    the labels as (vertex, label before), and counts. known: (keys of answers known before, number asked for): with k
    of them, or of them and the targets found, paths beyond the last are out (Rule 7)."""
    wanted = g.pois if targets is None else targets
    heap, labels, best, found = [(0, 0, start, -1)], [], {}, {}
    popped = pushed = 0
    two, seven = 2 in rules, known is not None
    keys, asked = (sorted(known[0]), known[1]) if seven else ([], 0)
    bound = keys[asked - 1] if seven and len(keys) >= asked else inf
    while heap:
        key, dist, v, before = heapq.heappop(heap)
        if seven and key > bound:
            break
        if two:
            if dist >= best.get(v, inf):
                continue
            best[v] = dist
        popped += 1
        me = len(labels)
        labels.append((v, before))
        if v in wanted and v not in found:
            found[v] = (key, dist, me)
            if len(found) >= k:
                break
            if seven:
                bisect.insort(keys, key)
                bound = keys[asked - 1] if len(keys) >= asked else inf
        for w, length, ess, unit in g.out[v]:
            new = dist + length
            if new >= dc or (two and new >= best.get(w, inf)):
                continue
            more = key + unit * length
            if seven and more > bound:
                continue
            if drop_step is not None and drop_step(v, dist, w, ess):
                continue
            pushed += 1
            if not two and pushed > MOST_PATHS:
                raise ValueError("too many paths without Rule 2; lower the bound")
            heapq.heappush(heap, (more, new, w, me))
    return found, labels, {"va": len({v for v, _ in labels}), "popped": popped, "pushed": pushed}


def comptree_query(g: Graph, start, k, dc, rules, literal=False):
    """The climb of the component tree with one queue for the level and one for the labels that wait at its borders."""
    comp, n_pois, d_border, d_poi, poi_list = g.tree
    levels = sorted(comp)
    fits = [s for s in levels if n_pois[s].get(comp[s][start], 0) >= k]
    at = levels.index(max(fits)) if fits else 0
    heap, waiting, labels, best, found = [(0, 0, start, -1, 99, False)], [], [], {}, {}
    counts = {"va": 0, "popped": 0, "pushed": 0, "parts": 1}
    three, four, two = 3 in rules, 4 in rules, 2 in rules
    previous = g.smax

    def vain(v, dist, ess, s_low, w=None, whole=None):
        """Entering form: a step from border v inside a node that leads neither to another border nor to a POI in time."""
        for s in levels:
            if s < s_low or s >= ess or g.worst_at[v] > s:
                continue
            if dist + d_border[s].get(v, inf) < dc:
                continue
            to_poi = dist + d_poi[s].get(v, inf)
            if three and to_poi >= dc:
                return True
            if four:
                most = 0
                for p in poi_list[s].get(comp[s][v], ()):
                    most = max(most, best.get(p, dc))
                    if to_poi < most:
                        break
                if to_poi >= min(most, dc) and most > 0:
                    return True
        return False

    while True:
        level = levels[at]
        while heap:
            key, dist, v, before, least, waited = heapq.heappop(heap)
            if waited:
                me = before
            else:
                if two:
                    if dist >= best.get(v, inf):
                        continue
                    best[v] = dist
                elif dist < best.get(v, inf):
                    best[v] = dist
                counts["popped"] += 1
                me = len(labels)
                labels.append((v, before))
                if v in g.pois and v not in found:
                    found[v] = (key, dist, me)
                    if len(found) >= k:
                        counts["va"] = len({x for x, _ in labels})
                        return found, labels, counts
            if g.worst_at[v] <= level:
                waiting.append((key, dist, v, me, 0, True))
            for w, length, ess, unit in g.out[v]:
                if ess <= level or (waited and ess > previous):
                    continue
                new = dist + length
                if new >= dc or (two and new >= best.get(w, inf)):
                    continue
                if literal:
                    if (three or four) and vain(w, new, g.smax + 1, level):
                        continue
                elif (three or four) and vain(v, dist, ess, level):
                    continue
                counts["pushed"] += 1
                if not two and counts["pushed"] > MOST_PATHS:
                    raise ValueError("too many paths without Rule 2; lower the bound")
                heapq.heappush(heap, (key + unit * length, new, w, me, 0, False))
        if at == 0:
            counts["va"] = len({x for x, _ in labels})
            return found, labels, counts
        previous, at = level, at - 1
        counts["parts"] += 1
        heap, waiting = waiting, []
        heapq.heapify(heap)


def safevor_query(g: Graph, start, k, dc, rules):
    """Unconstrained POIs in order of safety over the overlay of the cells, then the bounded search for the others.

    The listing ends when k valid ones or all POIs within the bound are listed, or when it has visited LISTING times the
    vertices within the bound; what it has not reached by then goes to the bounded search, so answers do not depend on it."""
    reach, near = within(g, start, dc)
    k, left = min(k, len(reach)), len(reach)
    cell, local, overlay, d_border, d_poi = g.cells
    counts = {"va": 0, "popped": 0, "pushed": 0, "extra": 0, "parts": 0}
    seen: set = set()
    # The own cell: every vertex on the way to its borders and its POI.
    heap, done, own = [(0, 0, start)], {}, cell.get(start)
    if own is None or not reach:
        return {}, [], counts
    while heap:
        key, dist, v = heapq.heappop(heap)
        if v in done:
            continue
        done[v] = (key, dist)
        for w, length, _, unit in g.out[v]:
            if cell.get(w) == own and w not in done:
                heapq.heappush(heap, (key + unit * length, dist + length, w))
    seen.update(done)
    heap = [(*done[b], b, b == own) for b in local[own] if b in done]
    if own in done and own not in local[own]:
        heap.append((*done[own], own, True))
    heapq.heapify(heap)
    settled, listed, good, parts = set(), [], 0, {own}
    least = {v: key for key, _, v, _ in heap}
    while heap and good < k and left and len(settled) < LISTING * near + 100:
        key, dist, v, is_poi = heapq.heappop(heap)
        if v in settled:
            continue
        settled.add(v)
        seen.add(v)
        parts.add(cell[v])
        if is_poi:
            listed.append((key, dist, v))
            good += dist < dc
            left -= v in reach
        for w, more, far in overlay.get(v, ()):
            new = key + more
            if w not in least or new < least[w]:
                least[w] = new
                heapq.heappush(heap, (new, dist + far, w, w in g.pois))
    counts["parts"] = len(parts)
    valid = [x for x in listed if x[1] < dc]
    others = (reach if good < k else {v for _, _, v in listed} & reach) - {v for _, _, v in valid}
    counts["extra"] = len(others)
    known = ([key for key, _, _ in valid], k) if 7 in rules else None
    found = {v: (key, dist, None) for key, dist, v in valid}
    labels: list = []
    if others:

        def vain(v, dist, w, ess):
            if cell.get(v) != cell.get(w) or v not in d_border:
                return False
            if dist + d_border[v] < dc:
                return False
            return (5 in rules) if cell[v] not in others else (6 in rules and dist + d_poi.get(v, inf) >= dc)

        more, labels, c = expand_query(g, start, len(others), dc, rules, others, known, drop_step=vain if {5, 6} & set(rules) else None)
        found |= more
        for x in ("popped", "pushed"):
            counts[x] += c[x]
        seen.update(v for v, _ in labels)
    counts["va"] = len(seen)
    best = sorted((key, v) for v, (key, _, _) in found.items())[:k]
    return {v: found[v] for _, v in best}, labels, counts


def euclid_query(g: Graph, start, k, dc, rules):
    x0, y0 = g.xy[start]
    picked = [p for p in sorted(g.pois) if p in g.xy and (g.xy[p][0] - x0) ** 2 + (g.xy[p][1] - y0) ** 2 < dc * dc]
    counts, found, paths = {"va": 0, "popped": 0, "pushed": 0, "extra": len(picked)}, {}, {}
    for p in picked:
        one, labels, c = expand_query(g, start, 1, dc, rules, {p})
        for x in ("va", "popped", "pushed"):
            counts[x] += c[x]
        for v, (key, dist, me) in one.items():
            found[v], paths[v] = (key, dist, None), trace(labels, me)
    best = sorted((key, v) for v, (key, _, _) in found.items())[:k]
    return {v: found[v] for _, v in best}, paths, counts


def knn_query(g: Graph, start, k):
    """The k nearest POIs by network distance, ties to the lesser POI."""
    heap, before, done, found, labels = [(0, start, -1)], {}, set(), {}, []
    while heap:
        dist, v, come = heapq.heappop(heap)
        if len(found) >= k and dist > max(x[1] for x in found.values()):
            break
        if v in done:
            continue
        done.add(v)
        me = len(labels)
        labels.append((v, come))
        if v in g.pois:
            found[v] = (dist, dist, me)
        for w, length, *_ in g.out[v]:
            if w not in done:
                heapq.heappush(heap, (dist + length, w, me))
    best = sorted((x[1], p) for p, x in found.items())[:k]
    return {p: found[p] for _, p in best}, labels, {"va": len(done), "popped": len(labels), "pushed": len(labels)}


def trace(labels, me):
    out = []
    while me is not None and me >= 0:
        out.append(labels[me][0])
        me = labels[me][1]
    return out[::-1]


def attach_tree(g: Graph, pointers, borders):
    """pointers (vid, lvl, comp), borders (lvl, vid, d_border, d_poi) as arrays."""
    comp, n_pois, poi_list, d_border, d_poi = {}, {}, {}, {}, {}
    for v, s, c in zip(*pointers, strict=True):
        i = g.index_of(v)
        if i is None:
            continue
        comp.setdefault(s, {})[i] = c
        if i in g.pois:
            n_pois.setdefault(s, {})[c] = n_pois.setdefault(s, {}).get(c, 0) + 1
            poi_list.setdefault(s, {}).setdefault(c, []).append(i)
    for s in comp:
        for x in (n_pois, poi_list, d_border, d_poi):
            x.setdefault(s, {})
    for s, v, b, p in zip(*borders, strict=True):
        i = g.index_of(v)
        if b is not None:
            d_border[s][i] = b
        if p is not None:
            d_poi[s][i] = p
    g.tree = (comp, n_pois, d_border, d_poi, poi_list)


def assign_cells(g: Graph) -> dict:
    """Every vertex with the POI of its safest path, by one search from all POIs; ties to the lesser POI."""
    heap, cell = [(0, p, p) for p in g.pois], {}
    heapq.heapify(heap)
    while heap:
        key, p, v = heapq.heappop(heap)
        if v in cell:
            continue
        cell[v] = p
        for w, length, _, unit in g.out.made(v):  # asked for once
            if w not in cell:
                heapq.heappush(heap, (key + unit * length, p, w))
    return cell


def ways_in_cell(p, out: dict, ends: set):
    """Inside the cell of p (out: its inner arcs (to, length, unit) by vertex; ends: vertices with an arc that leaves it):
    safest ways between p and the ends that meet no other end, since the others are chains of these; every end's
    safest way to p; and distances to another end and to p.

    Roads lead both ways, so one search from p tells the ways to it. A search from an end stops when all paths left meet
    another end, which in most cells is soon."""
    goals = {*ends, p}
    direct, d_border = {}, {}
    for b in goals:
        heap, done, direct[b], apart = [(0, 0, b, False)], set(), [], 1  # apart: entries of the heap that met no other end
        while apart:
            key, dist, v, through = heapq.heappop(heap)
            apart -= not through
            if v in done:
                continue
            done.add(v)
            if v in goals and v != b:
                if not through:
                    direct[b].append((v, key, dist))
                through = True
            for w, length, unit in out.get(v, ()):
                if w not in done:
                    heapq.heappush(heap, (key + unit * length, dist + length, w, through))
                    apart += not through
        if b not in ends:
            continue
        heap, done = [(0, b)], set()
        while heap:
            dist, v = heapq.heappop(heap)
            if v in done:
                continue
            done.add(v)
            if v in ends and v != b:
                d_border[b] = dist
                break
            for w, length, _ in out.get(v, ()):
                if w not in done:
                    heapq.heappush(heap, (dist + length, w))
    home = ways_from(p, {v: [(w, unit * length, length) for w, length, unit in row] for v, row in out.items()})
    d_poi = ways_from(p, {v: [(w, length, length) for w, length, _ in row] for v, row in out.items()})
    return direct, {b: home[b] for b in ends if b != p and b in home}, d_border, {b: d_poi[b][1] for b in ends if b in d_poi}


def ways_from(p, steps: dict) -> dict:
    """Least key and its length from p to every vertex, over steps (to, key, length)."""
    heap, done = [(0, 0, p)], {}
    while heap:
        key, dist, v = heapq.heappop(heap)
        if v not in done:
            done[v] = key, dist
            for w, more, length in steps.get(v, ()):
                if w not in done:
                    heapq.heappush(heap, (key + more, dist + length, w))
    return done


def set_cells(g: Graph, cell: dict, local: dict, ways: dict, d_border: dict, d_poi: dict):
    """The overlay: stored ways inside the cells and the arcs between them."""
    overlay = {v: list(row) for v, row in ways.items()}
    for ends in local.values():
        for v in ends:
            overlay[v] += [(w, unit * length, length) for w, length, _, unit in g.out[v] if cell.get(w) != cell[v]]
    g.cells = (cell, local, overlay, d_border, d_poi)


def attach_cells(g: Graph):
    """Cells and their tables, made on the spot."""
    cell = assign_cells(g)
    inner: dict = {p: {} for p in g.pois}
    ends: dict = {p: set() for p in g.pois}
    for v, p in cell.items():
        inner[p][v] = [(w, length, unit) for w, length, _, unit in g.out[v] if cell.get(w) == p]
        if len(inner[p][v]) < len(g.out[v]):
            ends[p].add(v)
    overlay, d_border, d_poi = {}, {}, {}
    for p in g.pois:
        direct, _, border, home = ways_in_cell(p, inner[p], ends[p])
        overlay |= direct
        d_border |= {b: border.get(b, inf) for b in ends[p]}
        d_poi |= home
    set_cells(g, cell, {p: sorted(e) for p, e in ends.items()}, overlay, d_border, d_poi)


def attach_cell_tables(g: Graph, cells, ways, ends):
    """The same from the stored tables: cells (vid, cell), ways (b1, b2, sd, dist), ends (cell, b, d_border, d_poi) as lists."""
    at = {int(v): i for i, v in enumerate(g.vids)}
    cell = {at[v]: at[c] for v, c in zip(*cells, strict=True)}
    local: dict = {p: [] for p in g.pois}
    overlay: dict = {p: [] for p in g.pois}
    d_border, d_poi = {}, {}
    for c, b, near, home in zip(*ends, strict=True):
        local[at[c]].append(at[b])
        overlay.setdefault(at[b], [])
        d_border[at[b]] = inf if near is None else near
        if home is not None:
            d_poi[at[b]] = home
    for a, b, sd, dist in zip(*ways, strict=True):
        overlay[at[a]].append((at[b], g.key_of(sd), dist))
    set_cells(g, cell, local, overlay, d_border, d_poi)


def packed_cells(cells: Cells) -> DataFrame:
    """cell, data: the direct ways and the ends of every cell in one compressed array."""
    ways = cells.ways.where("direct").groupBy("cell").agg(F.collect_list(F.struct("b1", "b2", "dist", "sd")).alias("ways"))
    ends = cells.ends.groupBy("cell").agg(F.collect_list(F.struct("b", "d_border", "d_poi")).alias("ends"))

    def run(batches):
        for batch in batches:
            data = []
            for w, e in zip(batch.column("ways"), batch.column("ends"), strict=True):
                w, e = w.values, e.values
                whole = lambda x: np.zeros(0, np.int64) if x is None else x.fill_null(-1).to_numpy(zero_copy_only=False)
                parts = [whole(None if e is None else e.field(c)) for c in ("b", "d_border", "d_poi")]
                parts += [whole(None if w is None else w.field(c)) for c in ("b1", "b2", "dist")]
                parts.append(whole(None if w is None else w.field("sd").flatten()))
                data.append(zlib.compress(np.concatenate([[len(parts[0]), len(parts[3])], *parts]).astype(np.int64).tobytes(), 1))
            yield pa.RecordBatch.from_arrays([batch.column("cell"), pa.array(data, pa.binary())], ["cell", "data"])

    return ends.join(ways, "cell", "full").select("cell", "ways", "ends").mapInArrow(run, "cell bigint, data binary")


class StoredCells:
    """Cells and their tables as attach_cell_tables gives them, each opened when it is first asked for."""

    def __init__(self, g: Graph, vids, cells, names, offsets, data):
        of = np.full(len(g.vids), -1)
        of[np.searchsorted(g.vids, vids)] = np.searchsorted(g.vids, cells)
        self.g, self.of, self.offsets, self.data = g, of.tolist(), offsets, data
        self.row, self.opened = {c: i for i, c in enumerate(np.searchsorted(g.vids, names).tolist())}, {}
        g.cells = (CellOf(self.of), *(CellTable(self, i) for i in range(4)))

    def part(self, v) -> tuple[dict, dict, dict, dict]:
        p = self.of[v]
        if p not in self.opened:
            if len(self.opened) >= MOST_OPEN:
                self.opened.clear()
            self.opened[p] = self.read(p)
        return self.opened[p]

    def read(self, p):
        if p < 0:
            return {}, {}, {}, {}
        overlay, d_border, d_poi, ends = {p: []}, {}, {}, []
        if p in self.row:
            g, i = self.g, self.row[p]
            x = np.frombuffer(zlib.decompress(self.data[self.offsets[i] : self.offsets[i + 1]]), np.int64)
            m, n = int(x[0]), int(x[1])
            ends = np.searchsorted(g.vids, x[2 : 2 + m]).tolist()
            b1, b2 = (np.searchsorted(g.vids, x[2 + 3 * m + j * n : 2 + 3 * m + (j + 1) * n]).tolist() for j in (0, 1))
            rest = x[2 + 3 * m + 2 * n :]
            for b, near, home in zip(ends, x[2 + m : 2 + 2 * m].tolist(), x[2 + 2 * m : 2 + 3 * m].tolist(), strict=True):
                overlay.setdefault(b, [])
                d_border[b] = inf if near < 0 else near
                if home >= 0:
                    d_poi[b] = home
            for a, b, dist, sd in zip(b1, b2, rest[:n].tolist(), rest[n:].reshape(n, -1).tolist() if n else (), strict=True):
                overlay[a].append((b, g.key_of(sd), dist))
            for v in ends:
                overlay[v] += [(w, unit * length, length) for w, length, _, unit in g.out[v] if self.of[w] != p]
        return {p: ends}, overlay, d_border, d_poi


class CellOf:
    def __init__(self, of: list):
        self.of = of

    def get(self, v):
        return None if self.of[v] < 0 else self.of[v]

    def __getitem__(self, v):
        return self.of[v]


class CellTable:
    def __init__(self, stored: StoredCells, i: int):
        self.stored, self.i = stored, i

    def get(self, v, default=None):
        return self.stored.part(v)[self.i].get(v, default)

    def __getitem__(self, v):
        return self.stored.part(v)[self.i][v]

    def __contains__(self, v):
        return v in self.stored.part(v)[self.i]


@dataclass(frozen=True)
class Cells:
    """cells (vid, cell); ways (cell, b1, b2, sd, dist, direct): safest ways inside a cell, from its border ends to its POI
    (b2 = cell) and the direct ones between all of them; ends (cell, b, d_border, d_poi)."""

    cells: DataFrame
    ways: DataFrame
    ends: DataFrame


def build_cells_local(net: Network) -> Cells:
    """The cell tables of a network of a checked size: one task assigns the vertices, then every cell is a group."""
    spark, sent, smax = net.vertices.sparkSession, sent_network(net), net.smax

    def assign(batches):
        for batch in batches:
            if batch.num_rows:
                arrays, pois, _ = sent.value
                g = Graph(*both_ways(arrays), pois, smax)
                found = assign_cells(g)
                yield pa.RecordBatch.from_arrays([pa.array(g.vids[list(found)]), pa.array(g.vids[list(found.values())])], ["vid", "cell"])

    return cell_tables(net, durable(spark.range(1).coalesce(1).mapInArrow(assign, "vid bigint, cell bigint")))


def cell_tables(net: Network, cells: DataFrame) -> Cells:
    """The tables of given cells (vid, cell), for a network of any size: every cell is a group and has to fit a task."""
    smax = net.smax
    of = lambda end, name: cells.withColumnsRenamed({"vid": end, "cell": name})
    steps = net.arcs.select("src", "dst", "len", "ess").join(of("src", "cell"), "src").join(of("dst", "other"), "dst")
    alone = cells.select("cell", F.col("vid").alias("src"), F.lit(None).cast("bigint").alias("dst"), F.lit(None).cast("bigint").alias("len"), F.lit(None).cast("int").alias("ess"), F.col("cell").alias("other"))
    rows = steps.select("cell", "src", "dst", "len", "ess", "other").unionByName(alone)

    def ways(table):
        p, out, ends = table.column("cell")[0].as_py(), {}, set()
        bits = max(8, int(pc.sum(table.column("len")).as_py() or 0).bit_length() + 1)
        for v, w, length, e, other in zip(*(table.column(c).to_pylist() for c in ("src", "dst", "len", "ess", "other")), strict=True):
            if w is not None and other == p:
                out.setdefault(v, []).append((w, length, 1 << bits * (smax - e)))
            elif w is not None:
                ends.add(v)
        direct, home, d_border, d_poi = ways_in_cell(p, out, ends)
        vector = lambda key: [key >> bits * (smax - s) & (1 << bits) - 1 for s in range(1, smax + 1)]
        found = [(p, a, b, vector(key), dist, True, None, None) for a, row in direct.items() for b, key, dist in row]
        known = {(a, b) for _, a, b, *_ in found}
        found += [(p, a, p, vector(key), dist, False, None, None) for a, (key, dist) in home.items() if (a, p) not in known]
        found += [(p, a, None, None, None, None, d_border.get(a), d_poi.get(a)) for a in ends]
        columns = zip(*found, strict=True) if found else [()] * len(WAYS)
        return pa.Table.from_arrays([pa.array(c, kind) for c, kind in zip(columns, WAYS.types, strict=True)], schema=WAYS)

    told = durable(rows.groupBy("cell").applyInArrow(ways, "cell bigint, b1 bigint, b2 bigint, sd array<bigint>, dist bigint, direct boolean, d_border bigint, d_poi bigint"))
    inside = told.where("b2 is not null").select("cell", "b1", "b2", "sd", "dist", "direct")
    return Cells(cells, inside, told.where("b2 is null").select("cell", F.col("b1").alias("b"), "d_border", "d_poi"))


WAYS = pa.schema([("cell", pa.int64()), ("b1", pa.int64()), ("b2", pa.int64()), ("sd", pa.list_(pa.int64())), ("dist", pa.int64()), ("direct", pa.bool_()), ("d_border", pa.int64()), ("d_poi", pa.int64())])


#: What was made last of each kind, and of which frames.
_last: dict[str, tuple] = {}


def made_once(kind: str, frames: tuple, make):
    """make(), or what it gave for the very same frames: sets of rules over one network share what is sent."""
    if kind not in _last or len(_last[kind][0]) != len(frames) or any(a is not b for a, b in zip(_last[kind][0], frames, strict=True)):
        _last[kind] = (frames, make())
    return _last[kind][1]


def sent_network(net: Network):
    """A broadcast of edges (see both_ways), POIs and a name, of at most MOST_ARCS arcs."""

    def make():
        if not small_enough(net.edges, MOST_ARCS // 2):
            raise ValueError("the network is too large for this engine; use the search by rounds")
        edges = net.edges.select("u", "w", "len", "ess").toArrow()
        pois = np.sort(net.pois.toArrow().column("poi").to_numpy())
        return net.vertices.sparkSession.sparkContext.broadcast(([edges.column(c).to_numpy() for c in ("u", "w", "len", "ess")], pois, uuid.uuid4().hex))

    return made_once("network", (net.edges, net.pois), make)


def both_ways(edges: list) -> list:
    """src, dst, len, ess of the arcs of edges (u, w, len, ess)."""
    u, w, length, ess = edges
    return [np.concatenate(x) for x in ((u, w), (w, u), (length, length), (ess, ess))]


def tree_rows(net: Network, queries: DataFrame, tree: CompTree) -> DataFrame:
    """qid, tree: what the component tree tells of the vertices within each query's bound. n_pois counts the whole node."""
    network = sent_network(net)

    def near(batches):
        arrays = None
        for batch in batches:
            if arrays is None:
                src, dst, length, _ = both_ways(network.value[0])
                order = np.argsort(src, kind="stable")
                arrays = src[order], dst[order], length[order]
            for qid, start, dc in zip(*(batch.column(c).to_pylist() for c in ("qid", "src", "dc")), strict=True):
                heap, done = [(0, start)], set()
                while heap:
                    dist, v = heapq.heappop(heap)
                    if v in done:
                        continue
                    done.add(v)
                    a, b = np.searchsorted(arrays[0], v), np.searchsorted(arrays[0], v, "right")
                    for w, n in zip(arrays[1][a:b].tolist(), arrays[2][a:b].tolist(), strict=True):
                        if dist + n < dc and w not in done:
                            heapq.heappush(heap, (dist + n, w))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(done), qid, np.int64)), pa.array(list(done), pa.int64())], ["qid", "vid"])

    asked = queries.select(F.col("qid").cast("bigint"), F.col("src").cast("bigint"), F.col("dc").cast("double"))
    ball = durable(asked.repartition(max(1, asked.sparkSession.sparkContext.defaultParallelism), "qid").mapInArrow(near, "qid bigint, vid bigint"))
    at = tree.pointers.join(F.broadcast(ball.select("vid").distinct()), "vid", "left_semi").join(tree.nodes.select("lvl", "comp", "n_pois"), ["lvl", "comp"])
    at = at.join(tree.borders.select("lvl", "vid", "d_border", "d_poi"), ["lvl", "vid"], "left")
    row = F.struct("vid", F.col("lvl").cast("int").alias("lvl"), "comp", "n_pois", "d_border", "d_poi")
    return durable(ball.join(at, "vid").groupBy("qid").agg(F.collect_list(row).alias("tree")))


def attach_tree_rows(g: Graph, rows):
    """The tree's tables from one query's rows. A POI of a node that lies beyond the bound stands there as -1."""
    comp, n_pois, d_border, d_poi, poi_list = {}, {}, {}, {}, {}
    columns = [rows.field(c).to_pylist() for c in ("lvl", "comp", "n_pois", "d_border", "d_poi")] if rows is not None else [[]] * 5
    at = np.searchsorted(g.vids, rows.field("vid").to_numpy()).tolist() if rows is not None else []
    for i, s, c, n, b, p in zip(at, *columns, strict=True):
        for x in (comp, n_pois, d_border, d_poi, poi_list):
            x.setdefault(s, {})
        comp[s][i], n_pois[s][c] = c, n
        if i in g.pois:
            poi_list[s].setdefault(c, []).append(i)
        if b is not None:
            d_border[s][i] = b
        if p is not None:
            d_poi[s][i] = p
    for s, sizes in n_pois.items():
        for c, n in sizes.items():
            if n > len(poi_list[s].get(c, ())):
                poi_list[s].setdefault(c, []).append(-1)
    g.tree = (comp, n_pois, d_border, d_poi, poi_list)


DEFAULT_RULES = {"knn": (), "expand": (1, 2), "comptree": (1, 2, 3, 4), "safevor": (1, 2, 5, 6, 7), "euclid": (1, 2)}


def grouped_search(net: Network, queries: DataFrame, method: str, rules: Iterable[int] | None = None, tree: CompTree | None = None, literal: bool = False, cells: Cells | None = None) -> DataFrame:
    """One row for each answer with the counters of its query (rnk 0, poi null: a query without answers). The indexes are
    read, not made: tree for comptree, cells for safevor (built first where none are given)."""
    spark: SparkSession = queries.sparkSession
    rules = frozenset(DEFAULT_RULES[method] if rules is None else rules)
    network = sent_network(net)
    xy = net.vertices.select("vid", "x", "y").toArrow() if method == "euclid" else None
    xy = None if xy is None else list(zip(*(xy.column(c).to_pylist() for c in ("vid", "x", "y")), strict=True))
    index, asked = None, queries.select("qid", "src", "k", F.col("dc").cast("double").alias("dc"))
    if method == "comptree":
        rows = made_once("tree", (net.edges, queries, tree.pointers, tree.borders), lambda: tree_rows(net, queries, tree))
        asked = asked.join(rows, "qid", "left")
    if method == "safevor":
        cells = cells or build_cells_local(net)

        def packed():
            c, t = cells.cells.toArrow(), packed_cells(cells).toArrow()
            data = t.column("data").to_pylist()
            sent = ([c.column(x).to_numpy() for x in ("vid", "cell")], t.column("cell").to_numpy(), np.cumsum([0, *map(len, data)]), b"".join(data))
            return spark.sparkContext.broadcast(sent)  # of a network of at most MOST_ARCS arcs, compressed

        index = made_once("cells", (net.edges, cells.cells, cells.ways, cells.ends), packed)
    longest = queries.agg(F.max("dc")).first()[0] or 0
    sent = spark.sparkContext.broadcast((net.smax, xy, int(min(longest, 1 << 60))))  # places of a network of at most MOST_ARCS arcs
    n = max(1, min(queries.count(), spark.sparkContext.defaultParallelism))

    def run(batches):
        import time

        (edges, pois, name), (smax, xy, longest) = network.value, sent.value
        g = None
        for batch in batches:
            if g is None:
                g = kept_graph((name, smax, longest, xy is None), lambda: Graph(*both_ways(edges), pois, smax, xy, longest))
                if method == "safevor":
                    (vids, of), names, offsets, data = index.value
                    StoredCells(g, vids, of, names, offsets, data)
            out = []
            for i, (qid, v, k, dc) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("qid", "src", "k", "dc")), strict=True)):
                if method == "comptree":
                    attach_tree_rows(g, batch.column("tree")[i].values)
                began, start = time.perf_counter(), g.index_of(v)
                found, labels, c = {}, [], {"va": 0, "popped": 0, "pushed": 0}
                few = min(k, len(within(g, start, dc)[0])) if start is not None and method in ("expand", "comptree") else k
                if start is not None and few:
                    if method == "expand":
                        found, labels, c = expand_query(g, start, few, dc, rules)
                    elif method == "comptree":
                        found, labels, c = comptree_query(g, start, few, dc, rules, literal)
                    elif method == "knn":
                        found, labels, c = knn_query(g, start, k)
                    elif method == "safevor":
                        found, labels, c = safevor_query(g, start, k, dc, rules)
                    else:
                        found, labels, c = euclid_query(g, start, k, dc, rules)
                counts = (c["va"], c["popped"], c["pushed"], c.get("extra", 0), c.get("parts", 0), (time.perf_counter() - began) * 1000)
                if not found:
                    out.append((qid, 0, None, None, None, None, *counts))
                for r, (key, p) in enumerate(sorted((x[0], p) for p, x in found.items())):
                    path = labels[p] if method == "euclid" else trace(labels, found[p][2]) if found[p][2] is not None else None
                    out.append((qid, r + 1, int(g.vids[p]), found[p][1], None if method == "knn" else g.vector(key), None if path is None else [int(g.vids[x]) for x in path], *counts))
            if out:
                yield pa.RecordBatch.from_pylist([dict(zip(NAMES, row, strict=True)) for row in out], schema=ARROW)

    return asked.repartition(n).mapInArrow(run, OUT)  # dealt in turn: a hash of few queries gives some tasks twice as many


NAMES = [x.split()[0] for x in OUT.split(", ")]
ARROW = pa.schema([pa.field(n, {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "array<bigint>": pa.list_(pa.int64())}[t]) for n, t in (x.split() for x in OUT.split(", "))])
