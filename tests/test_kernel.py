"""The exact engine on small graphs against enumeration of all simple valid paths (5.1, 5.3, rules R1-R7)."""

import heapq
import random
from math import inf

import numpy as np
import pytest

from saferoads.operators import kernel
from saferoads.operators.kernel import Graph, comptree_query, euclid_query, expand_query, safevor_query


def graph(edges, pois, smax, xy=None):
    both = [(a, b, n, s) for u, w, n, s in edges for a, b in ((u, w), (w, u))]
    src, dst, length, ess = (np.array(c, np.int64) for c in zip(*both))
    g = Graph(src, dst, length, ess, np.array(sorted(pois), np.int64), smax, xy)
    attach(g, edges, pois, smax)
    kernel.attach_cells(g)
    return g


def attach(g, edges, pois, smax):
    """Pointers, border and POI distances by plain searches."""
    vids = [int(v) for v in g.vids]
    rows, borders = [], []
    for s in range(smax):
        near = {v: [] for v in vids}
        for u, w, n, e in edges:
            if e > s:
                near[u].append((w, n))
                near[w].append((u, n))
        comp = {}
        for v in vids:
            if v not in comp:
                todo = [v]
                while todo:
                    x = todo.pop()
                    if x not in comp:
                        comp[x] = v
                        todo += [y for y, _ in near[x]]
        rows += [(v, s, comp[v]) for v in vids]
        rim = {v for v in vids if any(e <= s and v in (u, w) for u, w, _, e in edges)}
        for b in rim:
            dist, todo = {b: 0}, [b]
            while todo:
                todo.sort(key=lambda x: -dist[x])
                x = todo.pop()
                for y, n in near[x]:
                    if dist[x] + n < dist.get(y, inf):
                        dist[y] = dist[x] + n
                        todo.append(y)
            other = min((d for v, d in dist.items() if v in rim and v != b), default=None)
            home = min((d for v, d in dist.items() if v in pois), default=None)
            borders.append((s, b, other, home))
    kernel.attach_tree(g, list(zip(*rows)), list(zip(*borders)) if borders else [[]] * 4)


def brute(edges, pois, smax, start, k, dc):
    near = {}
    for u, w, n, e in edges:
        near.setdefault(u, []).append((w, n, e))
        near.setdefault(w, []).append((u, n, e))
    best = {}

    def walk(v, seen, sd):
        if v in pois and (v not in best or sd < best[v]):
            best[v] = sd
        for w, n, e in near.get(v, ()):
            if w not in seen and sum(sd) + n < dc:
                walk(w, seen | {w}, tuple(x + n * (i == e - 1) for i, x in enumerate(sd)))

    walk(start, {start}, (0,) * smax)
    return [sd for sd, _ in sorted((sd, p) for p, sd in best.items())[:k]]


def keys(g, found):
    return [tuple(g.vector(key)) for key, _ in sorted((x[0], p) for p, x in found.items())]


def random_case(rng):
    n, smax = rng.randint(5, 9), rng.randint(2, 4)
    edges = {}
    for v in range(1, n):
        edges[(rng.randrange(v), v)] = None
    for _ in range(rng.randint(0, n)):
        a, b = sorted(rng.sample(range(n), 2))
        edges[(a, b)] = None
    edges = [(a, b, rng.randint(1, 12), rng.randint(1, smax)) for a, b in edges]
    pois = set(rng.sample(range(n), rng.randint(1, min(4, n))))
    return edges, pois, smax, rng.randrange(n), rng.randint(1, 3), rng.randint(5, 40)


CASES = [("expand", (1, 2)), ("expand", (1, 2)), ("comptree", (1, 2)), ("comptree", (1, 2, 3)), ("comptree", (1, 2, 4)), ("comptree", (1, 2, 3, 4)), ("safevor", (1, 2)), ("safevor", (1, 2, 5, 6)), ("safevor", (1, 2, 7)), ("safevor", (1, 2, 5, 6, 7))]


@pytest.mark.parametrize("method, rules", CASES)
def test_random_graphs(method, rules):
    rng = random.Random(11)
    for i in range(250):
        edges, pois, smax, start, k, dc = random_case(rng)
        g = graph(edges, pois, smax)
        run = {"expand": expand_query, "comptree": comptree_query, "safevor": safevor_query}[method]
        found, _, counts = run(g, g.index_of(start), k, dc, set(rules))
        assert keys(g, found) == brute(edges, pois, smax, start, k, dc), (i, edges, pois, start, k, dc)
        assert counts["va"] <= len(g.vids)


def test_basic_equals_enumeration():
    rng = random.Random(12)
    for _ in range(40):
        edges, pois, smax, start, k, _ = random_case(rng)
        g = graph(edges, pois, smax)
        assert keys(g, expand_query(g, g.index_of(start), k, 12, {1})[0]) == brute(edges, pois, smax, start, k, 12)


F1 = [(0, 1, 1, 2), (1, 2, 20, 2), (2, 3, 1, 2), (1, 4, 1, 1), (2, 5, 1, 1)]  # q=0 v=1 b=2 p1=3 p2=4 z=5


def test_rule_on_the_label_is_unsound():
    g = graph(F1, {3, 4}, 2)
    found, _, _ = comptree_query(g, g.index_of(0), 1, 10, {1, 2, 3, 4})
    assert [(p, x[1]) for p, x in found.items()] == [(g.index_of(4), 2)]
    assert comptree_query(g, g.index_of(0), 1, 10, {1, 2, 3, 4}, literal=True)[0] == {}


def test_short_unsafe_prefix_is_kept():
    # Vertex 1 by a safe long road or an unsafe short one; only the short one reaches the POI in time.
    g = graph([(0, 1, 8, 2), (0, 2, 1, 1), (2, 1, 1, 1), (1, 3, 5, 2)], {3}, 2)
    for run in (expand_query, comptree_query, safevor_query):
        found, _, _ = run(g, g.index_of(0), 1, 10, {1, 2, 3, 4, 5, 6, 7})
        assert [x[1] for x in found.values()] == [7]


def test_bound_is_strict_and_few_are_enough():
    g = graph([(0, 1, 10, 2), (0, 2, 3, 1)], {1, 2}, 2)
    for run in (expand_query, comptree_query, safevor_query):
        assert len(run(g, g.index_of(0), 5, 10, {1, 2, 3, 4, 5, 6, 7})[0]) == 1
        assert len(run(g, g.index_of(0), 5, 11, {1, 2, 3, 4, 5, 6, 7})[0]) == 2


def test_query_on_a_poi_and_disconnected_parts():
    g = graph([(0, 1, 2, 1), (2, 3, 2, 1)], {0, 3}, 2)
    for run in (expand_query, comptree_query, safevor_query):
        found, _, _ = run(g, g.index_of(0), 2, 10, {1, 2, 3, 4, 5, 6, 7})
        assert list(found.values())[0][:2] == (0, 0) and len(found) == 1


def test_straight_line_filter():
    xy = [(0, 0, 0), (1, 3, 0), (2, 30, 0)]
    g = graph([(0, 1, 3, 1), (1, 2, 30, 1)], {1, 2}, 1, xy)
    found, paths, counts = euclid_query(g, g.index_of(0), 2, 20, {1, 2})
    assert len(found) == 1 and counts["extra"] == 1 and paths[g.index_of(1)] == [0, 1]


def test_counters_fall_with_rules():
    rng = random.Random(3)
    edges = [(i, i + 1, rng.randint(5, 9), rng.randint(1, 5)) for i in range(59) if i % 10 != 9] + [(i, i + 10, rng.randint(5, 9), rng.randint(1, 5)) for i in range(50)]
    g = graph(edges, {7, 22, 41, 58}, 5)
    pushed = {r: comptree_query(g, g.index_of(33), 2, 60, set(r))[2]["pushed"] for r in ((1, 2), (1, 2, 3), (1, 2, 3, 4))}
    assert pushed[1, 2, 3, 4] <= pushed[1, 2, 3] <= pushed[1, 2]
    assert safevor_query(g, g.index_of(33), 2, 60, {1, 2, 5, 6, 7})[2]["pushed"] <= expand_query(g, g.index_of(33), 2, 60, {1, 2})[2]["pushed"]


def test_no_search_for_more_pois_than_are_in_reach():
    """A line of safe roads with many POIs, all beyond the bound, and one POI in reach by an unsafe road."""
    pois = {5001} | {i for i in range(0, 3001, 20) if i != 200}
    g = graph([(i, i + 1, 1, 2) for i in range(3000)] + [(200, 5001, 1, 1)], pois, 2)
    assert kernel.within(g, g.index_of(201), 10) == ({g.index_of(5001)}, 20)
    found, _, counts = safevor_query(g, g.index_of(201), 5, 10, {1, 2, 5, 6, 7})
    assert list(found) == [g.index_of(5001)] and counts["va"] < 300 and counts["extra"] == 1


@pytest.mark.parametrize("spread", [0, 4])
def test_listing_may_end_anywhere(monkeypatch, spread):
    monkeypatch.setattr(kernel, "LISTING", spread)
    rng = random.Random(13)
    for _ in range(100):
        edges, pois, smax, start, k, dc = random_case(rng)
        g = graph(edges, pois, smax)
        assert keys(g, safevor_query(g, g.index_of(start), k, dc, {1, 2, 5, 6, 7})[0]) == brute(edges, pois, smax, start, k, dc)


@pytest.mark.parametrize("seed", range(12))
def test_levels_by_arrays_equal_plain_searches(seed):
    """Components, borders and both distances of every level, on graphs of several parts with ties and lone vertices."""
    from saferoads.operators.comptree import level_rows

    rng = np.random.default_rng(seed)
    n, smax, reach = 40, 4, None if seed % 3 == 0 else float(rng.integers(4, 14))
    vids = np.arange(n) * 3 + 5
    pairs = sorted({tuple(sorted(rng.choice(n - 3, 2, replace=False).tolist())) for _ in range(50)})
    u, w = (vids[[p[i] for p in pairs]] for i in (0, 1))
    length, ess = rng.integers(1, 6, len(pairs)), rng.integers(1, smax + 1, len(pairs))
    arcs = [np.concatenate(x) for x in ((u, w), (w, u), (length, length), (ess, ess))]
    pois = vids[rng.choice(n, 4, replace=False)]
    for level in range(smax):
        out = {int(v): [] for v in vids}
        for a, b, x, e in zip(*(c.tolist() for c in arcs)):
            if e > level:
                out[a].append((b, x))

        def far(start):
            heap, done = [(0, start)], {}
            while heap:
                d, v = heapq.heappop(heap)
                if v not in done:
                    done[v] = d
                    for b, x in out[v]:
                        heapq.heappush(heap, (d + x, b))
            return done

        ways = {v: far(v) for v in out}
        border = {v: any(e <= level for a, e in zip(arcs[0].tolist(), arcs[3].tolist()) if a == v) for v in out}
        least = lambda found: min((d for d in found if reach is None or d < reach), default=None)  # noqa: B023, E731
        want = {v: (min(ways[v]), border[v], least([d for b, d in ways[v].items() if border[b] and b != v]) if border[v] else None, least([ways[v][p] for p in pois.tolist() if p in ways[v]])) for v in out}
        lvl, vid, comp, at, other, home = (c.tolist() for c in level_rows(level, vids, arcs, pois, reach))
        assert set(lvl) == {level} and {v: x for v, *x in zip(vid, comp, at, other, home)} == {v: list(x) for v, x in want.items()}


def test_arcs_of_a_vertex_are_made_when_asked_for(monkeypatch):
    """A large network costs its arrays; searches that stay near their start make few tuples, and may drop them."""
    n = 5000
    src, dst = np.arange(n - 1), np.arange(1, n)
    ones = np.ones(2 * n - 2, np.int64)
    g = Graph(np.concatenate([src, dst]), np.concatenate([dst, src]), ones, ones, np.array([100, 4000]), 2)
    assert kernel.within(g, 95, 10.0) == ({100}, 19) and len(g.out) <= 21
    monkeypatch.setattr(kernel, "MOST_ROWS", 7)
    assert kernel.within(g, 95, 40.0) == ({100}, 79) and len(g.out) <= 7
