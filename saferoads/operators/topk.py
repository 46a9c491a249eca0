"""One entrance to the safest top-k search: method, engine and rules by name."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame

from saferoads.functions.safety import LexSafety, Measure
from saferoads.operators import comptree, expand, kernel, safevor
from saferoads.plans.runtime import small_enough
from saferoads.sources.networks import Network

METHODS = ("expand", "comptree", "safevor", "euclid", "brute")


def safest_topk(net: Network, queries: DataFrame, method: str = "expand", engine: str = "auto", rules: Iterable[int] | None = None, measure: Measure = LexSafety, index=None) -> DataFrame:
    """qid, rnk, poi, dist, key, path for queries (qid, src, k, dc).

    engine: "kernel" (networks of at most MOST_ARCS arcs), "rounds" (any size), or "auto", the first where it can serve.
    index: what the method reads (CompTree, SafeVor or Cells); it is built where none is given. A measure other than the
    lexicographic one goes to EXPAND by rounds; the component tree refuses measures that its levels do not order."""
    if method not in METHODS or engine not in ("auto", "kernel", "rounds"):
        raise ValueError(f"method is one of {METHODS}, engine auto, kernel or rounds")
    if measure != LexSafety:
        if method == "comptree" and not measure.bottleneck:
            raise ValueError(f"{measure.name} is not ordered by the worst edge, as the component tree needs")
        return expand.expand(net, queries, tuple(rules or (1, 2)), measure)
    if method == "brute":
        return expand.brute_force(net, queries)
    if engine == "auto":
        engine = "kernel" if small_enough(net.edges, kernel.MOST_ARCS // 2) else "rounds"
    if engine == "kernel":
        tree = (index or comptree.build_comptree_local(net)) if method == "comptree" else None
        found = kernel.grouped_search(net, queries, method, rules, tree, cells=index if method == "safevor" else None)
        return found.where("rnk > 0").select("qid", "rnk", "poi", "dist", "key", "path")
    if method == "comptree":
        return comptree.comptree_search(net, index or comptree.build_comptree(net), queries, *([tuple(rules)] if rules else []))
    if method == "safevor":
        return safevor.safevor_search(net, index or safevor.build_safevor(net), queries, *([tuple(rules)] if rules else []))
    return (expand.expand if method == "expand" else expand.euclid_baseline)(net, queries, *([tuple(rules)] if rules else []))
