"""Functions for SQL users: registration, path edges as a table function, a point-segment distance to check the columns."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


@F.pandas_udf(DoubleType())
def segment_distance(x: pd.Series, y: pd.Series, xu: pd.Series, yu: pd.Series, xw: pd.Series, yw: pd.Series) -> pd.Series:
    dx, dy = xw - xu, yw - yu
    t = (((x - xu) * dx + (y - yu) * dy) / np.maximum(dx * dx + dy * dy, 1e-300)).clip(0, 1)
    return np.hypot(x - xu - t * dx, y - yu - t * dy)


@F.udtf(returnType="step int, u bigint, w bigint")
class PathEdges:
    """Edges of a path of vertices."""

    def eval(self, path):
        for i, (u, w) in enumerate(zip(path or [], (path or [])[1:], strict=False)):
            yield i, u, w


def register(spark: SparkSession) -> None:
    """SQL names: pss(sd, base), path_length(sd), safer(a, b), path_edges(path)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION path_length(sd ARRAY<BIGINT>) RETURNS BIGINT RETURN aggregate(sd, 0L, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION safer(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS BOOLEAN RETURN a < b")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pss(sd ARRAY<BIGINT>, base DOUBLE) RETURNS DOUBLE RETURN try_divide(1D, aggregate(sd, 0D, (s, x) -> s * base + x))")
    spark.udtf.register("path_edges", PathEdges)


def register_safest_paths(spark: SparkSession, net, name: str = "safest_paths") -> None:
    """SQL table function name(src, k, dc) over a network of a checked size: rnk, poi, dist, sd, path."""
    from saferoads.operators.kernel import MOST_ARCS, Graph, expand_query, trace
    from saferoads.plans.runtime import small_enough

    if not small_enough(net.edges, MOST_ARCS // 2):
        raise ValueError("the network is too large for a table function")
    arcs = net.arcs.select("src", "dst", "len", "ess").toArrow()
    arrays = [arcs.column(c).to_numpy() for c in ("src", "dst", "len", "ess")]
    pois, smax = np.sort(net.pois.toArrow().column("poi").to_numpy()), net.smax

    @F.udtf(returnType="rnk int, poi bigint, dist bigint, sd array<bigint>, path array<bigint>")
    class SafestPaths:
        def __init__(self):
            self.graph = Graph(*arrays, pois, smax)

        def eval(self, src: int, k: int, dc: float):
            start = self.graph.index_of(src)
            if start is None:
                return
            found, labels, _ = expand_query(self.graph, start, k, float(dc), {1, 2})
            for r, (key, p) in enumerate(sorted((x[0], p) for p, x in found.items())):
                path = trace(labels, found[p][2])
                yield r + 1, int(self.graph.vids[p]), found[p][1], self.graph.vector(key), [int(self.graph.vids[v]) for v in path]

    spark.udtf.register(name, SafestPaths)
