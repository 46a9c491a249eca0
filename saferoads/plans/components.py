"""Connected components by contraction: every round a vertex joins the neighbour of least rank.

The first round ranks by id, which ends stars around their least vertex at once; later rounds rank by hash, so the number
of vertices falls by a constant factor a round whatever the diameter: a long road component takes O(log V) rounds. All
steps are joins and pre-aggregated minima. Once at most LAST links are left, a count of them checks, one task
joins their ends by union and find; the rounds' maps then lead every vertex to its component.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from saferoads.plans.runtime import drop, durable

LAST = 16_384


def forest(links: DataFrame) -> DataFrame:
    """(id, comp) of the vertices of at most LAST links, in one task; comp is the least id reachable."""

    def run(batches):
        up: dict = {}

        def top(v):
            while up.setdefault(v, v) != v:
                up[v] = v = up[up[v]]
            return v

        for batch in batches:
            for x, y in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), strict=True):
                p, q = top(x), top(y)
                up[max(p, q)] = min(p, q)
        if up:
            ids = list(up)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(np.fromiter((top(v) for v in ids), np.int64, len(ids)))], ["id", "comp"])

    return links.coalesce(1).mapInArrow(run, "id bigint, comp bigint")


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", last: int = LAST) -> DataFrame:
    """edges: two bigint columns. Returns (id, comp) for every vertex of an edge; comp is the least id reachable.

    Nulls and loops are ignored; repeated edges do no harm; an empty table gives an empty result.
    """
    links = edges.select(F.col(a).cast("bigint").alias("a"), F.col(b).cast("bigint").alias("b")).where("a <> b")
    links = durable(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    maps: list[DataFrame] = []
    while links.count() > last:
        both = links.union(links.select("b", "a"))
        turn = len(maps)
        rank = lambda c: F.struct(F.lit(0) if turn == 0 else F.xxhash64(F.lit(turn), F.col(c)), F.col(c).alias("v"))
        nearest = durable(both.groupBy("a").agg(F.least(F.min(rank("b")), F.min(rank("a")))["v"].alias("to")))
        maps.append(nearest)
        one, other = nearest.withColumnsRenamed({"to": "ta"}), nearest.withColumnsRenamed({"a": "b", "to": "tb"})
        fewer = links.join(one, "a").join(other, "b").where("ta <> tb").select(F.least("ta", "tb").alias("a"), F.greatest("ta", "tb").alias("b"))
        before, links = links, durable(fewer.distinct())
        drop(before)
    labels = durable(forest(links))
    drop(links)
    if not maps:
        return labels
    for step in reversed(maps):
        labels = step.join(labels, step["to"] == labels["id"], "left").select(F.col("a").alias("id"), F.coalesce("comp", "to").alias("comp"))
    labels = durable(labels)
    drop(*maps)
    least = labels.groupBy("comp").agg(F.min("id").alias("least"))
    return labels.join(least, "comp").select("id", F.col("least").alias("comp"))
