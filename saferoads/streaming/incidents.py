"""Incident streams: windowed counts, changes of levels, and application of change batches to an index."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from saferoads.plans.runtime import exists, mark, names_in

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def incident_stream(spark: SparkSession, path: str, delay: str = "2 days", kinds: tuple[str, ...] = ("error",), edges: int = 500, files: int = 1, pattern: str = "*.parquet") -> DataFrame:
    """Incidents of the listed kinds with the edge they fall on, without repeats inside the watermark."""
    raw = spark.readStream.schema(EVENTS.replace("ts timestamp", "ts timestamp_ntz")).option("maxFilesPerTrigger", files).option("pathGlobFilter", pattern).parquet(path)
    timed = raw.where(F.col("event_type").isin(*kinds)).withColumn("ts", F.col("ts").cast("timestamp"))
    unique = timed.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])
    return unique.withColumn("eid", F.col("event_id") * 611953 % edges)


def window_counts(incidents: DataFrame, length: str = "7 days", slide: str | None = None) -> DataFrame:
    """Incidents per edge in tumbling or sliding windows; rows later than the watermark are dropped."""
    return incidents.groupBy(F.window("ts", length, slide or length).alias("w"), "eid").agg(F.count("*").alias("n")).select("w.start", "w.end", "eid", "n")


def session_counts(incidents: DataFrame, gap: str = "6 hours") -> DataFrame:
    return incidents.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("w.start", "w.end", "user_id", "n")


def level_changes(incidents: DataFrame, smax: int, per_level: int) -> DataFrame:
    """eid, ess, n: a row whenever an edge's running count moves its level (a level for each `per_level` incidents).

    The state is one count for each edge, so the network bounds it; a timeout would forget incidents."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, level = state.get if state.exists else (0, smax)
        n += sum(len(b) for b in batches)
        fresh = max(1, smax - n // per_level)
        state.update((n, fresh))
        if fresh != level:
            yield pd.DataFrame({"eid": [key[0]], "ess": [fresh], "n": [n]})

    return incidents.groupBy("eid").applyInPandasWithState(step, "eid bigint, ess int, n bigint", "n bigint, ess int", "update", GroupStateTimeout.NoTimeout)


def near_openings(incidents: DataFrame, openings: DataFrame, within: str = "1 day") -> DataFrame:
    """Stream-stream join: incidents on an edge up to `within` after a POI opened there (openings: eid, opened, with watermark)."""
    i, o = incidents.alias("i"), openings.alias("o")
    return i.join(o, F.expr(f"i.eid = o.eid and i.ts >= o.opened and i.ts <= o.opened + interval {within}")).select("i.event_id", "i.eid", "i.ts", "o.opened")


def with_edges(incidents: DataFrame, edges: DataFrame) -> DataFrame:
    """Stream-static join: the incident's edge with its ends and level."""
    return incidents.join(edges.select("eid", "u", "w", "ess"), "eid")


def apply_batches(changes: DataFrame, apply: Callable[[DataFrame, int], None], checkpoint: str):
    """Runs apply(batch, number) for each micro-batch; a number that was applied before must be skipped by `apply`."""
    return changes.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).outputMode("update").start()


class VersionedIndex:
    """Applies change batches to a network and its component tree; each batch leaves a version in the shared folder.

    A version holds the network, the tree and, written last, a mark. A new object goes on from the newest marked version in
    its folder, and a batch number whose version is marked is skipped: a batch that is sent again counts once, also after
    the driver was started anew."""

    MARK = "_complete"

    def __init__(self, net, tree, root: str):
        self.net, self.tree, self.root, self.applied = net, tree, root, -1
        spark = net.edges.sparkSession
        known = sorted((int(x.split("=")[1]) for x in names_in(spark, root) if x.startswith("version=")), reverse=True)
        for number in known:
            if exists(spark, f"{self.at(number)}/{self.MARK}"):
                self.load(number)
                break

    def at(self, number: int) -> str:
        return f"{self.root}/version={number}"

    def load(self, number: int) -> None:
        from saferoads.operators.update import load_index

        spark, path = self.net.edges.sparkSession, self.at(number)
        read = lambda name: spark.read.schema(getattr(self.net, name).schema).parquet(f"{path}/net_{name}")
        self.net = replace(self.net, vertices=read("vertices"), edges=read("edges"), pois=read("pois"))
        self.tree, self.applied = load_index(spark, path, self.tree), number

    def __call__(self, changes: DataFrame, number: int) -> None:
        from saferoads.operators.update import comptree_update, save_index

        if number <= self.applied:
            return
        net, tree = comptree_update(self.net, self.tree, changes)
        path = self.at(number)
        save_index(tree, path)
        for name in ("vertices", "edges", "pois"):
            getattr(net, name).write.mode("overwrite").parquet(f"{path}/net_{name}")
        mark(net.edges.sparkSession, f"{path}/{self.MARK}")
        self.load(number)
