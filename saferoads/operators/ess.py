"""Edge safety scores from incidents."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def of_kinds(incidents: DataFrame, kinds: tuple[str, ...] | None, column: str = "kind") -> DataFrame:
    """Incidents of the listed kinds; all of them where no kinds are given."""
    return incidents if kinds is None else incidents.where(F.col(column).isin(*kinds))


def crime_counts(edges: DataFrame, incidents: DataFrame, radius: int, cell: int | None = None) -> DataFrame:
    """edges (eid, xu, yu, xw, yw, ...) with n: incidents (x, y) within radius of the segment.

    Incidents of one point are counted before the join; edges go to the grid cells that their widened box touches,
    and the join is on the cell. All tests are in integers.
    """
    cell = cell or max(radius, 10)
    points = incidents.groupBy("x", "y").agg(F.count("*").alias("c")).withColumns({"gx": F.floor(F.col("x") / cell), "gy": F.floor(F.col("y") / cell)})
    span = lambda a, b: F.sequence(F.floor((F.least(a, b) - radius) / cell), F.floor((F.greatest(a, b) + radius) / cell))
    boxes = edges.select("eid", "xu", "yu", "xw", "yw", F.explode(span("xu", "xw")).alias("gx")).select("*", F.explode(span("yu", "yw")).alias("gy"))
    dx, dy, px, py = F.col("xw") - F.col("xu"), F.col("yw") - F.col("yu"), F.col("x") - F.col("xu"), F.col("y") - F.col("yu")
    length2, dot, cross, r2 = dx * dx + dy * dy, px * dx + py * dy, px * dy - py * dx, F.lit(radius * radius)
    end2 = (F.col("x") - F.col("xw")) * (F.col("x") - F.col("xw")) + (F.col("y") - F.col("yw")) * (F.col("y") - F.col("yw"))
    near = F.when(dot <= 0, px * px + py * py <= r2).when(dot >= length2, end2 <= r2).otherwise(cross * cross <= r2 * length2)
    counted = boxes.join(points, ["gx", "gy"]).where(near).groupBy("eid").agg(F.sum("c").alias("n"))
    return edges.join(counted, "eid", "left").withColumn("n", F.coalesce("n", F.lit(0)))


def ess_from_counts(counts: DataFrame, smax: int) -> DataFrame:
    """Counts n as levels 1..smax: equal ranges between least and largest count, most incidents lowest."""
    low, high = counts.agg(F.min("n"), F.max("n")).first()
    if low is None:
        return counts.withColumn("ess", F.lit(smax))
    score = 1 + F.floor((F.col("n") - low) * smax / F.lit(high - low + 1))
    return counts.withColumn("ess", (smax + 1 - score).cast("int"))


def ess_asof(asked: DataFrame, history: DataFrame) -> DataFrame:
    """asked (eid, at) with the level of history (eid, ess, valid_from) that holds then; null before the first.

    Both sides meet in one sorted union by edge, so nothing is joined by range."""
    from pyspark.sql import Window

    cols = ["eid", "at", "ess", "row"]
    a = asked.select("eid", "at", F.lit(None).cast("int").alias("ess"), F.lit(1).alias("row"))
    h = history.select("eid", F.col("valid_from").alias("at"), F.col("ess").cast("int").alias("ess"), F.lit(0).alias("row"))
    last = F.last("ess", ignorenulls=True).over(Window.partitionBy("eid").orderBy("at", "row").rowsBetween(Window.unboundedPreceding, 0))
    return a.select(cols).unionAll(h.select(cols)).withColumn("ess", last).where("row = 1").select("eid", "at", "ess")
