"""Road networks from the given tables: integers only, so any engine derives the same network."""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from saferoads.operators.ess import crime_counts, ess_from_counts
from saferoads.plans.runtime import read_table

#: Multipliers of the samples of vertices.
POI_MULTIPLIER, QUERY_MULTIPLIER, QUERY_SHIFT, SAMPLE_MODULUS = 611953, 514229, 77, 1000003


@dataclass(frozen=True)
class Network:
    """vertices (vid, x, y), edges (eid, u, w, len, ess) with u < w, pois (poi), levels 1..smax."""

    vertices: DataFrame
    edges: DataFrame
    pois: DataFrame
    smax: int

    @property
    def arcs(self) -> DataFrame:
        """Edges in both directions: src, dst, len, ess, eid."""
        return self.edges.select(F.explode(F.array(F.struct(F.col("u").alias("src"), F.col("w").alias("dst")), F.struct(F.col("w").alias("src"), F.col("u").alias("dst")))).alias("a"), "len", "ess", "eid").select("a.src", "a.dst", "len", "ess", "eid")

    def with_weight(self, column: Column) -> Network:
        """Another weight of the edges: travel time, fuel."""
        return replace(self, edges=self.edges.withColumn("len", column.cast("bigint")))

    def for_key(self, key: str) -> Network:
        """The level of one key (daytime, kind of crime) of edges with a column ess_by map<string,int>."""
        return replace(self, edges=self.edges.withColumn("ess", F.col("ess_by")[key]))


def scale_weights(edges: DataFrame) -> DataFrame:
    """Weights divided by the least and rounded up, so that each is an integer of at least 1."""
    least = edges.agg(F.min("len")).first()[0]
    return edges.withColumn("len", F.ceil(F.col("len") / F.lit(least)).cast("bigint")) if least else edges


def _sample(vertices: DataFrame, multiplier: int, shift: int, n: int, bands: int = 1000) -> DataFrame:
    """The n vertices least in a hash order. Counts of `bands` ranges of the order tell the range that holds the n-th; only
    that one is sorted, all before it are taken as they are."""
    rows = vertices.select("vid", ((F.col("vid") * multiplier + shift) % SAMPLE_MODULUS).alias("o")).withColumn("band", F.floor(F.col("o") * bands / SAMPLE_MODULUS))
    taken = 0
    for band, size in rows.groupBy("band").count().orderBy("band").collect():  # at most `bands` rows
        if taken + size >= n:
            edge = rows.where(F.col("band") == band).orderBy("o", "vid").limit(n - taken)
            return rows.where(F.col("band") < band).unionAll(edge).drop("band")
        taken += size
    return rows.drop("band")


def sample_pois(vertices: DataFrame, rho: float, n: int) -> DataFrame:
    return _sample(vertices, POI_MULTIPLIER, 0, max(1, round(rho * n))).select(F.col("vid").alias("poi"))


def sample_queries(net: Network, k: int, dc: float, n: int = 100) -> DataFrame:
    """qid, src, k, dc: the first vertices of a hash order."""
    from pyspark.sql import Window

    rows = _sample(net.vertices, QUERY_MULTIPLIER, QUERY_SHIFT, n)
    numbered = rows.withColumn("qid", F.row_number().over(Window.orderBy("o", "vid")).cast("bigint") - 1)
    return numbered.select("qid", F.col("vid").alias("src"), F.lit(k).alias("k"), F.lit(float(dc)).alias("dc"))


def lattice_vertices(part: DataFrame) -> tuple[DataFrame, int, int]:
    n = part.count()
    width = int(n**0.5)
    vid = F.col("p_partkey")
    return part.select(vid.alias("vid"), (vid % width * 10).alias("x"), (F.floor(vid / width) * 10).cast("bigint").alias("y"), "p_size"), n, width


def lattice_edges(vertices: DataFrame, width: int) -> DataFrame:
    """eid, u, w, len and the ends' coordinates; right and down neighbours, some left out."""
    one = vertices.select(F.col("vid").alias("u"), F.col("x").alias("xu"), F.col("y").alias("yu"), F.col("p_size").alias("su"))
    sides = []
    for step, gap, factor, odd in ((1, 0, 3, 0), (width, 1, 7, 1)):
        other = vertices.select((F.col("vid") - step).alias("u"), F.col("vid").alias("w"), F.col("x").alias("xw"), F.col("y").alias("yw"), F.col("p_size").alias("sw"))
        keep = ((F.col("su") + F.col("sw")) % 8 != gap) & ((F.col("u") % width != width - 1) if step == 1 else F.lit(True))
        sides.append(one.join(other, "u").where(keep).select((F.col("u") * 2 + odd).alias("eid"), "u", "w", (10 + (F.col("su") + factor * F.col("sw")) % 11).cast("bigint").alias("len"), "xu", "yu", "xw", "yw"))
    return sides[0].unionAll(sides[1])


def lattice_incidents(lineitem: DataFrame, width: int, clustered: bool = False) -> DataFrame:
    rows = lineitem.where("l_returnflag = 'R'")
    cx, cy = F.col("l_partkey") % width, F.floor(F.col("l_partkey") / width)
    if clustered:
        rows = rows.where((F.col("l_orderkey") * 31 + F.col("l_linenumber")) % 10 < (F.floor(cx / 8) * 3 + F.floor(cy / 8) * 7) % 10 + 1)
    return rows.select((cx * 10 + F.col("l_suppkey") % 10).alias("x"), (cy * 10 + F.col("l_orderkey") % 10).cast("bigint").alias("y"))


def lattice_counts(spark: SparkSession, sf_dir: str, radius: int = 10, clustered: bool = False) -> tuple[DataFrame, DataFrame, int]:
    """Vertices, edges with their incidents (eid, u, w, len, n), number of vertices: what networks of any levels and POIs share."""
    vertices, n, width = lattice_vertices(read_table(spark, sf_dir, "part"))
    counts = crime_counts(lattice_edges(vertices, width), lattice_incidents(read_table(spark, sf_dir, "lineitem"), width, clustered), radius)
    return vertices.select("vid", "x", "y"), counts.select("eid", "u", "w", "len", "n"), n


def lattice_network(spark: SparkSession, sf_dir: str, smax: int = 10, radius: int = 10, rho: float = 0.01, clustered: bool = False, counted: tuple | None = None) -> Network:
    """counted: what lattice_counts gives, where it is known."""
    vertices, counts, n = counted or lattice_counts(spark, sf_dir, radius, clustered)
    scored = ess_from_counts(counts, smax).select("eid", "u", "w", "len", "ess")
    return Network(vertices, scored, sample_pois(vertices, rho, n), smax)


def zone_network(spark: SparkSession, sf_dir: str, rho: float = 0.1, unsafe: tuple[int, ...] = (0, 2)) -> Network:
    """Two levels: edges with an end in a zone whose region is unsafe have level 1, others 2."""
    vertices, n, width = lattice_vertices(read_table(spark, sf_dir, "part"))
    zones = read_table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("bigint").alias("zone"), F.col("n_regionkey").isin(*unsafe).alias("bad"))
    flagged = vertices.withColumn("zone", F.col("vid") % 25).join(zones, "zone")
    edges = lattice_edges(vertices, width)
    for end in ("u", "w"):
        edges = edges.join(flagged.select(F.col("vid").alias(end), F.col("bad").alias(f"bad_{end}")), end)
    edges = edges.withColumn("ess", F.when(F.col("bad_u") | F.col("bad_w"), 1).otherwise(2))
    return Network(vertices.select("vid", "x", "y"), edges.select("eid", "u", "w", "len", "ess"), sample_pois(vertices, rho, n), 2)


def daytime_network(spark: SparkSession, sf_dir: str, smax: int = 5, rho: float = 0.1) -> Network:
    """Levels by daytime from weighted error events at the edges' ends: ess_by has the keys day and night."""
    vertices, n, width = lattice_vertices(read_table(spark, sf_dir, "part"))
    hour = F.hour("ts")
    weight = F.coalesce(F.get_json_object("props", "$.k").cast("bigint"), F.lit(1))
    events = read_table(spark, sf_dir, "events").where("event_type = 'error'").select((F.col("event_id") * POI_MULTIPLIER % n).alias("vid"), F.when((hour >= 6) & (hour < 18), "day").otherwise("night").alias("key"), weight.alias("weight"))
    at = events.groupBy("vid").pivot("key", ["day", "night"]).agg(F.sum("weight"))
    edges = lattice_edges(vertices, width).select("eid", "u", "w", "len")
    for end in ("u", "w"):
        edges = edges.join(at.select(F.col("vid").alias(end), F.coalesce("day", F.lit(0)).alias(f"day_{end}"), F.coalesce("night", F.lit(0)).alias(f"night_{end}")), end, "left")
    scored = edges
    for key in ("day", "night"):
        counted = scored.withColumn("n", F.coalesce(F.col(f"{key}_u"), F.lit(0)) + F.coalesce(F.col(f"{key}_w"), F.lit(0)))
        scored = ess_from_counts(counted, smax).withColumnRenamed("ess", f"ess_{key}").drop("n")
    by = F.create_map(F.lit("day"), F.col("ess_day"), F.lit("night"), F.col("ess_night"))
    scored = scored.withColumns({"ess_by": by, "ess": F.col("ess_day")}).select("eid", "u", "w", "len", "ess", "ess_by")
    return Network(vertices.select("vid", "x", "y"), scored, sample_pois(vertices, rho, n), smax)


def trade_network(spark: SparkSession, sf_dir: str, smax: int = 5, rho: float = 0.1) -> Network:
    """Customers (2 * key) and suppliers (2 * key + 1), an edge for each pair that traded: hubs, no coordinates."""
    lines = read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_returnflag")
    orders = read_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    pairs = lines.join(orders, "l_orderkey").groupBy("o_custkey", "l_suppkey").agg(F.count("*").alias("n"), F.sum((F.col("l_returnflag") == "R").cast("int")).alias("back"))
    a, b = F.col("o_custkey") * 2, F.col("l_suppkey") * 2 + 1
    edges = pairs.select(F.least(a, b).alias("u"), F.greatest(a, b).alias("w"), (1 + F.col("n") % 5).alias("len"), (smax - F.floor(F.col("back") * (smax - 1) / F.col("n"))).cast("int").alias("ess"))
    edges = edges.withColumn("eid", F.col("u") * 4294967296 + F.col("w"))
    vertices = edges.select(F.explode(F.array("u", "w")).alias("vid")).distinct().withColumns({"x": F.lit(None).cast("bigint"), "y": F.lit(None).cast("bigint")})
    return Network(vertices, edges.select("eid", "u", "w", "len", "ess"), sample_pois(vertices, rho, vertices.count()), smax)


def proximity_network(spark: SparkSession, sf_dir: str, smax: int = 5, near: int = 4, rho: float = 0.1) -> Network:
    """Vectors joined to their nearest ones of the same label or of the next label, by squared distance."""
    from saferoads.operators.nearest import nearest_by_label

    v = read_table(spark, sf_dir, "embeddings").where("embedding is not null and label is not null").select("vec_id", "embedding", "label")
    best = nearest_by_label(v, near, [F.col("label"), (F.col("label") + 9) % 10]).withColumnRenamed("id", "vec_id")
    edges = best.select(F.least("vec_id", "id2").alias("u"), F.greatest("vec_id", "id2").alias("w"), (1 + F.ceil(F.col("gap") * 100)).cast("bigint").alias("len"), F.when(F.col("label") == F.col("l2"), smax).otherwise(1 + (F.col("label") + F.col("l2")) % (smax - 1)).cast("int").alias("ess"))
    edges = edges.groupBy("u", "w").agg(F.min("len").alias("len"), F.max("ess").alias("ess")).withColumn("eid", F.col("u") * 4294967296 + F.col("w"))
    vertices = v.select(F.col("vec_id").alias("vid")).withColumns({"x": F.lit(None).cast("bigint"), "y": F.lit(None).cast("bigint")})
    return Network(vertices, edges.select("eid", "u", "w", "len", "ess"), sample_pois(vertices, rho, v.count()), smax)


def read_network(spark: SparkSession, path: str, fmt: str = "parquet", smax: int = 10, **options) -> Network:
    """An edge list (u, w, len, ess) in CSV, JSON, Parquet or ORC; a column poi marks edges whose first end is one."""
    schema = "u bigint, w bigint, len bigint, ess int, poi boolean"
    reader = spark.read.options(**options)
    raw = (reader.schema(schema) if fmt in ("csv", "json") else reader).format(fmt).load(path)
    u, w = F.least("u", "w"), F.greatest("u", "w")
    edges = raw.where("u <> w and len >= 1").select(u.alias("u"), w.alias("w"), "len", "ess").distinct().withColumn("eid", F.xxhash64("u", "w", "len", "ess"))
    pois = raw.where("poi").select(F.col("u").alias("poi")).distinct() if "poi" in raw.columns else raw.select(F.col("u").alias("poi")).limit(0)
    vertices = reduce(DataFrame.unionAll, [edges.select(F.col(c).alias("vid")) for c in ("u", "w")]).distinct()
    return Network(vertices.withColumns({"x": F.lit(None).cast("bigint"), "y": F.lit(None).cast("bigint")}), edges.select("eid", "u", "w", "len", "ess"), pois, smax)
