"""Operators on embedding tables: exact top-k inner product search and near-duplicate detection.

`top_k`: pivot-table elimination. Inner products become distances by lifting every vector to one sphere of radius R
(the largest norm); the index holds each row's distances to a fixed number of pivots. By the triangle inequality the
largest difference of pivot distances is a lower bound of the distance to a query, hence an upper bound of the score.
Candidates are evaluated in the order of their bounds until no bound reaches the k-th score: the result is exact.

`near_duplicates`: random-hyperplane signs in several tables, exact cosine of the pairs that share a bucket, components.
The number of bits follows the size of the largest label, that of the tables the bits and the wanted recall. Copies of
one vector are one class from the start; only pairs of classes are formed.

Vectors that are null or hold null or non-finite components take no part; neither do zero vectors in `near_duplicates`.
Vectors are compared with vectors of their own length only. Rows are vectors of their own, also where they share a vec_id:
in `near_duplicates` each has its own links, and the component is the least vec_id among the rows reached. Equal scores in
`top_k` go to the smaller vec_id; rows without vec_id take no part. Other columns may have any name. Empty tables give no
rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from saferoads.plans.components import connected_components
from saferoads.llm.blocks import lean
from saferoads.plans.runtime import durable

PIVOTS, SAMPLE, QUERY_BLOCK = 24, 512, 4096


def usable(vector: str) -> Column:
    """Neither null nor with a component that is null, infinite or no number."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.col(vector).isNotNull() & ~bad


def matrix(column) -> np.ndarray:
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(n, -1)


def choose_pivots(sample: np.ndarray, radius: float, count: int) -> np.ndarray:
    """Lifted pivots far from one another: each next one is farthest from those before."""
    lifted = lift(sample, radius)
    chosen = [0]
    gap = np.linalg.norm(lifted - lifted[0], axis=1)
    while len(chosen) < min(count, len(lifted)):
        chosen.append(int(gap.argmax()))
        gap = np.minimum(gap, np.linalg.norm(lifted - lifted[chosen[-1]], axis=1))
    return lifted[chosen]


def lift(rows: np.ndarray, radius: float) -> np.ndarray:
    rest = np.sqrt(np.maximum(radius * radius - np.einsum("ij,ij->i", rows, rows), 0))
    return np.hstack([rows, rest[:, None]])


def distances(rows: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    square = np.einsum("ij,ij->i", rows, rows)[:, None] + np.einsum("ij,ij->i", pivots, pivots)[None, :] - 2 * rows @ pivots.T
    return np.sqrt(np.maximum(square, 0))


def products(rows: np.ndarray, query: np.ndarray, largest: float) -> np.ndarray:
    """Integer inner products; in doubles while they are exact there."""
    if largest * largest * rows.shape[1] < 2**53:
        return (rows @ query).astype(np.int64)
    return rows.astype(np.int64) @ query.astype(np.int64)


def top_k(vectors: DataFrame, is_query: Column, k: int = 5, scale: int = 256, evaluated=None) -> DataFrame:
    """vectors: vec_id, embedding. query_id, rank, vec_id, score for every row that is_query selects. evaluated: a Spark
    accumulator of the inner products that the pivots did not spare. Queries are taken in blocks of a fixed size."""
    spark = vectors.sparkSession
    scaled = F.transform("embedding", lambda x: F.floor(x.cast("double") * scale).cast("double"))
    rows = vectors.where(F.col("vec_id").isNotNull() & usable("embedding") & (F.size("embedding") > 0)).select(F.col("vec_id").cast("bigint").alias("vec_id"), scaled.alias("v"), F.size("embedding").alias("dim"), is_query.alias("asked"))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    largest = F.array_max(F.transform("v", F.abs))
    stats = rows.groupBy("dim").agg(F.max(norm).alias("radius"), F.max(largest).alias("largest"), F.sum(F.col("asked").cast("int")).alias("asked")).collect()
    found = None
    for part in stats:  # one pass for each vector length, usually one
        if not part["asked"]:
            continue
        dim, radius, most = part["dim"], part["radius"] * (1 + 1e-12) + 1e-9, part["largest"]
        same = rows.where(F.col("dim") == dim)
        sample = same.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).select("v").toArrow()
        pivots = choose_pivots(matrix(sample.column("v").combine_chunks()), radius, PIVOTS)
        index = durable(pivot_table(same, pivots, radius))
        asked = index.where("asked").select("vec_id", "v", F.pmod(F.xxhash64("vec_id"), F.lit(-(-part["asked"] // (QUERY_BLOCK // 2)))).alias("block"))
        for block in range(-(-part["asked"] // (QUERY_BLOCK // 2))):
            queries = asked.where(F.col("block") == block).orderBy("vec_id").toArrow()
            if not queries.num_rows:
                continue
            ids, q = queries.column("vec_id").to_numpy(), matrix(queries.column("v").combine_chunks())
            best, sent = search(index, ids, q, distances(np.hstack([q, np.zeros((len(q), 1))]), pivots), radius, most, k, evaluated=evaluated)
            found = durable(best, onto=found)  # one block's queries at a time on the driver and the executors
            sent.destroy()
    if found is None:
        return spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score bigint")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def pivot_table(rows: DataFrame, pivots: np.ndarray, radius: float) -> DataFrame:
    @lean
    def run(batches):
        for batch in batches:
            if batch.num_rows:
                d = distances(lift(matrix(batch.column("v")), radius), pivots)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, d.size + 1, d.shape[1], dtype=np.int32)), pa.array(d.ravel()))
                yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("v"), batch.column("asked"), lists], ["vec_id", "v", "asked", "d"])

    return rows.select("vec_id", "v", "asked").mapInArrow(run, "vec_id bigint, v array<double>, asked boolean, d array<double>")


def search(index: DataFrame, ids: np.ndarray, q: np.ndarray, dq: np.ndarray, radius: float, most: float, k: int, step: int = 256, evaluated=None):
    """The k best rows of every partition for every query of one block, and the broadcast that the rows need."""
    sent = index.sparkSession.sparkContext.broadcast((ids, q, dq))  # at most QUERY_BLOCK queries

    @lean
    def run(batches):
        ids, q, dq = sent.value
        square = np.einsum("ij,ij->i", q, q) + radius * radius
        best, tried = [(np.zeros(0, np.int64), np.zeros(0, np.int64)) for _ in ids], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            own, v, d = batch.column("vec_id").to_numpy(), matrix(batch.column("v")), matrix(batch.column("d"))
            for i, query in enumerate(q):
                low = np.zeros(len(v))
                for p in range(d.shape[1]):
                    np.maximum(low, np.abs(d[:, p] - dq[i, p]), out=low)
                high = (square[i] - low * low) / 2
                high += 1e-6 * square[i] + 1e-6
                score, name = best[i]
                order = np.argsort(-high)
                for at in range(0, len(order), step):
                    some = order[at : at + step]
                    if len(score) == k and high[some[0]] < score[-1]:
                        break
                    some = some[own[some] != ids[i]]
                    tried += len(some)
                    score, name = np.concatenate([score, products(v[some], query, most)]), np.concatenate([name, own[some]])
                    top = np.lexsort((name, -score))[:k]
                    score, name = score[top], name[top]
                best[i] = (score, name)
        if evaluated is not None:
            evaluated.add(tried)
        counts = [len(s) for s, _ in best]
        if sum(counts):
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.repeat(ids, counts)), pa.array(np.concatenate([n for _, n in best])), pa.array(np.concatenate([s for s, _ in best]))],
                ["query_id", "vec_id", "score"],
            )

    return index.select("vec_id", "v", "d").mapInArrow(run, "query_id bigint, vec_id bigint, score bigint"), sent


def tables_for(bits: int, cosine: float, miss: float) -> int:
    """Tables needed so that a pair at the threshold is missed with probability `miss` at most."""
    same = (1 - math.acos(cosine) / math.pi) ** bits
    return math.ceil(math.log(miss) / math.log1p(-same))


def near_duplicates(vectors: DataFrame, cosine: float = 0.93, miss: float = 1e-4, seed: int = 17) -> DataFrame:
    """vectors: vec_id, embedding, label. vec_id, n_links, component_id, kept for every row."""
    nonzero = F.exists("embedding", lambda x: x != 0)
    rows = vectors.select(F.col("vec_id").cast("bigint").alias("vec_id"), "embedding", F.col("label").cast("string").alias("label"))
    takes_part = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & usable("embedding") & nonzero
    keyed = rows.withColumns({"h1": F.xxhash64("label", "embedding"), "h2": F.xxhash64(F.reverse("embedding"), "label"), "part": F.coalesce(takes_part, F.lit(False))})
    classes = keyed.where("part").groupBy("h1", "h2").agg(F.min("vec_id").alias("least"), F.count("*").alias("size"), F.first("label").alias("label"), F.first("embedding").alias("embedding"))
    classes = durable(classes.withColumn("rep", F.monotonically_increasing_id()))  # vec_id may stand for several vectors
    largest = classes.groupBy("label").count().agg(F.max("count")).first()[0] or 1
    bits = min(max(math.ceil(math.log2(largest)) + 3, 8), 24)
    hashed = hyperplane_buckets(classes, bits, tables_for(bits, cosine, miss), seed)
    buckets = durable(hashed)
    pairs = buckets.alias("x").join(buckets.alias("y"), "key").where("x.rep < y.rep").selectExpr("x.rep a", "y.rep b").distinct()
    one = classes.selectExpr("rep a", "size sa", "label la", "embedding ea")
    other = classes.selectExpr("rep b", "size sb", "label lb", "embedding eb")
    close = pairs.join(one, "a").join(other, "b").where("la = lb and size(ea) = size(eb)")
    links = durable(cosine_links(close, cosine))
    per_class = links.selectExpr("a rep", "sb n").unionAll(links.selectExpr("b rep", "sa n")).groupBy("rep").agg(F.sum("n").alias("n"))
    joined = durable(connected_components(links).withColumnRenamed("id", "rep").join(classes.select("rep", "least"), "rep"))
    labels = joined.select("rep", "comp").join(joined.groupBy("comp").agg(F.min("least").alias("component")), "comp").drop("comp")
    known = classes.select("h1", "h2", "rep", "least", "size").join(per_class, "rep", "left").join(labels, "rep", "left")
    out = keyed.select("vec_id", "h1", "h2", "part").join(known.withColumn("part", F.lit(True)), ["h1", "h2", "part"], "left")
    component = F.coalesce("component", "least", "vec_id")
    return out.select("vec_id", (F.coalesce(F.col("size") - 1, F.lit(0)) + F.coalesce("n", F.lit(0))).cast("bigint").alias("n_links"), component.alias("component_id"), (F.col("vec_id") == component).alias("kept"))


def hyperplane_buckets(classes: DataFrame, bits: int, tables: int, seed: int) -> DataFrame:
    """(key, rep): a key for each table, from the signs of `bits` projections, the label and the length."""

    @lean
    def run(batches):
        planes: dict[int, np.ndarray] = {}
        for batch in batches:
            sizes = np.array([len(x) for x in batch.column("embedding")])
            for dim in np.unique(sizes):
                at = np.flatnonzero(sizes == dim)
                some = batch.take(pa.array(at))
                if dim not in planes:
                    planes[dim] = np.random.default_rng(seed).normal(size=(dim, tables * bits))
                v = matrix(some.column("embedding"))
                v /= np.linalg.norm(v, axis=1, keepdims=True)
                for start in range(0, len(at), 2048):
                    signs = (v[start : start + 2048] @ planes[dim] >= 0).reshape(-1, tables, bits)
                    code = (signs * (np.int64(1) << np.arange(bits))).sum(2)
                    key = (code * 4096 + np.arange(tables)) * 65536 + dim
                    n = len(key)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(key.ravel()), pa.array(np.repeat(some.column("label").to_numpy(zero_copy_only=False)[start : start + n], tables)), pa.array(np.repeat(some.column("rep").to_numpy()[start : start + n], tables))],
                        ["code", "label", "rep"],
                    )

    coded = classes.select("rep", "label", "embedding").mapInArrow(run, "code bigint, label string, rep bigint")
    return coded.select(F.xxhash64("code", "label").alias("key"), "rep")


def cosine_links(pairs: DataFrame, cosine: float) -> DataFrame:
    """a, b, sa, sb, ea, eb -> (a, b, sa, sb) of the pairs that reach the cosine, in double precision."""

    @lean
    def run(batches):
        for batch in batches:
            if batch.num_rows:
                keep = np.empty(batch.num_rows, bool)
                sizes = np.array([len(x) for x in batch.column("ea")])
                for dim in np.unique(sizes):
                    at = np.flatnonzero(sizes == dim)
                    x, y = (matrix(batch.column(c).take(pa.array(at))) for c in ("ea", "eb"))
                    dot = np.einsum("ij,ij->i", x, y)
                    keep[at] = dot / (np.sqrt(np.einsum("ij,ij->i", x, x)) * np.sqrt(np.einsum("ij,ij->i", y, y))) >= cosine
                yield batch.select(["a", "b", "sa", "sb"]).filter(pa.array(keep))

    return pairs.select("a", "b", "sa", "sb", "ea", "eb").mapInArrow(run, "a bigint, b bigint, sa bigint, sb bigint")
