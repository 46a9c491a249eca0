"""The nearest vectors of every vector, exact, in blocks of pairs.

A block is a group of query rows and of candidate rows that fits a task. A product of matrices tells all its distances up to
a known error; pairs that may be among the nearest by more than that error are summed again as the definition says: the
differences and squares in the type of the vectors, their sum from the first component on in double precision.
Components that are null or missing in either vector add nothing; pairs without a common component have no distance and
come last. Of vectors that are equal in all components only the first ids are candidates, which is all that a query can
take of them, so copies are not paired with each other.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Components of the candidates of a block (its queries have half of them), rows of the parts that are multiplied at once.
BLOCK, QUERY_PART, CANDIDATE_PART = 1 << 19, 256, 2048
#: Parts in which the copies of one vector are first cut to their first ids.
SALT = 16
FOUND = pa.schema([("id", pa.int64()), ("id2", pa.int64()), ("gap", pa.float64()), ("label", pa.int32()), ("l2", pa.int32())])


def matrix(column) -> tuple[np.ndarray, np.ndarray]:
    """Vectors as rows, and which components they have."""
    column = column.combine_chunks()
    flat, sizes = column.flatten(), column.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    there = np.zeros((len(sizes), max(sizes.max(initial=0), 1)), bool)
    there[:] = np.arange(there.shape[1]) < sizes[:, None]
    known = flat.is_valid().to_numpy(zero_copy_only=False)
    values = np.zeros(there.shape, np.float32 if pa.types.is_float32(flat.type) else np.float64)
    values[there] = flat.fill_null(0).to_numpy(zero_copy_only=False)
    there[there] = known
    return values, there


def widened(x: np.ndarray, width: int) -> np.ndarray:
    return x if x.shape[1] == width else np.pad(x, ((0, 0), (0, width - x.shape[1])))


def gaps(a, ha, b, hb, whole: bool) -> np.ndarray:
    """Distances of the rows of a and b, summed in the order of the components."""
    total = np.zeros(len(a))
    for i in range(a.shape[1]):
        x = a[:, i] - b[:, i]
        x = (x * x).astype(np.float64)
        total += x if whole else np.where(ha[:, i] & hb[:, i], x, 0.0)
    return np.sqrt(total)


def nearest_in_block(table: pa.Table, near: int) -> pa.Table:
    """The `near` nearest candidates of every query of one block."""
    asked = table.column("asked").to_numpy(zero_copy_only=False)
    ids, labels = (table.column(c).to_numpy() for c in ("vec_id", "label"))
    values, there = matrix(table.column("embedding"))
    order = np.flatnonzero(~asked)
    order = order[np.argsort(ids[order], kind="stable")]
    b, hb, idb, lb = values[order], there[order], ids[order], labels[order]
    a, ha, ida, la = values[asked], there[asked], ids[asked], labels[asked]
    whole = bool(there.all())
    top = np.finfo(values.dtype).max
    slack = 16 * float(np.finfo(values.dtype).eps)  # of the differences, squares and sums of the definition
    tiny = 4.0 * values.shape[1] * float(np.finfo(values.dtype).smallest_subnormal)
    out = []
    with np.errstate(all="ignore"):
        wide_b, part_b = b.astype(np.float64), hb.astype(np.float64)
        square_b = wide_b * wide_b
        norm_b = square_b.sum(1)
        largest = norm_b[norm_b < 4 * float(top)].max(initial=0.0)  # longer ones are too far from all but vectors of such length
        for at in range(0, len(a), QUERY_PART):
            rows = slice(at, at + QUERY_PART)
            wide_a, part_a = a[rows].astype(np.float64), ha[rows].astype(np.float64)
            norm_a = (wide_a * wide_a).sum(1)
            error = 4e-16 * (values.shape[1] + 4) * (5 * norm_a + largest) + tiny
            error[~np.isfinite(error)] = np.inf
            low, high = np.searchsorted(idb, ida[rows]), np.searchsorted(idb, ida[rows], "right")
            own = [(r, range(x, y)) for r, (x, y) in enumerate(zip(low.tolist(), high.tolist(), strict=True)) if x < y]
            limit, picked = np.full(len(wide_a), np.inf), []
            for start in range(0, len(b), CANDIDATE_PART):
                cut = slice(start, start + CANDIDATE_PART)
                if whole:
                    square = norm_a[:, None] + norm_b[cut] - 2 * (wide_a @ wide_b[cut].T)
                else:
                    square = (wide_a * wide_a) @ part_b[cut].T + part_a @ square_b[cut].T - 2 * (wide_a @ wide_b[cut].T)
                    square[part_a @ part_b[cut].T == 0] = np.inf
                square[~(square < top)] = np.inf  # may be beyond the type of the vectors: told by the definition only
                barred = np.zeros(square.shape, bool) if own else None
                for r, places in own:
                    for j in places:
                        if start <= j < start + CANDIDATE_PART:
                            square[r, j - start], barred[r, j - start] = np.inf, True
                if square.shape[1] >= near:
                    worst = np.partition(square, near - 1, axis=1)[:, near - 1] if start == 0 else None
                    if worst is not None:
                        bound = (worst + error) * (1 + slack) * (1 + slack) + error
                        limit = np.where(bound < top, bound, np.inf)
                taken = square <= limit[:, None]
                if barred is not None:
                    taken &= ~barred
                r, c = np.nonzero(taken)
                picked.append((r + at, c + start))
            r, c = (np.concatenate(x) for x in zip(*picked, strict=True)) if picked else (np.zeros(0, np.int64),) * 2
            gap = np.concatenate([gaps(a[r[i : i + 65536]], ha[r[i : i + 65536]], b[c[i : i + 65536]], hb[c[i : i + 65536]], whole) for i in range(0, len(r), 65536)] or [np.zeros(0)])
            none = np.zeros(len(r), bool) if whole else np.concatenate([~(ha[r[i : i + 65536]] & hb[c[i : i + 65536]]).any(1) for i in range(0, len(r), 65536)] or [np.zeros(0, bool)])
            best = np.lexsort((idb[c], gap, none, r))  # nan comes after every number
            r, c, gap, none = r[best], c[best], gap[best], none[best]
            first = np.searchsorted(r, r)
            kept = np.arange(len(r)) - first < near
            r, c, gap, none = r[kept], c[kept], gap[kept], none[kept]
            out.append(pa.Table.from_arrays([pa.array(ida[r], pa.int64()), pa.array(idb[c], pa.int64()), pa.array(gap, mask=none), pa.array(la[r], pa.int32()), pa.array(lb[c], pa.int32())], schema=FOUND))
    return pa.concat_tables(out) if out else FOUND.empty_table()


def nearest_by_label(vectors: DataFrame, near: int, others: list) -> DataFrame:
    """id, id2, gap, label, l2: for every vec_id of vectors (vec_id, embedding, label) the `near` nearest rows of another id,
    ties to the lesser id. others: columns of a row, the labels whose rows it is a candidate for."""
    rows = vectors.where("vec_id is not null")
    width = rows.agg(F.max(F.size("embedding"))).first()[0]
    most = max(64, BLOCK // max(1, width or 1))
    # A query takes at most `near` rows of equal vectors, and those of its own id are none of them.
    alike = rows.groupBy("label", "embedding", "vec_id").agg(F.count("*").alias("n"))
    for keys in (["label", "embedding", "salt"], ["label", "embedding"]):
        alike = alike.withColumn("salt", F.pmod(F.xxhash64("vec_id"), F.lit(SALT)))
        alike = alike.withColumn("r", F.row_number().over(Window.partitionBy(*keys).orderBy("vec_id"))).where(F.col("r") <= near + 1).drop("r")
    copies = F.explode(F.array_repeat(F.lit(False), F.least(F.col("n"), F.lit(near)).cast("int")))
    candidates = alike.select("vec_id", "embedding", "label", F.explode(F.array(*others)).alias("target"), "n").select("vec_id", "embedding", "label", "target", copies.alias("asked"))
    queries = rows.select("vec_id", "embedding", "label", F.col("label").alias("target"), F.lit(True).alias("asked"))
    sizes = rows.select(F.col("label").alias("target"), F.lit(1).alias("q"), F.lit(0).alias("c")).unionAll(rows.select(F.explode(F.array(*others)).alias("target"), F.lit(0).alias("q"), F.lit(1).alias("c")))
    sizes = sizes.groupBy("target").agg(F.ceil(F.sum("q") * 2 / most).alias("across"), F.ceil(F.sum("c") / most).alias("down")).where("across > 1 or down > 1")
    both = queries.unionByName(candidates).join(F.broadcast(sizes), "target", "left")  # one row for each label of more than a block
    across, down = (F.greatest(F.coalesce(c, F.lit(1)), F.lit(1)) for c in ("across", "down"))
    of = lambda n: F.pmod(F.xxhash64("vec_id", F.lit(7)), n)
    spread = F.when(F.col("asked"), F.transform(F.sequence(F.lit(0).cast("bigint"), down - 1), lambda j: F.struct(of(across).alias("i"), j.alias("j"))))
    spread = spread.otherwise(F.transform(F.sequence(F.lit(0).cast("bigint"), across - 1), lambda i: F.struct(i.alias("i"), of(down).alias("j"))))
    blocks = both.select("vec_id", "embedding", F.col("label").cast("int").alias("label"), "target", "asked", F.explode(spread).alias("b"))
    blocks = blocks.select("vec_id", "embedding", "label", "asked", "target", "b.i", "b.j")
    found = blocks.groupBy("target", "i", "j").applyInArrow(lambda table: nearest_in_block(table, near), "id bigint, id2 bigint, gap double, label int, l2 int")
    order = Window.partitionBy("id").orderBy(F.col("gap").asc_nulls_last(), "id2")
    return found.withColumn("r", F.row_number().over(order)).where(F.col("r") <= near).drop("r")
