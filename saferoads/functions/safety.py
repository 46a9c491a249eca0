"""Path algebra: s-vectors, their order, scores, and the measures that a search can use.

An s-vector is `array<bigint>`: entry i is the length travelled on roads of level i + 1, the worst first. Spark orders
arrays entry by entry, which is the safety order; the double score is for reports only.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def s_distance(path_edges: DataFrame, s: int) -> DataFrame:
    """path_id, d_s from path_id, len, ess."""
    return path_edges.groupBy("path_id").agg(F.sum(F.when(F.col("ess") == s, F.col("len")).otherwise(0)).cast("bigint").alias("d_s"))


def s_vector(path_edges: DataFrame, smax: int) -> DataFrame:
    """path_id, sd, dist: one pass with a sum for each level."""
    level = [F.sum(F.when(F.col("ess") == s, F.col("len")).otherwise(0)).cast("bigint") for s in range(1, smax + 1)]
    return path_edges.groupBy("path_id").agg(F.array(*level).alias("sd"), F.sum("len").cast("bigint").alias("dist"))


def zeros(smax: int) -> Column:
    return F.array_repeat(F.lit(0).cast("bigint"), smax)


def add_edge(sd: Column | str, ess: Column | str, length: Column | str) -> Column:
    """The s-vector of a path after one more edge."""
    ess, length = _col(ess), _col(length)
    return F.transform(_col(sd), lambda x, i: x + F.when(i == ess - 1, length).otherwise(F.lit(0)).cast("bigint"))


def concat_paths(one: Column | str, other: Column | str) -> Column:
    return F.zip_with(_col(one), _col(other), lambda x, y: x + y)


def path_length(sd: Column | str) -> Column:
    return F.aggregate(_col(sd), F.lit(0).cast("bigint"), lambda s, x: s + x)


def level_weights(base: Column | float, smax: int) -> Column:
    """base^(smax - s) for s = 1..smax."""
    base = base if isinstance(base, Column) else F.lit(float(base))
    return F.array(*(F.pow(base, F.lit(float(smax - s))) for s in range(1, smax + 1)))


def cost(sd: Column | str, base: Column | float, smax: int) -> Column:
    """Weighted length, by Horner's rule: the reciprocal of the score."""
    base = base if isinstance(base, Column) else F.lit(float(base))
    return F.aggregate(_col(sd), F.lit(0.0), lambda s, x: s * base + x.cast("double"))


def exact_cost(sd: Column | str, base: int, smax: int) -> Column:
    """The weighted length as decimal(38,0); base^smax must stay below 10^37."""
    if base**smax >= 10**37:
        raise ValueError("the weights exceed 38 digits; compare s-vectors instead")
    d = _col(sd)
    total = F.lit(0).cast("decimal(38,0)")
    for s in range(1, smax + 1):
        total = (total + d[s - 1].cast("decimal(19,0)") * F.lit(str(base ** (smax - s))).cast("decimal(38,0)")).cast("decimal(38,0)")
    return total


def pss(sd: Column | str, base: Column | float, smax: int) -> Column:
    """Path safety score; infinite for the path without an edge."""
    c = cost(sd, base, smax)
    return F.when(c == 0, F.lit(float("inf"))).otherwise(1 / F.when(c == 0, F.lit(1.0)).otherwise(c))


def pss_concat(one: Column | str, other: Column | str) -> Column:
    """Score of a concatenation from the scores of its parts: reciprocals add."""
    return 1 / (1 / _col(one) + 1 / _col(other))


def safer(one: Column | str, other: Column | str) -> Column:
    return _col(one) < _col(other)


def valid(dist: Column | str, dc: Column | str) -> Column:
    return _col(dist) < _col(dc)


def min_ess(sd: Column | str) -> Column:
    """Level of the worst edge of a path; null without edges."""
    at = F.array_position(F.transform(_col(sd), lambda x: (x > 0).cast("int")), 1)
    return F.when(at > 0, at.cast("int"))


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def pareto(labels: DataFrame, by: tuple[str, ...] = ("qid", "vid")) -> DataFrame:
    """Labels (key, dist, path, ...) that no other of the same group beats or equals in key and dist. One sort per group."""
    before = Window.partitionBy(*by).orderBy("key", "dist", "path").rowsBetween(Window.unboundedPreceding, -1)
    return labels.withColumn("_least", F.min("dist").over(before)).where(F.col("_least").isNull() | (F.col("dist") < F.col("_least"))).drop("_least")


def check_order(labels: DataFrame, smax: int, base: float) -> DataFrame:
    """Pairs of rows (a, b: s-vectors) whose order by s-vector and by cost differ: none where paths are shorter than base."""
    return labels.where((F.col("a") < F.col("b")) & (cost("a", base, smax) >= cost("b", base, smax)))


def check_subpath(steps: DataFrame) -> DataFrame:
    """Steps (before, after: s-vectors) that made a path safer: none are expected."""
    return steps.where(F.col("after") < F.col("before"))


def check_bottleneck(pairs: DataFrame) -> DataFrame:
    """Pairs (a, b) where the worse bottleneck is not the less safe path: none are expected."""
    return pairs.where((min_ess("a") < min_ess("b")) & ~(F.col("a") > F.col("b")))


@dataclass(frozen=True)
class Measure:
    """Keys of labels: arrays whose order is the order of safety, the safest first.

    subpath: a subpath is never less safe. bottleneck: the worst edge decides first (needed by the component tree)."""

    name: str
    subpath: bool = True
    bottleneck: bool = True

    def start(self, smax: int) -> Column:
        return zeros(smax) if self.name == "lex" else F.array(F.lit(0).cast("bigint"))

    def extend(self, key: str, ess: str, length: str, smax: int) -> Column:
        if self.name == "lex":
            return add_edge(key, ess, length)
        if self.name == "min":
            return F.array(F.greatest(F.col(key)[0], (F.lit(smax + 1) - F.col(ess)).cast("bigint")))
        # Scores as probabilities ess / smax: a product is a sum of logarithms, kept in integers.
        return F.array(F.col(key)[0] + F.round(F.log(F.lit(float(smax)) / F.col(ess)) * 1_000_000).cast("bigint"))


LexSafety, MinEss, ProductEss = Measure("lex"), Measure("min"), Measure("product", bottleneck=False)
