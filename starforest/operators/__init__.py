"""Relational operators around the methods: range, interval, as-of, salted and top-k joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from starforest.algebra.kernel import BROADCAST_ROWS


def range_join(left: DataFrame, right: DataFrame, x: str, y: str, delta: float) -> DataFrame:
    """Pairs with ``|x - y| <= delta``: an equi-join on bins of width delta, then the exact test."""
    wide = F.floor(F.col(x) / delta).cast("long")
    a = left.withColumn("_bin", F.explode(F.array(wide - 1, wide, wide + 1)))
    b = right.withColumn("_bin", F.floor(F.col(y) / delta).cast("long"))
    return a.join(b, "_bin").where(F.abs(F.col(x) - F.col(y)) <= delta).drop("_bin")


def interval_join(left: DataFrame, right: DataFrame, keys: list[str], start: str, at: str, length: int) -> DataFrame:
    """Rows of ``right`` with ``start <= at < start + length`` and equal keys: an equi-join on bins, then the exact test."""
    b = F.floor(F.col(start) / length).cast("long")
    a = left.withColumn("_bin", F.explode(F.array(b, b + 1)))
    r = right.withColumn("_bin", F.floor(F.col(at) / length).cast("long"))
    return a.join(r, [*keys, "_bin"]).where((F.col(at) >= F.col(start)) & (F.col(at) < F.col(start) + length)).drop("_bin")


def asof_join(left: DataFrame, right: DataFrame, keys: list[str], at: str, right_at: str, value: str) -> DataFrame:
    """Each row of ``left`` with ``right``'s last ``value`` of equal keys before or at ``at``: a union and a window."""
    a = left.select(*left.columns, F.col(at).alias("_t"), F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    b = right.select(*[F.col(c) if c in keys else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.col(right_at).alias("_t"), F.lit(0).alias("_side"), F.col(value).alias("_v"))
    w = Window.partitionBy(*keys).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(f"last_{value}", F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_t", "_side", "_v")


def small_side_join(left: DataFrame, right: DataFrame, keys: list[str], *, most: int = BROADCAST_ROWS) -> DataFrame:
    """Inner join that broadcasts ``right`` if it has ``most`` rows at most (counted first); beyond, both sides are shuffled.

    A broadcast passes through the driver whole, and no setting of Spark's holds back one that a hint asks for.
    """
    fits = right.select(*keys).limit(most + 1).count() <= most
    return left.join(F.broadcast(right) if fits else right.hint("merge"), keys)


def salted_join(left: DataFrame, right: DataFrame, keys: list[str], salts: int, spread: Column) -> DataFrame:
    """Inner join that deals each key of ``left`` to ``salts`` tasks (``spread``: a column that differs within a key)."""
    a = left.withColumn("_salt", F.pmod(F.xxhash64(spread), F.lit(salts)).cast("int"))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [*keys, "_salt"]).drop("_salt")


def lightest_per_vertex(entries: DataFrame, k: int) -> DataFrame:
    """``(i, j, rank, w)``: the k edges of least rank of each vertex; a hub's edges are thinned in bins first."""
    # Two rankings: within (vertex, bin), which bounds what a hub sends on, then within the vertex.
    first = Window.partitionBy("i", "_bin").orderBy("rank")
    thin = entries.withColumn("_bin", F.pmod(F.xxhash64("j"), F.lit(16))).withColumn("_k", F.row_number().over(first)).where(F.col("_k") <= k)
    return thin.withColumn("_k", F.row_number().over(Window.partitionBy("i").orderBy("rank"))).where(F.col("_k") <= k).select("i", "j", "rank", "w")


def diff_parents(a: DataFrame, b: DataFrame) -> DataFrame:
    """``(v, p, q)``: vertices whose parents differ, or that only one table has."""
    return a.withColumnRenamed("p", "p").join(b.withColumnRenamed("p", "q"), "v", "full").where(~F.col("p").eqNullSafe(F.col("q"))).select("v", "p", "q")
