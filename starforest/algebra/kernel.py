"""The triple kernel ``w_i = reduce_j f(x_i, a_ij, y_j)`` and its relatives, over entry tables ``(i, j, ...)``.

All plans evaluate f while joining, so nothing of the size of the matrix is ever written; the two-pass
form, which does write it, is kept for comparison. Plans: ``shuffle`` (both vectors joined by key),
``broadcast`` (vectors of a checked size), ``grid`` (entries stay in blocks of a g x g grid, vectors are sent along rows
and columns, partial results reduced over each row) and ``auto`` (the engine's own choice).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from starforest.algebra.monoid import Monoid, Semiring
from starforest.runtime import cut_state

#: Rows of a vector that may be broadcast (two LONGs each).
BROADCAST_ROWS = 1_000_000


def _sized(v: DataFrame, plan: str) -> DataFrame:
    if plan != "broadcast":
        return v.hint("merge") if plan == "shuffle" else v
    if (n := v.count()) > BROADCAST_ROWS:
        raise ValueError(f"a vector of {n} rows is not broadcast; use plan='shuffle' or 'grid'")
    return F.broadcast(v)


def grid_block(v: Column, g: int) -> Column:
    return F.pmod(F.xxhash64(v), F.lit(g)).cast("int")


def grid_partition(entries: DataFrame, g: int) -> DataFrame:
    """Adds the grid block ``(rb, cb)`` and deals entries out by it."""
    return entries.withColumns({"rb": grid_block(F.col("i"), g), "cb": grid_block(F.col("j"), g)}).repartition("rb", "cb")


def triple_kernel(entries: DataFrame, x: DataFrame, y: DataFrame, f: Callable[[Column, Column, Column], Column], monoid: Monoid, *, keep: Column | None = None, row_mask: DataFrame | None = None, plan: str = "auto", grid: int = 4, value: str = "a", reduce_to: str = "row") -> DataFrame:
    """``(v, value)``. ``entries(i, j, value)``, ``x(v, x)``, ``y(v, y)``; ``keep`` drops products of identity value early.

    ``row_mask(v)`` limits the output rows; ``reduce_to='x'`` groups by x_i instead of i (projection to the root
    fused into the kernel).
    """
    if row_mask is not None:
        entries = entries.join(row_mask.select(F.col("v").alias("i")), "i", "left_semi")
    xs, ys = x.select(F.col("v").alias("i"), F.col("x").alias("_x")), y.select(F.col("v").alias("j"), F.col("y").alias("_y"))
    if plan == "grid":
        entries = grid_partition(entries, grid)
        spread = F.explode(F.sequence(F.lit(0), F.lit(grid - 1)))
        xs = xs.withColumns({"rb": grid_block(F.col("i"), grid), "cb": spread})
        ys = ys.withColumns({"cb": grid_block(F.col("j"), grid), "rb": spread})
        joined = entries.join(xs, ["rb", "cb", "i"]).join(ys, ["rb", "cb", "j"])
    else:
        joined = entries.join(_sized(xs, plan), "i").join(_sized(ys, plan), "j")
    if keep is not None:
        joined = joined.where(keep)
    product = joined.select((F.col("i") if reduce_to == "row" else F.col("_x")).alias("v"), f(F.col("_x"), F.col(value), F.col("_y")).alias("_f"))
    return product.groupBy("v").agg(monoid.reduce(F.col("_f")).alias("value"))


def two_pass_kernel(entries: DataFrame, x: DataFrame, y: DataFrame, g: Callable[[Column, Column], Column], f: Callable[[Column, Column], Column], monoid: Monoid, *, keep: Column | None = None, value: str = "a") -> tuple[DataFrame, DataFrame]:
    """The pairwise alternative: writes g(a_ij, y_j) for every entry, then combines with x. Returns (result, written)."""
    written = cut_state(entries.join(y.select(F.col("v").alias("j"), F.col("y").alias("_y")), "j").select("i", "j", g(F.col(value), F.col("_y")).alias("_g")))
    joined = written.join(x.select(F.col("v").alias("i"), F.col("x").alias("_x")), "i")
    if keep is not None:
        joined = joined.where(keep)
    return joined.select(F.col("i").alias("v"), f(F.col("_x"), F.col("_g")).alias("_f")).groupBy("v").agg(monoid.reduce(F.col("_f")).alias("value")), written


def spmv(entries: DataFrame, x: DataFrame, ring: Semiring, *, direction: str = "row", value: str = "a") -> DataFrame:
    """``(v, value)``: x A over a semiring (``row``: y_j = sum_k x_k a_kj) or A x (``col``)."""
    a, b = ("i", "j") if direction == "row" else ("j", "i")
    joined = entries.join(x.select(F.col("v").alias(a), F.col("x").alias("_x")), a)
    return joined.select(F.col(b).alias("v"), ring.mul(F.col("_x"), F.col(value)).alias("_f")).groupBy("v").agg(ring.add.reduce(F.col("_f")).alias("value"))


def spmm(left: DataFrame, right: DataFrame, ring: Semiring, *, value: str = "a") -> DataFrame:
    """``(i, j, value)``: product of two sparse matrices over a semiring."""
    joined = left.select("i", F.col("j").alias("k"), F.col(value).alias("_a")).join(right.select(F.col("i").alias("k"), "j", F.col(value).alias("_b")), "k")
    return joined.groupBy("i", "j").agg(ring.add.reduce(ring.mul(F.col("_a"), F.col("_b"))).alias("value"))


def gather(p: DataFrame, idx: DataFrame) -> DataFrame:
    """``(v, idx, value)``: p at the positions ``idx(v, idx)``; ``p(v, value)``."""
    return idx.join(p.select(F.col("v").alias("idx"), "value"), "idx", "left").select("v", "idx", "value")


def scatter_reduce(df: DataFrame, idx: str, value: str, monoid: Monoid) -> DataFrame:
    """``(v, value)``: values that meet at the same position are reduced."""
    return df.groupBy(F.col(idx).alias("v")).agg(monoid.reduce(F.col(value)).alias("value"))


def sampled_product(entries: DataFrame, x: DataFrame, y: DataFrame, *, value: str = "a") -> DataFrame:
    """``(i, j, value)``: a_ij times the dot product of factor rows, at the stored entries only."""
    dot = F.aggregate(F.zip_with("_x", "_y", lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    joined = entries.join(x.select(F.col("v").alias("i"), F.col("x").alias("_x")), "i").join(y.select(F.col("v").alias("j"), F.col("y").alias("_y")), "j")
    return joined.select("i", "j", (F.col(value) * dot).alias("value"))
