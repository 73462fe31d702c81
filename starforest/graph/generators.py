"""Synthetic graphs: uniform random, recursive-matrix (R-MAT) and small shapes. Deterministic by seed."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from starforest.graph.order import canonical_edges, mixed

#: The usual quadrant probabilities of the recursive matrix, in hundredths.
QUADRANTS = (57, 19, 19, 5)


def uniform_edges(ids: DataFrame, n: int, seed: int = 1, hi: int = 255) -> DataFrame:
    """``(lo, hi, w)``: an edge for each row of ``ids(id)`` between two of n vertices (loops and repeats are dropped)."""
    e = ids.select((mixed(seed, F.col("id"), 1) % n).alias("a"), (mixed(seed, F.col("id"), 2) % n).alias("b"), (mixed(seed, F.col("id"), 3) % hi + 1).alias("w"))
    return canonical_edges(e)


def uniform_graph(spark: SparkSession, n: int, m: int, seed: int = 1, hi: int = 255) -> DataFrame:
    """``(lo, hi, w)``: at most m edges between n vertices."""
    return uniform_edges(spark.range(m), n, seed, hi)


def uniform_percent(spark: SparkSession, n: int, percent: float, seed: int = 1) -> DataFrame:
    """Edge percentage f = 100 m / n**2, as in edge weak scaling."""
    return uniform_graph(spark, n, round(percent * n * n / 100), seed)


def rmat_graph(spark: SparkSession, scale: int, degree: int, seed: int = 1, hi: int = 255, quadrants: tuple[int, int, int, int] = QUADRANTS) -> DataFrame:
    """``(lo, hi, w)``: 2**scale vertices, degree * 2**scale edges before loops and repeats are dropped."""
    return rmat_edges(spark.range(degree << scale), scale, seed, hi, quadrants)


def rmat_edges(ids: DataFrame, scale: int, seed: int = 1, hi: int = 255, quadrants: tuple[int, int, int, int] = QUADRANTS) -> DataFrame:
    """``(lo, hi, w)``: an edge for each row of ``ids(id)`` between two of 2**scale vertices."""
    a = b = F.lit(0).cast("long")
    one, two, three = quadrants[0], sum(quadrants[:2]), sum(quadrants[:3])
    for level in range(scale):
        d = F.col(f"d{level}")
        a = a * 2 + F.when(d >= two, 1).otherwise(0)
        b = b * 2 + F.when(((d >= one) & (d < two)) | (d >= three), 1).otherwise(0)
    digits = [(mixed(seed, F.col("id"), level + 10) % 100).alias(f"d{level}") for level in range(scale)]
    e = ids.select("id", *digits)
    return canonical_edges(e.select(a.alias("a"), b.alias("b"), (mixed(seed, F.col("id"), 3) % hi + 1).alias("w")))


def path_graph(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(max(0, n - 1)).select(F.col("id").alias("lo"), (F.col("id") + 1).alias("hi"), (F.col("id") + 1).alias("w"))


def cycle_graph(spark: SparkSession, n: int, w: int = 1) -> DataFrame:
    e = spark.range(n).select(F.col("id").alias("a"), ((F.col("id") + 1) % n).alias("b"), F.lit(w).cast("long").alias("w"))
    return canonical_edges(e)


def star_graph(spark: SparkSession, leaves: int) -> DataFrame:
    return spark.range(1, leaves + 1).select(F.lit(0).cast("long").alias("lo"), F.col("id").alias("hi"), F.col("id").alias("w"))


def grid_graph(spark: SparkSession, rows: int, cols: int, seed: int = 1) -> DataFrame:
    """Lattice with mixed weights: sparse and of large diameter, like a road network."""
    c = spark.range(rows * cols).select("id", F.expr(f"id div {cols}").alias("r"), (F.col("id") % cols).alias("c"))
    right = c.where(F.col("c") < cols - 1).select(F.col("id").alias("lo"), (F.col("id") + 1).alias("hi"))
    down = c.where(F.col("r") < rows - 1).select(F.col("id").alias("lo"), (F.col("id") + cols).alias("hi"))
    return right.union(down).select("lo", "hi", (mixed(seed, F.col("lo"), F.col("hi")) % 1_000_000 + 1).alias("w"))


def grid_edges(cells: DataFrame, cols: int, seed: int = 1) -> DataFrame:
    """The lattice on the rows of ``cells(id)`` alone, ``cols`` to a line: edges whose two cells are there."""
    right = cells.where(F.col("id") % cols < cols - 1).select(F.col("id").alias("lo"), (F.col("id") + 1).alias("hi"))
    both = right.union(cells.select(F.col("id").alias("lo"), (F.col("id") + cols).alias("hi")))
    there = both.join(cells.select(F.col("id").alias("hi")), "hi", "left_semi")
    return there.select("lo", "hi", (mixed(seed, F.col("lo"), F.col("hi")) % 1_000_000 + 1).alias("w"))


def complete_graph(spark: SparkSession, n: int, seed: int = 1) -> DataFrame:
    e = spark.range(n).select(F.col("id").alias("lo"), F.explode(F.sequence(F.col("id") + 1, F.greatest(F.col("id") + 1, F.lit(n - 1)))).alias("hi")).where(F.col("hi") < n)
    return e.select("lo", "hi", (mixed(seed, F.col("lo"), F.col("hi")) % 1_000_000 + 1).alias("w"))
