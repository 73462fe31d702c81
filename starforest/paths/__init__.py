"""Single-source shortest paths by products with the matrix over (min, +)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.algebra.kernel import spmv
from starforest.algebra.monoid import MIN_PLUS
from starforest.graph.order import directed
from starforest.runtime import cut_state


def tense_edges(edges: DataFrame, dist: DataFrame) -> DataFrame:
    """``(i, j, w)``: directed edges that would improve a distance."""
    d = directed(edges).select("i", "j", "w").join(dist.select(F.col("v").alias("i"), F.col("dist").alias("di")), "i")
    return d.join(dist.select(F.col("v").alias("j"), F.col("dist").alias("dj")), "j", "left").where("dj is null or dj > di + w").select("i", "j", "w")


def bellman_ford(edges: DataFrame, source: int, *, max_hops: int | None = None, frontier: bool = False, n: int | None = None) -> DataFrame:
    """``(v, dist, hops)``: shortest distances from ``source`` (over at most ``max_hops`` edges), hops being the round that set them.

    No row means unreachable. With ``frontier`` only vertices that changed are multiplied. Raises if distances
    still fall after n rounds (a negative cycle; ``n`` defaults to counting the vertices).
    """
    spark = edges.sparkSession
    entries = directed(edges).select("i", "j", F.col("w").alias("a"))
    dist = spark.createDataFrame([(source, 0, 0)], "v long, dist long, hops int")
    new = dist
    limit = max_hops if max_hops is not None else 1 << 30
    k = 0
    while k < limit:
        k += 1
        if max_hops is None:
            # The n-th round may still run, but must not change anything.
            n = n or entries.select(F.col("i")).distinct().count()
            if k > n:
                raise ValueError("distances keep falling: there is a negative cycle")
        start = new if frontier else dist
        step = spmv(entries, start.select("v", F.col("dist").alias("x")), MIN_PLUS).select("v", F.col("value").alias("_d"))
        # A vertex keeps its own distance: the diagonal of the matrix is not stored.
        nxt = cut_state(dist.join(step, "v", "full").select("v", F.least("dist", "_d").alias("dist"), F.when(F.col("dist").isNull() | (F.col("_d") < F.col("dist")), k).otherwise(F.col("hops")).alias("hops")))
        new = nxt.where(F.col("hops") == k)
        dist = nxt
        if not new.limit(1).count():
            break
    return dist


def has_negative_cycle(edges: DataFrame, source: int) -> bool:
    """Whether distances from ``source`` fall for ever: on an undirected graph, whether it reaches an edge of negative weight."""
    try:
        bellman_ford(edges, source, frontier=True)
    except ValueError:
        return True
    return False
