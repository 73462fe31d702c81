"""Cost and accuracy measures, cuts and outgoing edges."""

from __future__ import annotations

from math import sqrt

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.baselines import divide_and_merge_forest
from starforest.components.links import link_components
from starforest.graph.order import directed
from starforest.runtime import cut_state


def outgoing_edges(edges: DataFrame, parents: DataFrame) -> DataFrame:
    """``(rank, lo, hi, w, p_lo, p_hi)``: edges between different trees."""
    a, b = (parents.select(F.col("v").alias(s), F.col("p").alias(f"p_{s}")) for s in ("lo", "hi"))
    return edges.join(a, "lo").join(b, "hi").where("p_lo <> p_hi").select("rank", "lo", "hi", "w", "p_lo", "p_hi")


def min_outgoing_per_tree(edges: DataFrame, parents: DataFrame) -> DataFrame:
    """``(root, rank)``."""
    o = outgoing_edges(edges, parents)
    return o.select("rank", F.explode(F.array("p_lo", "p_hi")).alias("root")).groupBy("root").agg(F.min("rank").alias("rank"))


def min_outgoing_per_vertex(edges: DataFrame, parents: DataFrame) -> DataFrame:
    """``(v, rank)``."""
    o = outgoing_edges(edges, parents)
    return o.select("rank", F.explode(F.array("lo", "hi")).alias("v")).groupBy("v").agg(F.min("rank").alias("rank"))


def lightest_outgoing_edge(edges: DataFrame, inside: DataFrame) -> DataFrame:
    """The lightest edge with exactly one end in ``inside(v)`` (one row at most)."""
    s = inside.select("v", F.lit(True).alias("_in"))
    marked = edges.join(s.withColumnsRenamed({"v": "lo", "_in": "a"}), "lo", "left").join(s.withColumnsRenamed({"v": "hi", "_in": "b"}), "hi", "left")
    return marked.where(F.col("a").isNull() != F.col("b").isNull()).orderBy("rank").limit(1).select("rank", "lo", "hi", "w")


def check_cut_property(forest: DataFrame, edges: DataFrame, inside: DataFrame) -> bool:
    """Whether the lightest edge that leaves ``inside(v)``, if any does, belongs to the forest."""
    return lightest_outgoing_edge(edges, inside).join(forest.select("rank"), "rank", "left_anti").count() == 0


def verify_forest(forest: DataFrame, edges: DataFrame, vertices: DataFrame) -> dict[str, bool]:
    """Size, span, acyclicity and optimality of ``forest``. The strict order makes the forest unique, so it is
    optimal if the divide-and-merge method, which shares no step with the loop, keeps the same edges.
    """
    n = vertices.count()
    of_graph, of_forest = link_components(edges, "lo", "hi"), link_components(forest, "lo", "hi")
    trees = n - of_graph.where("node <> component").count()
    same = of_graph.join(of_forest.withColumnRenamed("component", "c2"), "node", "left").where("c2 is null or c2 <> component").limit(1).count() == 0
    size, other = forest.count(), cut_state(divide_and_merge_forest(edges).select("rank"))
    optimal = other.count() == size and not other.join(forest, "rank", "left_anti").limit(1).count()
    return {"count": size == n - trees, "spans": same, "acyclic": size == of_forest.where("node <> component").count(), "optimal": optimal}


def graph_stats(edges: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """One row: n, m, average degree (hundredths), largest degree, edge percentage (parts per million), weights."""
    deg = directed(edges).groupBy("i").agg(F.count("*").alias("d"))
    if vertices is not None:
        deg = vertices.select(F.col("v").alias("i")).join(deg, "i", "left").select("i", F.coalesce("d", F.lit(0)).alias("d"))
    d = deg.agg(F.count("*").alias("n"), F.sum("d").alias("ends"), F.max("d").alias("max_degree"))
    w = edges.agg(F.min("w").alias("min_w"), F.max("w").alias("max_w"), F.countDistinct("w").alias("distinct_w"))
    return d.crossJoin(w).select("n", F.expr("ends div 2").alias("m"), F.expr("ends * 100 div n").alias("degree_x100"), "max_degree", F.expr("cast(ends as decimal(38,0)) * 50000000 div (cast(n as decimal(38,0)) * n)").cast("long").alias("percent_ppm"), "min_w", "max_w", "distinct_w")


def kernel_writes(n: int, m: int, p: int) -> dict[str, float]:
    """Main-memory writes of the kernel on a sqrt(p) x sqrt(p) grid, all at once and pairwise."""
    return {"all_at_once": n / sqrt(p), "pairwise": n / sqrt(p) + 2 * m}


def kernel_communication(n: int, p: int) -> float:
    """Vector entries that a process redistributes, broadcasts and reduces."""
    return 3 * n / sqrt(p)
