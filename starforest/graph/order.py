"""Edge tables: one row for each undirected edge, ``lo < hi``, with a rank that is a strict total order.

All comparisons of edges use the order (w, lo, hi). It is strict once parallel edges are merged, so tied
weights cannot close a cycle and the forest is unique. ``rank`` stands for it in one LONG, which keeps
minimum aggregations in hash aggregates.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from starforest.runtime import cut_state


class GraphError(ValueError):
    """An edge or vertex table breaks an invariant."""


def canonical_edges(edges: DataFrame, a: str = "a", b: str = "b", w: str = "w", merge: str = "min") -> DataFrame:
    """``(lo, hi, w)`` without loops; parallel edges keep the smallest weight (or their sum or count)."""
    x, y = F.col(a), F.col(b)
    kept = edges.where(x != y).select(F.least(x, y).alias("lo"), F.greatest(x, y).alias("hi"), F.col(w).alias("w"))
    how = {"min": F.min, "max": F.max, "sum": F.sum}[merge]
    return kept.groupBy("lo", "hi").agg(how("w").alias("w"))


def rank_edges(edges: DataFrame, *, dense: bool = False) -> DataFrame:
    """``(rank, lo, hi, w)``, materialised. Range partitions in sorted order: no global window.

    Ranks ascend with (w, lo, hi); ``dense`` makes them 0, 1, 2, ... at the price of one count for each partition.
    """
    # Ranges are drawn from a pass of their own: edges that are not written before would be made twice.
    ordered = cut_state(edges.select("lo", "hi", "w")).repartitionByRange("w", "lo", "hi").sortWithinPartitions("w", "lo", "hi")
    ranked = cut_state(ordered.select(F.monotonically_increasing_id().alias("rank"), "lo", "hi", "w"))
    if not dense:
        return ranked
    part, place = F.shiftright("rank", 33), F.col("rank").bitwiseAND((1 << 33) - 1)
    sizes = ranked.groupBy(part.alias("part")).agg(F.count("*").alias("n"))
    before = sizes.alias("x").join(sizes.alias("y"), F.col("y.part") < F.col("x.part"), "left").groupBy(F.col("x.part").alias("part")).agg(F.coalesce(F.sum("y.n"), F.lit(0)).alias("offset"))
    return ranked.withColumn("part", part).join(F.broadcast(before), "part").select((F.col("offset") + place).alias("rank"), "lo", "hi", "w")


def directed(edges: DataFrame) -> DataFrame:
    """Both directions ``(i, j, rank[, w])`` of each edge, in one pass over the table."""
    more = [c for c in ("rank", "w") if c in edges.columns]
    both = F.explode(F.array(F.struct(F.col("lo").alias("i"), F.col("hi").alias("j")), F.struct(F.col("hi").alias("i"), F.col("lo").alias("j"))))
    return edges.select(*more, both.alias("e")).select("e.i", "e.j", *more)


def vertices_of(edges: DataFrame, more: DataFrame | None = None) -> DataFrame:
    """``(v)``: endpoints and the vertices of ``more(v)``, isolated ones included."""
    ends = edges.select(F.explode(F.array("lo", "hi")).alias("v"))
    return (ends.union(more.select("v")) if more is not None else ends).distinct()


def validate_graph(edges: DataFrame, vertices: DataFrame | None = None) -> None:
    """Raises :class:`GraphError` for null or NaN weights, loops, wrong order, parallel edges or unknown endpoints."""
    nan = F.isnan("w") if dict(edges.dtypes)["w"] in ("double", "float") else F.lit(False)
    bad = edges.agg(F.count(F.when(F.col("w").isNull() | nan, 1)).alias("weights"), F.count(F.when(F.col("lo").isNull() | F.col("hi").isNull() | (F.col("lo") >= F.col("hi")), 1)).alias("ends"), F.count("*").alias("n"), F.countDistinct("lo", "hi").alias("pairs")).first()
    for what, wrong in (("null or NaN weights", bad.weights), ("loops, null or unordered endpoints", bad.ends), ("parallel edges", bad.n - bad.pairs)):
        if wrong:
            raise GraphError(f"{wrong} rows with {what}")
    if vertices is not None and (lost := vertices_of(edges).join(vertices, "v", "left_anti").count()):
        raise GraphError(f"{lost} endpoints are not in the vertex table")


def mixed(*parts: Column | int) -> Column:
    """A 31-bit integer mixed from integers below 2**31 in plain BIGINT arithmetic (the same in any SQL engine)."""
    h = F.lit(17).cast("long")
    for p in parts:
        p = p.cast("long") if isinstance(p, Column) else F.lit(p).cast("long")
        h = (h * 69_069 + p % 2_147_483_647 + 1) % 2_147_483_647
        h = (h * h + 48_271) % 2_147_483_647  # the square keeps mixes of neighbouring integers from being shifts of each other
    return (h * 16_807 + F.floor(h / 8_191)) % 2_147_483_647


def with_random_weights(edges: DataFrame, seed: int, hi: int = 255) -> DataFrame:
    """Integer weights 1..hi for ``(lo, hi)``: many ties for small ``hi``."""
    return edges.select("lo", "hi", (mixed(F.lit(seed), F.col("lo"), F.col("hi")) % hi + 1).alias("w"))


def induced_subgraph(edges: DataFrame, inside: DataFrame) -> DataFrame:
    """The edges with both ends in ``inside(v)``."""
    v = inside.select("v").distinct()
    return edges.join(v.withColumnRenamed("v", "lo"), "lo", "left_semi").join(v.withColumnRenamed("v", "hi"), "hi", "left_semi").select(*edges.columns)


def filter_edges(edges: DataFrame, *, at_least: int | float | None = None, at_most: int | float | None = None) -> DataFrame:
    """The edges whose weights lie between two bounds (null weights in none)."""
    kept = edges if at_least is None else edges.where(F.col("w") >= at_least)
    return kept if at_most is None else kept.where(F.col("w") <= at_most)


def largest_component(edges: DataFrame, parts: DataFrame) -> DataFrame:
    """The edges of the component of most vertices, of several as large the one with the smallest name; ``parts(v, component)``."""
    top = parts.groupBy("component").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "component").limit(1)
    return induced_subgraph(edges, parts.join(F.broadcast(top), "component", "left_semi").select("v"))


def sample_edges(edges: DataFrame, share: float, *, seed: int = 17) -> DataFrame:
    """About ``share`` of the edges, the same ones in every run and layout: those whose mixed ends fall below it."""
    return edges.where(mixed(F.col("lo"), F.col("hi"), F.lit(seed)) < F.lit(int(share * 2147483647)))
