"""What a forest is used for: bottlenecks, clusters, rooted trees, repairs, reports."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.components.links import link_components
from starforest.graph.order import directed, vertices_of
from starforest.runtime import cut_observing, cut_state


def root_forest(forest: DataFrame, roots: DataFrame, *, max_levels: int = 100_000) -> DataFrame:
    """``(v, parent, depth, w, rank)``: the forest's edges directed towards ``roots(v)``, level by level."""
    d = cut_state(directed(forest).select("i", "j", "rank", "w"))
    level = cut_state(roots.select("v", F.lit(None).cast("long").alias("parent"), F.lit(0).alias("depth"), F.lit(None).cast("long").alias("w"), F.lit(None).cast("long").alias("rank")))
    out = level
    for k in range(1, max_levels):
        nxt = d.join(level.select(F.col("v").alias("i"), F.col("parent").alias("up")), "i").where("up is null or j <> up").select(F.col("j").alias("v"), F.col("i").alias("parent"), F.lit(k).alias("depth"), "w", "rank")
        level, seen = cut_observing(nxt, n=F.count(F.lit(1)))
        if not seen["n"]:
            return out
        out = cut_state(out.union(level)) if k % 16 == 0 else out.union(level)
    raise RuntimeError("the forest is deeper than max_levels")


def bottleneck_between(forest: DataFrame, pairs: DataFrame) -> DataFrame:
    """``(a, b, rank)``: the heaviest edge between the ends of ``pairs(a, b)`` on the forest; none if not connected.

    Every vertex's path to its root is climbed in both ends together, deeper end first.
    """
    parts = link_components(forest, "lo", "hi")
    tree = cut_state(root_forest(forest, parts.select(F.col("component").alias("v")).distinct()))
    up = tree.select(F.col("v").alias("x"), F.col("parent").alias("px"), F.col("depth").alias("dx"), F.col("rank").alias("rx"))
    cur = cut_state(pairs.select("a", "b", F.col("a").alias("x"), F.col("b").alias("y"), F.lit(-1).cast("long").alias("m")))
    done = None
    while True:
        two = cur.join(up, "x").join(up.withColumnsRenamed({"x": "y", "px": "py", "dx": "dy", "rx": "ry"}), "y")
        goes_x, goes_y = F.col("dx") >= F.col("dy"), F.col("dy") >= F.col("dx")
        nxt = two.select("a", "b", F.when(goes_x, F.col("px")).otherwise(F.col("x")).alias("x"), F.when(goes_y, F.col("py")).otherwise(F.col("y")).alias("y"), F.greatest("m", F.when(goes_x, F.col("rx")), F.when(goes_y, F.col("ry"))).alias("m"))
        nxt = nxt.where("x is not null and y is not null")
        nxt, seen = cut_observing(nxt, n=F.count_if(F.col("x") != F.col("y")))
        met = nxt.where("x = y").select("a", "b", F.col("m").alias("rank"))
        done = met if done is None else done.union(met)
        cur = nxt.where("x <> y")
        if not seen["n"]:
            return done


def single_linkage(forest: DataFrame, vertices: DataFrame, *, threshold: int | float | None = None, k: int | None = None) -> DataFrame:
    """``(v, cluster)``: components of the forest's edges of weight at most ``threshold``, or of all but the heaviest so that ``k``
    clusters are left (as many as the graph has components, if those are more; one for each vertex, if those are fewer)."""
    if (threshold is None) == (k is None):
        raise ValueError("either threshold or k")
    if k is None:
        kept = forest.where(F.col("w") <= threshold)
    else:
        # Trees = vertices - edges: cutting k - trees edges leaves k. The cut is a rank, so ties are cut in the strict order.
        n, m = vertices.count(), forest.count()
        drop = min(m, max(0, k - (n - m)))
        kept = forest
        if drop:
            edge = forest.select("rank").orderBy(F.desc("rank")).limit(drop).agg(F.min("rank")).first()[0]
            kept = forest.where(F.col("rank") < edge)
    parts = link_components(kept, "lo", "hi")
    return vertices.join(parts, F.col("v") == F.col("node"), "left").select("v", F.coalesce("component", "v").alias("cluster"))


def subtree_weights(rooted: DataFrame) -> DataFrame:
    """``(v, size, weight)``: vertices of each vertex's subtree (itself included) and the weight of the edges in it; ``rooted`` of
    :func:`root_forest`. Levels from the deepest up: as many rounds as the trees are deep."""
    top = rooted.agg(F.max("depth")).first()[0]
    if top is None:
        return rooted.select("v", F.lit(1).cast("long").alias("size"), F.lit(0).cast("long").alias("weight"))
    base = cut_state(rooted.select("v", "parent", "depth", F.coalesce("w", F.lit(0)).alias("w")))
    out, below = None, None
    for depth in range(top, -1, -1):
        level = base.where(F.col("depth") == depth)
        if below is not None:
            level = level.join(below, F.col("v") == F.col("up"), "left")
        else:
            level = level.withColumns({"s": F.lit(None).cast("long"), "t": F.lit(None).cast("long")})
        level = cut_state(level.select("v", "parent", "w", (F.coalesce("s", F.lit(0)) + 1).alias("size"), F.coalesce("t", F.lit(0)).alias("weight")))
        below = level.groupBy(F.col("parent").alias("up")).agg(F.sum("size").alias("s"), F.sum(F.col("weight") + F.col("w")).alias("t"))
        done = level.select("v", "size", "weight")
        out = done if out is None else out.union(done)
        if (top - depth) % 16 == 15:
            out = cut_state(out)
    return out


def replace_edge(forest: DataFrame, edges: DataFrame, removed: int) -> DataFrame:
    """``(rank, lo, hi, w)``: the lightest edge that reconnects the forest without rank ``removed`` (no row if none does)."""
    rest = forest.where(F.col("rank") != removed)
    parts = vertices_of(forest).join(link_components(rest, "lo", "hi"), F.col("v") == F.col("node"), "left").select("v", F.coalesce("component", "v").alias("c"))
    a, b = (parts.select(F.col("v").alias(s), F.col("c").alias(f"c_{s}")) for s in ("lo", "hi"))
    return edges.where(F.col("rank") != removed).join(a, "lo").join(b, "hi").where("c_lo <> c_hi").orderBy("rank").limit(1).select("rank", "lo", "hi", "w")


def insert_edge(forest: DataFrame, new: DataFrame) -> DataFrame:
    """``(rank)`` of the one edge that leaves when ``new(rank, lo, hi, w)`` (one row) joins the forest, which may be itself."""
    ends = new.select(F.col("lo").alias("a"), F.col("hi").alias("b"))
    heavy = bottleneck_between(forest, ends).select("rank")
    return heavy.union(new.select("rank")).agg(F.max("rank").alias("rank"))


def network_report(forest: DataFrame, edges: DataFrame) -> DataFrame:
    """One row: cost of the forest against building every link."""
    f, e = forest.agg(F.count("*").alias("links"), F.sum("w").alias("cost")), edges.agg(F.count("*").alias("all_links"), F.sum("w").alias("all_cost"))
    return f.crossJoin(e).select("links", "cost", "all_links", "all_cost", (F.col("all_cost") - F.col("cost")).alias("saving"))


def component_report(forest: DataFrame, edges: DataFrame) -> DataFrame:
    """``(component, vertices, links, cost, all_links, all_cost, saving)``: the report for each tree of the forest."""
    parts = link_components(forest, "lo", "hi")
    side = parts.select(F.col("node").alias("lo"), "component")
    f = forest.join(side, "lo").groupBy("component").agg(F.count("*").alias("links"), F.sum("w").alias("cost"))
    e = edges.join(side, "lo").groupBy("component").agg(F.count("*").alias("all_links"), F.sum("w").alias("all_cost"))
    return f.join(e, "component").select("component", (F.col("links") + 1).alias("vertices"), "links", "cost", "all_links", "all_cost", (F.col("all_cost") - F.col("cost")).alias("saving"))


def tour(forest: DataFrame, edges: DataFrame) -> DataFrame:
    """``(place, v, w)``: a closed tour of a complete metric graph, the vertices in pre-order of its spanning tree; ``w``: the edge to
    the next (null if the graph has none). For graphs of up to a million vertices: one task orders the tree."""
    n = forest.count() + 1
    if n > 1_000_000:
        raise ValueError(f"a tree of {n} vertices is not ordered in one task")
    parts = link_components(forest, "lo", "hi")
    rooted = root_forest(forest, parts.select(F.col("component").alias("v")).distinct())

    def walk(table: pa.Table) -> pa.Table:
        below: dict[int | None, list[int]] = {}
        for v, parent in sorted(zip(table.column("v").to_pylist(), table.column("parent").to_pylist(), strict=True), reverse=True):
            below.setdefault(parent, []).append(v)
        stack, out = list(below.get(None, [])), []
        while stack:
            out.append(stack.pop())
            stack += below.get(out[-1], [])
        return pa.table({"place": pa.array(range(len(out)), pa.int64()), "v": pa.array(out, pa.int64()), "next": pa.array(out[1:] + out[:1], pa.int64())})

    order = rooted.select("v", "parent", F.lit(0).alias("one")).groupBy("one").applyInArrow(walk, "place long, v long, next long")
    pair = order.withColumns({"lo": F.least("v", "next"), "hi": F.greatest("v", "next")})
    return pair.join(edges.select("lo", "hi", "w"), ["lo", "hi"], "left").select("place", "v", "w")


def tour_upper_bound(forest: DataFrame) -> DataFrame:
    """One row: twice the tree's weight, a bound on the shortest closed tour of a metric graph."""
    return forest.agg((F.sum("w") * 2).alias("tour_bound"))
