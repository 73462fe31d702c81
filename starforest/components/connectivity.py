"""Connected components by conditional and unconditional star hooking on any edge."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.forest import shortcut as sc
from starforest.forest import steps
from starforest.graph.order import directed, vertices_of
from starforest.runtime import cut_state


def _entries(edges: DataFrame) -> DataFrame:
    return directed(edges.select("lo", "hi"))


def min_neighbour_parent(edges: DataFrame, flags: DataFrame) -> DataFrame:
    """``(v, h)``: for each star member the smallest parent among its neighbours."""
    far = flags.select(F.col("v").alias("j"), F.col("p").alias("h"))
    members = flags.where("is_star").select(F.col("v").alias("i"))
    return _entries(edges).join(members, "i", "left_semi").join(far, "j").groupBy(F.col("i").alias("v")).agg(F.min("h").alias("h"))


def conditional_hook(flags: DataFrame, low: DataFrame) -> DataFrame:
    """``(root, parent)``: roots that some member's neighbour would give a smaller parent."""
    return low.join(flags.select("v", "p"), "v").where("h < p").groupBy(F.col("p").alias("root")).agg(F.min("h").alias("parent"))


def unconditional_hook(flags: DataFrame, low: DataFrame, stagnant: DataFrame) -> DataFrame:
    """``(root, parent)`` without the guard, for ``stagnant(root)`` stars only: those that neither hooked nor were hooked onto."""
    own = low.join(flags.select("v", "p"), "v").where("h <> p").join(stagnant.select(F.col("root").alias("p")), "p", "left_semi")
    return own.groupBy(F.col("p").alias("root")).agg(F.min("h").alias("parent"))


def connected_components(edges: DataFrame, vertices: DataFrame | None = None, *, hooking: str = "both", shortcut: str = "full", max_iterations: int = 10_000) -> DataFrame:
    """``(v, component)``, named by the smallest member. ``hooking``: ``both`` or ``conditional`` only."""
    e = edges.select("lo", "hi")
    parents = cut_state(steps.initial_parents(vertices_of(e, vertices)))
    for _ in range(max_iterations):
        stepwise = shortcut == "step"
        flags = cut_state(steps.star_flags(parents)) if stepwise else steps.all_stars(parents)
        first = cut_state(conditional_hook(flags, min_neighbour_parent(e, flags)))
        hooked = steps.hook(parents, first)
        moved = first.count()
        if hooking == "both":
            # Stars that took no part: not a root that hooked, nor a tree that was hooked onto. Their members keep
            # their parents, so flags still hold for them.
            hooked = cut_state(hooked)
            busy = first.select(F.col("root").alias("v")).union(first.select(F.col("parent").alias("v"))).join(hooked.select("v", "p"), "v").select(F.explode(F.array("v", "p")).alias("root")).distinct()
            idle = flags.where("is_star and v = p").select(F.col("v").alias("root")).join(busy, "root", "left_anti")
            now = hooked.join(flags.select("v", "is_star"), "v")
            second = cut_state(unconditional_hook(now.select("v", "p", "is_star"), min_neighbour_parent(e, now), idle))
            moved += second.count()
            hooked = steps.hook(hooked, second)
        if stepwise:
            nxt = cut_state(sc.shortcut_step(hooked))
            moved += nxt.join(parents.select("v", F.col("p").alias("o")), "v").where("p <> o").limit(1).count()
            parents = nxt
        else:
            parents = cut_state(sc.shortcut_queried(cut_state(hooked))[0])
        if not moved:
            break
    low = parents.groupBy("p").agg(F.min("v").alias("component"))
    return parents.join(low, "p").select("v", "component")


def any_spanning_forest(edges: DataFrame, vertices: DataFrame | None = None, *, max_iterations: int = 200) -> DataFrame:
    """``(lo, hi)``: some spanning forest, whatever the weights. Every star with a neighbour of smaller name hooks and
    notes the edge; names fall along hooks, so no cycle can close, and no star but local minima is left over.
    """
    e = edges.select("lo", "hi")
    parents = cut_state(steps.initial_parents(vertices_of(e, vertices)))
    found = None
    for _ in range(max_iterations):
        a, b = (parents.select(F.col("v").alias(s), F.col("p").alias(f"p_{s}")) for s in ("lo", "hi"))
        across = e.join(a, "lo").join(b, "hi").where("p_lo <> p_hi")
        low = across.groupBy(F.greatest("p_lo", "p_hi").alias("root")).agg(F.min(F.struct(F.least("p_lo", "p_hi").alias("parent"), "lo", "hi")).alias("m"))
        hooks = cut_state(low.select("root", "m.parent", "m.lo", "m.hi"))
        if not hooks.limit(1).count():
            return hooks.select("lo", "hi") if found is None else found
        found = hooks.select("lo", "hi") if found is None else found.union(hooks.select("lo", "hi"))
        parents = cut_state(sc.shortcut_queried(cut_state(steps.hook(parents, hooks.select("root", "parent"))))[0])
    raise RuntimeError(f"no forest within {max_iterations} iterations")
