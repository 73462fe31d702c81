"""Shortcuts: ways to flatten the parent forest.

``step`` replaces each parent by the grandparent once. The full forms end with stars: ``queried`` asks the parent
table for each distinct parent, round after round; ``prefetched`` closes the small map of changed roots first and
applies it in one join (broadcast if its size allows, else shuffled).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.algebra.kernel import BROADCAST_ROWS
from starforest.forest.steps import grandparents, is_star_forest
from starforest.runtime import cut_observing, cut_state

#: Fixed value: changed roots beyond which the thresholded form does not prefetch (20 MB at 16 bytes).
THRESHOLD = 1_310_000
ENTRY_BYTES = 16


def shortcut_step(parents: DataFrame, flags: DataFrame | None = None) -> DataFrame:
    """Every vertex takes its grandparent (for star members, with ``flags``, that is the parent they keep)."""
    out = grandparents(parents).select("v", F.col("g").alias("p"))
    if flags is None:
        return out
    return out.join(flags.select("v", F.col("p").alias("_p"), "is_star"), "v").select("v", F.when(F.col("is_star"), F.col("_p")).otherwise(F.col("p")).alias("p"))


def shortcut_queried(parents: DataFrame, *, merge: bool = True, max_rounds: int = 64) -> tuple[DataFrame, int]:
    """Star forest and the number of sub-iterations that changed it.

    Only vertices that may still move travel; with ``merge`` each distinct parent is asked for once.
    """
    cur, done, rounds = parents, None, 0
    for _ in range(max_rounds):
        ask = cur.select("p").distinct() if merge else cur.select("p")
        table = parents if done is None else done.union(cur)
        answer = ask.join(table.select(F.col("v").alias("p"), F.col("p").alias("g")), "p")
        moved, seen = cut_observing(cur.join(answer if merge else answer.distinct(), "p").select("v", F.col("g").alias("p"), (F.col("p") != F.col("g")).alias("m")), m=F.bool_or("m"))
        still = moved.where("m").select("v", "p")
        settled = moved.where("not m").select("v", "p")
        done = settled if done is None else cut_state(done.union(settled))
        if not seen["m"]:
            return done, rounds
        cur, rounds = still, rounds + 1
    raise ValueError("the parent table has a cycle")


def close_changed(changed: DataFrame, max_rounds: int = 64, *, small: bool = False) -> tuple[DataFrame, int]:
    """``changed(root, parent)`` with chains followed to their ends, by pointer doubling on the map alone."""
    cur, rounds = changed.select("root", "parent"), 0
    for _ in range(max_rounds):
        up = cur.select(F.col("root").alias("parent"), F.col("parent").alias("g"))
        up = F.broadcast(up) if small else up
        nxt, seen = cut_observing(cur.join(up, "parent", "left").select("root", F.coalesce("g", "parent").alias("parent"), F.col("g").isNotNull().alias("m")), m=F.bool_or("m"))
        if not seen["m"]:
            return nxt.select("root", "parent"), rounds
        cur, rounds = nxt.select("root", "parent"), rounds + 1
    raise ValueError("the map of changed roots has a cycle")


def apply_closed(stars: DataFrame, closed: DataFrame, *, ship: str = "broadcast") -> DataFrame:
    """Hooks and flattens at once: a vertex of a star forest moves with its root. The parent table is not shuffled by ``broadcast``."""
    m = closed.select(F.col("root").alias("p"), F.col("parent").alias("_to"))
    m = F.broadcast(m) if ship == "broadcast" else m.hint("merge")
    return stars.join(m, "p", "left").select("v", F.coalesce("_to", "p").alias("p"))


def shortcut_prefetched(stars: DataFrame, changed: DataFrame, *, ship: str = "auto", checked: bool = False, n: int | None = None) -> tuple[DataFrame, int]:
    """Star forest after hooking ``changed(root, parent)`` onto ``stars``, which must be a star forest."""
    if not checked and not is_star_forest(stars):
        raise ValueError("prefetching needs a star forest before hooking: only then do roots alone change")
    n = changed.count() if n is None else n
    closed, rounds = close_changed(changed, small=n <= BROADCAST_ROWS)
    if ship == "auto":
        ship = "broadcast" if n < THRESHOLD else "shuffle"
    return apply_closed(stars, closed, ship=ship), rounds


def shortcut_full(parents: DataFrame, max_rounds: int = 64) -> tuple[DataFrame, int]:
    """Star forest by whole sub-iterations: everyone takes their grandparent until nothing moves. Returns how many moved something."""
    cur = parents
    for rounds in range(max_rounds):
        nxt, seen = cut_observing(grandparents(cur).select("v", F.col("g").alias("p"), (F.col("p") != F.col("g")).alias("m")), m=F.bool_or("m"))
        cur = nxt.select("v", "p")
        if not seen["m"]:
            return cur, rounds
    raise ValueError("the parent table has a cycle")


def shortcut_mixed(parents: DataFrame, first: int) -> tuple[DataFrame, int]:
    """``first`` plain sub-iterations, then what is left of the map is closed and applied at once."""
    cur = parents
    for rounds in range(first):
        nxt, seen = cut_observing(grandparents(cur).select("v", F.col("g").alias("p"), (F.col("p") != F.col("g")).alias("m")), m=F.bool_or("m"))
        cur = nxt.select("v", "p")
        if not seen["m"]:
            return cur, rounds
    left = cut_state(grandparents(cur).where("p <> g").select(F.col("p").alias("root"), F.col("g").alias("parent")).distinct())
    n = left.count()
    if not n:
        return cur, first
    closed, rounds = close_changed(left, small=n <= BROADCAST_ROWS)
    return cut_state(apply_closed(cur, closed, ship="broadcast" if n <= BROADCAST_ROWS else "shuffle")), first + rounds + 1


def shortcut_queries(parents: DataFrame, parts: int) -> DataFrame:
    """``(queries, merged)``: look-ups of one sub-iteration without and with merging duplicates in each of ``parts`` processes."""
    need = grandparents(parents).where("p <> g").select(F.pmod(F.col("v"), F.lit(parts)).alias("part"), "p")
    return need.agg(F.count("*").alias("queries"), F.countDistinct("part", "p").alias("merged"))
