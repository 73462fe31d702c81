"""The minimum spanning forest by star hooking.

Each iteration: every star's lightest edge to another tree (one pass over the edge table, which is never rewritten),
hooking, undoing one side of mutual hooks, shortcutting. The plan is cut once for the hooks and once for the parents; the
driver sees counts only. Up to ``HELD_FROM`` vertices the parents are broadcast and one task settles the candidates (their
seconds count as kernel time); up to ``HELD_ROWS`` every task holds the parents (:mod:`starforest.forest.held`) and one task settles
them, too; beyond, the edge table lies in grid blocks and stays there. Where tasks cannot hold them, they are broadcast up to ``BROADCAST_ROWS``.
"""

from __future__ import annotations

import time
from contextlib import nullcontext
from dataclasses import asdict, dataclass, field
from functools import cached_property, reduce
from math import ceil, log
from typing import NamedTuple

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.algebra.kernel import BROADCAST_ROWS
from starforest.forest import held, steps
from starforest.forest import shortcut as sc
from starforest.forest.held import HELD_FROM, HELD_ROWS
from starforest.graph.order import vertices_of
from starforest.runtime import cut_observing, cut_state

SHORTCUTS = ("step", "full", "queried", "queried_plain", "prefetched", "thresholded", "adaptive", "scheduled")


@dataclass
class Iteration:
    iteration: int
    candidates: int
    hooks: int
    undone: int
    changed: int
    sub_iterations: int = 0
    gathered_bytes: int = 0
    rows_written: int = 0
    strategy: str = ""
    kernel_s: float = 0.0
    hook_s: float = 0.0
    shortcut_s: float = 0.0


@dataclass
class ForestResult:
    edges: DataFrame
    accepted: DataFrame
    parents: DataFrame
    trace: list[Iteration] = field(default_factory=list)
    #: (weight, edges) of a run that kept no forest.
    total: tuple[int | float, int] | None = None

    @cached_property
    def forest(self) -> DataFrame:
        """``(rank, lo, hi, w, iteration)``."""
        if self.total is not None:
            raise ValueError("this run kept the weight only")
        return self.accepted.join(self.edges, "rank").select("rank", "lo", "hi", "w", "iteration")

    @property
    def iterations(self) -> int:
        """Rounds that hooked something (the confirming one is not counted)."""
        return sum(t.hooks > 0 for t in self.trace)

    def weight(self) -> DataFrame:
        """One row ``(total_weight, n_edges, iterations)``."""
        if self.total is not None:
            kind = dict(self.edges.dtypes)["w"]
            return self.edges.sparkSession.createDataFrame([(*self.total, self.iterations)], f"total_weight {'double' if kind in ('double', 'float') else 'long'}, n_edges long, iterations long")
        return self.forest.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("total_weight"), F.count("*").alias("n_edges")).withColumn("iterations", F.lit(self.iterations).cast("long"))

    def components(self) -> DataFrame:
        """``(v, component)``, named by the smallest member."""
        low = self.parents.groupBy("p").agg(F.min("v").alias("component"))
        return self.parents.join(low, "p").select("v", "component")

    def trace_frame(self) -> DataFrame:
        spark = self.edges.sparkSession
        kinds = "iteration int, candidates long, hooks long, undone long, changed long, sub_iterations int, gathered_bytes long, rows_written long, strategy string, kernel_s double, hook_s double, shortcut_s double"
        return spark.createDataFrame([tuple(asdict(t).values()) for t in self.trace], kinds)


def minimum_spanning_forest(edges: DataFrame, vertices: DataFrame | None = None, *, mode: str = "forest", shortcut: str = "thresholded", kernel: str = "triple", plan: str = "auto", grid: int | None = None, threshold: int = sc.THRESHOLD, first_iterations: int = 3, first_sub_iterations: int = 0, budget_bytes: int = 20 << 20, compact: bool = False, max_iterations: int = 200) -> ForestResult:
    """``edges(rank, lo, hi, w)`` from :func:`starforest.graph.order.rank_edges`; ``vertices(v)`` adds isolated ones.

    ``mode``: ``forest``, or ``weight``, which adds up the weights of accepted hooks and keeps no forest. ``kernel``: ``triple``,
    ``vertex`` (candidates per vertex, then projected) or ``two_pass``. ``compact`` drops edges inside a tree from the working
    copy after each iteration (result unchanged, by the cycle property). ``shortcut="scheduled"`` does without prefetching in the
    ``first_iterations``, or, with ``first_sub_iterations``, in that many sub-iterations of each iteration.
    """
    if shortcut not in SHORTCUTS:
        raise ValueError(f"unknown shortcut {shortcut!r}; one of {', '.join(SHORTCUTS)}")
    if kernel not in ("triple", "vertex", "two_pass"):
        raise ValueError(f"unknown kernel {kernel!r}")
    if mode not in ("forest", "weight") or (mode == "weight" and kernel != "triple"):
        raise ValueError("mode is 'forest' or, with the triple kernel, 'weight'")
    carry = ("w",) if mode == "weight" else ()
    parents, seen = cut_observing(steps.initial_parents(vertices_of(edges, vertices)), n=F.count(F.lit(1)), named=F.count("v"))
    n = seen["n"]
    small = n <= BROADCAST_ROWS
    if plan == "broadcast" and not small:
        raise ValueError(f"a parent table of {n} rows is not broadcast; use plan='held', 'shuffle' or 'grid'")
    if plan in ("auto", "held"):
        longs = {dict(edges.dtypes)[c] for c in ("rank", "lo", "hi")} == {"bigint"} and dict(parents.dtypes)["v"] == "bigint"
        least = min(HELD_FROM, BROADCAST_ROWS) if plan == "auto" else -1
        holds = longs and n == seen["named"] and least < n <= HELD_ROWS and shortcut != "step" and kernel == "triple" and held.can_hold(parents)
        if plan == "held" and not holds:
            raise ValueError(f"a parent table of {n} rows is not held with kernel={kernel!r}, shortcut={shortcut!r}; use plan='auto', 'shuffle' or 'grid'")
        plan = "held" if holds else "broadcast" if small else "grid"
    grid = grid or max(2, ceil(int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")) ** 0.5))
    work = edges.select("rank", "lo", "hi", *carry)
    options = _Options(mode, shortcut, kernel, plan, grid, threshold, first_iterations, first_sub_iterations, budget_bytes, compact, max_iterations, small or plan == "held", carry, n)
    if plan == "held":
        names, places = parents, edges.sparkSession.range(n)
        found = _grow(edges, cut_state(held.number_edges(work, names)), cut_state(places.select(F.col("id").alias("v"), F.col("id").alias("p"))), options)
        found.parents = held.named(found.parents, names)
        return found
    with steps.grid_layout(work, grid) if plan == "grid" else nullcontext(work) as laid:
        return _grow(edges, laid, parents, options)


class _Options(NamedTuple):
    mode: str
    shortcut: str
    kernel: str
    plan: str
    grid: int
    threshold: int
    first_iterations: int
    first_sub_iterations: int
    budget_bytes: int
    compact: bool
    max_iterations: int
    small: bool
    carry: tuple[str, ...]
    n: int


def _grow(edges: DataFrame, work: DataFrame, parents: DataFrame, o: _Options) -> ForestResult:
    spark, stepwise, one = edges.sparkSession, o.shortcut == "step", F.count(F.lit(1))
    parts: list[DataFrame] = []
    trace: list[Iteration] = []
    spent = {"queried": 0.0, "prefetched": 0.0}
    weight, kept = 0, 0
    for k in range(1, o.max_iterations + 1):
        t0 = time.monotonic()
        flags = cut_state(steps.star_flags(parents)) if stepwise else steps.all_stars(parents)
        written = 0
        if o.kernel == "two_pass":
            roots, written = steps.two_pass_candidates(work, flags)
        elif o.kernel == "vertex":
            roots = steps.project_to_root(steps.vertex_candidates(work, flags), parents)
        elif o.plan == "held":
            roots = held.root_candidates(work, parents, o.n, o.carry)
        else:
            roots = steps.root_candidates(work, flags, plan=o.plan, grid=o.grid, carry=o.carry)
        sums = {"n": one} | ({"weight": F.sum("w")} if o.carry else {})
        closed, rounds = None, 0
        if o.small:
            settled = held.settle(roots, o.n) if o.plan == "held" else steps.settle(roots)
            hooks, seen = cut_observing(settled, **sums, candidates=F.max("candidates"), rounds=F.max("rounds"))
            n, rounds, closed = seen["candidates"] or 0, seen["rounds"] or 0, hooks.select("root", F.col("to").alias("parent"))
            t1 = time.monotonic()
        else:
            roots, seen = cut_observing(roots, n=one)
            n = seen["n"]
            t1 = time.monotonic()
            if n:
                hooks, seen = cut_observing(steps.accepted_hooks(roots, small=False), **sums)
        if not n and not stepwise:
            break
        changed = seen["n"]
        if not n:
            hooks = spark.createDataFrame([], "root long, rank long, parent long")
        row = Iteration(k, n, changed, n - changed, changed, rows_written=written, kernel_s=t1 - t0)
        if o.carry:
            weight, kept = weight + (seen["weight"] or 0), kept + changed
        else:
            parts.append(hooks.select("rank", F.lit(k).alias("iteration")))
        t2 = time.monotonic()
        if stepwise:
            stepped = sc.shortcut_step(cut_state(steps.hook(parents, hooks))).join(parents.select("v", F.col("p").alias("o")), "v")
            nxt, seen = cut_observing(stepped, m=F.bool_or(F.col("p") != F.col("o")))
            nxt, moved = nxt.select("v", "p"), seen["m"]
            row.strategy, row.sub_iterations, parents = "step", 1, nxt
            if not n and not moved:
                break
        else:
            row.strategy = _strategy(o, k, changed, spent)
            if row.strategy == "prefetched":
                ship = "broadcast" if changed * sc.ENTRY_BYTES <= o.budget_bytes else "shuffle"
                if closed is None:
                    nxt, row.sub_iterations = sc.shortcut_prefetched(parents, hooks, ship=ship, checked=True, n=changed)
                else:
                    nxt, row.sub_iterations = sc.apply_closed(parents, closed, ship=ship), rounds
                row.gathered_bytes = changed * sc.ENTRY_BYTES
                parents = cut_state(nxt)
            elif row.strategy == "queried" and o.plan == "held" and o.shortcut != "queried_plain":
                parents, row.sub_iterations = held.shortcut_queried(parents, hooks, o.n)
            else:
                hooked = cut_state(steps.hook(parents, hooks))
                if row.strategy == "full":
                    parents, row.sub_iterations = sc.shortcut_full(hooked)
                elif row.strategy == "mixed":
                    parents, row.sub_iterations = sc.shortcut_mixed(hooked, o.first_sub_iterations)
                else:
                    parents, row.sub_iterations = sc.shortcut_queried(hooked, merge=o.shortcut != "queried_plain")
                    parents = cut_state(parents)
        t3 = time.monotonic()
        row.hook_s, row.shortcut_s = t2 - t1, t3 - t2
        if row.strategy in spent:
            spent[row.strategy] = t3 - t2
        trace.append(row)
        if o.compact:
            a, b = (parents.select(F.col("v").alias(s), F.col("p").alias(f"_{s}")) for s in ("lo", "hi"))
            work = cut_state(work.join(a, "lo").join(b, "hi").where("_lo <> _hi").select(*work.columns))
    else:
        raise RuntimeError(f"no forest within {o.max_iterations} iterations")
    nothing = spark.createDataFrame([], "rank long, iteration int")
    accepted = reduce(DataFrame.union, parts, nothing) if parts else nothing
    return ForestResult(edges, accepted, parents, trace, (weight, kept) if o.carry else None)


def _strategy(o: _Options, k: int, changed: int, spent: dict[str, float]) -> str:
    if o.shortcut in ("prefetched", "full"):
        return o.shortcut
    if o.shortcut == "thresholded":
        return "prefetched" if changed < o.threshold else "queried"
    if o.shortcut == "scheduled":
        return "mixed" if o.first_sub_iterations else "queried" if k <= o.first_iterations else "prefetched"
    if o.shortcut == "adaptive":
        # Within the byte budget prefetching always; beyond it, whatever the last rounds of either kind cost less.
        fits = changed * sc.ENTRY_BYTES <= o.budget_bytes
        return "prefetched" if fits or (spent["queried"] and spent["prefetched"] < spent["queried"]) else "queried"
    return "queried"


def minimum_spanning_tree(edges: DataFrame, vertices: DataFrame | None = None, **options) -> ForestResult:
    """The forest of a connected graph; raises if there is more than one tree."""
    found = minimum_spanning_forest(edges, vertices, **options)
    if (trees := found.parents.where("v = p").count()) > 1:
        raise ValueError(f"the graph has {trees} components")
    return found


def iteration_bound(n: int) -> int:
    """Logarithm of n to the base 3/2, rounded up."""
    return max(1, ceil(log(max(n, 2)) / log(1.5)))


def check_bounds(result: ForestResult) -> dict[str, bool]:
    """Whether a run kept the analytical bounds."""
    n = result.parents.count()
    full = [t for t in result.trace if t.strategy != "step"]
    return {
        "iterations": result.iterations <= iteration_bound(n),
        "half_hook": all(2 * t.hooks >= t.candidates for t in full),
        "sub_iterations": all(t.sub_iterations <= iteration_bound(n) for t in result.trace),
    }
