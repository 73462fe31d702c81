"""Baselines: sequential methods for tests, contraction, message passing, divide and merge, closure."""

from __future__ import annotations

from collections.abc import Iterator
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.forest.shortcut import close_changed
from starforest.forest.steps import accepted_hooks
from starforest.graph.order import directed, vertices_of
from starforest.runtime import cut_observing, cut_state


def _kruskal(rank: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Positions of the forest's edges, by union-find over the edges in order of rank."""
    names, ends = np.unique(np.concatenate([lo, hi]), return_inverse=True)
    a, b = ends[: len(lo)].tolist(), ends[len(lo) :].tolist()
    up = list(range(len(names)))
    kept = []
    for k in np.argsort(rank, kind="stable").tolist():
        x, y = a[k], b[k]
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        while up[y] != y:
            up[y] = up[up[y]]
            y = up[y]
        if x != y:
            up[max(x, y)] = min(x, y)
            kept.append(k)
    return np.array(kept, np.int64)


def kruskal_local(edges: list[tuple[int, int, int]]) -> set[tuple[int, int, int]]:
    """Forest of ``(lo, hi, w)`` rows on the driver (for tests), in the order (w, lo, hi)."""
    if not edges:
        return set()
    rows = sorted(edges, key=lambda e: (e[2], e[0], e[1]))
    keep = _kruskal(np.arange(len(rows)), np.array([e[0] for e in rows]), np.array([e[1] for e in rows]))
    return {rows[k] for k in keep}


def prim_local(edges: list[tuple[int, int, int]]) -> set[tuple[int, int, int]]:
    """Forest of ``(lo, hi, w)`` rows on the driver (for tests), one tree grown after another."""
    near: dict[int, list] = {}
    for e in edges:
        near.setdefault(e[0], []).append(e)
        near.setdefault(e[1], []).append(e)
    seen: set[int] = set()
    out = set()
    for start in near:
        if start in seen:
            continue
        seen.add(start)
        heap: list = []
        for e in near[start]:
            heappush(heap, ((e[2], e[0], e[1]), e))
        while heap:
            _, e = heappop(heap)
            new = [v for v in e[:2] if v not in seen]
            if new:
                seen.add(new[0])
                out.add(e)
                for x in near[new[0]]:
                    heappush(heap, ((x[2], x[0], x[1]), x))
    return out


_RANKED = "rank long, lo long, hi long"


def _local_forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Forest of one partition's edges."""
    table = pa.Table.from_batches(list(batches)) if batches else None
    if table is not None and table.num_rows:
        rank, lo, hi = (np.asarray(table.column(k).combine_chunks()) for k in range(3))
        yield from table.take(pa.array(_kruskal(rank, lo, hi))).to_batches()


def local_forest(edges: DataFrame) -> DataFrame:
    """Forest of each partition by itself: ``(rank, lo, hi)``."""

    def run(batches):
        held = list(batches)
        yield from _local_forest(held) if held else ()

    return edges.select("rank", "lo", "hi").mapInArrow(run, _RANKED)


def divide_and_merge_forest(edges: DataFrame, *, parts: int = 8, fan_in: int = 4) -> DataFrame:
    """``(rank, lo, hi)``: local forests of ``parts`` shares of the edges, merged ``fan_in`` at a time.

    An edge that is not in the forest of its share is in no forest of the whole (cycle property).
    """
    cur = cut_state(local_forest(edges.select("rank", "lo", "hi").repartition(parts, F.xxhash64("rank"))))
    while parts > 1:
        parts = -(-parts // fan_in)
        cur = cut_state(local_forest(cur.repartition(parts, F.xxhash64("rank"))))
    return cur


def kruskal(edges: DataFrame) -> DataFrame:
    """``(rank, lo, hi)`` by union-find in one task: small graphs."""
    return local_forest(edges.select("rank", "lo", "hi").coalesce(1))


def _prim(lo: np.ndarray, hi: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Positions of the forest's edges, one tree grown after another; edges stand in the heap by their place in the order (w, lo, hi)."""
    order, m = np.lexsort((hi, lo, w)), len(lo)
    names, ends = np.unique(np.concatenate([lo[order], hi[order]]), return_inverse=True)
    by = np.argsort(ends, kind="stable")
    start = np.searchsorted(ends[by], np.arange(len(names) + 1)).tolist()
    near, a, b = (by % max(m, 1)).tolist(), ends[:m].tolist(), ends[m:].tolist()
    seen, kept = bytearray(len(names)), []
    for root in range(len(names)):
        if seen[root]:
            continue
        seen[root] = 1
        heap = near[start[root] : start[root + 1]]
        heapify(heap)
        while heap:
            k = heappop(heap)
            x = b[k] if seen[a[k]] else a[k]
            if seen[x]:
                continue
            seen[x] = 1
            kept.append(k)
            for y in near[start[x] : start[x + 1]]:
                if not (seen[a[y]] and seen[b[y]]):
                    heappush(heap, y)
    return order[np.array(kept, np.int64)]


def prim(edges: DataFrame) -> DataFrame:
    """``(lo, hi, w)`` by growing trees, in each partition, then in two, then in one task of at most twice the vertices in edges.

    An edge that is not in the forest of its share is in no forest of the whole (cycle property).
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if held:
            table = pa.Table.from_batches(held)
            lo, hi, w = (np.asarray(c.combine_chunks()) for c in table.columns)
            yield from table.take(pa.array(_prim(lo, hi, w))).to_batches()

    cur, kinds = edges.select("lo", "hi", "w"), "lo long, hi long, w long"
    for parts in (None, 2, 1):
        cur = (cur if parts is None else cur.repartition(parts, F.xxhash64("lo", "hi"))).mapInArrow(run, kinds)
    return cur


def boruvka(edges: DataFrame, *, max_rounds: int = 64) -> DataFrame:
    """``(rank)``: every component takes its lightest edge and is contracted; the edge table is rewritten each round."""
    cur = edges.select("rank", F.col("lo").alias("a"), F.col("hi").alias("b"))
    found: DataFrame | None = None
    for _ in range(max_rounds):
        both = cur.select("rank", F.explode(F.array(F.struct(F.col("a").alias("root"), F.col("b").alias("parent")), F.struct(F.col("b").alias("root"), F.col("a").alias("parent")))).alias("e")).select("rank", "e.*")
        best = cut_state(both.groupBy("root").agg(F.min("rank").alias("rank"), F.min_by("parent", "rank").alias("parent")))
        hooks, seen = cut_observing(accepted_hooks(best), n=F.count(F.lit(1)))
        if not seen["n"]:
            return found.select("rank") if found is not None else edges.select("rank").limit(0)
        found = hooks.select("rank") if found is None else found.union(hooks.select("rank"))
        to, _ = close_changed(hooks)
        a, b = (to.select(F.col("root").alias(s), F.col("parent").alias(f"_{s}")) for s in "ab")
        cur = cut_state(cur.join(a, "a", "left").join(b, "b", "left").select("rank", F.coalesce("_a", "a").alias("a"), F.coalesce("_b", "b").alias("b")).where("a <> b"))
    raise RuntimeError(f"not contracted within {max_rounds} rounds")


def vertex_centric_forest(edges: DataFrame, *, max_rounds: int = 64) -> tuple[DataFrame, list[dict]]:
    """``(rank)`` and messages by superstep: vertices tell neighbours their component, leaders reduce, members ask leaders for theirs."""
    state = cut_state(vertices_of(edges).select("v", F.col("v").alias("c")))
    entries = directed(edges).select("i", "j", "rank")
    found: DataFrame | None = None
    log: list[dict] = []
    for _ in range(max_rounds):
        told, seen = cut_observing(entries.join(state.withColumnsRenamed({"v": "i", "c": "ci"}), "i").select("j", "ci", "rank"), n=F.count(F.lit(1)))
        heard = told.join(state.withColumnsRenamed({"v": "j", "c": "cj"}), "j").where("ci <> cj").groupBy(F.col("cj").alias("root")).agg(F.min("rank").alias("rank"), F.min_by("ci", "rank").alias("parent"))
        heard = cut_state(heard)
        hooks, got = cut_observing(accepted_hooks(heard), n=F.count(F.lit(1)))
        log.append({"neighbour_messages": seen["n"], "leaders": got["n"]})
        if not got["n"]:
            return (found if found is not None else edges.select("rank").limit(0)), log
        found = hooks.select("rank") if found is None else found.union(hooks.select("rank"))
        to, rounds = close_changed(hooks)
        log[-1]["pointer_rounds"] = rounds
        state = cut_state(state.join(to.select(F.col("root").alias("c"), F.col("parent").alias("_c")), "c", "left").select("v", F.coalesce("_c", "c").alias("c")))
    raise RuntimeError(f"no forest within {max_rounds} rounds")


def bottleneck_closure(edges: DataFrame, *, max_rounds: int = 32) -> DataFrame:
    """``(i, j, b)``: the smallest possible largest rank on a path from i to j; small graphs only."""
    cur = cut_state(directed(edges).select("i", "j", F.col("rank").alias("b")))
    for _ in range(max_rounds):
        step = cur.select("i", F.col("j").alias("k"), F.col("b").alias("x")).join(cur.select(F.col("i").alias("k"), "j", F.col("b").alias("y")), "k").where("i <> j").select("i", "j", F.greatest("x", "y").alias("b"))
        nxt = cut_state(cur.union(step).groupBy("i", "j").agg(F.min("b").alias("b")))
        if not nxt.exceptAll(cur).limit(1).count():
            return nxt
        cur = nxt
    raise RuntimeError(f"no closure within {max_rounds} rounds")


def bottleneck_closure_forest(edges: DataFrame) -> DataFrame:
    """``(rank)``: an edge stays if no path of lighter edges joins its ends; small graphs only."""
    close = bottleneck_closure(edges)
    return edges.join(close, (F.col("lo") == F.col("i")) & (F.col("hi") == F.col("j"))).where("b = rank").select("rank")
