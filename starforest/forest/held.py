"""The parent table held by every task, for graphs whose vertices are too many to broadcast and few enough to hold.

Vertices are numbered 0, 1, 2, ... in the order of their names, so ties fall as they do among names, and a parent table is one array
of four bytes a vertex that each task reads from the shared folder. The edges are numbered once and, like in the other plans, never
rewritten or moved; a task hands on at most one candidate for each root.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.runtime import cut_observing, open_store

#: Vertices from which tasks hold the parents: a broadcast is built anew, and its rows are looked up by hash, in every iteration.
HELD_FROM = 250_000
#: Vertices up to which a task holds their parents (16 bytes a vertex with its candidates).
HELD_ROWS = 16_000_000
#: Candidates up to which the task that settles them also finds the lightest of each root; more are aggregated before.
SETTLED_ROWS = 32_000_000
_FREE = np.iinfo(np.int64).max


def can_hold(state: DataFrame) -> bool:
    """Whether tasks can open the files of a state by themselves."""
    try:
        for uri in state.inputFiles()[:1]:
            store, path = open_store(uri)
            store.open_input_file(path).close()
    except Exception:  # noqa: BLE001  (a store that Arrow does not know, or an address it does not read)
        return False
    return True


def _columns(uris: list[str], *names: str) -> Iterator[list[np.ndarray]]:
    """Some columns of a state, file after file."""
    for uri in uris:
        store, path = open_store(uri)
        with store.open_input_file(path) as f:
            table = pq.ParquetFile(f).read(columns=list(names), use_threads=False)
        yield [table.column(c).to_numpy() for c in names]


def _parents(uris: list[str], n: int) -> np.ndarray:
    out = np.full(n, -1, np.int32)
    for v, p in _columns(uris, "v", "p"):
        out[v] = p
    if n and out.min() < 0:
        raise ValueError("the parent table lacks vertices")
    return out


def _names(uris: list[str]) -> np.ndarray:
    return np.sort(np.concatenate([np.zeros(0, np.int64), *(v for (v,) in _columns(uris, "v"))]))


def _sliced(columns: dict[str, np.ndarray], rows: int = 1 << 16) -> Iterator[pa.RecordBatch]:
    yield from pa.table(columns).to_batches(max_chunksize=rows)


def _places(name: np.ndarray) -> Callable[[np.ndarray], np.ndarray]:
    """Finds names' places among the sorted ``name``: by one look-up where they are spread evenly, else by bisection."""
    if n := len(name):
        span, shift = int(name[-1]) - int(name[0]), 0
        while span >> shift > 2 * n:
            shift += 1
        if span < 1 << 62 and ((slot := (name - name[0]) >> shift)[1:] > slot[:-1]).all():
            table = np.zeros(int(slot[-1]) + 1, np.int32)
            table[slot] = np.arange(n, dtype=np.int32)
            return lambda x: table[(x - name[0]) >> shift]
    return lambda x: np.searchsorted(name, x).astype(np.int32)


def number_edges(edges: DataFrame, names: DataFrame) -> DataFrame:
    """``(rank, lo, hi[, w])`` with the ends' places among the sorted ``names(v)``, a state."""
    uris = names.inputFiles()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = _places(_names(uris))
        for b in batches:
            ends = {c: pa.array(place(b.column(c).to_numpy())) for c in ("lo", "hi")}
            yield pa.RecordBatch.from_arrays([ends.get(c, b.column(c)) for c in b.schema.names], names=b.schema.names)

    kinds = ", ".join(f"{c} {'int' if c in ('lo', 'hi') else t}" for c, t in edges.dtypes)
    return edges.mapInArrow(run, kinds)


def named(parents: DataFrame, names: DataFrame) -> DataFrame:
    """``(v, p)`` by name again."""
    uris = names.inputFiles()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name = _names(uris)
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(name[c.to_numpy()]) for c in b.columns], names=["v", "p"])

    return parents.select("v", "p").mapInArrow(run, "v long, p long")


class _Lightest:
    """The lightest candidate of each root so far: its rank, the far side's parent, columns that come along."""

    def __init__(self, n: int) -> None:
        self.rank, self.parent, self.more = np.full(n, _FREE), np.zeros(n, np.int32), {}

    def add(self, root: np.ndarray, rank: np.ndarray, parent: np.ndarray, more: list[np.ndarray]) -> None:
        at = np.flatnonzero((root != parent) & (rank < self.rank[root]))
        to, r = root[at], rank[at]
        np.minimum.at(self.rank, to, r)
        won = at[self.rank[to] == r]
        self.parent[root[won]] = parent[won]
        for k, x in enumerate(more):
            self.more.setdefault(k, np.zeros(len(self.rank), x.dtype))[root[won]] = x[won]

    def roots(self) -> np.ndarray:
        return np.flatnonzero(self.rank < _FREE)


def root_candidates(edges: DataFrame, parents: DataFrame, n: int, carry: tuple[str, ...] = ()) -> DataFrame:
    """``(root, rank, parent)`` as :func:`starforest.forest.steps.root_candidates`, for states: numbered ``edges``, and a star forest of ``n`` vertices.

    A task reads files of edges by itself. Up to ``SETTLED_ROWS`` a root may have a row from each of them (:func:`settle` sees to it).
    """
    stars, files = parents.inputFiles(), edges.inputFiles()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, best = _parents(stars, n), _Lightest(n)
        for k in (k for b in batches for k in b.column(0).to_pylist()):
            store, path = open_store(files[k])
            with store.open_input_file(path) as f:
                for b in pq.ParquetFile(f).iter_batches(1 << 18, columns=["rank", "lo", "hi", *carry], use_threads=False):
                    rank, lo, hi, *own = (b.column(c).to_numpy() for c in ("rank", "lo", "hi", *carry))
                    a, c = p[lo], p[hi]
                    best.add(a, rank, c, own)
                    best.add(c, rank, a, own)
        if len(root := best.roots()):
            yield from _sliced({"root": root, "rank": best.rank[root], "parent": best.parent[root].astype(np.int64)} | {c: best.more[k][root] for k, c in enumerate(carry)})

    kinds = "root long, rank long, parent long" + "".join(f", {c} {dict(edges.dtypes)[c]}" for c in carry)
    out = edges.sparkSession.range(0, len(files), 1, max(1, len(files))).mapInArrow(run, kinds)
    if len(files) * n <= SETTLED_ROWS:
        return out
    return out.groupBy("root").agg(F.min("rank").alias("rank"), F.min_by("parent", "rank").alias("parent"), *[F.min_by(c, "rank").alias(c) for c in carry])


def settle(roots: DataFrame, n: int) -> DataFrame:
    """:func:`starforest.forest.steps.settle` for ``n`` numbered vertices, of whose candidates the lightest counts: what one task holds does not grow with their rows."""
    carry = [c for c in ("w",) if c in roots.columns]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = _Lightest(n)
        for b in batches:
            root, rank, parent, *own = (b.column(c).to_numpy() for c in ("root", "rank", "parent", *carry))
            best.add(root, rank, parent, own)
        if not len(root := best.roots()):
            return
        parent = best.parent[root]
        hooked = best.rank[parent] < _FREE
        stays = ~(hooked & (best.parent[parent] == root)) | (root > parent)
        kept, to, rounds = np.zeros(n, bool), np.arange(n, dtype=np.int32), 0
        kept[root] = stays
        to[root[stays & hooked]] = parent[stays & hooked]
        while not ((nxt := to[to]) == to).all():
            to, rounds = nxt, rounds + 1
            if rounds > 64:
                raise ValueError("the map of changed roots has a cycle")
        # The last root of a chain that stays and whose parent does not hook moves to that parent.
        total, root, last = len(root), root[stays], to[root[stays]]
        final = np.where(kept[last], best.parent[last], last)
        if len(root):
            yield from _sliced({"root": root, "rank": best.rank[root], "parent": best.parent[root].astype(np.int64), "to": final.astype(np.int64), "candidates": np.full(len(root), total), "rounds": np.full(len(root), rounds, np.int32)} | {c: best.more[k][root] for k, c in enumerate(carry)})

    kinds = "root long, rank long, parent long, to long, candidates long, rounds int" + "".join(f", {c} {dict(roots.dtypes)[c]}" for c in carry)
    return roots.repartition(1).mapInArrow(run, kinds)


def shortcut_queried(parents: DataFrame, hooks: DataFrame, n: int, max_rounds: int = 64) -> tuple[DataFrame, int]:
    """Star forest after hooking ``hooks(root, parent)``, a state, and the number of sub-iterations that changed it.

    Every task holds the table that is asked, so a question is a look-up and nothing travels; a task writes the vertices it was given.
    """
    stars, changed = parents.inputFiles(), hooks.inputFiles()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cur, rounds = _parents(stars, n), 0
        for root, parent in _columns(changed, "root", "parent"):
            cur[root] = parent
        while not ((nxt := cur[cur]) == cur).all():
            cur, rounds = nxt, rounds + 1
            if rounds > max_rounds:
                raise ValueError("the parent table has a cycle")
        for b in batches:
            v = b.column(0)
            yield pa.RecordBatch.from_arrays([v, pa.array(cur[v.to_numpy()].astype(np.int64)), pa.array(np.full(len(v), rounds, np.int32))], names=["v", "p", "rounds"])

    out, seen = cut_observing(parents.select("v").mapInArrow(run, "v long, p long, rounds int"), rounds=F.max("rounds"))
    return out.select("v", "p"), seen["rounds"] or 0
