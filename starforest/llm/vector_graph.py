"""Embedding near-duplicates by a robust-pruned flat graph over overlapping cluster shards.

Centroids are fitted on a bounded sample (``sample`` rows, in the order of a hash); every vector goes to the shards of its
``overlap`` nearest centroids. In each shard a graph is built by robust pruning of near and random
candidates, with reverse edges and with edges that make every node reachable from the medoid. A vector's adjacency lists of
all its shards are united. Greedy beam search from each shard's medoid then finds every member's
neighbourhood, and range expansion walks on through everything within the threshold. Links are
verified by cosine in double precision. Recall is audited against brute force over all rows, as the mean over a
fixed number of query vectors that are drawn whatever was found; below ``recall`` the shards are made to overlap more,
and when no overlap passes, all pairs are compared exactly, in blocks.

Scale: shards hold about ``shard`` vectors. The driver fits and tasks are sent 4,096 centroids at most, whatever the number of
vectors; a shard of more than ``most`` is then split by centroids of its own, fitted in a task on a bounded sample of it, up to
``LEVELS`` times, so the number of shards grows with the vectors. What centroids cannot split (a dense group, whose members are
nearly all within the threshold of each other) is cut into blocks whose pairs are compared exactly, each pair of blocks a task. A
pair that several shards share is counted in the first of them only, so links are counted without being listed; for components a
task hands on a spanning star. Equal vectors are one representative with a count.

Vectors of each length are linked among themselves: the most frequent length and those of more than ``most`` vectors one
after the other by the graph, all others exactly in one pass.

Edge cases: vectors that are null, zero, or hold null or non-finite components link with nothing; rows with the same vec_id are one node; an empty table gives
an empty result; other columns (labels) are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.components.links import link_components
from starforest.runtime import cut

THRESHOLD = 0.95
#: Centroids of the first level and of each split, and rows a split's centroids are fitted on.
_MAX_CENTROIDS, _SPLIT_SAMPLE, LEVELS = 4096, 4096, 3


def usable(vectors: DataFrame) -> DataFrame:
    """``(vec_id, v)`` of the rows that can link, components as double."""
    v = F.transform("embedding", lambda x: x.cast("double"))
    ok = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists("v", lambda x: x != 0)
    return vectors.select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v")).where("vec_id is not null").where(ok)


def _unit(v: np.ndarray) -> np.ndarray:
    v = v / np.abs(v).max(1, keepdims=True)  # no overflow in the squares
    return v / np.sqrt((v * v).sum(1, keepdims=True))


def _matrix(column: pa.Array) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return np.asarray(column.flatten(), np.float64).reshape(len(column), -1)


def fit_centroids(reps: DataFrame, n: int, *, shard: int = 1000, sample: int = 20_000, rounds: int = 8) -> np.ndarray:
    """Spherical k-means on at most ``sample`` vectors."""
    rows = reps.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).select("v").toArrow()
    return _centroids(_unit(_matrix(rows.column("v"))), min(-(-n // shard), _MAX_CENTROIDS), rounds)


def _centroids(x: np.ndarray, k: int, rounds: int = 8) -> np.ndarray:
    k = int(np.clip(k, 1, len(x)))
    c = x[np.linspace(0, len(x) - 1, k).astype(int)].copy()
    for _ in range(rounds):
        near = (x @ c.T).argmax(1)
        for d in range(c.shape[1]):
            c[:, d] = np.bincount(near, x[:, d], k)
        empty = np.flatnonzero(np.bincount(near, minlength=k) == 0)
        c[empty] = x[(empty * 7919) % len(x)]
        c /= np.maximum(np.sqrt((c * c).sum(1, keepdims=True)), 1e-12)
    return c


def _nearest(x: np.ndarray, centroids: np.ndarray, m: int) -> np.ndarray:
    """Positions of each row's ``m`` nearest centroids, ascending."""
    m = min(m, len(centroids))
    return np.sort(np.argpartition(-(x @ centroids.T), m - 1, 1)[:, :m], 1)


def split_shards(placed: DataFrame, *, shard: int, most: int, overlap: int) -> DataFrame:
    """``placed`` with its large shards split by centroids of their own, as long as that makes them smaller."""
    dense = None
    for _ in range(LEVELS):
        sizes = placed.groupBy("shard").agg(F.count("*").alias("n")).where(F.col("n") > most)
        if dense is not None:
            sizes = sizes.join(dense, "shard", "left_anti")
        sizes = cut(sizes)
        if sizes.isEmpty():
            break
        rows = placed.join(sizes, "shard")
        # By a hash that differs from level to level: what a sample saw does not bind the next.
        share = F.lit(float(_SPLIT_SAMPLE) * (1 << 62)) / F.col("n")
        sample = rows.where(F.shiftrightunsigned(F.xxhash64("vec_id", "shard"), 2) < share)

        def fit(table: pa.Table) -> pa.Table:
            k = min(-(-table.column("n")[0].as_py() // shard), _MAX_CENTROIDS)
            order = np.argsort(np.asarray(table.column("vec_id").combine_chunks()))
            c = _centroids(_matrix(table.column("v"))[order], k)
            return pa.table({"shard": pa.array([table.column("shard")[0].as_py()], pa.int64()), "d": pa.array([c.shape[1]], pa.int32()), "c": pa.array([c.ravel()], pa.list_(pa.float64()))})

        # Each salt of a shard meets its centroids in one task of bounded size.
        salts = F.ceil(F.col("n") / most).cast("int")
        fitted = sample.select("shard", "vec_id", "v", "n").groupBy("shard").applyInArrow(fit, "shard long, d int, c array<double>")
        sent = fitted.join(sizes, "shard").select("shard", "d", "c", F.explode(F.sequence(F.lit(0), salts - 1)).alias("salt"))
        dealt = rows.withColumn("salt", F.pmod(F.xxhash64("vec_id", F.lit(3)), salts.cast("long")).cast("int"))

        def deal(left: pa.Table, right: pa.Table) -> pa.Table:
            x, c = _matrix(left.column("v")), np.asarray(right.column("c").combine_chunks().flatten()).reshape(-1, right.column("d")[0].as_py())
            near = _nearest(x, c, overlap)
            pick = pa.array(np.repeat(np.arange(len(x)), near.shape[1]))
            return pa.table({"old": left.column("shard").take(pick), "sub": pa.array(near.ravel().astype(np.int64)), **{k: left.column(k).take(pick) for k in ("vec_id", "copies", "v")}})

        moved = dealt.groupBy("shard", "salt").cogroup(sent.groupBy("shard", "salt")).applyInArrow(deal, "old long, sub long, vec_id long, copies long, v array<double>")
        moved = cut(moved.withColumn("shard", F.xxhash64("old", "sub")))
        # A child that keeps more than half of its parent will not be split further.
        stuck = moved.groupBy("old", "shard").agg(F.count("*").alias("m")).join(sizes.withColumnRenamed("shard", "old"), "old").where(F.col("m") * 2 > F.col("n")).select("shard")
        dense = cut(stuck if dense is None else dense.union(stuck))
        others = placed.join(sizes.select("shard"), "shard", "left_anti").select("shard", "vec_id", "copies", "v")
        placed = cut(others.unionByName(moved.select("shard", "vec_id", "copies", "v")))
    if "shards" in placed.columns:
        return placed
    # A vector can come to one child from two parents never (names differ), so its list has no repeats.
    lists = placed.groupBy("vec_id").agg(F.array_sort(F.collect_list("shard")).alias("shards"))
    return cut(placed.join(lists, "vec_id").select("shard", "vec_id", "copies", "shards", "v"))


def assign_shards(reps: DataFrame, centroids: np.ndarray, overlap: int) -> DataFrame:
    """``(shard, vec_id, copies, shards, v)``: a row for each of a vector's shards; v has length one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 2048):
                batch = whole.slice(at, 2048)
                x = _unit(_matrix(batch.column(2)))
                near = _nearest(x, centroids, overlap)
                m = near.shape[1]
                pick = np.repeat(np.arange(len(x)), m)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(pick) + 1) * m, pa.int32()), pa.array(near[pick].ravel().astype(np.int64)))
                vecs = pa.ListArray.from_arrays(pa.array(np.arange(len(pick) + 1) * x.shape[1], pa.int32()), pa.array(x[pick].ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(near.ravel().astype(np.int64)), batch.column(0).take(pa.array(pick)), batch.column(1).take(pa.array(pick)), lists, vecs], names=["shard", "vec_id", "copies", "shards", "v"])

    return reps.select("vec_id", "copies", "v").mapInArrow(run, "shard long, vec_id long, copies long, shards array<long>, v array<double>")


def build_graph(v: np.ndarray, *, degree: int = 32, near: int = 48, far: int = 16, alpha: float = 1.2) -> list[np.ndarray]:
    """Out-neighbours of each node of one shard (positions)."""
    x = v.astype(np.float32)
    n = len(x)
    if n == 1:
        return [np.zeros(0, np.int64)]
    rng = np.random.default_rng(n)
    edges = []
    for at in range(0, n, 512):
        some = np.arange(at, min(n, at + 512))
        sims = x[some] @ x.T
        sims[np.arange(len(some)), some] = -2
        m = min(near, n - 1)
        cand = np.argpartition(-sims, m - 1, 1)[:, :m]
        cand = np.concatenate([cand, rng.integers(0, n, (len(some), far))], 1)
        rank = np.argsort(-np.take_along_axis(sims, cand, 1), 1, kind="stable")
        cand = np.take_along_axis(cand, rank, 1)
        kept = _prune(x, cand, some, degree, alpha)
        a, b = np.nonzero(kept >= 0)
        edges.append(np.stack([some[a], kept[a, b]], 1))
    e = np.concatenate(edges)
    e = np.unique(np.concatenate([e, e[:, ::-1]]), axis=0)
    # Reverse edges make hubs: a node keeps its nearest 2 * degree.
    sim = np.einsum("nd,nd->n", x[e[:, 0]], x[e[:, 1]])
    e = e[np.lexsort((-sim, e[:, 0]))]
    place = np.arange(len(e)) - np.searchsorted(e[:, 0], e[:, 0])
    e = e[place < 2 * degree]
    # Whatever the medoid does not reach hangs on the nearest node that it reaches.
    seen = np.zeros(n, bool)
    front = np.array([medoid(x)])
    adj = _lists(e, n)
    while len(front):
        seen[front] = True
        front = np.unique(np.concatenate([adj[i] for i in front]))
        front = front[~seen[front]]
    lost, reached = np.flatnonzero(~seen), np.flatnonzero(seen)
    if len(lost):
        to = reached[(x[lost] @ x[reached].T).argmax(1)]
        e = np.concatenate([e, np.stack([to, lost], 1), np.stack([lost, to], 1)])
    return _lists(np.unique(e, axis=0), n)


def _prune(x: np.ndarray, near: np.ndarray, own: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """Robust pruning for the nodes ``own`` at once: int[node, degree], -1 where fewer stay. ``near``: candidates, nearest first."""
    n, k = near.shape
    me, vecs = np.arange(n), x[near]
    dist = np.sqrt(np.maximum(2 - 2 * np.einsum("nkd,nd->nk", vecs, x[own]), 0))
    alive = near != own[:, None]
    out = np.full((n, degree), -1)
    for r in range(degree):
        has = alive.any(1)
        if not has.any():
            break
        first = alive.argmax(1)
        p = near[me, first]
        out[has, r] = p[has]
        between = np.sqrt(np.maximum(2 - 2 * np.einsum("nkd,nd->nk", vecs, x[p]), 0))
        alive &= (alpha * between > dist) & (np.arange(k) != first[:, None]) & has[:, None]
    return out


def medoid(x: np.ndarray) -> int:
    """The row nearest to the mean."""
    return int((x @ x.mean(0)).argmax())


def _lists(e: np.ndarray, n: int) -> list[np.ndarray]:
    e = e[np.argsort(e[:, 0], kind="stable")]
    return np.split(e[:, 1], np.searchsorted(e[:, 0], np.arange(1, n)))


def range_search(v: np.ndarray, adj: list[np.ndarray], threshold: float, *, beam: int = 32, steps: int = 64) -> np.ndarray:
    """bool[node, node]: pairs within the threshold that search and expansion find."""
    n = len(v)
    x = v.astype(np.float32)
    wide = max(1, max(len(a) for a in adj))
    table = np.full((n, wide), n)
    for i, a in enumerate(adj):
        table[i, : len(a)] = a
    table = np.concatenate([table, np.full((1, wide), n)])
    xs = np.concatenate([x, np.zeros((1, x.shape[1]), np.float32)])
    found = np.zeros((n, n), bool)
    start = medoid(x)
    for at in range(0, n, 256):
        q = np.arange(at, min(n, at + 256))
        k = len(q)
        seen = np.zeros((k, n + 1), bool)
        seen[:, n] = True
        ids = np.full((k, beam), n)
        sims = np.full((k, beam), -2, np.float32)
        open_ = np.zeros((k, beam), bool)
        ids[:, 0], sims[:, 0], open_[:, 0], seen[:, start] = start, x[q] @ x[start], True, True
        for _ in range(steps):
            live = open_.any(1)
            if not live.any():
                break
            pick = np.where(open_, sims, -3).argmax(1)
            node = np.where(live, ids[np.arange(k), pick], n)
            open_[np.arange(k), pick] = False
            nb = np.sort(table[node], 1)
            fresh = ~np.take_along_axis(seen, nb, 1)
            fresh[:, 1:] &= nb[:, 1:] != nb[:, :-1]
            nb = np.where(fresh, nb, n)
            seen[np.arange(k)[:, None], nb] = True
            s = np.where(nb < n, np.einsum("kwd,kd->kw", xs[nb], x[q]), -2)
            all_i, all_s, all_o = np.concatenate([ids, nb], 1), np.concatenate([sims, s], 1), np.concatenate([open_, nb < n], 1)
            top = np.argpartition(-all_s, beam - 1, 1)[:, :beam]
            ids, sims, open_ = (np.take_along_axis(a, top, 1) for a in (all_i, all_s, all_o))
        # Range expansion: through everything within the threshold, however far the group reaches.
        a, b = np.nonzero(sims >= threshold - 1e-4)
        own, node = a, ids[a, b]
        done = np.zeros((k, n + 1), bool)
        done[:, n] = True
        done[own, node] = True
        done[np.arange(k), q] = True
        own, node = np.concatenate([own, np.arange(k)]), np.concatenate([node, q])
        inside = np.zeros((k, n), bool)
        while len(own):
            nxt = []
            for s0 in range(0, len(own), 1 << 14):
                o, m = own[s0 : s0 + (1 << 14)], node[s0 : s0 + (1 << 14)]
                inside[o, m] = True
                flat = (o[:, None] * (n + 1) + table[m]).ravel()
                flat = np.unique(flat[~done.ravel()[flat]])
                done.ravel()[flat] = True
                o, m = flat // (n + 1), flat % (n + 1)
                good = np.concatenate([np.einsum("nd,nd->n", x[q[o[c : c + 65536]]], x[m[c : c + 65536]]) for c in range(0, len(o), 65536)] or [np.zeros(0)]) >= threshold - 1e-4
                nxt.append((o[good], m[good]))
            own, node = np.concatenate([p[0] for p in nxt]), np.concatenate([p[1] for p in nxt])
        found[q] = inside
    found |= found.T
    np.fill_diagonal(found, False)
    for at in range(0, n, 512):  # verified in double precision
        rows = slice(at, at + 512)
        if found[rows].any():
            found[rows] &= (v[rows] @ v.T) >= threshold
    return found


def _tally(found: np.ndarray, ids: np.ndarray, copies: np.ndarray, shards: np.ndarray, shard: int) -> tuple[np.ndarray, np.ndarray]:
    """Links counted here (each pair in the first shard that both have), and the smallest id linked through."""
    n = len(ids)
    links = np.zeros(n, np.int64)
    for at in range(0, n, 256):
        a, b = np.nonzero(found[at : at + 256])
        if len(a):
            # Shard lists ascend: the pair is this shard's unless they share a smaller one.
            both = (shards[at + a][:, :, None] == shards[b][:, None, :]) & (shards[at + a] < shard)[:, :, None]
            mine = ~both.any((1, 2))
            np.add.at(links, at + a[mine], copies[b[mine]])
    low = ids.copy()
    order = np.argsort(ids)
    rank = np.empty(n, np.int64)
    rank[order] = np.arange(n)
    label = rank.copy()
    touched = np.flatnonzero(found.any(1))
    while len(touched):
        new = label.copy()
        for at in range(0, len(touched), 256):
            t = touched[at : at + 256]
            new[t] = np.minimum(label[t], np.where(found[t], label[None, :], n).min(1))
        new = np.minimum(new, new[order[new]])
        if (new == label).all():
            break
        label = new
    return links, ids[order[label]] if n else low


def _group(fn, df: DataFrame, key: str, kind: str) -> DataFrame:
    return df.groupBy(key).applyInArrow(fn, kind)


def found_links(placed: DataFrame, *, threshold: float, most: int, exact_only: bool = False) -> DataFrame:
    """``(vec_id, links, low)`` from every shard; ``exact_only``: without a graph."""
    sizes = placed.groupBy("shard").agg(F.count("*").alias("n"))
    placed = placed.join(sizes, "shard")
    usual, dense = placed.where(F.col("n") <= most), placed if exact_only else placed.where(F.col("n") > most)

    def build(table: pa.Table) -> pa.Table:
        ids = np.asarray(table.column("vec_id").combine_chunks())
        adj = build_graph(_matrix(table.column("v")))
        return pa.table({"vec_id": ids, "near": pa.array([ids[a] for a in adj], pa.list_(pa.int64()))})

    if not exact_only:
        flat = _group(build, usual, "shard", "vec_id long, near array<long>").groupBy("vec_id").agg(F.array_distinct(F.flatten(F.collect_list("near"))).alias("near"))
        flat = cut(flat)

    def search(table: pa.Table) -> pa.Table:
        ids = np.asarray(table.column("vec_id").combine_chunks())
        order = np.argsort(ids)
        near = table.column("near").combine_chunks()
        own, to = np.repeat(np.arange(len(ids)), np.diff(np.asarray(near.offsets))), np.asarray(near.flatten())
        at = order[np.minimum(np.searchsorted(ids[order], to), len(ids) - 1)]
        here = ids[at] == to
        v = _matrix(table.column("v"))
        found = range_search(v, _lists(np.stack([own[here], at[here]], 1), len(ids)), threshold)
        return tallied(table, found)

    def tallied(table: pa.Table, found: np.ndarray) -> pa.Table:
        ids = np.asarray(table.column("vec_id").combine_chunks())
        links, low = _tally(found, ids, np.asarray(table.column("copies").combine_chunks()), _ints(table.column("shards")), table.column("shard")[0].as_py())
        return pa.table({"vec_id": ids, "links": links, "low": low})

    blocks = dense.withColumn("blocks", F.ceil(F.col("n") * 2 / most).cast("int")).withColumn("mine", F.pmod(F.xxhash64("vec_id"), F.col("blocks").cast("long")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    units = blocks.withColumn("o", other).withColumns({"i": F.least("mine", "o"), "j": F.greatest("mine", "o")})

    def exact(table: pa.Table) -> pa.Table:
        v, side = _matrix(table.column("v")), np.asarray(table.column("mine").combine_chunks())
        found = np.zeros((len(v), len(v)), bool)
        for at in range(0, len(v), 512):
            found[at : at + 512] = v[at : at + 512] @ v.T >= threshold
        np.fill_diagonal(found, False)
        if table.column("i")[0].as_py() != table.column("j")[0].as_py():
            found &= side[:, None] != side[None, :]
        return tallied(table, found)

    compared = units.groupBy("shard", "i", "j").applyInArrow(exact, "vec_id long, links long, low long")
    return compared if exact_only else _group(search, usual.join(flat, "vec_id"), "shard", "vec_id long, links long, low long").union(compared)


def _ints(column: pa.ChunkedArray) -> np.ndarray:
    """Ascending lists as rows of one width, with different fill-ins for each row so that no two share one."""
    column = column.combine_chunks()
    size = np.diff(np.asarray(column.offsets))
    out = np.iinfo(np.int64).max - np.arange(len(column) * (size.max() if len(size) else 0), dtype=np.int64).reshape(len(column), -1)
    own = np.repeat(np.arange(len(column)), size)
    out[own, np.arange(len(own)) - np.repeat(np.cumsum(size) - size, size)] = np.asarray(column.flatten())
    return out


def audit_recall(reps: DataFrame, counted: DataFrame, *, threshold: float, queries: int) -> float:
    """Mean share of its links that was found, over those of ``queries`` vectors that have a link among all rows."""
    # Drawn by a hash, whatever was found; every query counts alike, however many links it has.
    drawn = reps.orderBy(F.xxhash64("vec_id", F.lit(5)), "vec_id").limit(queries)
    picked = drawn.join(counted, "vec_id", "left").select("vec_id", "v", F.coalesce("links", F.lit(0)).alias("links")).toArrow()
    q, ids, n = _unit(_matrix(picked.column("v"))), np.asarray(picked.column("vec_id")), picked.num_rows

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits = np.zeros(n, np.int64)
        for whole in batches:
            for at in range(0, whole.num_rows, 2048):
                batch = whole.slice(at, 2048)
                close = (q @ _unit(_matrix(batch.column(2))).T >= threshold) & (ids[:, None] != np.asarray(batch.column(0))[None, :])
                hits += close @ np.asarray(batch.column(1))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(n)), pa.array(hits)], names=["q", "hits"])

    if not n:
        return 1.0
    true = {r.q: r.hits for r in reps.select("vec_id", "copies", "v").mapInArrow(count, "q long, hits long").groupBy("q").agg(F.sum("hits").alias("hits")).collect()}
    there = np.array([true[i] for i in range(n)], float)
    got = np.asarray(picked.column("links")).astype(float)
    has = there > 0
    return float((np.minimum(got, there)[has] / there[has]).mean()) if has.any() else 1.0


def whole_shards(reps: DataFrame) -> DataFrame:
    """As :func:`assign_shards`, with all vectors of a length in one shard, named by the length."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            size = np.diff(np.asarray(batch.column(2).offsets))
            for n in np.unique(size):
                some = batch.filter(pa.array(size == n))
                x, at = _unit(_matrix(some.column(2))), np.arange(some.num_rows + 1, dtype=np.int32)
                shard = pa.array(np.full(some.num_rows, n, np.int64))
                yield pa.RecordBatch.from_arrays([shard, some.column(0), some.column(1), pa.ListArray.from_arrays(pa.array(at), shard), pa.ListArray.from_arrays(pa.array(at * np.int32(n)), pa.array(x.ravel()))], names=["shard", "vec_id", "copies", "shards", "v"])

    return reps.select("vec_id", "copies", "v").mapInArrow(run, "shard long, vec_id long, copies long, shards array<long>, v array<double>")


def _links_of_length(reps: DataFrame, n: int, *, threshold: float, shard: int, most: int, overlap: int, recall: float, queries: int, tries: int) -> tuple[DataFrame, float]:
    """``(vec_id, links, low)`` of vectors of one length, and the audited recall: no attempt is taken without its audit."""
    centroids = fit_centroids(reps, n, shard=shard)
    for k in range(tries):
        placed = split_shards(cut(assign_shards(reps, centroids, overlap + k)), shard=shard, most=most, overlap=overlap + k)
        found = cut(found_links(placed, threshold=threshold, most=most))
        counted = found.groupBy("vec_id").agg(F.sum("links").alias("links"))
        seen = audit_recall(reps, counted, threshold=threshold, queries=queries)
        if seen >= recall:
            return found, seen
    return cut(found_links(cut(whole_shards(reps)), threshold=threshold, most=most, exact_only=True)), 1.0


def vector_links(vectors: DataFrame, *, threshold: float = THRESHOLD, shard: int = 1000, most: int = 4096, overlap: int = 2, recall: float = 0.95, queries: int = 512, tries: int = 3) -> DataFrame:
    """``(vec_id, n_links, component_id, kept, audited_recall)`` of every row; the recall is the lowest of any length's audit."""
    rows = usable(vectors)
    reps = cut(rows.groupBy("v").agg(F.min("vec_id").alias("vec_id"), F.count("*").alias("copies")).select("vec_id", "copies", "v"))
    every = vectors.select(F.col("vec_id").cast("long").alias("vec_id"))
    lengths = reps.groupBy(F.size("v").alias("size")).agg(F.count("*").alias("n"))
    top = [(r["size"], r["n"]) for r in lengths.orderBy(F.desc("n"), "size").limit(1).collect()]
    if not top:
        return every.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"), F.lit(1.0).alias("audited_recall"))
    large = top + [(r["size"], r["n"]) for r in lengths.where((F.col("n") > most) & (F.col("size") != top[0][0])).collect()]
    found, audited = None, 1.0
    for size, n in large:
        part, seen = _links_of_length(reps.where(F.size("v") == size), n, threshold=threshold, shard=shard, most=most, overlap=overlap, recall=recall, queries=queries, tries=tries)
        found, audited = part if found is None else found.union(part), min(audited, seen)
    small = reps.where(~F.size("v").isin([size for size, _ in large]))
    if not small.isEmpty():
        found = found.union(cut(found_links(cut(whole_shards(small)), threshold=threshold, most=most, exact_only=True)))
    counted = found.groupBy("vec_id").agg(F.sum("links").alias("links"))
    parts = link_components(found.where("low < vec_id").select(F.col("vec_id").alias("a"), F.col("low").alias("b")))
    of_rep = reps.select(F.col("vec_id").alias("rep"), "copies", "v").join(counted.withColumnRenamed("vec_id", "rep"), "rep", "left").join(parts, F.col("rep") == F.col("node"), "left")
    named = rows.join(of_rep, "v").groupBy("vec_id").agg(F.max(F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n"), F.min(F.coalesce("component", "rep")).alias("c"))
    return every.join(named, "vec_id", "left").select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), F.coalesce("c", "vec_id").alias("component_id")).withColumns({"kept": F.col("vec_id").eqNullSafe(F.col("component_id")), "audited_recall": F.lit(audited)})
