"""Single steps of star hooking on parent tables ``P(v, p)``."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.algebra.kernel import grid_block
from starforest.graph.order import directed
from starforest.runtime import cut_state


def initial_parents(vertices: DataFrame) -> DataFrame:
    """Every vertex is its own parent."""
    return vertices.select("v", F.col("v").alias("p"))


def grandparents(parents: DataFrame) -> DataFrame:
    """``(v, p, g)``."""
    up = parents.select(F.col("v").alias("p"), F.col("p").alias("g"))
    return parents.join(up, "p").select("v", "p", "g")


def star_flags(parents: DataFrame) -> DataFrame:
    """``(v, p, is_star)``: whether a vertex belongs to a tree of height one at most.

    A vertex whose parent is no root is in no star, nor is its grandparent; everyone else has its parent's answer.
    """
    g = grandparents(parents)
    deep = g.where("p <> g")
    bad = deep.select("v").union(deep.select(F.col("g").alias("v"))).distinct().withColumn("bad", F.lit(True))
    own = g.join(bad, "v", "left").select("v", "p", F.col("bad").isNull().alias("own"))
    above = own.select(F.col("v").alias("p"), F.col("own").alias("above"))
    return own.join(above, "p").select("v", "p", (F.col("own") & F.col("above")).alias("is_star"))


def all_stars(parents: DataFrame) -> DataFrame:
    """Flags where every tree is known to be a star: no check needed."""
    return parents.select("v", "p", F.lit(True).alias("is_star"))


def vertex_candidates(edges: DataFrame, flags: DataFrame) -> DataFrame:
    """``(v, rank, parent)``: each star member's lightest edge to another tree, with the far side's parent."""
    d = directed(edges).select("i", "j", "rank")
    near = flags.where("is_star").select(F.col("v").alias("i"), F.col("p").alias("pi"))
    far = flags.select(F.col("v").alias("j"), F.col("p").alias("pj"))
    return d.join(near, "i").join(far, "j").where("pi <> pj").groupBy(F.col("i").alias("v")).agg(F.min("rank").alias("rank"), F.min_by("pj", "rank").alias("parent"))


def project_to_root(candidates: DataFrame, parents: DataFrame) -> DataFrame:
    """``(root, rank, parent)``: the lightest candidate among a root's members."""
    return candidates.join(parents.select("v", F.col("p").alias("root")), "v").groupBy("root").agg(F.min("rank").alias("rank"), F.min_by("parent", "rank").alias("parent"))


@contextmanager
def grid_layout(edges: DataFrame, grid: int) -> Iterator[DataFrame]:
    """The edge table dealt out once by grid block, as a bucketed table that later joins by block never move.

    While it is open, joins may be co-partitioned by some of their keys (here: the block), which a session allows
    or not by a setting that may change while it runs.
    """
    spark, name, setting = edges.sparkSession, f"grid_{uuid.uuid4().hex}", "spark.sql.requireAllClusterKeysForCoPartition"
    cell = (grid_block(F.col("lo"), grid) * grid + grid_block(F.col("hi"), grid)).cast("int")
    columns = [c for c in ("rank", "lo", "hi", "w") if c in edges.columns]
    before = spark.conf.get(setting)
    edges.select(*columns, cell.alias("cell")).repartition(grid * grid, "cell").write.bucketBy(grid * grid, "cell").saveAsTable(name)
    spark.conf.set(setting, "false")
    try:
        yield spark.table(name)
    finally:
        spark.conf.set(setting, before)
        spark.sql(f"DROP TABLE IF EXISTS {name}")


def root_candidates(edges: DataFrame, flags: DataFrame, *, plan: str = "auto", grid: int = 4, carry: tuple[str, ...] = ()) -> DataFrame:
    """Both of the above in one aggregation: each edge yields a candidate for either side's root.

    The edge table is read once and neither written nor exploded before its two joins; partial aggregation
    leaves at most one row for each root and task to shuffle. ``broadcast`` is for callers that have checked
    the number of vertices (the loop does); ``grid`` wants the table of :func:`grid_layout`, which stays where it is while the
    parents are sent along its rows and columns. ``carry``: columns of the edges that come along.
    """
    side = {s: flags.select(F.col("v").alias(s), F.col("p").alias(f"p_{s}"), F.col("is_star").alias(f"s_{s}")) for s in ("lo", "hi")}
    if plan == "grid":
        spread, block = F.explode(F.sequence(F.lit(0), F.lit(grid - 1))).alias("other"), {s: grid_block(F.col(s), grid) for s in ("lo", "hi")}
        lo = side["lo"].select("*", spread).withColumn("cell", (block["lo"] * grid + F.col("other")).cast("int")).drop("other").hint("merge")
        hi = side["hi"].select("*", spread).withColumn("cell", (F.col("other") * grid + block["hi"]).cast("int")).drop("other").hint("merge")
        joined = edges.select("rank", "lo", "hi", *carry, "cell").join(lo, ["cell", "lo"]).join(hi, ["cell", "hi"])
    else:
        if plan == "broadcast":
            side = {k: F.broadcast(v) for k, v in side.items()}
        elif plan == "shuffle":
            side = {k: v.hint("merge") for k, v in side.items()}
        joined = edges.select("rank", "lo", "hi", *carry).join(side["lo"], "lo").join(side["hi"], "hi")
    def half(a: str, b: str):
        return F.when(F.col(f"s_{a}"), F.struct(F.col(f"p_{a}").alias("root"), F.col(f"p_{b}").alias("parent")))

    both = F.explode(F.array_compact(F.array(half("lo", "hi"), half("hi", "lo"))))
    out = joined.where("p_lo <> p_hi and (s_lo or s_hi)").select("rank", *carry, both.alias("c")).select("c.root", "c.parent", "rank", *carry)
    return out.groupBy("root").agg(F.min("rank").alias("rank"), F.min_by("parent", "rank").alias("parent"), *[F.min_by(c, "rank").alias(c) for c in carry])


def settle(roots: DataFrame) -> DataFrame:
    """``(root, rank, parent, to, candidates, rounds[, w])``: hooks that stay and the root that each chain of them ends at.

    For candidates of a checked number (the loop does): one task chases the whole map, as every process does once the changed
    roots are gathered. ``candidates`` (all there were) and ``rounds`` (of pointer doubling) are the same in every row.
    """
    more = [c for c in ("w",) if c in roots.columns]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not held or not sum(b.num_rows for b in held):
            return
        t = pa.Table.from_batches(held)
        root, parent = (t.column(c).to_numpy() for c in ("root", "parent"))
        order = np.argsort(root)
        name = root[order]
        at = np.minimum(np.searchsorted(name, parent), len(name) - 1)
        hooked = name[at] == parent  # whether the parent hooks, too
        back = hooked & (parent[order][at] == root)
        stays = ~back | (root > parent)
        # Where each root points among the roots; those that stay put point to themselves.
        place = np.empty(len(root), np.int64)
        place[order] = np.arange(len(root))
        to = np.where(stays & hooked, at, place)[order]
        end, rounds = to, 0
        while not ((nxt := end[end]) == end).all():
            end, rounds = nxt, rounds + 1
            if rounds > 64:
                raise ValueError("the map of changed roots has a cycle")
        # The last root of a chain that stays and whose parent does not hook moves to that parent.
        last = order[end[place]]
        final = np.where(stays[last], parent[last], root[last])
        n = int(stays.sum())
        cols = [pa.array(root[stays]), t.column("rank").combine_chunks().filter(pa.array(stays)), pa.array(parent[stays]), pa.array(final[stays]), pa.array(np.full(n, len(root))), pa.array(np.full(n, rounds, np.int32)), *(t.column(c).combine_chunks().filter(pa.array(stays)) for c in more)]
        yield pa.RecordBatch.from_arrays(cols, names=["root", "rank", "parent", "to", "candidates", "rounds", *more])

    kinds = "root long, rank long, parent long, to long, candidates long, rounds int" + "".join(f", {c} {dict(roots.dtypes)[c]}" for c in more)
    return roots.repartition(1).mapInArrow(run, kinds)


def two_pass_candidates(edges: DataFrame, flags: DataFrame) -> tuple[DataFrame, int]:
    """The pairwise form: writes (rank, far parent) for every entry of the matrix first. Returns rows written, too."""
    far = flags.select(F.col("v").alias("j"), F.col("p").alias("parent"))
    written = cut_state(directed(edges).select("i", "j", "rank").join(far, "j").select("i", "rank", "parent"))
    near = flags.where("is_star").select(F.col("v").alias("i"), F.col("p").alias("root"))
    out = written.join(near, "i").where("root <> parent").groupBy("root").agg(F.min("rank").alias("rank"), F.min_by("parent", "rank").alias("parent"))
    return out, written.count()


def hook(parents: DataFrame, roots: DataFrame) -> DataFrame:
    """Roots take the parent of their candidate; all others stay."""
    new = roots.select(F.col("root").alias("v"), F.col("parent").alias("_new"))
    return parents.join(new, "v", "left").select("v", F.coalesce("_new", "p").alias("p"))


def undone_roots(roots: DataFrame) -> DataFrame:
    """``(root)``: of two roots that hooked onto each other in this iteration, the smaller."""
    back = roots.select(F.col("root").alias("parent"), F.col("parent").alias("_back"))
    return roots.join(back, "parent").where("_back = root and root < parent").select("root")


def accepted_hooks(roots: DataFrame, *, small: bool = False) -> DataFrame:
    """``(root, rank, parent)`` without the undone ones: also the map of changed roots. ``small``: their number was checked."""
    back = roots.select(F.col("root").alias("parent"), F.col("parent").alias("_back"))
    back = F.broadcast(back) if small else back
    return roots.join(back, "parent", "left").where("_back is null or _back <> root or root > parent").select("root", "rank", "parent")


def break_ties(parents: DataFrame, roots: DataFrame) -> DataFrame:
    """Undone roots become roots again."""
    undone = undone_roots(roots).select(F.col("root").alias("v"), F.lit(True).alias("_undone"))
    return parents.join(undone, "v", "left").select("v", F.when(F.col("_undone"), F.col("v")).otherwise(F.col("p")).alias("p"))


def changed_roots(parents: DataFrame, previous: DataFrame) -> DataFrame:
    """``(root, parent)``: vertices whose parent is not what it was (compare two parent tables)."""
    return parents.alias("n").join(previous.alias("o"), "v").where("n.p <> o.p").select(F.col("v").alias("root"), F.col("n.p").alias("parent"))


def tree_heights(parents: DataFrame, max_rounds: int = 64) -> DataFrame:
    """``(v, root, depth)`` by pointer doubling; raises on a cycle."""
    cur = cut_state(parents.select("v", "p", F.when(F.col("v") == F.col("p"), 0).otherwise(1).cast("long").alias("d")))
    for _ in range(max_rounds):
        up = cur.select(F.col("v").alias("p"), F.col("p").alias("g"), F.col("d").alias("e"))
        nxt = cut_state(cur.join(up, "p").select("v", F.col("g").alias("p"), (F.col("d") + F.col("e")).alias("d"), (F.col("p") != F.col("g")).alias("m")))
        moved = nxt.agg(F.bool_or("m")).first()[0]
        cur = nxt.select("v", "p", "d")
        if not moved:
            roots = parents.where("v = p").select(F.col("v").alias("p"))
            if cur.join(roots, "p", "left_anti").limit(1).count():
                raise ValueError("the parent table has a cycle")
            return cur.select("v", F.col("p").alias("root"), F.col("d").alias("depth"))
    raise ValueError("the parent table has a cycle")


def is_star_forest(parents: DataFrame) -> bool:
    return grandparents(parents).where("p <> g").limit(1).count() == 0


def height_potential(parents: DataFrame) -> int:
    """Sum of the heights of all trees."""
    h = tree_heights(parents).groupBy("root").agg(F.max("depth").alias("h"))
    return int(h.agg(F.sum("h")).first()[0] or 0)


def is_rooted_forest(parents: DataFrame) -> bool:
    """Whether the parent table is a function on its vertices without cycles but the roots' own."""
    sound = parents.agg(F.count("*").alias("n"), F.countDistinct("v").alias("d"), F.count("p").alias("p")).first()
    if sound.n != sound.d or sound.n != sound.p:
        return False
    if parents.join(parents.select(F.col("v").alias("p")), "p", "left_anti").limit(1).count():
        return False
    try:
        tree_heights(parents)
    except ValueError:
        return False
    return True
