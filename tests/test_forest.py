"""The hand graph, edge cases and random graphs against union-find."""

import random

import pytest
from pyspark.sql import functions as F

from starforest.baselines import kruskal_local, prim_local
from starforest.components.connectivity import connected_components
from starforest.components.links import link_components
from starforest.forest import shortcut as sc
from starforest.forest import held, loop, steps
from starforest.forest.loop import check_bounds, minimum_spanning_forest, minimum_spanning_tree
from starforest.forest.measures import check_cut_property
from starforest.graph.order import GraphError, canonical_edges, rank_edges, validate_graph, vertices_of
from starforest.sources import from_rows

HAND = [(0, 1, 4), (1, 2, 7), (2, 3, 2), (0, 3, 9), (3, 4, 5), (4, 5, 1), (2, 5, 8), (6, 7, 6), (7, 8, 3), (6, 8, 10)]


@pytest.fixture(scope="module")
def hand(spark):
    return rank_edges(from_rows(spark, HAND)), spark.range(10).withColumnRenamed("id", "v")


def _rows(df):
    return {tuple(r) for r in df.collect()}


def test_hand_graph_first_iteration(hand):
    edges, vertices = hand
    p = steps.initial_parents(vertices)
    r = steps.root_candidates(edges, steps.all_stars(p))
    assert {(x.root, x.parent) for x in r.collect()} == {(0, 1), (1, 0), (2, 3), (3, 2), (4, 5), (5, 4), (6, 7), (7, 8), (8, 7)}
    assert {x.root for x in steps.undone_roots(r).collect()} == {0, 2, 4, 7}
    hooked = steps.break_ties(steps.hook(p, r), r)
    assert [x.p for x in hooked.orderBy("v").collect()] == [0, 0, 2, 2, 4, 4, 7, 7, 7, 9]
    assert {(x.root, x.parent) for x in steps.accepted_hooks(r).collect()} == {(1, 0), (3, 2), (5, 4), (6, 7), (8, 7)}


@pytest.mark.parametrize("shortcut", ["step", "queried", "prefetched"])
def test_hand_graph(hand, shortcut):
    edges, vertices = hand
    found = minimum_spanning_forest(edges, vertices, shortcut=shortcut)
    assert {r.w for r in found.forest.collect()} == {1, 2, 3, 4, 5, 6, 7}
    assert {frozenset(g) for g in _groups(found.components())} == {frozenset(range(6)), frozenset({6, 7, 8}), frozenset({9})}
    assert all(check_bounds(found).values())


def _groups(df):
    out = {}
    for v, c in df.collect():
        out.setdefault(c, set()).add(v)
    return out.values()


def test_ties_cannot_close_a_cycle(spark):
    edges = rank_edges(from_rows(spark, [(0, 1, 1), (1, 2, 1), (0, 2, 1)]))
    assert _rows(minimum_spanning_forest(edges).forest.select("lo", "hi", "w")) == {(0, 1, 1), (0, 2, 1)}


def test_random_graphs_match_union_find(spark):
    rng = random.Random(5)
    rows, expected = [], set()
    for g in range(25):  # graphs side by side in one table: their forests are the forest of the whole
        n = rng.randint(2, 14)
        own = {}
        for _ in range(rng.randint(1, 2 * n)):
            a, b = rng.sample(range(n), 2)
            key = (g * 100 + min(a, b), g * 100 + max(a, b))
            own[key] = min(own.get(key, 99), rng.randint(-2, 3))
        mine = [(a, b, w) for (a, b), w in own.items()]
        rows += mine
        expected |= kruskal_local(mine)
        assert kruskal_local(mine) == prim_local(mine)
    edges = rank_edges(from_rows(spark, rows))
    for options in ({"shortcut": "step"}, {"shortcut": "prefetched"}, {"kernel": "two_pass"}):
        assert _rows(minimum_spanning_forest(edges, **options).forest.select("lo", "hi", "w")) == expected
    low = {}
    for v, c in connected_components(edges).collect():
        low.setdefault(c, set()).add(v)
    for v, c in link_components(edges, "lo", "hi").collect():
        assert v in low[c]


def test_empty_and_isolated(spark):
    none = rank_edges(from_rows(spark, [(1, 1, 5)]))
    found = minimum_spanning_forest(none, spark.range(3).withColumnRenamed("id", "v"))
    assert found.forest.count() == 0 and found.components().count() == 3


def test_errors(spark, hand):
    edges, vertices = hand
    with pytest.raises(ValueError, match="components"):
        minimum_spanning_tree(edges, vertices)
    with pytest.raises(ValueError, match="unknown shortcut"):
        minimum_spanning_forest(edges, shortcut="none")
    deep = spark.createDataFrame([(0, 0), (1, 0), (2, 1)], "v long, p long")
    with pytest.raises(ValueError, match="star forest"):
        sc.shortcut_prefetched(deep, deep.limit(0).selectExpr("v as root", "p as parent"))
    with pytest.raises(ValueError, match="cycle"):
        steps.tree_heights(spark.createDataFrame([(0, 1), (1, 0)], "v long, p long"), max_rounds=4)
    with pytest.raises(GraphError):
        validate_graph(edges.withColumn("w", F.lit(None).cast("long")))


def test_star_check_inherits(spark):
    # Height three with a sibling at depth one: nobody of that tree is in a star.
    p = spark.createDataFrame([(0, 0), (1, 0), (2, 1), (3, 2), (4, 0), (5, 5), (6, 5)], "v long, p long")
    flags = {r.v: r.is_star for r in steps.star_flags(p).collect()}
    assert flags == {0: False, 1: False, 2: False, 3: False, 4: False, 5: True, 6: True}


def test_kernel_plan_has_no_sort_aggregate(hand):
    edges, vertices = hand
    flags = steps.all_stars(steps.initial_parents(vertices_of(edges)))
    plan = steps.root_candidates(edges, flags)._jdf.queryExecution().toString()
    assert "SortAggregate" not in plan and "Python" not in plan


def test_grid_plan_leaves_the_edges_where_they_are(spark):
    rows = [(i, i, i + 1, i) for i in range(200)]
    edges = spark.createDataFrame(rows, "rank long, lo long, hi long, w long")
    before = spark.conf.get("spark.sql.requireAllClusterKeysForCoPartition")
    flags = steps.all_stars(steps.initial_parents(vertices_of(edges)))
    with steps.grid_layout(edges, 3) as laid:
        plan = steps.root_candidates(laid, flags, plan="grid", grid=3)._jdf.queryExecution().executedPlan().toString()
        lines = plan.splitlines()
        scan = next(i for i, x in enumerate(lines) if "FileScan" in x)
        # Above the scan of the edges, up to the aggregation by root, nothing is exchanged.
        depth, above = len(lines[scan]) - len(lines[scan].lstrip(" :+-")), []
        for x in reversed(lines[:scan]):
            here = len(x) - len(x.lstrip(" :+-*()0123456789"))
            if here < depth:
                depth = here
                above.append(x)
        assert sum("Exchange" in x for x in above) == 1 and "hashpartitioning(root" in next(x for x in above if "Exchange" in x)
    assert spark.conf.get("spark.sql.requireAllClusterKeysForCoPartition") == before


def test_weight_mode_full_and_mixed_shortcuts(spark):
    rng = random.Random(8)
    rows = [(rng.randrange(300), rng.randrange(300), rng.randrange(50)) for _ in range(500)]
    edges = rank_edges(canonical_edges(spark.createDataFrame(rows, "a long, b long, w long")))
    whole = minimum_spanning_forest(edges)
    total = whole.weight().first()
    light = minimum_spanning_forest(edges, mode="weight")
    assert light.weight().first() == total
    with pytest.raises(ValueError):
        light.forest
    ranks = {r.rank for r in whole.accepted.collect()}
    for options in ({"shortcut": "full"}, {"shortcut": "scheduled", "first_sub_iterations": 1}, {"plan": "grid", "grid": 3}):
        found = minimum_spanning_forest(edges, **options)
        assert {r.rank for r in found.accepted.collect()} == ranks
    full = minimum_spanning_forest(edges, shortcut="full")
    assert all(check_bounds(full).values()) and max(t.sub_iterations for t in full.trace) > 0
    assert steps.is_rooted_forest(full.parents)
    assert not steps.is_rooted_forest(spark.createDataFrame([(1, 2), (2, 1)], "v long, p long"))
    assert not steps.is_rooted_forest(spark.createDataFrame([(1, 9)], "v long, p long"))
    inside = spark.createDataFrame([(v,) for v in range(0, 300, 3)], "v long")
    assert check_cut_property(whole.forest, edges, inside)
    assert not check_cut_property(whole.forest.where("rank < 0"), edges, inside)


def test_held_plan_is_the_grid_plan(spark, monkeypatch):
    # Names uneven and negative, one of them isolated; the trace, the forest and the parents are those of the grid.
    rng = random.Random(8)
    rows = [(rng.randrange(300) ** 2 - 900, rng.randrange(300) ** 2 - 900, rng.randrange(50)) for _ in range(500)]
    edges, alone = rank_edges(canonical_edges(spark.createDataFrame(rows, "a long, b long, w long"))), spark.createDataFrame([(-5000,)], "v long")
    grid = minimum_spanning_forest(edges, alone, plan="grid", grid=2)
    told = [(t.iteration, t.candidates, t.hooks, t.undone, t.strategy, t.sub_iterations) for t in grid.trace]
    for most in (held.SETTLED_ROWS, 0):
        monkeypatch.setattr(held, "SETTLED_ROWS", most)
        found = minimum_spanning_forest(edges, alone, plan="held")
        assert [(t.iteration, t.candidates, t.hooks, t.undone, t.strategy, t.sub_iterations) for t in found.trace] == told
        assert _rows(found.forest) == _rows(grid.forest) and _rows(found.parents) == _rows(grid.parents)
    asked = minimum_spanning_forest(edges, alone, plan="held", shortcut="queried")
    assert _rows(asked.parents) == _rows(grid.parents) and {t.strategy for t in asked.trace} == {"queried"}
    light = minimum_spanning_forest(edges, plan="held", mode="weight")
    assert light.total == tuple(grid.forest.selectExpr("sum(w)", "count(*)").first())
    # Beyond what is broadcast the loop takes this plan by itself: no bucketed table, no exchange of the parents.
    monkeypatch.setattr(loop, "BROADCAST_ROWS", 10)
    monkeypatch.setattr(steps, "grid_layout", None)
    assert _rows(minimum_spanning_forest(edges).forest) == _rows(grid.forest)


def test_parents_are_held_before_they_are_too_many_to_broadcast(spark, monkeypatch):
    rng = random.Random(9)
    rows = [(rng.randrange(200), rng.randrange(200), rng.randrange(50)) for _ in range(400)]
    edges = rank_edges(canonical_edges(spark.createDataFrame(rows, "a long, b long, w long")))
    sent = minimum_spanning_forest(edges)
    told = [(t.iteration, t.candidates, t.hooks, t.undone, t.strategy, t.sub_iterations) for t in sent.trace]
    monkeypatch.setattr(loop, "HELD_FROM", 10)
    pairwise = minimum_spanning_forest(edges, kernel="vertex")  # cannot hold them, and may still broadcast
    monkeypatch.setattr(steps, "root_candidates", None)
    found = minimum_spanning_forest(edges)
    assert [(t.iteration, t.candidates, t.hooks, t.undone, t.strategy, t.sub_iterations) for t in found.trace] == told
    assert _rows(found.forest) == _rows(sent.forest) == _rows(pairwise.forest) and _rows(found.parents) == _rows(sent.parents)


def test_edges_are_made_once_to_be_ranked(spark):
    seen = spark.sparkContext.accumulator(0)

    def watched(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    rows = [(i, i + 1, 7 - i % 3) for i in range(60)]
    ranked = rank_edges(spark.createDataFrame(rows, "lo long, hi long, w long").mapInArrow(watched, "lo long, hi long, w long"))
    assert [(r.lo, r.hi, r.w) for r in ranked.orderBy("rank").collect()] == sorted(rows, key=lambda r: (r[2], *r[:2]))
    assert seen.value == len(rows)


def test_held_names_spread_evenly_or_not():
    import numpy as np

    for name in ([], [5], [16, 32, 48, 80], [-7, 1, 2, 3, 10**9], [-(2**63), 0, 2**63 - 1]):
        name = np.array(name, np.int64)
        assert held._places(name)(name).tolist() == list(range(len(name)))
