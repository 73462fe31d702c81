"""Graphs of shared tokens: the thinned edges against all pairs."""

import random

import pytest
from pyspark.sql import functions as F

from starforest.baselines import kruskal_local
from starforest.graph.token_sets import forest_edges, link_counts, token_sets


def _tables():
    rng = random.Random(3)
    mixed = [(i, [f"t{rng.randrange(9)}" for _ in range(rng.randrange(5))] + ["common"] * (i % 2)) for i in rng.sample(range(1000), 60)]
    copies = [(i, ["a", "b", "c"][: 1 + i % 3]) for i in range(40)] + [(100, None), (101, ["alone"]), (102, ["a", None, "a"]), (7, ["b", "z"])]
    return [mixed, copies, [(i, ["common", f"own{i}"]) for i in range(50)]]


@pytest.mark.parametrize("rows", _tables(), ids=["mixed", "copies", "common"])
def test_thinned_edges_hold_the_forest_and_counts_are_exact(spark, rows):
    own = {}
    for v, t in rows:
        own.setdefault(v, set()).update(x for x in t or [] if x)
    names = sorted(own)
    full = [(a, b, 1000 - len(own[a] & own[b])) for i, a in enumerate(names) for b in names[i + 1 :] if own[a] & own[b]]
    sets = token_sets(spark.createDataFrame(rows, "v long, t array<string>"), F.col("v"), F.col("t"))
    thin = [tuple(r) for r in forest_edges(sets).collect()]
    assert kruskal_local(thin) == kruskal_local(full)
    assert {e[:2] for e in thin} <= {e[:2] for e in full}
    want = {v: sum(v in e[:2] for e in full) for v in names}
    assert dict(tuple(r) for r in link_counts(sets).collect()) == {v: n for v, n in want.items() if n}


def test_a_common_token_makes_no_pairs(spark):
    rows = [(i, ["common", f"x{i // 2}"]) for i in range(200)]
    sets = token_sets(spark.createDataFrame(rows, "v long, t array<string>"), F.col("v"), F.col("t"))
    # 19,900 pairs share the common token.
    assert forest_edges(sets).count() <= 300
    assert {r.n_links for r in link_counts(sets).collect()} == {199}
