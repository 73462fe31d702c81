"""Any spanning forest, sliding forests, vectors within a radius, the experiments' settings, the entry without a session."""

import os
import random
import subprocess
import sys
from itertools import combinations

from pyspark.sql import functions as F

from starforest.baselines import kruskal_local, prim, prim_local
from starforest.components.connectivity import any_spanning_forest
from starforest.graph import generators
from starforest.graph.builders import radius_edges
from starforest.operators import small_side_join
from starforest.plans import surroundings  # noqa: F401  (adds its queries to the catalogue)
from starforest.plans.catalogue import QUERIES, write_table
from starforest.plans.experiments import parallelism
from starforest.sources import from_rows
from starforest.streaming import IncrementalForest, sliding_forest, stream_forest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
HAND = [(0, 1, 4), (1, 2, 7), (2, 3, 2), (0, 3, 9), (3, 4, 5), (4, 5, 1), (2, 5, 8), (6, 7, 6), (7, 8, 3), (6, 8, 10)]


def test_any_forest_spans_but_is_not_the_lightest(spark):
    found = {tuple(r) for r in any_spanning_forest(from_rows(spark, HAND)).collect()}
    weight = {(a, b): w for a, b, w in HAND}
    again = kruskal_local([(a, b, 1) for a, b in found])
    assert len(found) == len(again) == 7
    assert sum(weight[e] for e in found) > sum(w for *_, w in kruskal_local(HAND))


def test_sliding_forest_is_the_forest_of_each_window(spark):
    rows = [(k % 3, *e) for k, e in enumerate(HAND)]
    found = sliding_forest(spark.createDataFrame(rows, "slice long, lo long, hi long, w long"), 2).collect()
    for win in range(4):
        want = kruskal_local([r[1:] for r in rows if win - 1 <= r[0] <= win])
        assert {(r.lo, r.hi, r.w) for r in found if r.win == win} == want


def _triples(frame):
    return {(r.lo, r.hi, r.w) for r in frame.collect()}


def test_restarted_stream_goes_on_with_its_forest(spark, tmp_path):
    lines, state = str(tmp_path / "edges"), str(tmp_path / "state")
    for upto, part in ((5, HAND[:5]), (10, HAND[5:])):
        spark.createDataFrame(part, "lo long, hi long, w long").coalesce(1).write.mode("append").parquet(lines)
        edges = spark.readStream.schema("lo long, hi long, w long").parquet(lines)
        # Each call makes a keeper of its own: nothing of the first one's memory is left.
        assert _triples(stream_forest(edges, folder=state)) == kruskal_local(HAND[:upto])


def test_batches_delivered_again_or_broken_off_do_not_change_the_forest(spark, tmp_path):
    batches = [spark.createDataFrame(HAND[k : k + 3], "lo long, hi long, w long") for k in (0, 3, 6)]
    folder = str(tmp_path / "forest")
    for k, batch in enumerate(batches):
        IncrementalForest(spark, folder).add(batch, k)
    kept = IncrementalForest(spark, folder)
    assert kept.versions(spark) == [1, 2]
    os.remove(f"{folder}/v2/_SUCCESS")
    assert _triples(kept.current(spark)) == kruskal_local(HAND[:6])
    for _ in range(2):
        IncrementalForest(spark, folder).add(batches[2], 2)
        assert _triples(kept.current(spark)) == kruskal_local(HAND[:9])


def test_sliding_forest_of_nothing(spark):
    assert not sliding_forest(spark.createDataFrame([], "slice long, lo long, hi long, w long"), 2).count()


def test_radius_edges_against_all_pairs(spark):
    points = [(k, [float(k * 7 % 5) - 2, float(k * 3 % 7) - 3, k % 2 * 1.0]) for k in range(30)]
    df = spark.createDataFrame([*points, (99, None)], "id long, x array<float>")
    found = {tuple(r) for r in radius_edges(df, F.col("id"), "x", 1.5).collect()}
    far = {(a, b): sum((p - q) ** 2 for p, q in zip(x, y, strict=True)) ** 0.5 for (a, x), (b, y) in combinations(points, 2)}
    assert found == {(a, b, round(d * 1000)) for (a, b), d in far.items() if d <= 1.5}


def test_parallelism_is_put_back(spark):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    with parallelism(spark, 3):
        assert spark.conf.get("spark.sql.shuffle.partitions") == "3"
    assert spark.conf.get("spark.sql.shuffle.partitions") == before


def test_entry_imports_without_a_session():
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; assert set(e.oracle_sql()) <= set(e.queries())"], cwd=ROOT, capture_output=True, text=True, timeout=120)
    assert not done.returncode, done.stderr


def test_modelled_writes_round_halves_as_sql_does(spark):
    # 10 / 4 = 2.5 and 2.5 + 2 * 3 = 8.5: to even they would be 2 and 8.
    assert [tuple(r) for r in write_table(spark, 10, 3, (16,)).collect()] == [(16, 3, 9)]


def test_only_a_counted_small_side_is_broadcast(spark):
    left, right = spark.range(20).select((F.col("id") % 5).alias("k")), spark.range(4).select(F.col("id").alias("k"), (F.col("id") * 2).alias("x"))
    few, many = small_side_join(left, right, ["k"]), small_side_join(left, right, ["k"], most=3)
    assert sorted(few.collect()) == sorted(many.collect()) and few.count() == 16
    assert "BroadcastHashJoin" in few._jdf.queryExecution().toString() and "Broadcast" not in many._jdf.queryExecution().executedPlan().toString()


def test_generators_take_the_keys_of_a_table(spark, tmp_path):
    ids = spark.createDataFrame([(k,) for k in (0, 1, 2, 5, 40, 41, 79, 80)], "id long")
    assert {tuple(r)[:2] for r in generators.grid_edges(ids, 40).collect()} == {(0, 1), (1, 2), (0, 40), (1, 41), (40, 41), (40, 80)}
    assert set(generators.uniform_edges(spark.range(50), 9).collect()) == set(generators.uniform_graph(spark, 9, 50).collect())
    assert set(generators.rmat_edges(spark.range(16), 3).collect()) == set(generators.rmat_graph(spark, 3, 2).collect())
    spark.range(30).select((F.col("id") * 3).alias("c_custkey")).write.parquet(str(tmp_path / "customer.parquet"))
    spark.range(30).select((F.col("id") * 3).alias("o_orderkey")).write.parquet(str(tmp_path / "orders.parquet"))
    of_source, of_column = QUERIES["source_uniform"](spark, str(tmp_path)), QUERIES["gen_uniform"](spark, str(tmp_path))
    assert set(of_source.collect()) == set(of_column.collect()) and of_source.count() > 20


def test_radius_edges_in_blocks(spark):
    rng = random.Random(4)
    points = [(k, [rng.gauss(0, 1) for _ in range(3)]) for k in range(60)] + [(60, []), (61, [float("nan"), 0.0, 0.0]), (62, [0.0, 0.0]), (63, [0.0, 1.0]), (64, [1e300, 0.0, 0.0]), (65, [1e300, 0.0, 0.0]), (66, [None, 0.0, 0.0])]
    rows = radius_edges(spark.createDataFrame(points, "id long, x array<double>"), F.col("id"), "x", 1.0, block=16)
    far = {(a, b): sum((p - q) ** 2 for p, q in zip(x, y, strict=True)) ** 0.5 for (a, x), (b, y) in combinations(points[:60], 2)}
    assert _triples(rows) == {(a, b, round(d * 1000)) for (a, b), d in far.items() if d <= 1.0} | {(62, 63, 1000), (64, 65, 0)}
    # No pair is tested in the engine's own lambda functions, which took the time.
    assert "FlatMapGroupsInArrow" in rows._jdf.queryExecution().executedPlan().toString()


def test_prim_in_shares_is_prim(spark):
    rng = random.Random(6)
    ends = {tuple(sorted(rng.sample(range(80), 2))) for _ in range(300)} | {(200, 201), (201, 202), (200, 202)}
    rows = [(a, b, rng.randrange(4)) for a, b in ends]
    assert _triples(prim(from_rows(spark, rows).repartition(5))) == prim_local(rows) == kruskal_local(rows)
    assert not prim(from_rows(spark, [])).count()
    # One task took every edge.
    plan = prim(from_rows(spark, rows))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == 3 and "Coalesce" not in plan
