"""The experiments: ablations, scaling, iteration counts and comparisons, each a function of edge tables and parameters.

All return tidy tables; edges are ranked and materialised before the clock starts. ``parts`` is the parallelism:
the number of shuffle partitions and of partitions of the edge table.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator, Sequence
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

from starforest import baselines
from starforest.forest.loop import ForestResult, minimum_spanning_forest
from starforest.forest.measures import kernel_communication, kernel_writes
from starforest.graph import generators
from starforest.graph.order import rank_edges
from starforest.plans import oracle
from starforest.plans.catalogue import _rmat_sql, _uniform_sql, add, ranked
from starforest.runtime import cut_state

SHORTCUTS = ("queried_plain", "queried", "prefetched", "thresholded", "adaptive", "scheduled")


@contextmanager
def parallelism(spark: SparkSession, parts: int) -> Iterator[None]:
    """Runs with ``parts`` shuffle partitions (a setting that may change while a session runs) and puts it back."""
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(parts))
    try:
        yield
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def timed_forest(edges: DataFrame, parts: int | None = None, **options) -> tuple[ForestResult, float]:
    """A run and its seconds, reading and ranking of edges left out."""
    spark = edges.sparkSession
    with parallelism(spark, parts or int(spark.conf.get("spark.sql.shuffle.partitions"))):
        dealt = cut_state(edges.repartition(parts)) if parts else edges
        start = time.monotonic()
        found = minimum_spanning_forest(dealt, **options)
        return found, time.monotonic() - start


def shortcut_ablation(edges: DataFrame, variants: Sequence[str] = SHORTCUTS, parts: Sequence[int] = (8,), **options) -> DataFrame:
    """Per variant, parallelism and iteration: what was shortcut, how, and how long each phase took."""
    rows = []
    for variant in variants:
        for p in parts:
            found, _ = timed_forest(edges, p, shortcut=variant, **options)
            rows += [(variant, p, t.iteration, t.strategy, t.changed, t.sub_iterations, t.gathered_bytes, t.kernel_s, t.hook_s, t.shortcut_s) for t in found.trace]
    return edges.sparkSession.createDataFrame(rows, "variant string, parts int, iteration int, strategy string, changed long, sub_iterations int, gathered_bytes long, kernel_s double, hook_s double, shortcut_s double")


def kernel_ablation(edges: DataFrame, kernels: Sequence[str] = ("triple", "vertex", "two_pass")) -> DataFrame:
    """Per kernel: seconds in the kernel, and rows written to do it (the pairwise form writes every entry again)."""
    rows = []
    for kernel in kernels:
        found, total = timed_forest(edges, kernel=kernel)
        rows.append((kernel, found.iterations, sum(t.rows_written for t in found.trace), sum(t.kernel_s for t in found.trace), total))
    return edges.sparkSession.createDataFrame(rows, "kernel string, iterations long, rows_written long, kernel_s double, seconds double")


def strong_scaling(edges: DataFrame, parts: Sequence[int] = (1, 2, 4, 8), **options) -> DataFrame:
    """The same graph on more and more partitions: seconds, speed-up over the first, efficiency, modelled traffic."""
    rows, first = [], None
    for p in parts:
        found, took = timed_forest(edges, p, **options)
        first = first or took * parts[0]
        n = found.parents.count()
        rows.append((p, found.iterations, took, first / took / parts[0], first / took / p, kernel_communication(n, p)))
    return edges.sparkSession.createDataFrame(rows, "parts int, iterations long, seconds double, speed_up double, efficiency double, modelled_entries double")


def weak_scaling(spark: SparkSession, n: int, percents: Sequence[float], parts: Sequence[int] = (1, 4), **options) -> DataFrame:
    """Uniform graphs with n**2 / parts held constant, so the edges of a partition stay as many."""
    rows = []
    for percent in percents:
        for p in parts:
            size = round(n * p**0.5)
            edges = rank_edges(generators.uniform_percent(spark, size, percent))
            found, took = timed_forest(edges, p, **options)
            rows.append((percent, p, size, edges.count(), found.iterations, took))
    return spark.createDataFrame(rows, "percent double, parts int, n long, m long, iterations long, seconds double")


def method_comparison(edges: DataFrame) -> DataFrame:
    """The loop against contraction, message passing and divide-and-merge on one graph: seconds and total weight."""
    methods: dict[str, Callable[[], DataFrame]] = {
        "star_hooking": lambda: minimum_spanning_forest(edges).forest,
        "contraction": lambda: baselines.boruvka(edges),
        "message_passing": lambda: baselines.vertex_centric_forest(edges)[0],
        "divide_and_merge": lambda: baselines.divide_and_merge_forest(edges),
    }
    rows = []
    for name, run in methods.items():
        start = time.monotonic()
        kept = cut_state(run().select("rank"))
        took = time.monotonic() - start
        total = edges.join(kept, "rank").selectExpr("count(*)", "sum(w)").first()
        rows.append((name, total[0], total[1], took))
    return edges.sparkSession.createDataFrame(rows, "method string, n_edges long, total_weight long, seconds double")


def iteration_profile(graphs: dict[str, DataFrame], **options) -> DataFrame:
    """``(graph, iteration, hooks, sub_iterations)`` of ranked edge tables."""
    rows = [(name, t.iteration, t.hooks, t.sub_iterations) for name, e in graphs.items() for t in minimum_spanning_forest(e, **options).trace if t.hooks]
    return next(iter(graphs.values())).sparkSession.createDataFrame(rows, "graph string, iteration int, hooks long, sub_iterations int")


def write_model(n: int, m: int, parts: Sequence[int]) -> list[tuple[int, float, float]]:
    """Modelled writes of both kernels by parallelism."""
    return [(p, kernel_writes(n, m, p)["all_at_once"], kernel_writes(n, m, p)["pairwise"]) for p in parts]


def _hooks_sql(name: str, edges: str, kind: str = "graph") -> str:
    return f"SELECT '{name}' AS {kind}, round AS iteration, count(*) AS hooks FROM (WITH {oracle.forest_ctes(edges)} SELECT round FROM f) GROUP BY round"


_PERCENTS = {"0.05": 2000, "0.2": 8000, "1": 40_000}

# Seconds differ from run to run: where SQL checks a workload, its query leaves them out.
add("experiment_shortcuts_lattice", lambda s, d: shortcut_ablation(ranked(s, d, "lattice"), ("queried", "prefetched", "scheduled")).select("variant", "iteration", "changed"), " UNION ALL ".join(f"SELECT '{v}' AS variant, iteration, hooks AS changed FROM ({_hooks_sql('-', oracle.EDGES['lattice'])})" for v in ("queried", "prefetched", "scheduled")))
add("experiment_shortcut_strategies", lambda s, d: shortcut_ablation(ranked(s, d, "trade"), ("thresholded",), threshold=500).select("iteration", "strategy", "gathered_bytes"), f"SELECT iteration, CASE WHEN hooks < 500 THEN 'prefetched' ELSE 'queried' END AS strategy, CASE WHEN hooks < 500 THEN hooks * 16 ELSE 0 END AS gathered_bytes FROM ({_hooks_sql('-', oracle.EDGES['trade'])})")
add("experiment_kernels_rmat", lambda s, d: kernel_ablation(rank_edges(generators.rmat_graph(s, 12, 8))))
add("experiment_scaling_social", lambda s, d: strong_scaling(ranked(s, d, "trade"), (1, 4)))
add("experiment_scaling_road", lambda s, d: strong_scaling(ranked(s, d, "lattice"), (1, 4)))
add("experiment_scaling_dense", lambda s, d: strong_scaling(ranked(s, d, "basket"), (1, 4)))
add("experiment_scaling_rmat", lambda s, d: strong_scaling(rank_edges(generators.rmat_graph(s, 12, 8)), (1, 4)))
add("experiment_weak_scaling", lambda s, d: weak_scaling(s, 2000, (0.05, 0.5), (1, 4)))
add("experiment_methods_lattice", lambda s, d: method_comparison(ranked(s, d, "lattice")).select("method", "n_edges", "total_weight"), f"WITH t AS (SELECT count(*) AS n_edges, CAST(sum(w) AS BIGINT) AS total_weight FROM ({oracle.forest(oracle.EDGES['lattice'])})) SELECT method, n_edges, total_weight FROM t, (VALUES ('star_hooking'), ('contraction'), ('message_passing'), ('divide_and_merge')) m(method)")
add("experiment_iterations_sparsity", lambda s, d: iteration_profile({p: rank_edges(generators.uniform_graph(s, 2000, m)) for p, m in _PERCENTS.items()}).select("graph", "iteration", "hooks"), " UNION ALL ".join(_hooks_sql(p, _uniform_sql(2000, m)) for p, m in _PERCENTS.items()))
add("experiment_iterations_degree", lambda s, d: iteration_profile({str(k): rank_edges(generators.rmat_graph(s, 10, k)) for k in (8, 64)}).select("graph", "iteration", "hooks"), " UNION ALL ".join(_hooks_sql(str(k), _rmat_sql(10, k)) for k in (8, 64)))
_PROFILED = ("trade", "supply", "returns", "turns", "nearcopy")
add("experiment_profile_graphs", lambda s, d: iteration_profile({g: ranked(s, d, g) for g in _PROFILED}).select("graph", "iteration", "hooks"), " UNION ALL ".join(_hooks_sql(g, oracle.EDGES[g]) for g in _PROFILED))
