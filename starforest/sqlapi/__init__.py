"""SQL surface: views of a forest, a table function, a grouped aggregate and per-group forests."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, LongType, StructField, StructType

from starforest.baselines import kruskal_local
from starforest.forest.loop import ForestResult, minimum_spanning_forest
from starforest.graph.order import canonical_edges, rank_edges


def forest_views(spark: SparkSession, edges_sql: str, *, prefix: str = "", **options) -> ForestResult:
    """Grows the forest of a query with columns (a, b, w) and registers ``forest_edges``, ``forest_parents`` and ``forest_trace``."""
    found = minimum_spanning_forest(rank_edges(canonical_edges(spark.sql(edges_sql))), **options)
    for name, df in (("forest_edges", found.forest), ("forest_parents", found.parents), ("forest_trace", found.trace_frame())):
        df.createOrReplaceTempView(prefix + name)
    return found


@udtf(returnType=StructType([StructField(c, LongType()) for c in ("lo", "hi", "w")]))
class SpanningForestEdges:
    """Forest of one partition's rows ``(lo, hi, w)``, which it holds: for graphs per group."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, int, int]] = []

    def eval(self, row) -> None:
        self.rows.append((row["lo"], row["hi"], row["w"]))

    def terminate(self):
        yield from sorted(kruskal_local(self.rows))


@pandas_udf(LongType())
def forest_weight(lo: pd.Series, hi: pd.Series, w: pd.Series) -> int:
    """Total weight of the forest of a group's edges."""
    return sum(e[2] for e in kruskal_local(list(zip(lo, hi, w, strict=True))))


def forest_per_group(edges: DataFrame, key: str) -> DataFrame:
    """``(key, lo, hi, w)``: the forest of each group's own graph."""
    kind = dict(edges.dtypes)[key]

    def grow(k: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        found = sorted(kruskal_local(list(rows[["lo", "hi", "w"]].itertuples(index=False, name=None))))
        return pd.DataFrame(found, columns=["lo", "hi", "w"]).assign(**{key: k[0]})[[key, "lo", "hi", "w"]]

    return edges.select(key, "lo", "hi", "w").groupBy(key).applyInPandas(grow, f"{key} {kind}, lo long, hi long, w long")


def register_all(spark: SparkSession) -> None:
    spark.udtf.register("spanning_forest_edges", SpanningForestEdges)
    spark.udf.register("forest_weight", forest_weight)


def reachable(spark: SparkSession, edges: DataFrame, source: int, *, hops: int) -> DataFrame:
    """``(v)``: what a recursive query reaches from ``source`` over at most ``hops`` edges; small graphs (walks are counted one by one)."""
    edges.select("lo", "hi").union(edges.select("hi", "lo")).createOrReplaceTempView("_reach_edges")
    return spark.sql(f"WITH RECURSIVE r(v, k) AS (SELECT CAST({int(source)} AS BIGINT), 0 UNION ALL SELECT e.hi, r.k + 1 FROM r JOIN _reach_edges e ON e.lo = r.v WHERE r.k < {int(hops)}) SELECT DISTINCT v FROM r")


@pandas_udf(DoubleType())
def l2_distance(a: pd.Series, b: pd.Series) -> pd.Series:
    """Control for the built-in form: Euclidean distance of two arrays."""
    return pd.Series([float(((x - y) ** 2).sum() ** 0.5) for x, y in zip(a, b, strict=True)])


def l2_builtin(a: str, b: str):
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def register_encode_vertex(spark: SparkSession, name: str = "encode_vertex") -> str:
    """A SQL function ``name(key, kind)``: the vertex of a table's key, as :func:`starforest.graph.builders.vertex` numbers it."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(k BIGINT, kind INT) RETURNS BIGINT RETURN k * 16 + kind")
    return name
