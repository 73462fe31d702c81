"""Fixture parent forests ``P(v, p)`` and their oracle SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from starforest.graph.builders import vertex
from starforest.plans.oracle import vid
from starforest.runtime import read_table


def geo(spark: SparkSession, d: str) -> DataFrame:
    """Customers and suppliers under nations under regions: height two."""
    n, r = read_table(spark, d, "nation"), read_table(spark, d, "region")
    up = n.select(vertex("n_nationkey", "nation").alias("v"), vertex("n_regionkey", "region").alias("p"))
    return _leaves(spark, d).union(up).union(r.select(vertex("r_regionkey", "region"), vertex("r_regionkey", "region")))


def _leaves(spark: SparkSession, d: str) -> DataFrame:
    c, s = read_table(spark, d, "customer"), read_table(spark, d, "supplier")
    return c.select(vertex("c_custkey", "customer").alias("v"), vertex("c_nationkey", "nation").alias("p")).union(s.select(vertex("s_suppkey", "supplier"), vertex("s_nationkey", "nation")))


def nation_only(spark: SparkSession, d: str) -> DataFrame:
    """Nations are roots: stars."""
    return _leaves(spark, d).union(read_table(spark, d, "nation").select(vertex("n_nationkey", "nation"), vertex("n_nationkey", "nation")))


def mixed(spark: SparkSession, d: str) -> DataFrame:
    """Height two in regions 0 to 2, stars elsewhere."""
    n, r = read_table(spark, d, "nation"), read_table(spark, d, "region")
    v = vertex("n_nationkey", "nation")
    up = n.select(v.alias("v"), F.when(F.col("n_regionkey") <= 2, vertex("n_regionkey", "region")).otherwise(v).alias("p"))
    return _leaves(spark, d).union(up).union(r.select(vertex("r_regionkey", "region"), vertex("r_regionkey", "region")))


def chain(spark: SparkSession, d: str) -> DataFrame:
    """Each event under its user's previous event."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    v = vertex("event_id", "event")
    return read_table(spark, d, "events").select(v.alias("v"), F.coalesce(F.lag(v).over(w), v).alias("p"))


_LEAVES = f"SELECT {vid('c_custkey', 0)} AS v, {vid('c_nationkey', 4)} AS p FROM customer UNION ALL SELECT {vid('s_suppkey', 1)}, {vid('s_nationkey', 4)} FROM supplier"
_REGIONS = f"SELECT {vid('r_regionkey', 5)}, {vid('r_regionkey', 5)} FROM region"
SQL = {
    "geo": f"{_LEAVES} UNION ALL SELECT {vid('n_nationkey', 4)}, {vid('n_regionkey', 5)} FROM nation UNION ALL {_REGIONS}",
    "nation_only": f"{_LEAVES} UNION ALL SELECT {vid('n_nationkey', 4)}, {vid('n_nationkey', 4)} FROM nation",
    "mixed": f"{_LEAVES} UNION ALL SELECT {vid('n_nationkey', 4)}, CASE WHEN n_regionkey <= 2 THEN {vid('n_regionkey', 5)} ELSE {vid('n_nationkey', 4)} END FROM nation UNION ALL {_REGIONS}",
    "chain": f"SELECT {vid('event_id', 6)} AS v, coalesce(lag({vid('event_id', 6)}) OVER w, {vid('event_id', 6)}) AS p FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
}
#: Root of each event in ``chain``, and how far it is.
CHAIN_ROOTS = f"SELECT {vid('event_id', 6)} AS v, first_value({vid('event_id', 6)}) OVER w AS root, row_number() OVER w - 1 AS depth FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"
