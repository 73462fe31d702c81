"""Monoids and semirings as Column functions."""

from __future__ import annotations

from collections.abc import Callable
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class Monoid(NamedTuple):
    """``reduce`` is the aggregate over a group; ``pair`` the operation on two values; no row means identity."""

    name: str
    reduce: Callable[[Column], Column]
    pair: Callable[[Column, Column], Column]
    identity: object


def _lightest(c: Column) -> Column:
    # Two aggregates over LONGs rather than the minimum of a struct: hash aggregates with code generation.
    return F.struct(F.min(c["rank"]).alias("rank"), F.min_by(c["parent"], c["rank"]).alias("parent"))


MIN = Monoid("min", F.min, F.least, None)
MAX = Monoid("max", F.max, F.greatest, None)
SUM = Monoid("sum", F.sum, lambda a, b: a + b, 0)
COUNT = Monoid("count", F.count, lambda a, b: a + b, 0)
ANY = Monoid("any", F.bool_or, lambda a, b: a | b, False)
ALL = Monoid("all", F.bool_and, lambda a, b: a & b, True)
MINWEIGHT = Monoid("minweight", _lightest, lambda a, b: F.when(a["rank"] <= b["rank"], a).otherwise(b), None)
#: Concatenation is associative but not commutative: its values carry their place, ``struct(place, text)``.
CONCAT = Monoid("concat", lambda c: F.array_join(F.transform(F.array_sort(F.collect_list(c)), lambda x: x["text"]), ""), lambda a, b: F.concat(a, b), "")


class Semiring(NamedTuple):
    name: str
    add: Monoid
    mul: Callable[[Column, Column], Column]


PLUS_TIMES = Semiring("plus_times", SUM, lambda a, b: a * b)
MIN_PLUS = Semiring("min_plus", MIN, lambda a, b: a + b)
OR_AND = Semiring("or_and", ANY, lambda a, b: a & b)
MAX_MIN = Semiring("max_min", MAX, F.least)
MIN_SELECT = Semiring("min_select", MIN, lambda a, b: a)


def monoid_reduce(df: DataFrame, keys: list[str], value: Column, monoid: Monoid, name: str = "value") -> DataFrame:
    return df.groupBy(*keys).agg(monoid.reduce(value).alias(name))


def check_monoid_laws(samples: DataFrame, monoid: Monoid) -> bool:
    """Associativity and identity on all triples of ``samples(x)`` (a handful of values)."""
    a, b, c = (samples.select(F.col("x").alias(n)) for n in "abc")
    t = a.crossJoin(b).crossJoin(c)
    p = monoid.pair
    ok = p(p(F.col("a"), F.col("b")), F.col("c")).eqNullSafe(p(F.col("a"), p(F.col("b"), F.col("c"))))
    if monoid.identity is not None:
        ok = ok & p(F.col("a"), F.lit(monoid.identity)).eqNullSafe(F.col("a"))
    return t.where(~ok).limit(1).count() == 0


def check_semiring_laws(samples: DataFrame, ring: Semiring) -> bool:
    """Commutative addition, associative product and both distributive laws on all triples of ``samples(x)``."""
    a, b, c = (samples.select(F.col("x").alias(n)) for n in "abc")
    add, mul, x, y, z = ring.add.pair, ring.mul, F.col("a"), F.col("b"), F.col("c")
    ok = add(x, y).eqNullSafe(add(y, x)) & mul(mul(x, y), z).eqNullSafe(mul(x, mul(y, z))) & mul(x, add(y, z)).eqNullSafe(add(mul(x, y), mul(x, z))) & mul(add(x, y), z).eqNullSafe(add(mul(x, z), mul(y, z)))
    return a.crossJoin(b).crossJoin(c).where(~ok).limit(1).count() == 0 and check_monoid_laws(samples, ring.add)
