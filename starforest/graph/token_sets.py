"""Graphs of rows that share tokens, without the pairs that one common token or a group of copies makes.

Two rows that share c tokens have an edge of weight ``most - c``. Rows of equal token sets are one class; of classes only pairs
that share two tokens and more are formed. A pair that shares two tokens shares one beside the more frequent of them, so the
most frequent token of each set may be left out when pairs are looked for: the very common token of a table meets nobody.
What shares a single token is summed up (:func:`link_counts`) or reached through that token's first row (:func:`forest_edges`).
Two tokens that are both very common and stand together in very many different sets still cost the pairs of those.
"""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from starforest.graph.order import canonical_edges
from starforest.runtime import cut_state


class TokenSets(NamedTuple):
    """``rows(v, ids, rep)``: the tokens that several rows have, rarest first, and the class's smallest row; ``often(id, n)``; ``pairs(a, b, c)`` of classes."""

    rows: DataFrame
    often: DataFrame
    pairs: DataFrame


def token_sets(df: DataFrame, v: Column, tokens: Column) -> TokenSets:
    """Null tokens are none; rows of one name are one row with the tokens of all."""
    held = df.select(v.alias("v"), F.explode(F.array_distinct(tokens)).alias("t")).where("t is not null").distinct()
    often = cut_state(held.groupBy("t").agg(F.count("*").alias("n")).where("n > 1").select("t", "n", F.monotonically_increasing_id().alias("id")))
    sets = held.join(often, "t").groupBy("v").agg(F.array_sort(F.collect_list(F.struct("n", "id"))).alias("s"))
    sets = cut_state(sets.select("v", F.col("s.id").alias("ids")))
    classes = cut_state(sets.groupBy("ids").agg(F.min("v").alias("rep")))
    looked = classes.where("size(ids) > 1").select("rep", "ids", F.explode(F.slice("ids", F.lit(1), F.size("ids") - 1)).alias("id"))
    one, two = (looked.select(F.col("rep").alias(x), "id") for x in "ab")
    met = one.join(two, "id").where("a < b").select("a", "b").distinct()
    x, y = (classes.select(F.col("rep").alias(n), F.col("ids").alias(f"_{n}")) for n in "ab")
    shared = F.size(F.array_intersect("_a", "_b")).cast("long")
    pairs = cut_state(met.join(x, "a").join(y, "b").select("a", "b", shared.alias("c")).where("c > 1"))
    return TokenSets(sets.join(classes, "ids").select("v", "ids", "rep"), often.select("id", "n"), pairs)


def forest_edges(sets: TokenSets, most: int = 1000) -> DataFrame:
    """``(lo, hi, w)``: edges among which the whole graph's minimum spanning forest is, in the order (w, lo, hi).

    By the cycle property: all edges between two classes, or within one, weigh the same, and of those only stars around the
    smallest row of either class are in the forest. An edge that stands for a single shared token is closed off by the two to
    the token's first row. Where that first row shares more with a row than this token, its edge here is too heavy and closed
    off by the right one. So components and every round's lightest edges are those of the whole graph, too.
    """
    member = sets.rows.select("rep", "v")
    near, far = (sets.pairs.join(member.select(F.col("rep").alias(s), "v"), s) for s in "ba")
    across = near.select("a", F.col("v").alias("b"), "c").union(far.where("v <> a").select(F.col("b").alias("a"), F.col("v").alias("b"), "c"))
    within = sets.rows.where("v <> rep").select(F.col("rep").alias("a"), F.col("v").alias("b"), F.size("ids").cast("long").alias("c"))
    each = sets.rows.select("v", F.explode("ids").alias("id"))
    first = each.groupBy("id").agg(F.min("v").alias("a"))
    single = each.join(first, "id").where("v <> a").select("a", F.col("v").alias("b"), F.lit(1).cast("long").alias("c"))
    return canonical_edges(across.union(within).union(single).select("a", "b", (F.lit(most) - F.col("c")).alias("w")))


def link_counts(sets: TokenSets) -> DataFrame:
    """``(v, n_links)``: with how many other rows each row shares a token; rows without a link are left out.

    Each token's other rows are added up; a row that shares c of them was counted c - 1 times too often.
    """
    sized = sets.rows.groupBy("rep").agg(F.count("*").alias("size"))
    reached = sets.rows.select("v", F.explode("ids").alias("id")).join(sets.often, "id").groupBy("v").agg(F.sum(F.col("n") - 1).alias("reached"))
    both = sets.pairs.select(F.col("a").alias("rep"), F.col("b").alias("other"), "c").union(sets.pairs.select("b", "a", "c"))
    again = both.join(sized.withColumnRenamed("rep", "other"), "other").groupBy("rep").agg(F.sum(F.col("size") * (F.col("c") - 1)).alias("again"))
    out = sets.rows.join(sized, "rep").join(again, "rep", "left").join(reached, "v")
    own = (F.col("size") - 1) * (F.size("ids") - 1)
    return out.select("v", (F.col("reached") - own - F.coalesce("again", F.lit(0))).cast("long").alias("n_links"))
