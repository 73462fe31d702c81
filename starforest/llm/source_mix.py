"""Mixing sources to target weights by a low-discrepancy schedule.

Each source's documents, in the order of a hash, form one stream of words that is cut into blocks of
equal size (to within a word). The schedule has one slot for each block to be taken: slot ``i`` of
``n`` lies at the golden-ratio lattice point ``(i * g mod n) / n``, where g is the odd step nearest
to ``n / 1.618...`` that is prime to n, and the cumulative shares of the sources map that point to a source. The
lattice visits every point once, so each source gets exactly its number of slots, evenly spread. The
rank of a slot among its source's slots names the block: in each epoch ranks run through all blocks once, in an order
that a step prime to their number shuffles and that begins elsewhere in every epoch. :func:`scheduled_spans` joins slots and
blocks: the mixed corpus, as spans of words in the order of the schedule.

Scale: only ids, sizes and hashes are shuffled, never texts. Prefix sums over a source's stream and
over its slots are taken in two levels (bins of the hash, chunks of slots), so a source that holds a
third of all rows is spread over all tasks. The number of slots stays below 2**31 by larger blocks.

Edge cases: a null or empty text has size 0 and is never taken; a null source is a source of its own,
ordered last; rows with a repeated doc_id are documents of their own; an empty table gives an empty
result; other columns are ignored by :func:`mix_plan` and kept by :func:`mixed_documents`.
"""

from __future__ import annotations

from math import ceil, gcd

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from starforest.runtime import cut

#: Primes one of which at least is no factor of a number below 2**62.
STEPS = (2_147_483_647, 1_000_000_007, 998_244_353)
#: Blocks that a source has at least (if it has as many words): bounds the rounding of its target.
LEAST_BLOCKS = 2048
_GOLDEN = 0.6180339887498949
_CHUNK = 1 << 16
_BIN = 1 << 12
#: Hexadecimal digits of a place that make a bin: 2**20 bins of a source at most, however many rows it has.
_DIGITS = 5


def word_count(text: str):
    return F.coalesce(F.regexp_count(F.col(text), F.lit(r"[^\x20\x09-\x0D]++")), F.lit(0)).cast("long")


def doc_sizes(docs: DataFrame) -> DataFrame:
    """``(rid, doc_id, source, size, place)``: place orders a source's documents; those without a doc_id by their text."""
    doc_id, text = F.col("doc_id").cast("long"), F.coalesce(F.col("text").cast("string"), F.lit(""))
    place = F.md5(F.concat(F.lit("mix:"), F.coalesce(doc_id.cast("string"), F.concat(F.lit("-"), F.sha2(text, 256)))))
    return docs.select(F.monotonically_increasing_id().alias("rid"), doc_id.alias("doc_id"), F.col("source").cast("string").alias("source"), word_count("text").alias("size"), place.alias("place"))


def source_targets(sizes: DataFrame, *, weights: tuple[int, ...] = (1, 2, 3), most: int = 3) -> DataFrame:
    """``(source, idx, source_size, target)``: shares by weight, none above ``most`` times its source."""
    s = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    s = s.withColumn("idx", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1)
    s = s.withColumn("w", F.element_at(F.array(*[F.lit(w) for w in weights]), (F.col("idx") % len(weights) + 1).cast("int")))
    order = Window.orderBy(F.col("source_size") * most / F.col("w"), "idx")
    left = F.sum("source_size").over(Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)) - most * F.coalesce(F.sum("source_size").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    share = F.sum("w").over(order.rowsBetween(0, Window.unboundedFollowing))
    # Filled up from the source that its cap binds first: the first that stays under its cap sets the level.
    s = s.withColumns({"left": left.cast("double"), "share": share.cast("double")}).withColumn("free", F.col("left") / F.col("share") <= F.col("source_size") * most / F.col("w"))
    level = F.min_by(F.struct("left", "share"), F.when(F.col("free"), F.struct(F.col("source_size") * most / F.col("w"), F.col("idx")))).over(Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    s = s.withColumn("level", level)
    cap = (F.col("source_size") * most).cast("double")
    return s.select("source", "idx", "source_size", F.coalesce(F.least(F.col("w") * F.col("level.left") / F.col("level.share"), cap), cap).alias("target"))


def with_blocks(targets: DataFrame, total: int, *, block_words: int = 4096) -> DataFrame:
    """Adds ``blocks`` (of the source) and ``slots`` (in the schedule)."""
    size = max(block_words, ceil(total / 2**29))
    blocks = F.greatest(F.ceil(F.col("source_size") / size), F.least("source_size", F.lit(LEAST_BLOCKS))).cast("long")
    t = targets.withColumn("blocks", blocks)
    return t.withColumn("slots", F.when(F.col("blocks") > 0, F.round(F.col("target") / F.col("source_size") * F.col("blocks"))).otherwise(0).cast("long"))


def golden_step(n: int) -> int:
    """The step nearest to n / 1.618... that is prime to n."""
    at = max(1, round(n * _GOLDEN))
    return next(g for d in range(n + 1) for g in (at - d, at + d) if g > 0 and gcd(g, n) == 1)


def schedule(targets: DataFrame) -> DataFrame:
    """``(slot, idx, rank, epoch, block)`` from ``targets(idx, blocks, slots)``."""
    spark = targets.sparkSession
    t = targets.withColumn("to", F.sum("slots").over(Window.orderBy("idx")))
    n = int(t.agg(F.max("to")).first()[0] or 0)
    t = t.select("idx", "blocks", (F.col("to") - F.col("slots")).alias("from"), "to").where("to > from")
    point = (F.col("id") * golden_step(max(n, 1))) % max(n, 1)
    slots = spark.range(n).select(F.col("id").alias("slot"), point.alias("point"))
    # Sources lie end to end on the points, so each bin of points meets few of them: an equi-join, then the exact interval.
    slots = slots.withColumn("bin", F.expr(f"point div {_BIN}"))
    t = t.withColumn("bin", F.explode(F.sequence(F.expr(f"from div {_BIN}"), F.expr(f"(to - 1) div {_BIN}"))))
    placed = slots.join(t, "bin").where("point >= from and point < to").select("slot", "idx", "blocks", F.expr(f"slot div {_CHUNK}").alias("chunk"))
    before = Window.partitionBy("idx").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    offsets = placed.groupBy("idx", "chunk").agg(F.count("*").alias("n")).select("idx", "chunk", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))
    ranked = placed.join(offsets, ["idx", "chunk"]).withColumn("rank", F.col("offset") + F.row_number().over(Window.partitionBy("idx", "chunk").orderBy("slot")) - 1)
    # A permutation of the blocks in each epoch: a prime that does not divide their number is prime to it.
    step = F.coalesce(*[F.when(F.col("blocks") % p != 0, p) for p in STEPS]).cast("long")
    ranked = ranked.withColumns({"epoch": F.expr("rank div blocks"), "step": step % F.col("blocks")})
    return ranked.select("slot", "idx", "rank", "epoch", F.expr("((rank % blocks) * step % blocks + epoch * 7919) % blocks").alias("block"))


def doc_blocks(sizes: DataFrame, targets: DataFrame) -> DataFrame:
    """``(rid, idx, block, words)``: how many of a document's words lie in each block of its source."""
    of_source = targets.select(F.col("source").alias("_s"), "idx", "source_size", "blocks")
    d = sizes.where("size > 0").join(of_source, F.col("source").eqNullSafe(F.col("_s"))).select("rid", "size", "place", "idx", "source_size", "blocks", F.substring("place", 1, _DIGITS).alias("bin"))
    # Prefix sums in three levels: 256 wide bins of a source, bins of a wide one, documents of a bin.
    bins = d.groupBy("idx", "bin").agg(F.sum("size").alias("n")).withColumn("wide", F.substring("bin", 1, 2))
    upto = Window.partitionBy("idx").orderBy("wide").rowsBetween(Window.unboundedPreceding, -1)
    wides = bins.groupBy("idx", "wide").agg(F.sum("n").alias("m")).select("idx", "wide", F.coalesce(F.sum("m").over(upto), F.lit(0)).alias("base"))
    before = Window.partitionBy("idx", "wide").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    bins = bins.withColumn("inner", F.coalesce(F.sum("n").over(before), F.lit(0))).join(wides, ["idx", "wide"]).select("idx", "bin", (F.col("base") + F.col("inner")).alias("offset"))
    within = Window.partitionBy("idx", "bin").orderBy("place", "rid").rowsBetween(Window.unboundedPreceding, -1)
    d = d.join(bins, ["idx", "bin"]).withColumn("a", F.col("offset") + F.coalesce(F.sum("size").over(within), F.lit(0)))
    d = d.withColumns({"q": F.expr("source_size div blocks"), "long": F.col("source_size") % F.col("blocks")})
    d = d.withColumn("edge", F.col("long") * (F.col("q") + 1))  # the first ``long`` blocks have one word more
    of = "case when {t} < edge then {t} div (q + 1) else long + ({t} - edge) div q end"
    d = d.withColumns({"b": F.col("a") + F.col("size"), "j": F.explode(F.sequence(F.expr(of.format(t="a")), F.expr(of.format(t="(a + size - 1)"))))})
    start = F.when(F.col("j") < F.col("long"), F.col("j") * (F.col("q") + 1)).otherwise(F.col("edge") + (F.col("j") - F.col("long")) * F.col("q"))
    end = start + F.col("q") + F.when(F.col("j") < F.col("long"), 1).otherwise(0)
    return d.select("rid", "idx", F.col("j").alias("block"), (F.greatest("a", start) - F.col("a")).alias("first_word"), (F.least("b", end) - F.greatest("a", start)).alias("words"))


def _planned(docs: DataFrame, weights: tuple[int, ...], most: int, block_words: int) -> tuple[DataFrame, DataFrame]:
    sizes = cut(doc_sizes(docs))
    total = sizes.agg(F.sum("size")).first()[0] or 0
    return sizes, cut(with_blocks(source_targets(sizes, weights=weights, most=most), total, block_words=block_words))


def mix_plan(docs: DataFrame, *, weights: tuple[int, ...] = (1, 2, 3), most: int = 3, block_words: int = 4096) -> DataFrame:
    """``(rid, doc_id, source, size, source_size, target, taken, first_slot)`` for each document."""
    sizes, targets = _planned(docs, weights, most, block_words)
    uses = schedule(targets).groupBy("idx", "block").agg(F.count("*").alias("uses"), F.min("slot").alias("slot"))
    taken = doc_blocks(sizes, targets).join(uses, ["idx", "block"]).groupBy("rid").agg(F.sum(F.col("words") * F.col("uses")).alias("taken"), F.min("slot").alias("first_slot"))
    own = sizes.join(targets.select(F.col("source").alias("_s"), "source_size", "target"), F.col("source").eqNullSafe(F.col("_s")))
    return own.join(taken, "rid", "left").select("rid", "doc_id", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"), "first_slot")


def scheduled_spans(docs: DataFrame, *, weights: tuple[int, ...] = (1, 2, 3), most: int = 3, block_words: int = 4096) -> DataFrame:
    """``(slot, place, doc_id, source, first_word, words)``: the mix itself, sorted by slot and by place within its block."""
    sizes, targets = _planned(docs, weights, most, block_words)
    spans = schedule(targets).select("slot", "idx", "block").join(doc_blocks(sizes, targets), ["idx", "block"])
    return spans.join(sizes.select("rid", "place", "doc_id", "source"), "rid").select("slot", "place", "doc_id", "source", "first_word", "words").orderBy("slot", "place")


def mixed_documents(docs: DataFrame, **parameters) -> DataFrame:
    """The rows that the mix takes, as whole documents in schedule order.

    A document comes as often as its taken words come to whole ones; the rest of a document is rounded up or down by a hash of its
    doc_id, in proportion, so a source's words come near its target and reruns agree. It comes at its first slot; which rows of a
    repeated doc_id the mix took does not matter, all come.
    """
    chance = F.pmod(F.xxhash64("doc_id", F.lit("whole")), F.lit(1 << 20)) / float(1 << 20)
    times = F.floor(F.col("taken") / F.col("size") + chance).cast("int")
    plan = mix_plan(docs, **parameters).where("taken > 0").groupBy(F.col("doc_id").alias("id")).agg(F.max(times).alias("times"), F.min("first_slot").alias("slot")).where("times > 0")
    # The rows travel as one struct, so that no column of theirs can clash with the plan's.
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").cast("long").alias("key"))
    back = rows.join(plan, F.col("key").eqNullSafe(F.col("id"))).withColumn("k", F.explode(F.sequence(F.lit(1), F.col("times"))))
    return back.orderBy("slot", "k", "key").select(*[F.col("row").getField(c).alias(c) for c in docs.columns])
