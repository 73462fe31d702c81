"""Exact dedup by deterministic block naming.

Each text, lower-cased in A-Z only, is cut into blocks of ``block_bytes`` UTF-8 bytes. Equal
blocks get the same integer name by sorting them; adjacent names are then paired and the pairs
named again, level by level, until each document has one name. Blocks and pairs are compared in
full, so two documents share a name if and only if their normalised texts are equal.

Scale: the texts are shuffled once, as blocks that each task has already combined (a block that
fills a third of the corpus arrives once for each task, not once for each copy). All later levels
carry integers only. The number of levels is log2 of the longest document in blocks. Names that 1/``HEAVY`` of all rows and more
share are ``HEAVY`` at most, a proven bound: they are broadcast, and only the rows of other names are shuffled by name, so no join
brings a large group's rows into one task.

Edge cases: a null text counts as empty (one empty block); rows with a null or repeated doc_id are
documents of their own; of equal texts the row with the largest doc_id stays, and of such rows with
the same doc_id one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starforest.llm.arrow_text import ASCII_LOWER, flat
from starforest.runtime import cut

#: Names that can be heavy at once; each has at least so great a part of the rows.
HEAVY = 2048
_BLOCKS = "content binary, rid array<long>, pos array<int>, blocks array<int>, doc_id array<long>, sha array<string>"
_NAMED = "rid long, doc_id long, pos int, blocks int, sha string, name long"
#: A task hands on what it has combined when it holds so many bytes; bounds its memory.
_HOLD = 48 << 20


def _cut_blocks(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = TaskContext.get().partitionId() << 33
        held: dict[bytes, list[tuple]] = {}
        n = 0
        weight = 0

        def out() -> pa.RecordBatch:
            occ = list(held.values())
            cols = [pa.array(list(held), pa.binary())]
            for k, kind in enumerate((pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.string())):
                cols.append(pa.array([[o[k] for o in x] for x in occ], pa.list_(kind)))
            return pa.RecordBatch.from_arrays(cols, names=["content", "rid", "pos", "blocks", "doc_id", "sha"])

        for batch in batches:
            data, ends = flat(batch.column(1))
            data = data.translate(ASCII_LOWER)
            for i, doc in enumerate(batch.column(0).to_pylist()):
                text = data[ends[i] : ends[i + 1]]
                blocks = max(1, -(-len(text) // size))
                sha = hashlib.sha256(text).hexdigest()
                for p in range(blocks):
                    block = text[p * size : (p + 1) * size]
                    mine = held.get(block)
                    if mine is None:
                        mine = held[block] = []
                        weight += len(block) + 200
                    mine.append((first + n, p, blocks, doc if not p else None, sha if not p else None))
                    weight += 100
                n += 1
                if weight > _HOLD:
                    yield out()
                    held.clear()
                    weight = 0
        if held:
            yield out()

    return run


def _name_sorted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows of a partition come sorted by content: a new content takes the next integer."""
    name = (TaskContext.get().partitionId() << 33) - 1
    last = None
    for batch in batches:
        names = np.empty(batch.num_rows, np.int64)
        for i, content in enumerate(batch.column(0).to_pylist()):
            if content != last:
                name, last = name + 1, content
            names[i] = name
        occ = [batch.column(k) for k in range(1, 6)]
        counts = np.diff(np.asarray(occ[0].offsets))
        rid, pos, blocks, doc, sha = (x.flatten() for x in occ)
        yield pa.RecordBatch.from_arrays([rid, doc, pos, blocks, sha, pa.array(np.repeat(names, counts))], names=["rid", "doc_id", "pos", "blocks", "sha", "name"])


def name_blocks(docs: DataFrame, *, block_bytes: int = 4096) -> DataFrame:
    """Level 0: one row for each block of each document, with the block's integer name."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    blocks = rows.mapInArrow(_cut_blocks(block_bytes), _BLOCKS)
    return blocks.repartition(F.xxhash64("content")).sortWithinPartitions("content").mapInArrow(_name_sorted, _NAMED)


def _join_names(rows: DataFrame, names: DataFrame, keys: list[str], uses: str) -> DataFrame:
    """``rows`` joined with ``names``, which has one row for each key and counts its ``uses`` in rows."""
    heavy = max(2, -(-rows.count() // HEAVY))
    large = F.broadcast(names.where(F.col(uses) >= heavy))
    others = rows.join(F.broadcast(names.where(F.col(uses) >= heavy).select(*keys)), keys, "left_anti")
    return rows.join(large, keys).unionByName(others.join(names.where(F.col(uses) < heavy), keys))


def name_documents(docs: DataFrame, *, block_bytes: int = 4096) -> DataFrame:
    """``(rid, doc_id, sha, level, name)``: (level, name) is the document's identity."""
    base = cut(name_blocks(docs, block_bytes=block_bytes))
    most = base.agg(F.max("blocks")).first()[0] or 1
    level, done = 0, base.where("blocks = 1").select("rid", F.lit(0).alias("level"), "name")
    cur = base.where("blocks > 1").select("rid", "pos", "blocks", "name")
    while most > 1:
        level, most = level + 1, -(-most // 2)
        pairs = cur.groupBy("rid", F.shiftright("pos", 1).alias("pos")).agg(
            F.max(F.when(F.col("pos") % 2 == 0, F.col("name"))).alias("l"),
            F.coalesce(F.max(F.when(F.col("pos") % 2 == 1, F.col("name"))), F.lit(-1)).alias("r"),
            F.max(F.ceil(F.col("blocks") / 2)).cast("int").alias("blocks"),
        )
        pairs = cut(pairs)
        named = cut(pairs.groupBy("l", "r").agg(F.count("*").alias("uses")).sortWithinPartitions("l", "r").withColumn("name", F.monotonically_increasing_id()))
        cur = cut(_join_names(pairs, named, ["l", "r"], "uses").select("rid", "pos", "blocks", "name"))
        done = done.union(cur.where("blocks = 1").select("rid", F.lit(level).alias("level"), "name"))
        cur = cur.where("blocks > 1")
    return base.where("pos = 0").select("rid", "doc_id", "sha").join(done, "rid")


def exact_copies(docs: DataFrame, *, block_bytes: int = 4096) -> DataFrame:
    """One row for each document: doc_id, keep_id, group_size, kept, text_sha256."""
    named = cut(name_documents(docs, block_bytes=block_bytes))
    groups = cut(named.groupBy("level", "name").agg(F.max("doc_id").alias("keep_id"), F.max(F.struct(F.col("doc_id"), F.col("rid"))).alias("last"), F.count("*").alias("group_size")))
    return _join_names(named, groups, ["level", "name"], "group_size").select("doc_id", "keep_id", "group_size", (F.col("rid") == F.col("last.rid")).alias("kept"), F.col("sha").alias("text_sha256"))


def drop_exact_copies(docs: DataFrame, *, block_bytes: int = 4096) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns."""
    stay = exact_copies(docs, block_bytes=block_bytes).where("kept").select(F.col("doc_id").alias("id"), F.col("text_sha256").alias("sha"))
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    # The rows travel as one struct, so that no column of theirs can clash with the keys.
    own = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    marked = docs.select(own, F.col("doc_id").cast("long").alias("id"), F.sha2(F.translate(F.coalesce(F.col("text").cast("string"), F.lit("")), upper, lower), 256).alias("sha"))
    same = F.col("l.id").eqNullSafe(F.col("r.id")) & (F.col("l.sha") == F.col("r.sha"))
    once = marked.alias("l").join(stay.alias("r"), same, "left_semi").groupBy("id", "sha").agg(F.first("row").alias("row"))
    return once.select(*[F.col("row").getField(c).alias(c) for c in docs.columns])
