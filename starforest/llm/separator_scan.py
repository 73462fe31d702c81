"""Token counts of documents in flat, unindexed token files, by scanning for the end-of-document id.

A file is nothing but ids (little-endian, 2 or 4 bytes), each document followed by the end id. Files are
cut into blocks regardless of documents; every block is searched at once with numpy; blocks are then
stitched by prefix scans over each file (ids and separators before the block, place of the last separator
before it), in window functions.

Scale: blocks are independent tasks of fixed size; what a block hands on is the lengths inside it. The
scans are partitioned by file.

Edge cases: an empty document is a separator right after another (0 tokens); ids after the last
separator are one unfinished document; an empty file has no document; an empty table of files gives an
empty result. For the writer: a null text counts as empty, repeated rows and doc_ids are documents of
their own, other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from starforest.llm.byte_bpe import WordEncoder, slices, tokenizer_path
from starforest.llm.shared_files import read_range, write_whole

#: Fixed value: the end-of-document id of the 50k byte-level vocabulary; no ordinary text has it.
END_ID = 50256
FILE_IDS = 8 << 20


def write_flat_files(docs: DataFrame, folder: str, *, tokenizer: str | None = None, end_id: int = END_ID, width: int = 2) -> DataFrame:
    """Writes flat files as it is computed; ``(path, bytes, doc_ids)`` of each, doc_ids in file order."""
    path = tokenizer or tokenizer_path()

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, piece, encoder = TaskContext.get().partitionId(), 0, WordEncoder.of(path)
        held: list[bytes] = []
        names: list = []
        size = 0

        def flush() -> pa.RecordBatch:
            uri = f"{folder}/flat-{part:06d}-{piece:05d}.bin"
            write_whole(uri, *held)
            return pa.RecordBatch.from_pydict({"path": [uri], "bytes": pa.array([size], pa.int64()), "doc_ids": pa.array([names], pa.list_(pa.int64()))})

        for batch in slices(batches):
            ids, n = encoder.encode(batch.column(1))
            if len(ids) and (ids.max() >= 1 << 8 * width or (ids == end_id).any()):
                raise ValueError("an id does not fit the file's width, or is the end id")
            held.append(np.insert(ids, np.cumsum(n), end_id).astype(f"<u{width}").tobytes())
            names += batch.column(0).to_pylist()
            size += len(held[-1])
            if size >= FILE_IDS * width:
                yield flush()
                held, names, size, piece = [], [], 0, piece + 1
        if names:
            yield flush()

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(write, "path string, bytes long, doc_ids array<long>")


def scan_blocks(files: DataFrame, *, block_ids: int = 1 << 20, end_id: int = END_ID, width: int = 2) -> DataFrame:
    """``(path, block, ids, seps, first, last, inner)``: places of separators relative to the block."""
    size = block_ids * width
    blocks = files.where("bytes > 0").select("path", "bytes", F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"(bytes - 1) div {size}"))).alias("block"))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri, total, block in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                ids = np.frombuffer(read_range(uri, block * size, min(size, total - block * size)), f"<u{width}")
                at = np.flatnonzero(ids == end_id)
                yield pa.RecordBatch.from_pydict({"path": [uri], "block": pa.array([block], pa.int64()), "ids": pa.array([len(ids)], pa.int64()), "seps": pa.array([len(at)], pa.int64()), "first": pa.array([int(at[0]) if len(at) else None], pa.int64()), "last": pa.array([int(at[-1]) if len(at) else None], pa.int64()), "inner": pa.array([np.diff(at) - 1], pa.list_(pa.int64()))})

    # A row is a few bytes, its block is megabytes: the number of tasks is stated, or adaptive execution would merge them.
    spread = blocks.repartition(int(files.sparkSession.conf.get("spark.sql.shuffle.partitions")), F.xxhash64("path", "block"))
    return spread.mapInArrow(scan, "path string, block long, ids long, seps long, first long, last long, inner array<long>")


def stitch(blocks: DataFrame) -> DataFrame:
    """``(path, ordinal, n_tokens)``: the documents of each file in order."""
    before = Window.partitionBy("path").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    placed = blocks.withColumns({"offset": F.coalesce(F.sum("ids").over(before), F.lit(0)), "ordinal": F.coalesce(F.sum("seps").over(before), F.lit(0))})
    placed = placed.withColumn("sep", F.col("offset") + F.col("last"))
    placed = placed.withColumns({"prior": F.coalesce(F.max("sep").over(before), F.lit(-1)), "following": F.lead("block").over(Window.partitionBy("path").orderBy("block"))})
    open_end = F.col("offset") + F.col("ids") - 1 - F.coalesce("sep", "prior")
    sizes = F.concat(
        F.when(F.col("seps") > 0, F.concat(F.array(F.col("offset") + F.col("first") - F.col("prior") - 1), "inner")).otherwise(F.array().cast("array<bigint>")),
        F.when(F.col("following").isNull() & (open_end > 0), F.array(open_end)).otherwise(F.array().cast("array<bigint>")),
    )
    return placed.select("path", "ordinal", F.posexplode(sizes).alias("k", "n_tokens")).select("path", (F.col("ordinal") + F.col("k")).alias("ordinal"), "n_tokens")


def count_tokens(files: DataFrame, **parameters) -> DataFrame:
    return stitch(scan_blocks(files.select("path", "bytes"), **parameters))
