"""Token-id files: static range asymmetric numeral coding in interleaved lanes.

A file holds whole documents in ascending doc_id order. Its blocks of ``BLOCK`` ids share one frequency
table (scaled to 2**20) and are coded independently; within a block ``LANES`` coder states take turns,
so that numpy advances all of them at once. The footer holds the table, each block's checkpoint (byte
offset, number of ids, CRC-32 of the ids) and each document's id and length, so that any block
can be decoded alone and checked.

Layout: magic, blocks (lane states as u64, then u32 words), zlib-packed footer, its length as u64, magic.

Scale: texts are shuffled once, by ranges of doc_id; a task writes files of at most about ``FILE_IDS`` ids
and holds one at a time. Reading back is a unit of ``UNIT_IDS`` ids: it fetches the footer and the byte range of the blocks that
its documents (those that begin in it) touch, and decodes only these. Writes are atomic and repeatable.

Edge cases: a null text counts as empty (its ids are the end id alone); a null doc_id sorts first; rows
with a repeated doc_id are documents of their own, ordered by a hash of the text; an empty table writes
no file and reads as no row; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from starforest.llm.byte_bpe import WordEncoder, slices, tokenizer_path
from starforest.llm.shared_files import read_range, size_of, write_whole

MAGIC = b"SFRANS01"
SCALE, LANES, BLOCK, FILE_IDS, UNIT_IDS = 20, 1024, 1 << 18, 4 << 20, 1 << 20
_LOW = np.uint64(1 << 31)
_WORD, _MASK = np.uint64(32), np.uint64((1 << SCALE) - 1)


class Table(NamedTuple):
    """Shared static model: the ids that occur, their frequencies and cumulative frequencies."""

    ids: np.ndarray
    freq: np.ndarray
    cum: np.ndarray

    @classmethod
    def of(cls, ids: np.ndarray, freq: np.ndarray) -> Table:
        freq = freq.astype(np.uint64)
        return cls(ids, freq, np.cumsum(freq) - freq)

    @classmethod
    def count(cls, ids: np.ndarray) -> Table:
        n = np.bincount(ids)
        used = np.flatnonzero(n)
        n = n[used]
        if len(used) > 1 << SCALE:
            raise ValueError(f"more than {1 << SCALE} different ids in a file")
        freq = 1 + n * ((1 << SCALE) - len(used)) // n.sum()
        freq[np.argmax(freq)] += (1 << SCALE) - freq.sum()
        return cls.of(used, freq)


def encode_block(symbols: np.ndarray, table: Table) -> bytes:
    """``symbols``: positions in ``table.ids``."""
    lanes = min(LANES, max(1, len(symbols)))
    x = np.full(lanes, _LOW, np.uint64)
    words = []
    for at in range((len(symbols) - 1) // lanes * lanes, -1, -lanes):
        s = symbols[at : at + lanes]
        f, y = table.freq[s], x[: len(s)]
        full = y >= f << np.uint64(63 - SCALE)
        words.append(y[full].astype(np.uint32))
        y = np.where(full, y >> _WORD, y)
        q = y // f
        x[: len(s)] = (q << np.uint64(SCALE)) + (y - q * f) + table.cum[s]
    return x.tobytes() + (np.concatenate(words[::-1]).tobytes() if words else b"")


def decode_block(data: bytes, n: int, table: Table, slots: np.ndarray) -> np.ndarray:
    lanes = min(LANES, max(1, n))
    x = np.frombuffer(data, np.uint64, lanes).copy()
    words = np.frombuffer(data, np.uint32, offset=8 * lanes).astype(np.uint64)
    out = np.empty(n, slots.dtype)
    used = 0
    for at in range(0, n, lanes):
        y = x[: min(lanes, n - at)]
        low = y & _MASK
        s = slots[low.astype(np.int64)]
        out[at : at + len(s)] = s
        y = table.freq[s] * (y >> np.uint64(SCALE)) + low - table.cum[s]
        small = np.flatnonzero(y < _LOW)
        y[small] = (y[small] << _WORD) | words[used : used + len(small)]
        used += len(small)
        x[: len(y)] = y
    if used != len(words) or not (x == _LOW).all():
        raise ValueError("a block does not end where its coder began")
    return out


def pack(ids: np.ndarray, doc_ids: list, sizes: np.ndarray) -> bytes:
    """One file's bytes: flat ids of whole documents with their ids (None allowed) and sizes."""
    table = Table.count(ids) if len(ids) else Table.of(np.zeros(0, np.int64), np.zeros(0))
    place = np.zeros(int(table.ids[-1]) + 1 if len(table.ids) else 1, np.int32)
    place[table.ids] = np.arange(len(table.ids))
    symbols = place[ids]
    blocks, points, at = [], [], len(MAGIC)
    for k in range(0, len(ids), BLOCK):
        some = ids[k : k + BLOCK]
        blocks.append(encode_block(symbols[k : k + BLOCK], table))
        points.append((at, len(some), zlib.crc32(some.astype("<u4").tobytes())))
        at += len(blocks[-1])
    nulls = np.array([d is None for d in doc_ids], np.uint8)
    docs = np.array([d or 0 for d in doc_ids], "<i8")
    parts = [table.ids.astype("<u4"), table.freq.astype("<u4"), np.array(points, "<u8").reshape(-1, 3), docs, nulls, sizes.astype("<i8")]
    footer = zlib.compress(b"".join(np.array(len(p), "<u8").tobytes() for p in parts) + b"".join(p.tobytes() for p in parts))
    return b"".join([MAGIC, *blocks, footer, np.array(len(footer), "<u8").tobytes(), MAGIC])


class TokenFile:
    """A file's footer, and its blocks on demand. ``fetch(at, size)`` reads bytes of the file, which has ``total``."""

    def __init__(self, fetch: Callable[[int, int], bytes], total: int) -> None:
        end = fetch(max(0, total - 16), 16)
        if total < 24 or fetch(0, 8) != MAGIC or end[8:] != MAGIC:
            raise ValueError("not a token-id file, or not a whole one")
        size = int(np.frombuffer(end, "<u8", 1)[0])
        raw = zlib.decompress(fetch(total - 16 - size, size))
        lens, at, got = np.frombuffer(raw, "<u8", 6).astype(int), 48, []
        for n, kind in zip(lens, ("<u4", "<u4", ("<u8", 3), "<i8", "u1", "<i8"), strict=True):
            kind, wide = kind if isinstance(kind, tuple) else (kind, 1)
            got.append(np.frombuffer(raw, kind, n * wide, at))
            at += n * wide * np.dtype(kind).itemsize
        self.fetch, self.points, self.sizes = fetch, got[2].reshape(-1, 3).astype(np.int64), got[5]
        self.table = Table.of(got[0], got[1])
        self.doc_ids = [None if z else int(d) for d, z in zip(got[3], got[4], strict=True)]
        self.slots = np.repeat(np.arange(len(self.table.ids), dtype=np.int32), self.table.freq.astype(np.int64))
        self.ends = [*self.points[1:, 0], total - 16 - size]

    @classmethod
    def of(cls, data: bytes) -> TokenFile:
        return cls(lambda at, size: data[at : at + size], len(data))

    @classmethod
    def open(cls, uri: str) -> TokenFile:
        return cls(lambda at, size: read_range(uri, at, size), size_of(uri))

    def blocks(self, lo: int, hi: int) -> np.ndarray:
        """Ids of the blocks from ``lo`` on, before ``hi``: one byte range."""
        base = int(self.points[lo, 0])
        data, out = self.fetch(base, int(self.ends[hi - 1]) - base), []
        for k in range(lo, hi):
            at, n, crc = (int(v) for v in self.points[k])
            ids = self.table.ids[decode_block(data[at - base : int(self.ends[k]) - base], n, self.table, self.slots)]
            if zlib.crc32(ids.astype("<u4").tobytes()) != crc:
                raise ValueError(f"block {k} fails its checksum")
            out.append(ids)
        return np.concatenate(out)

    def documents(self, lo: int = 0, hi: int | None = None) -> Iterator[tuple[int | None, int, np.ndarray]]:
        """(doc_id, first id's place in the file, ids) of the documents whose first id is from ``lo`` on, before ``hi``."""
        ends = np.cumsum(self.sizes)
        places = ends - self.sizes
        a, b = np.searchsorted(places, [lo, ends[-1] if hi is None else hi]) if len(places) else (0, 0)
        if a == b:
            return
        first = int(places[a]) // BLOCK
        ids = self.blocks(first, (int(ends[b - 1]) - 1) // BLOCK + 1)
        for k in range(a, b):
            at = int(places[k]) - first * BLOCK
            yield self.doc_ids[k], int(places[k]), ids[at : at + int(self.sizes[k])]


def write_token_files(docs: DataFrame, folder: str, *, tokenizer: str | None = None, end_id: int = 0) -> DataFrame:
    """Writes the files; ``(part, piece, path, docs, tokens)`` of each (lazy: files are written as it is computed)."""
    path = tokenizer or tokenizer_path()

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, piece, encoder = TaskContext.get().partitionId(), 0, WordEncoder.of(path)
        ids, names, sizes, held = [], [], [], 0

        def flush() -> pa.RecordBatch:
            uri = f"{folder}/part-{part:06d}-{piece:05d}.rans"
            write_whole(uri, pack(np.concatenate(ids), names, np.concatenate(sizes)))
            return pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "piece": pa.array([piece], pa.int32()), "path": [uri], "docs": pa.array([len(names)], pa.int64()), "tokens": pa.array([held], pa.int64())})

        for batch in slices(batches):
            got, n = encoder.encode(batch.column(1))
            ids.append(np.insert(got, np.cumsum(n), end_id))
            sizes.append(n + 1)
            names += batch.column(0).to_pylist()
            held += len(ids[-1])
            if held >= FILE_IDS:
                yield flush()
                ids, names, sizes, held, piece = [], [], [], 0, piece + 1
        if names:
            yield flush()

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    ordered = rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))
    return ordered.mapInArrow(write, "part int, piece int, path string, docs long, tokens long")


def read_token_files(files: DataFrame) -> DataFrame:
    """``(doc_id, start, n_tokens, ids_crc32)`` of every document, from the files' bytes."""
    # Sums over the parts (as many as tasks), then over the pieces of each.
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    parts = files.groupBy("part").agg(F.sum("tokens").alias("n")).select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    within = Window.partitionBy("part").orderBy("piece").rowsBetween(Window.unboundedPreceding, -1)
    placed = files.withColumn("within", F.coalesce(F.sum("tokens").over(within), F.lit(0))).join(parts, "part")
    units = placed.select("path", (F.col("base") + F.col("within")).cast("long").alias("start"), F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"(tokens - 1) div {UNIT_IDS}"))).alias("unit"))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri, start, unit in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                found = TokenFile.open(uri).documents(unit * UNIT_IDS, (unit + 1) * UNIT_IDS)
                rows = [(doc, start + place, len(ids), zlib.crc32(ids.astype("<u4").tobytes())) for doc, place, ids in found]
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], pa.int64()) for k in range(4)], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    # A path is a few bytes, its unit is megabytes: the number of tasks is stated, or adaptive execution would merge them.
    tasks = int(files.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return units.repartition(tasks, F.xxhash64("path", "unit")).mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")
