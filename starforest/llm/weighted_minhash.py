"""Near-duplicate classes by improved consistent weighted sampling over TF-IDF shingles.

Shingles are runs of five words (lower-cased runs of letters, marks and digits); a shorter text is one
shingle. A shingle's weight is its count in the text times ``1 + ln(N / df) / ln(N)``, with document
frequencies of the whole corpus, counted for every shingle. ``bands * rows`` consistent
weighted samples make the band keys. Texts of one band bucket are candidates; candidates are verified by their exact weighted
Jaccard similarity on whole texts, and verified links make the classes.

Scale: three scans; what is shuffled are shingle hashes (sorted, as differences of six bytes, packed by ranges of the
hash), band keys, and the texts of candidates. The counts go back to units of documents as files in the shared folder, one for
each unit, which the second scan forms again; rows of a plan that shuffles are written first. Copies of the same words
are one representative before anything is banded. Buckets with the same members are compared once. A bucket is cut into
blocks of bounded rows and words. First each block is compared within itself and with its bucket's leader (the smallest
representative), so a text travels once for each bucket and a group of near copies comes together in work that grows
with its size. Only where a bucket's members are then still of several components are its blocks compared across, and of
those only blocks of different components. The candidates' texts are kept in the shared folder meanwhile, so the texts of all
documents are dealt out once. A task hands on a spanning star of what it linked, never all pairs.

Edge cases: a null text counts as empty; a text without a word is in a class of its own; rows with the same
doc_id are one node; a null doc_id is never linked; an empty table gives an empty result; other columns
are ignored by :func:`near_classes` and kept by :func:`drop_near_copies`.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from starforest.components.links import link_components
from starforest.llm.arrow_text import hash_words, mix64
from starforest.llm.byte_bpe import slices
from starforest.llm.shared_files import read_whole, remove_tree, write_whole
from starforest.runtime import cut, cut_state, shared_dir

WORDS, THRESHOLD, BANDS, ROWS = 5, 0.8, 10, 3
#: Documents in a block of a bucket, and words.
BLOCK, BLOCK_WORDS = 128, 200_000
#: Shingles of a unit, and documents to a range of hashes (2**14 ranges at most).
_UNIT, _DOCS, _MAX_BITS = 1 << 20, 2048, 14
_P = np.uint64(0x9E3779B97F4A7C15)


def _gamma_quantiles(bits: int = 16) -> np.ndarray:
    """Quantiles of Gamma(2, 1) at the midpoints of 2**bits equal shares, by Newton's method."""
    q = (np.arange(1 << bits) + 0.5) / (1 << bits)
    x = np.sqrt(2 * q) + q
    for _ in range(60):
        x -= np.clip((1 - np.exp(-x) * (1 + x) - q) / (x * np.exp(-x)), -1, 1) * 0.9
        x = np.maximum(x, 1e-9)
    return x


_R = _gamma_quantiles(12).astype(np.float32)
_INV_R, _LN_C = (1 / _R).astype(np.float32), np.log(_gamma_quantiles()).astype(np.float32)
#: Shingles that are sampled at a time: their arrays stay in a core's cache.
_CHUNK = 1 << 14


class Shingles:
    """Distinct shingles of a batch of texts: ``owner`` ascending, ``h`` ascending within it, ``tf``."""

    def __init__(self, texts: pa.Array, words: int = WORDS) -> None:
        import pyarrow.compute as pc

        w, self.sizes = hash_words(pc.utf8_lower(pc.fill_null(texts.cast(pa.large_string()), "")), r"\pL\pM\pN")
        n = len(self.sizes)
        starts = np.cumsum(self.sizes) - self.sizes
        owner = np.repeat(np.arange(n), self.sizes)
        place = (np.arange(len(w)) - starts[owner]).astype(np.uint64)
        # Two hashes of the word sequence: texts with the same words share them.
        self.key = np.stack([self._sum(mix64(w + place * _P + np.uint64(s)), starts, n) for s in (1, 2)], 1)
        h = np.zeros(max(0, len(w) - words + 1), np.uint64)
        for k in range(words):
            h = h * _P + w[k : len(h) + k]
        own = owner[: len(h)]
        whole = own == owner[words - 1 :] if len(h) else np.zeros(0, bool)
        short = np.flatnonzero((self.sizes > 0) & (self.sizes < words))
        brief = np.zeros(len(short), np.uint64)
        for k in range(words - 1):
            has = self.sizes[short] > k
            brief[has] = brief[has] * _P + w[starts[short[has]] + k]
        h, own = np.concatenate([mix64(h[whole]), mix64(brief ^ _P)]), np.concatenate([own[whole], short])
        order = np.argsort(h)
        # By owner, in order of h within: a stable sort of 16-bit numbers is a radix sort.
        order = order[np.argsort(own[order].astype(np.uint16 if n <= 1 << 16 else np.int64), kind="stable")]
        h, own = h[order], own[order]
        new = np.ones(len(h), bool)
        new[1:] = (h[1:] != h[:-1]) | (own[1:] != own[:-1])
        at = np.flatnonzero(new)
        self.h, self.owner, self.tf = h[at], own[at].astype(np.int32), np.diff(np.append(at, len(h))).astype(np.int32)

    @staticmethod
    def _sum(values: np.ndarray, starts: np.ndarray, n: int) -> np.ndarray:
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(values, dtype=np.uint64)])
        ends = np.append(starts[1:], len(values)) if n else starts
        return total[ends] - total[starts]


class Counted(NamedTuple):
    """Documents, their number, and the folder with the document frequencies of each unit's shingles."""

    rows: DataFrame
    docs: int
    folder: str


def idf_weights(df: np.ndarray, docs: int) -> np.ndarray:
    return 1 + np.log(docs / df) / np.log(docs) if docs > 1 else np.ones(len(df))


def pack_hashes(h: np.ndarray) -> bytes:
    """Ascending hashes as differences of six bytes; larger ones stand as zero, their places and values at the end."""
    d = np.diff(h, prepend=np.uint64(0))
    far = np.flatnonzero(d >> np.uint64(48))
    near = d.copy()
    near[far] = 0
    return np.array([len(h)], "<i8").tobytes() + near.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6].tobytes() + far.astype("<i8").tobytes() + d[far].astype("<u8").tobytes()


def unpack_hashes(raw: bytes) -> np.ndarray:
    n = int(np.frombuffer(raw, "<i8", 1)[0])
    d = np.zeros((n, 8), np.uint8)
    d[:, :6] = np.frombuffer(raw, np.uint8, 6 * n, 8).reshape(n, 6)
    d = d.reshape(-1).view("<u8")
    far = np.frombuffer(raw, "<i8", offset=8 + 6 * n)
    d[far[: len(far) // 2]] = far[len(far) // 2 :].view("<u8")
    return np.cumsum(d, dtype=np.uint64)


def pack_counts(n: np.ndarray) -> bytes:
    """Counts from one on: a byte each, and those from 255 on at the end."""
    return np.minimum(n, 255).astype(np.uint8).tobytes() + n[n >= 255].astype("<i8").tobytes()


def unpack_counts(raw: bytes, size: int) -> np.ndarray:
    n = np.frombuffer(raw, np.uint8, size).astype(np.int64)
    n[n == 255] = np.frombuffer(raw, "<i8", offset=size)
    return n


def _units(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[str, list[tuple[pa.RecordBatch, Shingles]]]]:
    """Documents ``(doc_id, text)`` in units of about ``_UNIT`` shingles, each named by what it holds."""
    held: list[tuple[pa.RecordBatch, Shingles]] = []

    def named() -> tuple[str, list[tuple[pa.RecordBatch, Shingles]]]:
        name = hashlib.blake2b(digest_size=16)
        for _, s in held:
            name.update(s.key.tobytes() + s.sizes.tobytes())
        return name.hexdigest(), held

    for batch in slices(batches):
        held.append((batch, Shingles(batch.column(1))))
        if sum(len(s.h) for _, s in held) >= _UNIT:
            yield named()
            held = []
    if held:
        yield named()


def count_shingles(docs: DataFrame) -> Counted:
    """Exact document frequencies over all rows; no shingle meets the driver."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    # Both scans must form the same units: a plan that shuffles may deal its rows anew.
    if "Exchange" in rows._jdf.queryExecution().executedPlan().toString():
        rows = cut_state(rows)
    n = rows.count()
    folder = f"{shared_dir(docs.sparkSession)}/df-{uuid.uuid4().hex}"
    bits = int(np.clip(np.ceil(np.log2(max(n, 1) / _DOCS)), 0, _MAX_BITS))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = uuid.uuid4().hex  # equal units of two tasks, or of one, stay apart
        for at, (name, unit) in enumerate(_units(batches)):
            h, c = np.unique(np.concatenate([s.h for _, s in unit]), return_counts=True)
            ends = np.searchsorted(h, np.arange(1 << bits, dtype=np.uint64) << np.uint64(64 - bits)) if bits else np.zeros(1, np.int64)
            ends = np.append(ends, len(h))
            used = np.flatnonzero(np.diff(ends))
            cells = [(pack_hashes(h[ends[p] : ends[p + 1]]), pack_counts(c[ends[p] : ends[p + 1]])) for p in used]
            yield pa.RecordBatch.from_arrays([pa.array(used, pa.int32()), pa.array([name] * len(used), pa.string()), pa.array([f"{task}{at}"] * len(used), pa.string()), pa.array([x for x, _ in cells], pa.binary()), pa.array([x for _, x in cells], pa.binary())], names=["part", "unit", "copy", "h", "n"])

    def add(table: pa.Table) -> pa.Table:
        hs = [unpack_hashes(x) for x in table.column("h").to_pylist()]
        n = np.concatenate([unpack_counts(x, len(h)) for h, x in zip(hs, table.column("n").to_pylist(), strict=True)])
        _, place = np.unique(np.concatenate(hs), return_inverse=True)
        df = np.bincount(place, n).astype(np.int64)[place]
        cells = [pack_counts(x) for x in np.split(df, np.cumsum([len(h) for h in hs])[:-1])]
        return pa.table({"part": table.column("part"), "unit": table.column("unit"), "copy": table.column("copy"), "size": pa.array([len(h) for h in hs], pa.int64()), "df": pa.array(cells, pa.binary())})

    def store(table: pa.Table) -> pa.Table:
        order = np.argsort(np.asarray(table.column("part").combine_chunks()))
        sizes, cells = table.column("size").to_pylist(), table.column("df").to_pylist()
        df = np.concatenate([unpack_counts(cells[i], sizes[i]) for i in order])
        # Units of one name hold the same shingles, so it does not matter whose file stays.
        write_whole(f"{folder}/{table.column('unit')[0].as_py()}", pack_counts(df))
        return pa.table({"size": pa.array([len(df)], pa.int64())})

    summed = rows.mapInArrow(deal, "part int, unit string, copy string, h binary, n binary").groupBy("part").applyInArrow(add, "part int, unit string, copy string, size long, df binary")
    summed.groupBy("unit", "copy").applyInArrow(store, "size long").agg(F.sum("size")).collect()
    return Counted(rows, n, folder)


def sample_bands(s: Shingles, weights: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """int64[text, band]: keys of consistent weighted samples; texts without shingles get zeros."""
    keys = np.zeros((len(s.sizes), bands), np.uint64)
    if not len(s.h):
        return keys.view(np.int64)
    has, first = np.unique(s.owner, return_index=True)
    ends = np.append(first, len(s.h))
    at = 0
    while at < len(has):
        to = max(at + 1, int(np.searchsorted(ends, ends[at] + _CHUNK, "right")) - 1)
        lo, hi = ends[at], ends[to]
        keys[has[at:to]] = _sampled(s.h[lo:hi], s.tf[lo:hi] * weights[lo:hi], ends[at : to + 1] - lo, bands, rows)
        at = to
    return mix64(keys).view(np.int64)


def _sampled(h: np.ndarray, weights: np.ndarray, ends: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """Keys of texts with one shingle at least; text i has the shingles ``ends[i]`` to ``ends[i + 1]``."""
    first, length, m = ends[:-1], np.diff(ends), len(h)
    owner = np.repeat(np.arange(len(first)), length)
    keys = np.zeros((len(first), bands), np.uint64)
    ln_s = np.log(weights).astype(np.float32)
    base = h ^ (h >> np.uint64(32))
    z, y = np.empty(m, np.uint64), np.empty(m, np.uint64)
    r, inv, a, beta, t = (np.empty(m, np.float32) for _ in range(5))
    parts, scale = z.view(np.uint16).reshape(-1, 4), np.float32(2**-16)
    for k in range(bands * rows):
        np.multiply(base, mix64(np.array([k + 1]))[0] | np.uint64(1), out=z)
        np.bitwise_xor(z, np.right_shift(z, np.uint64(29), out=y), out=z)
        high = np.right_shift(z, np.uint64(52), out=y).view(np.int64)
        np.take(_R, high, out=r, mode="wrap")
        np.take(_INV_R, high, out=inv, mode="wrap")
        np.take(_LN_C, parts[:, 2], out=a, mode="wrap")
        np.multiply(parts[:, 1], scale, out=beta)
        np.floor(np.add(np.multiply(ln_s, inv, out=t), beta, out=t), out=t)
        # a = ln c - r (t - beta + 1)
        np.multiply(np.add(np.subtract(t, beta, out=beta), np.float32(1), out=beta), r, out=beta)
        np.subtract(a, beta, out=a)
        at = np.flatnonzero(a == np.repeat(np.minimum.reduceat(a, first), length))
        if len(at) > len(first):  # a tie: the smaller hash
            own = owner[at]
            at = at[np.append(True, own[1:] != own[:-1])]
        sample = mix64(h[at] + t[at].astype(np.int64).astype(np.uint64) * _P + np.uint64(k))
        keys[:, k // rows] = keys[:, k // rows] * _P + sample
    return keys


def signatures(counted: Counted, *, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """``(doc_id, k1, k2, words, df, b0, b1, ...)`` of every text with a word; df: packed counts in the order of its shingles."""
    n, folder = counted.docs, counted.folder

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for name, unit in _units(batches):
            h, place = np.unique(np.concatenate([s.h for _, s in unit]), return_inverse=True)
            found = unpack_counts(read_whole(f"{folder}/{name}"), len(h))[place] if len(h) else np.zeros(0, np.int64)
            at = 0
            for batch, s in unit:
                df, at = found[at : at + len(s.h)], at + len(s.h)
                keys = sample_bands(s, idf_weights(df, n), bands, rows)
                ends = np.searchsorted(s.owner, np.arange(len(s.sizes) + 1))
                keep = np.flatnonzero((s.sizes > 0) & np.asarray(batch.column(0).is_valid()))
                cells = [zlib.compress(pack_counts(df[ends[i] : ends[i + 1]]), 1) for i in keep]
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(keep)), *(pa.array(c[keep]) for c in s.key.view(np.int64).T), pa.array(s.sizes[keep]), pa.array(cells, pa.binary()), *(pa.array(c[keep]) for c in keys.T)], names=["doc_id", "k1", "k2", "words", "df", *(f"b{i}" for i in range(bands))])

    return counted.rows.mapInArrow(run, "doc_id long, k1 long, k2 long, words long, df binary" + "".join(f", b{i} long" for i in range(bands)))


def bucket_rows(reps: DataFrame, *, bands: int = BANDS, block: int = BLOCK, words: int = BLOCK_WORDS) -> DataFrame:
    """``(bucket, blocks, rep, k1, k2, words, leads)``: members of each set of two and more that share a bucket, once for each set."""
    node = F.xxhash64("rep", "k1", "k2")
    keyed = reps.select("rep", "k1", "k2", "words", F.posexplode(F.array(*[F.col(f"b{i}") for i in range(bands)])).alias("band", "key")).select("rep", "k1", "k2", "words", F.xxhash64("band", "key").alias("bucket"))
    full = keyed.groupBy("bucket").agg(F.count("*").alias("n"), F.sum("words").alias("size"), F.min(F.struct("rep", "k1", "k2")).alias("first"), F.max("rep").alias("hi"), F.bit_xor(node).alias("x"), F.bit_xor(F.xxhash64("rep", "k1", "k2", F.lit(1))).alias("y")).where("n > 1")
    blocks = F.greatest(F.ceil(F.col("n") / block), F.ceil(F.col("size") / words)).cast("int")
    once = full.groupBy("n", "size", "first", "hi", "x", "y").agg(F.min("bucket").alias("bucket")).select("bucket", "first", blocks.alias("blocks"))
    leads = (F.col("rep") == F.col("first.rep")) & (F.col("k1") == F.col("first.k1")) & (F.col("k2") == F.col("first.k2"))
    return keyed.join(once, "bucket").select("bucket", "blocks", "rep", "k1", "k2", "words", leads.alias("leads"))


def _part(node: str, parts: Column) -> Column:
    return F.pmod(F.xxhash64(node, F.lit(2)), parts.cast("long")).cast("int")


def near_units(rows: DataFrame) -> DataFrame:
    """``(bucket, i, j, mine, team, rep, k1, k2, blocks, once)``: each block as a unit, with its bucket's leader; once: one row of each member."""
    every = F.sequence(F.lit(0), F.col("blocks") - 1)
    placed = rows.withColumn("i", F.explode(F.when(F.col("leads"), every).otherwise(F.array(_part("rep", F.col("blocks"))))))
    return placed.select("bucket", "i", F.col("i").alias("j"), F.lit(0).alias("mine"), F.lit(None).cast("long").alias("team"), "rep", "k1", "k2", "blocks", (~F.col("leads") | (F.col("i") == 0)).alias("once"))


def far_units(rows: DataFrame, parts: DataFrame, *, block: int = BLOCK, words: int = BLOCK_WORDS) -> DataFrame:
    """As :func:`near_units`, pairs of blocks of different teams (components so far): what blocks alone cannot link.

    A team of more than a block has blocks of its own; smaller ones share the blocks before those.
    """
    split = rows.where("blocks > 1").join(parts, F.col("rep") == F.col("node"), "left").select("bucket", "rep", "k1", "k2", "words", F.coalesce("component", "rep").alias("team"))
    teams = split.groupBy("bucket", "team").agg(F.count("*").alias("n"), F.sum("words").alias("size"))
    teams = teams.withColumn("own", F.greatest(F.ceil(F.col("n") / block), F.ceil(F.col("size") / words)).cast("int"))
    small = F.col("own") == 1
    pool = teams.groupBy("bucket").agg(F.count("*").alias("teams"), F.greatest(F.ceil(F.sum(F.when(small, F.col("n"))) / block), F.ceil(F.sum(F.when(small, F.col("size"))) / words), F.lit(0)).cast("int").alias("pool")).where("teams > 1")
    # Few teams of a bucket have blocks of their own; only those are ordered.
    large = teams.where(~small).withColumn("upto", F.sum("own").over(Window.partitionBy("bucket").orderBy("team")))
    ends = large.groupBy("bucket").agg(F.max("upto").alias("owned"))
    teams = teams.select("bucket", "team").join(large.select("bucket", "team", "own", "upto"), ["bucket", "team"], "left").join(pool, "bucket").join(ends, "bucket", "left")
    start = (F.col("pool") + F.col("upto") - F.col("own")).cast("int")
    teams = teams.select("bucket", "team", "own", start.alias("start"), "pool", (F.col("pool") + F.coalesce("owned", F.lit(0))).cast("int").alias("total"))
    placed = split.join(teams, ["bucket", "team"])
    mine = F.when(F.col("own").isNull(), _part("team", F.col("pool"))).otherwise(F.col("start") + _part("rep", F.coalesce("own", F.lit(1))))
    placed = placed.withColumn("mine", mine).withColumn("o", F.explode(F.sequence(F.lit(0), F.col("total") - 1)))
    placed = placed.where("own is null or o < start or o >= start + own")
    return placed.select("bucket", F.least("mine", "o").alias("i"), F.greatest("mine", "o").alias("j"), "mine", "team", "rep", "k1", "k2")


def _linked(s: Shingles, weights: np.ndarray, lo: int, hi: int, threshold: float) -> np.ndarray:
    """Component labels (positions) of the texts lo..hi by their links."""
    m = hi - lo
    a, b = np.searchsorted(s.owner, [lo, hi])
    own, h, tf, w = s.owner[a:b] - lo, s.h[a:b], s.tf[a:b], weights[a:b]
    total = np.bincount(own, tf * w, m)
    _, col, n = np.unique(h, return_inverse=True, return_counts=True)
    shared = n[col] > 1
    own, col, tf, w = own[shared], col[shared], tf[shared], w[shared]
    if tf.size and tf.max() > 1:  # min(tf, tf') counts the levels that both reach
        own, col, w, level = np.repeat(own, tf), np.repeat(col, tf), np.repeat(w, tf), np.arange(tf.sum()) - np.repeat(np.cumsum(tf) - tf, tf)
        col = col * (int(tf.max()) + 1) + level
    _, col = np.unique(col, return_inverse=True)
    inter = np.zeros((m, m))
    order = np.argsort(col, kind="stable")
    own, col, root = own[order], col[order], np.sqrt(w[order])
    width = 1 << 13
    for at in range(0, (int(col[-1]) + 1) if len(col) else 0, width):
        p, q = np.searchsorted(col, [at, at + width])
        part = np.zeros((m, width))
        part[own[p:q], col[p:q] - at] = root[p:q]
        inter += part @ part.T
    union = total[:, None] + total[None, :] - inter
    link = (inter >= (threshold - 1e-12) * union) & (union > 0)
    np.fill_diagonal(link, True)
    label = np.arange(m)
    while True:
        low = np.where(link, label[None, :], m).min(1)
        low = low[low]
        if (low == label).all():
            return label
        label = low


def with_texts(units: DataFrame, reps: DataFrame, counted: Counted) -> DataFrame:
    """``units`` with the texts of their candidates and the counts of these (``df``)."""
    texts = counted.rows.select(F.col("doc_id").alias("rep"), "text")
    # Counts and text come to each candidate once, all dealt by rep alone. Both tables are as long as the documents, so no join
    # is a broadcast at any size and what is shuffled grows with the input. The test on the keys is no equality that would be a
    # key of the join, for which the texts would be dealt out again.
    own = reps.select("rep", F.col("k1").alias("_k1"), F.col("k2").alias("_k2"), "df").hint("merge").join(units.select("rep").distinct(), "rep", "left_semi")
    held = own.join(texts.hint("merge"), "rep").hint("merge")
    same = F.col("k1").bitwiseXOR(F.col("_k1")).bitwiseOR(F.col("k2").bitwiseXOR(F.col("_k2"))) == 0
    return units.join(held, "rep").where(same).select(*units.columns, "text", "df")


def far_texts(across: DataFrame, near: DataFrame) -> DataFrame:
    """:func:`with_texts` for :func:`far_units`, whose members all have a row among those of their bucket's own blocks, ``near``.

    The texts of all documents are not dealt out once more for the few that are compared across blocks.
    """
    held = near.where("once and blocks > 1").select("bucket", "rep", "k1", "k2", "text", "df").hint("merge")
    return across.hint("merge").join(held, ["bucket", "rep", "k1", "k2"]).select(*across.columns, "text", "df")


def verified_links(units: DataFrame, reps: DataFrame, counted: Counted, *, threshold: float = THRESHOLD) -> DataFrame:
    """:func:`links_within` of units whose texts are still to be joined."""
    return links_within(with_texts(units, reps, counted), counted.docs, threshold=threshold)


def links_within(rows: DataFrame, n: int, *, threshold: float = THRESHOLD) -> DataFrame:
    """``(a, b)``: stars that span what is linked in each pair of blocks; ``rows`` are units with their texts, of ``n`` documents."""
    rows = rows.select("bucket", "i", "j", "mine", "rep", "text", "k1", "k2", "df")
    rows = rows.repartition("bucket", "i", "j").sortWithinPartitions("bucket", "i", "j", "rep")

    def check(table: pa.Table) -> pa.RecordBatch:
        s = Shingles(table.column(5).combine_chunks())
        # A doc_id may stand on rows of other words: the candidate is the text with the representative's keys.
        own = (s.key.view(np.int64) == np.stack([np.asarray(table.column(k)) for k in (6, 7)], 1)).all(1)
        if not own.all():
            return check(table.filter(pa.array(own)))
        unit = np.stack([np.asarray(table.column(k)) for k in range(3)], 1)
        rep = np.asarray(table.column(4))
        sizes = np.bincount(s.owner, minlength=len(own))
        df = [unpack_counts(zlib.decompress(x), k) for x, k in zip(table.column(8).to_pylist(), sizes, strict=True)]
        weights = idf_weights(np.concatenate(df), n) if df else np.zeros(0)
        at = np.flatnonzero(np.append(True, (unit[1:] != unit[:-1]).any(1)))[: len(unit)]
        out_a, out_b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for lo, hi in zip(at, np.append(at[1:], len(unit)), strict=True):
            label = _linked(s, weights, lo, hi, threshold)
            moved = np.flatnonzero(label != np.arange(hi - lo))
            out_a.append(rep[lo:hi][moved])
            out_b.append(rep[lo:hi][label[moved]])
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(out_a), pa.int64()), pa.array(np.concatenate(out_b), pa.int64())], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        weight = 0
        for batch in slices(batches, text=5):
            held.append(batch)
            weight += batch.nbytes
            if weight < 1 << 20:
                continue
            table = pa.Table.from_batches(held)
            unit = np.stack([np.asarray(table.column(k)) for k in range(3)], 1)
            last = np.flatnonzero((unit != unit[-1]).any(1))  # the last unit may go on
            if not len(last):
                continue
            done = int(last[-1]) + 1
            yield check(table.slice(0, done))
            held = table.slice(done).combine_chunks().to_batches()
            weight = sum(b.nbytes for b in held)
        if held:
            yield check(pa.Table.from_batches(held))

    return rows.mapInArrow(run, "a long, b long")


def near_classes(docs: DataFrame, *, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, block: int = BLOCK) -> DataFrame:
    """``(doc_id, class_id, kept)`` of every row: class_id is the smallest doc_id of its class, which is kept."""
    counted = count_shingles(docs)
    sig = cut(signatures(counted, bands=bands, rows=rows))
    remove_tree(counted.folder)
    reps = sig.groupBy("k1", "k2").agg(F.min("doc_id").alias("rep"), F.max("words").alias("words"), F.min("df").alias("df"), *[F.min(f"b{i}").alias(f"b{i}") for i in range(bands)])
    reps = cut(reps)
    # A doc_id that stands on several rows joins what its rows' words join.
    same = cut(sig.select("doc_id", "k1", "k2").join(reps.select("k1", "k2", "rep"), ["k1", "k2"]).select("doc_id", "rep"))
    several = same.join(same.groupBy("doc_id").agg(F.count("*").alias("_n")).where("_n > 1"), "doc_id").select("doc_id", "rep")
    members = cut(bucket_rows(reps, bands=bands, block=block))
    folder = f"{shared_dir(docs.sparkSession)}/candidates-{uuid.uuid4().hex}"
    near = with_texts(near_units(members), reps, counted)
    near.write.parquet(folder)
    near = docs.sparkSession.read.schema(near.schema).parquet(folder)
    links = cut(links_within(near, counted.docs, threshold=threshold).union(several))
    parts = link_components(links)
    across = cut(far_units(members, parts, block=block))
    if not across.isEmpty():
        parts = link_components(links.union(links_within(far_texts(across, near), counted.docs, threshold=threshold)))
    remove_tree(folder)
    named = same.join(parts, F.col("rep") == F.col("node"), "left").groupBy("doc_id").agg(F.min(F.coalesce("component", "rep")).alias("class_id"))
    every = docs.select(F.col("doc_id").cast("long").alias("doc_id"))
    return every.join(named, "doc_id", "left").select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("class_id"), F.lit(True)))


def drop_near_copies(docs: DataFrame, **parameters) -> DataFrame:
    """The rows of ``docs`` that stay: one document of each class."""
    gone = near_classes(docs, **parameters).where("not kept").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs["doc_id"].cast("long") == gone["_gone"], "left_anti")
