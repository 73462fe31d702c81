"""SentencePiece encoding and decoding by shared-prefix Viterbi.

A text is marked (spaces become U+2581, one is put in front) and falls apart into marked words, since no
piece of the vocabulary has the mark after another character (a model that has such a piece is refused). The distinct words of a batch are sorted,
which lays them out as a trie in depth-first order: each word keeps the forward scores of the prefix it
shares with the word before and extends them character by character. At every character the live states
of the vocabulary's own trie are advanced, so only real pieces are tried. The best path has the largest
sum of piece scores; characters that no piece covers cost ten less than the worst piece and
become byte pieces. Ties go to the longer last piece.

The score sum is what the vocabulary's unigram reading asks for; where the file's own library would apply
merges by rank instead, ids may differ, decoding never does.

Scale: one pass over the texts, no shuffle; memory is bounded by a slice of text and a bounded store of words.

Edge cases: a null text counts as empty and has no ids; a text that holds U+2581 itself decodes to a space
there (as in the reference format); decoding of null ids is empty; repeated rows are encoded alike; an
empty table gives an empty result; other columns are kept if named, whatever their names (a result column whose name is taken
gets underscores at its end); a text of any length is cut into words first, so only its distinct words and ids are held.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from starforest.llm.arrow_text import flat as flat_bytes
from starforest.llm.arrow_text import hash_runs, hold_store
from starforest.llm.byte_bpe import WordStore, outer_bytes, slices, tokenizer_path

MARK = "▁"
_BYTE = re.compile(r"^<0x([0-9A-F]{2})>$")
_KEEP = 300_000
_SCORE, _IDS = 0, 1


class PieceModel:
    """Vocabulary of a model file with its scores, as a trie; one per worker and file."""

    _made: dict[str, PieceModel] = {}

    @classmethod
    def of(cls, path: str) -> PieceModel:
        if path not in cls._made:
            import sentencepiece

            sp = sentencepiece.SentencePieceProcessor(model_file=path)
            n = sp.get_piece_size()
            special = {i for i in range(n) if sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)}
            cls._made[path] = cls([(sp.id_to_piece(i), sp.get_score(i)) for i in range(n)], special, sp.unk_id())
        return cls._made[path]

    def __init__(self, pieces: list[tuple[str, float]], special: set[int], unk: int) -> None:
        self.pieces, self.unk = [p for p, _ in pieces], unk
        self.bytes = {int(m[1], 16): i for i, (p, _) in enumerate(pieces) if i not in special and (m := _BYTE.match(p))}
        plain = [(i, p, s) for i, (p, s) in enumerate(pieces) if i not in special and i not in set(self.bytes.values())]
        if any(re.search(f"[^{MARK}]{MARK}", p) for _, p, _ in plain):
            raise ValueError("a piece has the mark after another character: texts do not fall apart into words")
        self.penalty = min((s for _, _, s in plain), default=0.0) - 10.0
        self.trie: dict = {}
        for i, p, s in plain:
            node = self.trie
            for c in p:
                node = node.setdefault(c, {})
            if "" not in node or node[""][0] < s:
                node[""] = (s, i)
        self.raw: list[bytes] = [p.replace(MARK, " ").encode() for p in self.pieces]
        for b, i in self.bytes.items():
            self.raw[i] = bytes([b])
        for i in special:
            self.raw[i] = b""
        self.forget()

    def forget(self) -> None:
        # By hash, in arrays: a quarter of the memory of a dictionary by word.
        self.store = WordStore(_KEEP)

    @property
    def known(self) -> int:
        """Words in the store."""
        return len(self.store.names)

    @property
    def older(self) -> int:
        """Words in the store that the last texts did not have."""
        return int((self.store.used < self.store.now - 1).sum())

    def trie_score(self, piece: str) -> float | None:
        """The score of a plain piece; None if the vocabulary has none of that name."""
        node = self.trie
        for c in piece:
            node = node.get(c)
            if node is None:
                return None
        end = node.get("")
        return end[0] if end is not None else None

    def _spell(self, c: str) -> list[int]:
        return [self.bytes[b] for b in c.encode()] if len(self.bytes) == 256 else [self.unk]

    def segment(self, words: list[str]) -> list[list[int]]:
        """Ids of each of ``words``, which must be sorted and distinct."""
        trie, penalty = self.trie, self.penalty
        best: list[float] = [0.0]  # forward score of each prefix of the path
        back: list[tuple[int, int]] = [(0, -1)]  # where its last piece begins, and the piece (-1: none)
        live: list[list] = [[(0, trie)]]  # (start, vocabulary node) of pieces that may go on
        last, out = "", []
        for word in words:
            n, m = 0, min(len(last), len(word))
            while n < m and last[n] == word[n]:
                n += 1
            del best[n + 1 :], back[n + 1 :], live[n + 1 :]
            for j in range(n, len(word)):
                c = word[j]
                top, came, going = best[j] + penalty, (j, -1), []
                for start, node in live[j]:
                    node = node.get(c)
                    if node is not None:
                        going.append((start, node))
                        end = node.get("")
                        if end is not None:
                            score = best[start] + end[0]
                            if score > top or (score == top and came[1] < 0):
                                top, came = score, (start, end[1])
                best.append(top)
                back.append(came)
                going.append((j + 1, trie))
                live.append(going)
            ids: list[int] = []
            at = len(word)
            while at:
                start, piece = back[at]
                if piece < 0:
                    ids.extend(reversed(self._spell(word[start:at])))
                else:
                    ids.append(piece)
                at = start
            ids.reverse()
            out.append(ids)
            last = word
        return out

    def _coded(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The order in which distinct words are sorted, their ids in that order, flat, and how many each has."""
        named = words.to_pylist()
        order = sorted(range(len(named)), key=named.__getitem__)
        ids, size = np.empty(1 << 12, np.int32), np.zeros(len(named), np.int64)
        at = 0
        for lo in range(0, len(order), 1 << 12):  # lists of ids are long: a few words at a time
            for k, got in enumerate(self.segment([named[i] for i in order[lo : lo + (1 << 12)]]), lo):
                size[k], to = len(got), at + len(got)
                if to > len(ids):
                    ids = np.concatenate([ids, np.empty(max(len(ids), len(got)), np.int32)])
                ids[at:to], at = got, to
        return np.array(order, np.int64), ids[:at], size

    def _found(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """A pool of ids, and where each of the distinct ``words`` starts in it and how many ids it has."""
        data, ends = flat_bytes(words)
        name, check = np.zeros(len(words), np.uint64), np.zeros(len(words), np.uint64)
        some = np.flatnonzero(np.diff(ends))
        if len(some):
            first, last = ends[some], ends[some + 1] - 1
            name[some], check[some] = hash_runs(np.frombuffer(data, np.uint8), first, last), outer_bytes(data, first, last)
        at = self.store.places(name, check) if len(np.unique(name)) == len(name) else None
        if at is None:  # two words of one hash
            order, pool, sizes = self._coded(words)
            start, size = np.zeros(len(words), np.int64), np.zeros(len(words), np.int64)
            start[order], size[order] = np.cumsum(sizes) - sizes, sizes
            return pool, start, size
        new = np.flatnonzero(at < 0)
        if len(new):
            order, ids, sizes = self._coded(words.take(pa.array(new)))
            self.store.add(name[new[order]], check[new[order]], ids, sizes)
            at = self.store.places(name, check)
        return self.store.pool, self.store.starts[at], self.store.sizes[at]

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids (int32) and, for each text, how many."""
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        marked = pc.if_else(pc.equal(texts, ""), texts, pc.binary_join_element_wise(pa.scalar(MARK, pa.large_string()), pc.replace_substring(texts, " ", MARK), pa.scalar("", pa.large_string())))
        # Words begin at a mark that follows another character: runs of marks stay with the word after them.
        cut = pc.replace_substring_regex(marked, f"([^{MARK}])({MARK})", "\\1 \\2")
        split = pc.split_pattern(cut, " ")
        sizes = np.diff(np.asarray(split.offsets))
        coded = split.flatten().dictionary_encode()
        use = np.asarray(coded.indices, np.int64)
        pool, start, size = self._found(coded.dictionary)
        length = size[use]
        ends = np.cumsum(length)
        flat = pool[np.repeat(start[use] - (ends - length), length) + np.arange(ends[-1] if len(ends) else 0)] if len(pool) else np.zeros(0, np.int32)
        doc_ends = np.concatenate([[0], ends])[np.cumsum(sizes)]
        return flat, np.diff(doc_ends, prepend=0)

    def decode(self, flat: np.ndarray, counts: np.ndarray) -> list[str]:
        """The texts: pieces and bytes in a row, marks as spaces, without the one put in front."""
        size = np.array([len(r) for r in self.raw], np.int64)
        pool = np.frombuffer(b"".join(self.raw), np.uint8)
        start, length = (np.cumsum(size) - size)[flat], size[flat]
        ends = np.cumsum(length)
        data = pool[np.repeat(start - (ends - length), length) + np.arange(ends[-1] if len(ends) else 0)].tobytes()
        bounds = np.concatenate([[0], ends])[np.concatenate([[0], np.cumsum(counts)])]
        return [data[a + (data[a : a + 1] == b" ") : b].decode(errors="replace") if b > a else "" for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]


def model_path(name: str = "piece_bpe_32k.model") -> str:
    return tokenizer_path(name)


def _free(name: str, keep: tuple[str, ...]) -> str:
    while name in keep:
        name += "_"
    return name


def _travel(df: DataFrame, keep: tuple[str, ...]) -> tuple[list[Column], str, list[Column]]:
    """Kept columns under names of their own, their types, and the way back."""
    kinds = "".join(f"c{i} {df.schema[c].dataType.simpleString()}, " for i, c in enumerate(keep))
    return [F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(keep)], kinds, [F.col(f"c{i}").alias(c) for i, c in enumerate(keep)]


def encode_pieces(docs: DataFrame, *, model: str | None = None, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """``(*keep, ids)`` of every whole text."""
    path = model or model_path()
    there, kinds, back = _travel(docs, keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = PieceModel.of(path)
        # The trie goes with the words: it is read again in half a second if this worker encodes once more.
        hold_store("pieces", PieceModel._made.clear)
        for batch in slices(batches, text=len(keep), most=1 << 20, store="pieces"):
            flat, counts = coder.encode(batch.column(len(keep)))
            ids = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]), pa.int32()), pa.array(flat))
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], ids], names=[*batch.schema.names[:-1], "ids"])

    coded = docs.select(*there, F.col(f"`{text}`").cast("string").alias("text")).mapInArrow(run, f"{kinds}ids array<int>")
    return coded.select(*back, F.col("ids").alias(_free("ids", keep)))


def decode_pieces(encoded: DataFrame, *, model: str | None = None, keep: tuple[str, ...] = ("doc_id",), ids: str = "ids") -> DataFrame:
    """``(*keep, text)`` from ids."""
    path = model or model_path()
    there, kinds, back = _travel(encoded, keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = PieceModel.of(path)
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                some = batch.slice(at, 500)
                lists = some.column(len(keep))
                counts = np.asarray(pc.fill_null(pc.list_value_length(lists), 0), np.int64)
                texts = coder.decode(np.asarray(lists.flatten(), np.int64), counts)
                yield pa.RecordBatch.from_arrays([*some.columns[: len(keep)], pa.array(texts, pa.string())], names=[*some.schema.names[:-1], "text"])

    decoded = encoded.select(*there, F.col(f"`{ids}`").alias("ids")).mapInArrow(run, f"{kinds}text string")
    return decoded.select(*back, F.col("text").alias(_free("text", keep)))


def piece_digests(docs: DataFrame, *, model: str | None = None) -> DataFrame:
    """``(doc_id, n_pieces, ids_sha256, round_trip)``: every text encoded, decoded and compared."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    # The mark itself is the one character that the format cannot tell from a space.
    rows = rows.withColumn("sha", F.sha2(F.regexp_replace("text", MARK, " "), 256))
    coded = encode_pieces(rows, model=model, keep=("doc_id", "sha"))
    coded = coded.withColumns({"n_pieces": F.size("ids"), "ids_sha256": F.sha2(F.array_join(F.col("ids").cast("array<string>"), ","), 256)})
    back = decode_pieces(coded, model=model, keep=("doc_id", "sha", "n_pieces", "ids_sha256"))
    return back.select("doc_id", F.col("n_pieces").cast("long").alias("n_pieces"), "ids_sha256", (F.sha2("text", 256) == F.col("sha")).alias("round_trip"))
