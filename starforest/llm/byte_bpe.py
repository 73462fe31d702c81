"""Byte-level BPE ids of whole texts with the tokenizers library, each distinct word encoded once.

The tokenizer splits a text into words by a pattern and encodes each word by itself, so a batch need only
encode its distinct words. Texts of Latin letters without runs of white space or contractions are split into
words right away. Others are cut before spaces only: no word of the pattern joins a character to a space
that follows it, so that cut is safe unless the space stands between two white-space characters (or
between one and the end). Texts with such a space go through the library whole. Where all that is not ASCII are letters, words
are found on the bytes and known by their hashes, so that only new ones become strings. A worker remembers the last words.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from starforest.llm.arrow_text import drop_stores, flat, hand_back, hash_runs, mix64

_SPACE = r"\s\x0B\x{85}\pZ"
#: A space among white space, or at the end after it, forbids the cut.
_WHOLE = rf"[{_SPACE}] ([{_SPACE}]|\z)"
#: Texts that are not split into words right away: runs of white space, contractions, more than Latin letters and punctuation.
_RARE = rf"[{_SPACE}]{{2}}|'(?:[stmd]|re|ve|ll)|[^\x00-\x{{24F}}\x{{2010}}-\x{{2027}}]"
_WORDS = rf"( ?\pL+| ?\pN+| ?[^{_SPACE}\pL\pN]+|[{_SPACE}])"
#: Ends words while they are split; texts that hold it themselves are cut before spaces instead.
_END = "\x00"
#: Classes of bytes: space, other white space, letters (and bytes of longer characters), digits, the rest.
_CLASS = np.array([0 if b == 32 else 1 if 9 <= b <= 13 else 2 if b >= 128 or chr(b).isalpha() else 3 if chr(b).isdigit() else 4 for b in range(256)], np.uint8)
_SLICE_BYTES = 2 << 20
_KEEP = 300_000


def _byte_letters() -> dict[int, int]:
    """The byte-level alphabet, by its public rule: printable bytes stand for themselves, others follow from U+0100."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in own]
    return {b: b for b in own} | {b: 256 + i for i, b in enumerate(rest)}


_LETTERS = _byte_letters()


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class WordStore:
    """Ids of the words used last, by hash."""

    def __init__(self, most: int = _KEEP) -> None:
        self.most, self.now = most, 0
        self.names, self.checks = np.zeros(0, np.uint64), np.zeros(0, np.uint64)
        self.starts, self.sizes, self.used = (np.zeros(0, np.int64) for _ in range(3))
        self.pool = np.zeros(0, np.int32)

    def places(self, names: np.ndarray, checks: np.ndarray) -> np.ndarray | None:
        """Where each word is, -1 if it is not known; None if another word has its hash."""
        if not len(self.names):
            return np.full(len(names), -1)
        at = np.minimum(np.searchsorted(self.names, names), len(self.names) - 1)
        known = self.names[at] == names
        if not (self.checks[at[known]] == checks[known]).all():
            return None
        self.used[at[known]] = self.now
        return np.where(known, at, -1)

    def add(self, names: np.ndarray, checks: np.ndarray, ids: list[int] | np.ndarray, sizes: list[int] | np.ndarray) -> None:
        keep = np.arange(len(self.names))
        if len(keep) + len(names) > self.most:  # the words of this batch stay, and of the others those used last
            order = np.argsort(-self.used, kind="stable")
            keep = np.sort(order[: max(self.most // 2, int((self.used == self.now).sum()))])
        length = self.sizes[keep]
        to = np.cumsum(length)
        old = self.pool[np.repeat(self.starts[keep] - (to - length), length) + np.arange(to[-1] if len(to) else 0)]
        size = np.concatenate([length, np.array(sizes, np.int64)])
        self.pool = np.concatenate([old, np.array(ids, np.int32)])
        every = np.concatenate([self.names[keep], names])
        order = np.argsort(every)
        self.names, self.checks = every[order], np.concatenate([self.checks[keep], checks])[order]
        self.starts, self.sizes = (np.cumsum(size) - size)[order], size[order]
        self.used = np.concatenate([self.used[keep], np.full(len(names), self.now)])[order]
        self.now += 1


def outer_bytes(data: bytes, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """A second hash of each run, of its first and last eight bytes and its length: words up to sixteen bytes are told apart by them."""
    # Every window of eight bytes as one number; zeros around the data.
    padded = np.frombuffer(bytes(8) + data + bytes(8), np.uint8)
    windows = np.lib.stride_tricks.as_strided(padded, (len(padded) - 7, 8), (1, 1))
    size = last - first + 1
    spare = (np.maximum(8 - size, 0) * 8).astype(np.uint64)
    head = windows[first + 8].view("<u8").ravel() << spare
    tail = windows[last + 1].view("<u8").ravel() >> spare
    return mix64(mix64(head) + tail * np.uint64(3)) ^ size.astype(np.uint64)


class WordEncoder:
    """Encodes Arrow string arrays; one per worker and file."""

    _made: dict[str, WordEncoder] = {}

    @classmethod
    def of(cls, path: str) -> WordEncoder:
        if path not in cls._made:
            cls._made[path] = cls(path)
        return cls._made[path]

    def __init__(self, path: str) -> None:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True  # their strings are ordinary text
        self.known: dict[str, int] = {}
        self.pool, self.starts = np.zeros(0, np.int32), np.zeros(1, np.int64)
        self.store = WordStore()

    def _tokenize(self, words: list[str]) -> tuple[list[int], list[int]]:
        """Flat ids, and how many each word has."""
        tokenize, ids, sizes = self.tokenizer.model.tokenize, [], []
        for w in words:
            got = tokenize((w if w.isascii() and w[:1] != " " else w.encode().decode("latin-1")).translate(_LETTERS))
            ids += [t.id for t in got]
            sizes.append(len(got))
        return ids, sizes

    def _learn(self, new: list[str]) -> None:
        """Encodes words and appends their ids to the pool."""
        ids, sizes = self._tokenize(new)
        self.known.update(zip(new, range(len(self.known), len(self.known) + len(new)), strict=True))
        self.starts = np.concatenate([self.starts, self.starts[-1] + np.cumsum(sizes, dtype=np.int64)])
        self.pool = np.concatenate([self.pool, np.array(ids, np.int32)])

    def _ids(self, words: list[str], use: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of ``words[use]``, and where each of them ends."""
        new = [w for w in words if w not in self.known]
        if len(self.known) + len(new) > _KEEP:
            self.known, new = {}, words
            self.pool, self.starts = np.zeros(0, np.int32), np.zeros(1, np.int64)
        self._learn(new)
        at = np.array([self.known[w] for w in words], np.int64)[use]
        length = self.starts[at + 1] - self.starts[at]
        ends = np.cumsum(length)
        return self.pool[np.repeat(self.starts[at + 1] - ends, length) + np.arange(ends[-1] if len(ends) else 0)], ends

    @staticmethod
    def _parts(texts: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
        """Distinct parts of texts cut before spaces, which of them follow each other, and how many each text has."""
        split = pc.split_pattern(texts, " ")
        sizes = np.diff(np.asarray(split.offsets))
        coded = split.flatten().dictionary_encode()
        part = np.array(coded.indices, np.int64)
        words = coded.dictionary
        spaced = pc.binary_join_element_wise(pa.scalar("", pa.large_string()), words, pa.scalar(" ", pa.large_string()))
        # The first part of a text has no space before it; the others have.
        part[np.cumsum(sizes) - sizes] += len(words)
        seen = np.zeros(2 * len(words), bool)
        seen[part] = True
        return pa.concat_arrays([spaced, words]).filter(pa.array(seen)), (np.cumsum(seen) - 1)[part], sizes

    @staticmethod
    def _spread(pool: np.ndarray, ends: np.ndarray, use: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of ``use``, entry k of ``pool`` ending at ``ends[k]``; and how many fall to each text of ``sizes`` entries."""
        length = np.diff(ends, prepend=0)[use]
        to = np.cumsum(length)
        flat = pool[np.repeat(ends[use] - to, length) + np.arange(to[-1] if len(to) else 0)]
        return flat, np.diff(to[np.cumsum(sizes) - 1], prepend=0)

    def _by_bytes(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        data, ends = flat(texts)
        raw = np.frombuffer(data, np.uint8)
        kind = _CLASS[raw]
        before = np.concatenate([np.ones(1, np.uint8), kind[:-1]]) if len(raw) else kind
        before[ends[:-1][ends[:-1] < len(raw)]] = 1
        # A word begins at white space, and where the class changes unless a space begins it.
        first = np.flatnonzero((kind <= 1) | ((kind != before) & (before != 0)))
        if not len(first):
            return np.zeros(0, np.int32), np.zeros(len(texts), np.int64)
        last = np.append(first[1:], len(raw)) - 1
        name, check = hash_runs(raw, first, last), outer_bytes(data, first, last)
        names, one, use = np.unique(name, return_index=True, return_inverse=True)
        if not (check[one][use] == check).all():  # two words of one hash
            return self._by_words(texts)
        at = self.store.places(names, check[one])
        if at is None:
            return self._by_words(texts)
        new = np.flatnonzero(at < 0)
        if len(new):
            words = [data[a : b + 1].decode() for a, b in zip(first[one[new]].tolist(), last[one[new]].tolist(), strict=True)]
            self.store.add(names[new], check[one[new]], *self._tokenize(words))
            at = self.store.places(names, check[one])
        start, length = self.store.starts[at][use], self.store.sizes[at][use]
        to = np.cumsum(length)
        ids = self.store.pool[np.repeat(start - (to - length), length) + np.arange(to[-1])]
        return ids, np.diff(np.concatenate([[0], to])[np.searchsorted(first, ends)])

    def _by_words(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        parts, use, sizes = self._parts(texts)
        # Parts that are a word as they stand need no splitting.
        plain = pc.match_substring_regex(parts, r"\A ?\pL+\z")
        ended = pc.if_else(plain, pc.binary_join_element_wise(parts, pa.scalar("", pa.large_string()), pa.scalar(_END, pa.large_string())), "")
        mixed = pc.replace_substring_regex(parts.filter(pc.invert(plain)), _WORDS, "\\1" + _END)
        split = pc.split_pattern(pc.replace_with_mask(ended, pc.invert(plain), mixed), _END)
        coded = split.flatten().dictionary_encode()
        # A part's last word is empty (every word ends with the mark): it has no ids.
        pool, ends = self._ids(coded.dictionary.to_pylist(), np.asarray(coded.indices, np.int64))
        return self._spread(pool, ends[np.asarray(split.offsets)[1:] - 1], use, sizes)

    def _by_spaces(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        parts, use, sizes = self._parts(texts)
        parts = parts.to_pylist()
        got = [x.ids for at in range(0, len(parts), 20_000) for x in self.tokenizer.encode_batch_fast(parts[at : at + 20_000], add_special_tokens=False)]
        return self._spread(np.array([i for ids in got for i in ids], np.int32), np.cumsum([len(ids) for ids in got]), use, sizes)

    def _by_library(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        got = [self.tokenizer.encode(t, add_special_tokens=False).ids for t in texts.to_pylist()]
        return np.array([i for ids in got for i in ids], np.int32), np.array([len(ids) for ids in got], np.int64)

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids (int32) and, for each text, how many; a null counts as empty."""
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        n = len(texts)
        if not n:
            return np.zeros(0, np.int32), np.zeros(0, np.int64)
        rare = pc.or_(pc.match_substring_regex(texts, _RARE), pc.match_substring(texts, _END)).to_numpy(zero_copy_only=False)
        whole = np.zeros(n, bool)
        whole[rare] = pc.match_substring_regex(texts.filter(pa.array(rare)), _WHOLE).to_numpy(zero_copy_only=False)
        # Not ASCII and no letter: bytes do not tell where words end.
        other = pc.match_substring_regex(texts, r"[^\x00-\x7F\pL]").to_numpy(zero_copy_only=False) & ~rare
        ways = [(np.flatnonzero(~rare & ~other), self._by_bytes), (np.flatnonzero(other), self._by_words), (np.flatnonzero(rare & ~whole), self._by_spaces), (np.flatnonzero(whole), self._by_library)]
        counts = np.zeros(n, np.int64)
        done = [(rows, *way(texts.take(pa.array(rows)))) for rows, way in ways if len(rows)]
        for rows, _, sizes in done:
            counts[rows] = sizes
        if len(done) == 1:
            return done[0][1], counts
        out, at = np.empty(counts.sum(), np.int32), np.cumsum(counts) - counts
        for rows, flat, sizes in done:
            out[np.repeat(at[rows] - (np.cumsum(sizes) - sizes), sizes) + np.arange(len(flat))] = flat
        return out, counts


def slices(batches: Iterator[pa.RecordBatch], text: int = 1, most: int = _SLICE_BYTES, store: str = "") -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``most`` bytes of text (one row at least). Stores of operators other than ``store`` are dropped."""
    drop_stores(store)
    for batch in batches:
        ends = np.cumsum(np.asarray(pc.fill_null(pc.binary_length(batch.column(text)), 0), np.int64) + 16)
        at = 0
        while at < batch.num_rows:
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, "right")))
            yield batch.slice(at, to - at)
            at = to
            hand_back()  # what a slice took is not left to lie about beside the next one's
    hand_back()
