"""Whole columns of text as flat byte arrays: what the vectorised operators share."""

from __future__ import annotations

import ctypes
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Fixed table: lower-cases A-Z only. Bytes of longer UTF-8 sequences are 0x80 and above, so they stay.
ASCII_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def flat(column: pa.Array) -> tuple[bytes, np.ndarray]:
    """UTF-8 bytes of all rows in a row, and the n + 1 offsets; a null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    a = pc.fill_null(column.cast(pa.large_string()), "")
    if not len(a):
        return b"", np.zeros(1, np.int64)
    ends = np.frombuffer(a.buffers()[1], np.int64, len(a) + 1, a.offset * 8)
    raw = a.buffers()[2]
    data = raw.to_pybytes()[ends[0] : ends[-1]] if raw is not None else b""
    return data, ends - ends[0]


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser of a public 64-bit hash (three xor-shifts, two multiplications)."""
    x = np.asarray(x, np.uint64)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def hash_strings(values: pa.Array) -> np.ndarray:
    """One 64-bit hash for each string (polynomial over its bytes, then mixed), vectorised by length."""
    data, ends = flat(values)
    raw = np.frombuffer(data, np.uint8)
    size = np.diff(ends)
    out = np.zeros(len(size), np.uint64)
    left = np.arange(len(size))
    at = 0
    while len(left := left[size[left] > at]):
        out[left] = (out[left] + raw[ends[left] + at] + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15) ^ (out[left] >> np.uint64(29))
        at += 1
    return mix64(out ^ size.astype(np.uint64))


def _spaced(kept: str) -> bytes:
    """Translation that lower-cases A-Z and blanks all ASCII that is not of the kept classes; other bytes stay."""
    digits = r"\pN" in kept
    return bytes(c if c >= 128 or chr(c).isalpha() or (digits and chr(c).isdigit()) else 32 for c in ASCII_LOWER)


def word_bytes(texts: pa.Array, kept: str = r"\pL\pM") -> tuple[bytes, np.ndarray]:
    """:func:`flat`, in lower case of A-Z, with a space for whatever is not of the kept character classes."""
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    # One search tells which texts have more than ASCII to blank; replacing is slow.
    rare = pc.match_substring_regex(texts, rf"[^\x00-\x7F{kept}]")
    if pc.any(rare).as_py():
        texts = pc.replace_with_mask(texts, rare, pc.replace_substring_regex(texts.filter(rare), f"[^{kept}]+", " "))
    data, ends = flat(texts)
    return data.translate(_spaced(kept)), ends


_ODD = 0x9E3779B97F4A7C15
#: A 64-bit number for each byte.
_BYTES = mix64(np.arange(1, 257))
#: Bytes that are hashed at a time (a longer word is hashed whole).
_PIECE = 1 << 19
_powers_of: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    """At least ``n`` powers of a number modulo 2**64; what long words need is not kept."""
    if n <= _PIECE and base in _powers_of:
        return _powers_of[base]
    steps = np.full(max(n, _PIECE), base, np.uint64)
    steps[0] = 1
    found = np.cumprod(steps, dtype=np.uint64)
    if n <= _PIECE:
        _powers_of[base] = found
    return found


def hash_words(texts: pa.Array, kept: str = r"\pL\pM\pN") -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of every word (runs of the kept classes), and how many each text has.

    Polynomials over the bytes of a word, taken from one running sum over all bytes: no word is ever built.
    """
    data, ends = word_bytes(texts, kept)
    raw = np.frombuffer(data, np.uint8)
    inside = raw != 32
    before, after = np.concatenate([[False], inside[:-1]]), np.concatenate([inside[1:], [False]])
    edges = ends[1:-1]
    edges = edges[(edges > 0) & (edges < len(raw))]
    before[edges] = after[edges - 1] = False
    first, last = np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after)
    return hash_runs(raw, first, last), np.diff(np.searchsorted(first, ends)).astype(np.int64)


def hash_runs(raw: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the bytes from each ``first`` to ``last`` (ascending, apart)."""
    out, at = np.empty(len(first), np.uint64), 0
    while at < len(first):
        lo = first[at]
        to = max(at + 1, int(np.searchsorted(last, lo + _PIECE)))
        n = int(last[to - 1] - lo) + 1
        # Sum of byte value times power of the inverse: a difference, times the power of the word's end, is its polynomial.
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_BYTES[raw[lo : lo + n]] * _powers(pow(_ODD, -1, 1 << 64), n)[:n], dtype=np.uint64)])
        a, z = first[at:to] - lo, last[at:to] - lo
        out[at:to] = mix64((total[z + 1] - total[a]) * _powers(_ODD, n)[z] ^ (z - a + 1).astype(np.uint64))
        at = to
    return out


#: What a worker remembers between tasks for one operator, and how it forgets it.
_stores: dict[str, Callable[[], None]] = {}


def hold_store(name: str, forget: Callable[[], None]) -> None:
    _stores[name] = forget


def drop_stores(keep: str = "") -> None:
    """Forgets what other operators left in this worker: workers outlive a stage, and so would their stores."""
    if gone := [n for n in _stores if n != keep]:
        for name in gone:
            _stores.pop(name)()
        hand_back()


def hand_back() -> None:
    """Gives memory that a task no longer uses back to the machine: workers live on between tasks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # no such allocator here
        pass


def split_words(texts: pa.Array, kept: str = r"\pL\pM") -> tuple[pa.Array, np.ndarray]:
    """All words (runs of the kept character classes), A-Z in lower case, and how many each text has; a null counts as empty."""
    data, ends = word_bytes(texts, kept)
    spaced = pa.LargeStringArray.from_buffers(len(ends) - 1, pa.py_buffer(ends.astype(np.int64)), pa.py_buffer(data))
    split = pc.ascii_split_whitespace(spaced)
    sizes = np.diff(np.asarray(split.offsets))
    words = split.flatten()
    # White space at either end of a text splits off an empty string.
    empty = pc.equal(words, "").to_numpy(zero_copy_only=False).astype(bool)
    if empty.any():
        owner = np.repeat(np.arange(len(sizes)), sizes)
        sizes = sizes - np.bincount(owner[empty], minlength=len(sizes))
        words = words.filter(pa.array(~empty))
    return words, sizes.astype(np.int64)
