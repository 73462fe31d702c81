"""Language spans of mixed-language text.

A word's script (by Unicode ranges) narrows the candidate languages; each candidate scores the word by
log-probabilities of hashed character n-grams; Viterbi over the words with one penalty for every switch
labels each word. Runs of equal labels are the spans; the language that covers most letters is the
document's, and its share of the letters is the score.

The model is fitted on a sample of labelled texts that is bounded per language (``per_lang`` different texts, taken in the
order of a hash of the text, a documented bound that no layout of the input changes); more than ``MAX_LANGS`` languages are an
error. Prediction is one pass over the texts, vectorised over the distinct words of a batch and, for Viterbi, over its documents.

Edge cases: a text that is null or has no letter is ``und`` with score 0; without any labelled row every
text is ``und``; ties go to the language that sorts first; repeated rows are predicted alike; an empty
table gives an empty result; other columns are dropped.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from starforest.llm.arrow_text import flat, mix64, split_words
from starforest.llm.byte_bpe import slices

#: First code points of script ranges, and the script from there on (0: none or shared).
_STARTS = np.array([0, 0x41, 0x5B, 0x61, 0x7B, 0xAA, 0xAB, 0xB5, 0xB6, 0xBA, 0xBB, 0xC0, 0x250, 0x370, 0x400, 0x530, 0x590, 0x600, 0x700, 0x900, 0x980, 0xA00, 0xE00, 0xE80, 0x10A0, 0x1100, 0x1200, 0x1E00, 0x1F00, 0x2000, 0x3040, 0x30A0, 0x3100, 0x3400, 0xA000, 0xAC00, 0xD7B0, 0xF900, 0xFB00, 0x20000])
_SCRIPTS = np.array([0, 1, 0, 1, 0, 1, 0, 1, 0, 1, 0, 1, 1, 2, 3, 4, 5, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15, 1, 2, 0, 16, 16, 0, 17, 18, 14, 0, 17, 19, 17])
N_SCRIPTS = 20
#: Languages that a model can have: with 2**bits weights each, this bounds what the driver gathers and tasks are sent (256 MB).
MAX_LANGS = 512
#: Distinct words whose n-grams are scored, or counted, at a time.
_SCORED = 1 << 13


class LanguageModel(NamedTuple):
    langs: tuple[str, ...]
    logp: np.ndarray  # float32[bucket, lang]
    scripts: np.ndarray  # bool[script, lang]
    bits: int
    sizes: tuple[int, ...]

    def word_scores(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """float32[word, lang] and the words' letter counts."""
        # N-grams take over a hundred bytes for each byte of a word: a few words at a time.
        parts = [self._gram_scores(words.slice(at, _SCORED)) for at in range(0, len(words), _SCORED)]
        out = np.concatenate(parts) if parts else np.zeros((0, len(self.langs)))
        allowed = self.scripts[word_scripts(words)]
        narrows = allowed.any(1)
        out[narrows] = np.where(allowed[narrows], out[narrows], -1e6)
        out[~narrows] = 0  # no learned language uses the script: the word says nothing
        return out.astype(np.float32), np.asarray(pc.utf8_length(words), np.int64)

    def _gram_scores(self, words: pa.Array) -> np.ndarray:
        row, bucket = _ngrams(words, self.bits, self.sizes)
        n = len(words)
        count = np.maximum(np.bincount(row, minlength=n), 1)
        return np.stack([np.bincount(row, self.logp[bucket, k], n) / np.sqrt(count) for k in range(len(self.langs))], 1)


def word_scripts(words: pa.Array) -> np.ndarray:
    """The script of each word's first letter."""
    first = pc.fill_null(pc.utf8_slice_codeunits(words.cast(pa.large_string()), 0, 1), "").to_pylist()
    points = np.array([ord(c) if c else 0 for c in first], np.int64)
    return _SCRIPTS[np.searchsorted(_STARTS, points, "right") - 1]


def _ngrams(words: pa.Array, bits: int, sizes: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
    """(word, bucket) of the byte n-grams of `` word `` in lower case."""
    data, ends = flat(pc.utf8_lower(words.cast(pa.large_string())))
    n = len(ends) - 1
    size = np.diff(ends) + 2
    raw = np.full(int(size.sum()), 32, np.uint8)
    owner = np.repeat(np.arange(n), size)
    inside = np.ones(len(raw), bool)
    starts = (np.cumsum(size) - size).astype(np.int64)
    inside[starts] = inside[starts + size - 1] = False
    raw[inside] = np.frombuffer(data, np.uint8)
    rows, buckets = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for g in sizes:
        if len(raw) < g:
            continue
        h = np.zeros(len(raw) - g + 1, np.uint64)
        for k in range(g):
            h = (h << np.uint64(8)) | raw[k : len(raw) - g + 1 + k]
        same = owner[: len(h)] == owner[g - 1 :]
        rows.append(owner[: len(h)][same])
        buckets.append((mix64(h[same] * np.uint64(8) + np.uint64(g)) >> np.uint64(64 - bits)).astype(np.int64))
    return np.concatenate(rows), np.concatenate(buckets)


def _counted(langs: pa.Array, texts: pa.Array, bits: int, sizes: tuple[int, ...]) -> Iterator[tuple[str, np.ndarray, np.ndarray]]:
    """For each language the buckets of its texts' n-grams and, below zero, the scripts of their words, and how many there are of each."""
    coded = langs.dictionary_encode()
    words, n = split_words(texts)
    spoken = np.repeat(np.asarray(coded.indices, np.int64), n)
    for k, lang in enumerate(coded.dictionary.to_pylist()):
        mine = words.filter(pa.array(spoken == k))
        grams, scripts = np.zeros(1 << bits, np.int64), np.zeros(N_SCRIPTS, np.int64)
        for at in range(0, len(mine), _SCORED):
            some = mine.slice(at, _SCORED)
            grams += np.bincount(_ngrams(some, bits, sizes)[1], minlength=1 << bits)
            scripts += np.bincount(word_scripts(some), minlength=N_SCRIPTS)
        yield lang, np.concatenate([np.flatnonzero(grams), -1 - np.flatnonzero(scripts)]), np.concatenate([grams[grams > 0], scripts[scripts > 0]])


def fit_language_model(labelled: DataFrame, *, per_lang: int = 600, bits: int = 17, sizes: tuple[int, ...] = (1, 2, 3, 4), floor: float = 0.5) -> LanguageModel:
    """Fits on ``labelled(text, lang)``: about ``per_lang`` rows of each language at most, by the order of a hash."""
    rows = labelled.where("lang is not null and text is not null").select("lang", "text").withColumn("_h", F.xxhash64("text"))
    # A threshold on the hash first, at twice the different texts wanted: no language is ever sorted whole.
    share = rows.groupBy("lang").agg((2.0 * per_lang / F.greatest(F.approx_count_distinct("_h"), F.lit(1))).alias("_share")).limit(MAX_LANGS + 1).collect()
    if len(share) > MAX_LANGS:
        raise ValueError(f"more than {MAX_LANGS} languages")
    # One number for each language: broadcast, or the join would shuffle every text by its language.
    shares = labelled.sparkSession.createDataFrame(pa.table({"lang": pa.array([r[0] for r in share], pa.string()), "_share": pa.array([r[1] for r in share], pa.float64())}))
    near = rows.join(F.broadcast(shares), "lang").where(F.shiftrightunsigned("_h", 11) < F.col("_share") * float(1 << 53))
    # Of equal texts one: they all have one hash, and a group of copies would fill the sample.
    once = near.groupBy("lang", "_h").agg(F.min("text").alias("text"))
    table = once.withColumn("_k", F.row_number().over(Window.partitionBy("lang").orderBy("_h"))).where(F.col("_k") <= per_lang).select("lang", F.lower("text").alias("text"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            for lang, keys, found in _counted(batch.column(0), batch.column(1), bits, sizes):
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(keys)), pa.array(keys, pa.int64()), pa.array(found, pa.int64())], names=["lang", "key", "n"])

    counts = table.mapInArrow(count, "lang string, key long, n long").groupBy("lang", "key").agg(F.sum("n").alias("n")).toPandas()
    langs = tuple(sorted(counts["lang"].unique()))
    logp, scripts = np.full((1 << bits, len(langs)), floor), np.zeros((N_SCRIPTS, len(langs)), bool)
    for k, lang in enumerate(langs):
        mine = counts[counts["lang"] == lang]
        grams, used = mine[mine["key"] >= 0], mine[mine["key"] < 0]
        logp[grams["key"].to_numpy(), k] += grams["n"].to_numpy()
        # A script belongs to a language that writes at least a hundredth of its words in it.
        scripts[-1 - used["key"].to_numpy(), k] = used["n"].to_numpy() * 100 >= used["n"].sum()
    scripts[0] = False
    logp = np.log(logp / logp.sum(0)) if langs else logp
    return LanguageModel(langs, (logp - logp.mean(1, keepdims=True) if langs else logp).astype(np.float32), scripts, bits, sizes)


def viterbi(scores: np.ndarray, sizes: np.ndarray, penalty: float) -> np.ndarray:
    """Label of every word: ``scores`` [word, lang] of documents of ``sizes`` words, one after the other."""
    docs = np.flatnonzero(sizes)
    docs = docs[np.argsort(-sizes[docs], kind="stable")]
    starts, longest = (np.cumsum(sizes) - sizes)[docs], int(sizes.max()) if len(docs) else 0
    size, live = sizes[docs], np.zeros(longest + 1, np.int64)
    if not longest:
        return np.zeros(0, np.int16)
    live[:longest] = np.searchsorted(-size, -np.arange(longest), "left")
    came = np.zeros(scores.shape, np.int16)
    stay = np.arange(scores.shape[1], dtype=np.int16)
    v = scores[starts].astype(np.float64)
    for t in range(1, longest):
        k = live[t]
        at, old = starts[:k] + t, v[:k]
        best = old.argmax(1)
        jump = old[np.arange(k), best] - penalty
        switch = jump[:, None] > old
        came[at] = np.where(switch, best[:, None].astype(np.int16), stay)
        v[:k] = np.where(switch, jump[:, None], old) + scores[at]
    out = np.zeros(len(scores), np.int16)
    label = v.argmax(1)
    for t in range(longest - 1, -1, -1):
        k = live[t]
        at = starts[:k] + t
        out[at] = label[:k]
        if t:
            label[:k] = came[at, label[:k]]
    return out


def _labels(texts: pa.Array, model: LanguageModel, penalty: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Labels and letter counts of all words, and the words of each text."""
    words, sizes = split_words(texts)
    coded = words.dictionary_encode()
    scores, letters = model.word_scores(coded.dictionary)
    use = np.asarray(coded.indices, np.int64)
    return viterbi(scores[use], sizes, penalty), letters[use], sizes


def judge(texts: pa.Array, model: LanguageModel, penalty: float) -> tuple[np.ndarray, np.ndarray]:
    """The language that covers most letters (the number of languages: none), and its share of them."""
    n, k = len(texts), len(model.langs)
    best, score = np.full(n, k), np.zeros(n)
    if k:
        label, letters, sizes = _labels(texts, model, penalty)
        owner = np.repeat(np.arange(n), sizes)
        mass = np.bincount(owner * k + label, letters, n * k).reshape(n, k)
        has = mass.sum(1) > 0
        best[has], score[has] = mass[has].argmax(1), mass[has].max(1) / mass[has].sum(1)
    return best, score


def predict_language(docs: DataFrame, model: LanguageModel, *, penalty: float = 6.0) -> DataFrame:
    """``(doc_id, lang_pred, score)`` of every whole text."""
    langs = np.array([*model.langs, "und"], object)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            best, score = judge(batch.column(1), model, penalty)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(langs[best], pa.string()), pa.array(score)], names=["doc_id", "lang_pred", "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, lang_pred string, score double")


def drop_unsure(docs: DataFrame, model: LanguageModel, *, least: float = 0.5, penalty: float = 6.0) -> DataFrame:
    """The rows of ``docs`` with a language that covers at least ``least`` of their letters."""
    # Columns travel once, under names of their own; a text that is no string travels as one beside them.
    own = [F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(docs.columns)]
    at = docs.columns.index("text")
    if docs.schema["text"].dataType.simpleString() != "string":
        own, at = [*own, F.col("text").cast("string").alias("c")], len(own)
    rows = docs.select(*own)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, text=at):
            best, score = judge(batch.column(at), model, penalty)
            yield batch.filter(pa.array((best < len(model.langs)) & (score >= least)))

    return rows.mapInArrow(run, rows.schema).select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(docs.columns)])


def language_spans(docs: DataFrame, model: LanguageModel, *, penalty: float = 6.0) -> DataFrame:
    """``(doc_id, first_word, words, letters, lang)``: the labelled spans of each text, in words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            label, letters, sizes = _labels(batch.column(1), model, penalty)
            owner = np.repeat(np.arange(batch.num_rows), sizes)
            new = np.flatnonzero(np.concatenate([[True], (np.diff(owner) != 0) | (np.diff(label) != 0)])[: len(owner)])
            at = new - (np.cumsum(sizes) - sizes)[owner[new]]
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(owner[new])), pa.array(at, pa.int64()), pa.array(np.diff(np.append(new, len(owner))), pa.int64()), pa.array(np.add.reduceat(letters, new) if len(new) else letters, pa.int64()), pa.array(np.array(model.langs, object)[label[new]], pa.string())], names=["doc_id", "first_word", "words", "letters", "lang"])

    if not model.langs:
        return docs.sparkSession.createDataFrame([], "doc_id long, first_word long, words long, letters long, lang string")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, first_word long, words long, letters long, lang string")


def held_out(doc_id: str = "doc_id"):
    """Whether a document is kept out of training: CRC-32 of its id as text, modulo 4, is 2."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit_on_documents(docs: DataFrame, **parameters) -> LanguageModel:
    return fit_language_model(docs.where(~held_out()), **parameters)
