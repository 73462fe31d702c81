"""URL filter: host and path rules first, then logistic regression on hashed character n-grams.

The model is fitted on the driver from a labelled URL table of at most ``max_rows`` rows (a documented
bound; a larger table is thinned by the order of a hash) and scores every url in Arrow batches. Its
size is fixed: ``2 ** bits`` weights. ``labelled_urls.csv`` beside this module is such a table, written by hand: addresses under
the reserved top-level name ``test``, so none of its hosts can be a real one or one of the tables'. Hosts of one fold of four
(:func:`held_out_rates`) tell how well it does on hosts it has not seen.

Edge cases: a null url, or one without ``://``, has an empty host and path, fits no rule and gets the
model's verdict on empty text (the bias); repeated rows are judged alike; an empty table gives an
empty result; other columns are dropped, whatever their names; a url of any length is scored whole.
"""

from __future__ import annotations

import csv
import zlib
from collections.abc import Iterator, Sequence
from importlib import resources
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from starforest.llm.arrow_text import flat, mix64

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


#: Share of urls taken to be unwanted before anything is known about them.
PRIOR = 0.3


class Rule(NamedTuple):
    pattern: str
    verdict: str


#: The rules of the contract.
RULES = (Rule("com/en/", "block"), Rule("example.com/en/7", "allow"), Rule("net/de/", "allow"), Rule("example.net/de/8", "block"), Rule("org/es/", "block"))


def labelled_urls() -> list[tuple[str, int]]:
    """The labelled URL table beside this module (1: to be blocked)."""
    with (resources.files(__package__) / "labelled_urls.csv").open(encoding="utf-8", newline="") as f:
        return [(r["url"], int(r["label"])) for r in csv.DictReader(f)]


def with_host_path(df: DataFrame, url: str = "url") -> DataFrame:
    """Adds ``host`` (A-Z lower-cased) and ``path``."""
    u = F.coalesce(F.col(url).cast("string"), F.lit(""))
    shape = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    return df.withColumns({"host": F.translate(F.regexp_extract(u, shape, 1), _UPPER, _LOWER), "path": F.regexp_extract(u, shape, 2)})


def with_rule(df: DataFrame, rules: Sequence[Rule] = RULES) -> DataFrame:
    """Adds ``rule`` and ``rule_verdict``: the longest rule whose host covers ``host`` and whose path begins ``path``."""
    rule = verdict = F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.pattern), r.pattern)):
        host, slash, path = r.pattern.partition("/")
        fits = ((F.col("host") == host) | F.col("host").endswith("." + host)) & F.col("path").startswith(slash + path)
        rule, verdict = F.when(fits, r.pattern).otherwise(rule), F.when(fits, r.verdict).otherwise(verdict)
    return df.withColumns({"rule": rule, "rule_verdict": verdict})


def _features(hosts: pa.Array, paths: pa.Array, bits: int, sizes: Sequence[int]) -> tuple[np.ndarray, np.ndarray]:
    """(row, bucket) of every n-gram of characters of ``^host$`` and ``^path$``."""
    rows, buckets = [], []
    for part, column in enumerate((hosts, paths)):
        marked = pc.binary_join_element_wise(pa.scalar("^", pa.large_string()), pc.fill_null(column.cast(pa.large_string()), ""), pa.scalar("$", pa.large_string()), pa.scalar("", pa.large_string()))
        raw = np.frombuffer(flat(marked)[0].decode(errors="replace").encode("utf-32-le"), "<u4").astype(np.uint64)
        owner = np.repeat(np.arange(len(column)), np.asarray(pc.utf8_length(marked), np.int64))
        for g in sizes:
            if len(raw) < g:
                continue
            h = np.zeros(len(raw) - g + 1, np.uint64)
            for k in range(g):
                h = h * np.uint64(1_000_003) + raw[k : len(raw) - g + 1 + k] + np.uint64(1)
            same = owner[: len(h)] == owner[g - 1 :]
            rows.append(owner[: len(h)][same])
            buckets.append((mix64(h[same] * np.uint64(16) + np.uint64(part * 8 + g)) >> np.uint64(64 - bits)).astype(np.int64))
    return np.concatenate(rows or [np.zeros(0, np.int64)]), np.concatenate(buckets or [np.zeros(0, np.int64)])


class UrlModel(NamedTuple):
    weights: np.ndarray
    bias: float
    bits: int
    sizes: tuple[int, ...]

    def scores(self, hosts: pa.Array, paths: pa.Array) -> np.ndarray:
        """Probability that the url is to be blocked."""
        row, bucket = _features(hosts, paths, self.bits, self.sizes)
        n = len(hosts)
        z = np.bincount(row, self.weights[bucket], n) / np.sqrt(np.maximum(np.bincount(row, minlength=n), 1))
        return 1 / (1 + np.exp(-np.clip(z + self.bias, -60, 60)))


def fit_url_model(labelled: DataFrame, *, bits: int = 16, sizes: tuple[int, ...] = (3, 4, 5), max_rows: int = 20_000, rounds: int = 600, rate: float = 1.0, shrink: float = 1e-4, prior: float = PRIOR) -> UrlModel:
    """Logistic regression on ``labelled(url, label)``; label 1 means to be blocked. ``prior``: the share of urls that are."""
    rows = with_host_path(labelled.where("url is not null and label is not null").dropDuplicates(["url"])).orderBy(F.xxhash64("url"), "url").limit(max_rows).select("host", "path", "label").collect()
    hosts, paths = pa.array([r.host for r in rows], pa.string()), pa.array([r.path for r in rows], pa.string())
    y = np.array([r.label for r in rows], float)
    model = UrlModel(np.zeros(1 << bits), 0.0, bits, sizes)
    if not len(y) or y.min() == y.max():
        return model._replace(bias=4.0 if len(y) and y[0] else -4.0)
    row, bucket = _features(hosts, paths, bits, sizes)
    scale = (1 / np.sqrt(np.maximum(np.bincount(row, minlength=len(y)), 1)))[row]
    # Whatever shares the table has: a url that resembles no label gets the prior's verdict.
    share = np.where(y == 1, prior / y.sum(), (1 - prior) / (len(y) - y.sum()))
    w, b, dw, db = np.zeros(1 << bits), 0.0, np.zeros(1 << bits), 0.0
    for _ in range(rounds):  # gradient steps with momentum; features have length one at most, so a rate of one is stable
        z = np.bincount(row, w[bucket] * scale, len(y)) + b
        off = (1 / (1 + np.exp(-z)) - y) * share
        dw = 0.9 * dw - rate * (np.bincount(bucket, off[row] * scale, 1 << bits) + shrink * w)
        db = 0.9 * db - rate * off.sum()
        w, b = w + dw, b + db
    return model._replace(weights=w, bias=float(b))


def judge_urls(pages: DataFrame, model: UrlModel, *, rules: Sequence[Rule] = RULES, threshold: float = 0.5, id_col: str = "page_id") -> DataFrame:
    """``(id, host, path, rule, score, verdict)`` for every row."""
    ready = with_rule(with_host_path(pages.select(F.col(id_col).cast("long").alias(id_col), "url")), rules).select(id_col, "host", "path", "rule", "rule_verdict")

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = model.scores(batch.column(1), batch.column(2))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(p)], names=[*batch.schema.names, "score"])

    scored = ready.mapInArrow(score, f"{id_col} long, host string, path string, rule string, rule_verdict string, score double")
    return scored.select(id_col, "host", "path", "rule", "score", F.coalesce("rule_verdict", F.when(F.col("score") >= threshold, "block").otherwise("allow")).alias("verdict"))


def seed_model(spark: SparkSession) -> UrlModel:
    return fit_url_model(spark.createDataFrame(labelled_urls(), "url string, label int"))


def held_out_rates(spark: SparkSession, *, folds: int = 4, **parameters) -> tuple[float, float]:
    """Shares of the unwanted and of the wanted labelled urls that are blocked by models that saw no url of their host's fold."""
    rows, blocked = labelled_urls(), {0: [], 1: []}
    fold = [zlib.crc32(u.split("://")[1].split("/")[0].encode()) % folds for u, _ in rows]
    for k in range(folds):
        model = fit_url_model(spark.createDataFrame([r for r, f in zip(rows, fold, strict=True) if f != k], "url string, label int"), **parameters)
        test = with_host_path(spark.createDataFrame([r for r, f in zip(rows, fold, strict=True) if f == k], "url string, label int")).select("host", "path", "label").collect()
        p = model.scores(pa.array([r.host for r in test], pa.string()), pa.array([r.path for r in test], pa.string()))
        for r, x in zip(test, p, strict=True):
            blocked[r.label].append(x >= 0.5)
    return float(np.mean(blocked[1])), float(np.mean(blocked[0]))
