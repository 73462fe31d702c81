"""The corpus pipeline: five stages over documents, each written and read again.

Stage contracts. ``language``: documents whose language is ``und`` or whose main language covers less than
half of their letters go. ``exact_dedup``: of equal texts (lower-cased in A-Z) the largest doc_id stays.
``near_dedup``: of each near-duplicate class the smallest doc_id stays. ``mix``: documents that the source mix
does not take go, those it takes more than once are repeated, so doc_id may repeat from here on. ``encode``: piece
ids of every text and their number. All stages but the last return the columns of documents
and keep further columns; null and empty texts go in the first stage.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from starforest.llm import block_naming, language_spans, piece_viterbi, source_mix, weighted_minhash
from starforest.runtime import read_table, shared_dir

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: A document stays if its main language covers this share of its letters.
LEAST_SHARE = 0.5


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language_spans.drop_unsure(docs, language_spans.fit_on_documents(docs), least=LEAST_SHARE)


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return block_naming.drop_exact_copies(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return weighted_minhash.drop_near_copies(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return source_mix.mixed_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return piece_viterbi.encode_pieces(docs, keep=("doc_id", "source")).withColumn("n_pieces", F.size("ids").cast("long"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language", language),
    ("exact_dedup", exact_dedup),
    ("near_dedup", near_dedup),
    ("mix", mix),
    ("encode", encode),
]

#: Language scores, weighted samples and Viterbi are not expressible in SQL; tests/llm holds a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
