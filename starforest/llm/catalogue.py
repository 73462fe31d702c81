"""Queries of the training-data operators and, where SQL can express them, their oracle SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from starforest.llm import block_naming, language_spans, pii_bootstrap, piece_viterbi, separator_scan, source_mix, token_files, url_filter, vector_graph, weighted_minhash
from starforest.llm.shared_files import remove_tree
from starforest.runtime import cut, read_table, shared_dir


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(read_table(spark, sf_dir, "pages"), url_filter.seed_model(spark))


def op2_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return weighted_minhash.near_classes(read_table(spark, sf_dir, "documents"))


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii_bootstrap.find_pii(read_table(spark, sf_dir, "documents"))


def op4_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_viterbi.piece_digests(read_table(spark, sf_dir, "documents"))


def op5_vector_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_graph.vector_links(read_table(spark, sf_dir, "embeddings"))


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    found = language_spans.predict_language(docs, language_spans.fit_on_documents(docs))
    return found.select("doc_id", language_spans.held_out().alias("held_out"), "lang_pred", "score")


def op7_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return source_mix.mix_plan(read_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = f"{shared_dir(spark)}/flat-{uuid.uuid4().hex}"
    files = cut(separator_scan.write_flat_files(read_table(spark, sf_dir, "documents"), folder))
    counted = separator_scan.count_tokens(files)
    # As long as the documents: never broadcast, however small the planner takes it to be.
    named = files.select("path", F.posexplode("doc_ids").alias("ordinal", "doc_id")).hint("merge")
    result = cut(counted.join(named, ["path", "ordinal"]).select("doc_id", "n_tokens"))
    remove_tree(folder)
    return result


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return block_naming.exact_copies(read_table(spark, sf_dir, "documents").select("doc_id", "text"))


def op10_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}"
    files = cut(token_files.write_token_files(read_table(spark, sf_dir, "documents"), folder))
    result = cut(token_files.read_token_files(files))
    remove_tree(folder)
    return result


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_url_filter": op1_url_filter,
    "op2_near_dedup": op2_near_dedup,
    "op3_pii": op3_pii,
    "op4_piece_codec": op4_piece_codec,
    "op5_vector_dedup": op5_vector_dedup,
    "op6_language": op6_language,
    "op7_source_mix": op7_source_mix,
    "op8_token_counts": op8_token_counts,
    "op9_exact_dedup": op9_exact_dedup,
    "op10_token_files": op10_token_files,
}

ORACLE_SQL: dict[str, str] = {
    "op7_source_mix": r"""
        WITH RECURSIVE d AS MATERIALIZED (
            SELECT row_number() OVER () AS rid, doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
                   md5('mix:' || coalesce(CAST(doc_id AS VARCHAR), '-' || sha256(coalesce(text, '')))) AS place FROM documents),
        s0 AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS idx FROM d GROUP BY source),
        s1 AS (SELECT *, idx % 3 + 1 AS w, source_size * 3 / (idx % 3 + 1) AS bind FROM s0),
        s2 AS (SELECT *, CAST(sum(source_size) OVER () - 3 * coalesce(sum(source_size) OVER (ORDER BY bind, idx ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE) AS remaining,
                      CAST(sum(w) OVER (ORDER BY bind, idx ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS DOUBLE) AS share FROM s1),
        lv AS (SELECT remaining, share FROM s2 WHERE remaining / share <= bind ORDER BY bind, idx LIMIT 1),
        s3 AS (SELECT s2.source, s2.idx, s2.source_size, coalesce(least(s2.w * lv.remaining / lv.share, CAST(s2.source_size * 3 AS DOUBLE)), CAST(s2.source_size * 3 AS DOUBLE)) AS target FROM s2 LEFT JOIN lv ON true),
        sz AS (SELECT greatest(4096, CAST(ceil(sum(source_size) / 536870912.0) AS BIGINT)) AS b FROM s0),
        s4 AS (SELECT s3.*, CAST(greatest(ceil(source_size / b), least(source_size, 2048)) AS BIGINT) AS blocks FROM s3, sz),
        s5 AS MATERIALIZED (SELECT *, CASE WHEN blocks > 0 THEN CAST(round(target / source_size * blocks) AS BIGINT) ELSE 0 END AS slots FROM s4),
        s6 AS MATERIALIZED (SELECT *, CAST(sum(slots) OVER (ORDER BY idx) AS BIGINT) AS hi FROM s5),
        n AS (SELECT greatest(max(hi), 1) AS n, max(hi) AS m, greatest(1, CAST(round(greatest(max(hi), 1) * 0.6180339887498949) AS BIGINT)) AS a FROM s6),
        g AS MATERIALIZED (SELECT n, m, (SELECT first(x ORDER BY k) FROM (SELECT 2 * r AS k, a - r AS x FROM range(0, 1000) t(r) UNION ALL SELECT 2 * r + 1, a + r FROM range(0, 1000) t(r)) WHERE x > 0 AND gcd(x, n) = 1) AS g FROM n),
        slot AS (SELECT r AS slot, (r * g) % n AS point FROM g, range(0, (SELECT coalesce(max(hi), 0) FROM s6)) t(r)),
        ranked AS (SELECT s6.idx, s6.blocks, row_number() OVER (PARTITION BY s6.idx ORDER BY slot) - 1 AS rk FROM slot JOIN s6 ON point >= hi - slots AND point < hi),
        uses AS MATERIALIZED (SELECT idx, ((rk % blocks) * ((CASE WHEN blocks % 2147483647 <> 0 THEN 2147483647 WHEN blocks % 1000000007 <> 0 THEN 1000000007 ELSE 998244353 END) % blocks) % blocks + (rk // blocks) * 7919) % blocks AS block, count(*) AS uses FROM ranked GROUP BY 1, 2),
        p AS (SELECT d.rid, d.size, s6.idx, s6.source_size, s6.blocks, s6.source_size // s6.blocks AS q, s6.source_size % s6.blocks AS lng,
                     CAST(coalesce(sum(d.size) OVER (PARTITION BY s6.idx ORDER BY d.place, d.rid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS a
              FROM d JOIN s6 ON d.source IS NOT DISTINCT FROM s6.source WHERE d.size > 0),
        p2 AS (SELECT *, a + size AS b, lng * (q + 1) AS edge FROM p),
        p3 AS (SELECT *, unnest(range(CASE WHEN a < edge THEN a // (q + 1) ELSE lng + (a - edge) // q END, 1 + CASE WHEN b - 1 < edge THEN (b - 1) // (q + 1) ELSE lng + (b - 1 - edge) // q END)) AS j FROM p2),
        p4 AS (SELECT *, CASE WHEN j < lng THEN j * (q + 1) ELSE edge + (j - lng) * q END AS st, q + CASE WHEN j < lng THEN 1 ELSE 0 END AS ln FROM p3),
        t AS (SELECT rid, CAST(sum((least(b, st + ln) - greatest(a, st)) * uses) AS BIGINT) AS taken FROM p4 JOIN uses ON p4.idx = uses.idx AND p4.j = uses.block GROUP BY rid)
        SELECT d.doc_id, d.size, s6.source_size, s6.target, coalesce(t.taken, 0) AS taken
        FROM d JOIN s6 ON d.source IS NOT DISTINCT FROM s6.source LEFT JOIN t ON d.rid = t.rid
    """,
    "op9_exact_dedup": """
        WITH d AS (SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256 FROM documents)
        SELECT doc_id, max(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size, doc_id = max(doc_id) OVER g AS kept, text_sha256
        FROM d WINDOW g AS (PARTITION BY text_sha256)
    """,
}
