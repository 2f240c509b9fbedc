"""Registered queries of the operators, over whole tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from . import bundles, byte_bpe, jpeg_media, line_dedup, mixing, outliers, ranking, severity, sharding, trie_join
from .common import shared_dir


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def op1_outliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return outliers.judge_documents(_read(spark, sf_dir, "documents"))


def op2_ranking(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents")
    return ranking.score_documents(docs, ranking.train_on_tables(spark, docs, sf_dir))


def op3_trie_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trie_join.link_documents(_read(spark, sf_dir, "documents"))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_documents(_read(spark, sf_dir, "documents"), mixing.MixPlan(repetition_limit=2.0))


def op5_severity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents")
    return severity.grade_documents(docs, severity.learn(docs, _read(spark, sf_dir, "labels")))


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bundles.read_archives(bundles.store_archives(_read(spark, sf_dir, "pages"), shared_dir(spark)))


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.token_digests(_read(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"))


def op8_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jpeg_media.store_and_read(_read(spark, sf_dir, "documents"))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.dedup_documents(_read(spark, sf_dir, "documents"), exact_short=True)


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(_read(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_outliers, op2_ranking, op3_trie_join, op4_mixing, op5_severity, op6_warc, op7_byte_bpe, op8_media, op9_line_dedup, op10_sharding)}


def oracle_sql() -> dict[str, str]:
    return {"op3_trie_join": JACCARD_SQL, "op4_mixing": MIX_SQL, "op6_warc": WARC_SQL, "op10_sharding": SHARD_SQL}


WARC_SQL = """
WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS n, sha1(coalesce(html, '')) AS d FROM pages),
m AS (SELECT d, max(page_id) AS best FROM p GROUP BY d)
SELECT p.page_id, CAST(n AS BIGINT) AS payload_bytes, p.d AS payload_digest,
       CASE WHEN n >= 1000 AND p.page_id < m.best THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 1000 AND p.page_id < m.best THEN m.best END AS refers_to
FROM p JOIN m ON p.d = m.d
"""

JACCARD_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS words
  FROM documents),
s AS (
  SELECT DISTINCT doc_id, array_to_string(words[i : i + least(len(words), 5) - 1], ' ') AS shingle
  FROM (SELECT doc_id, words, unnest(range(1, greatest(len(words) - 4, 1) + 1)) AS i FROM w WHERE len(words) > 0)),
n AS (SELECT doc_id, count(*) AS k FROM s GROUP BY doc_id),
pairs AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS both_have FROM s a JOIN s b ON a.shingle = b.shingle AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (
  SELECT x, y FROM pairs JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * both_have >= 75 * (p.k + q.k - both_have)),
reach AS (SELECT doc_id AS x, doc_id AS y FROM documents UNION SELECT r.x, l.y FROM reach r JOIN links l ON l.x = r.y),
root AS (SELECT x, min(y) AS component_id FROM reach GROUP BY x)
SELECT d.doc_id, CAST(coalesce(n.k, 0) AS BIGINT) AS n_shingles, root.component_id
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id JOIN root ON root.x = d.doc_id
"""

MIX_SQL = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS n_tokens FROM documents),
t AS (SELECT source, CAST(sum(n_tokens) AS BIGINT) AS tokens FROM d GROUP BY source),
top AS (SELECT max(tokens) AS most, min(tokens) AS least FROM t WHERE tokens > 0),
halve AS (
  SELECT 0 AS step, CAST(0 AS DOUBLE) AS lo, CAST(1 AS DOUBLE) AS hi
  UNION ALL
  SELECT step + 1,
         CASE WHEN pow(CAST(most AS DOUBLE) / least, 1 - (lo + hi) / 2) <= 2.0 THEN lo ELSE (lo + hi) / 2 END,
         CASE WHEN pow(CAST(most AS DOUBLE) / least, 1 - (lo + hi) / 2) <= 2.0 THEN (lo + hi) / 2 ELSE hi END
  FROM halve, top WHERE step < 40),
e AS (
  SELECT source, tokens, CASE WHEN tokens > 0 THEN pow(CAST(most AS DOUBLE) / tokens, 1 - hi) ELSE 1 END AS epochs,
         greatest(1, CAST(ceil(tokens / 65536.0) AS BIGINT)) AS n_blocks
  FROM t, top, (SELECT hi FROM halve WHERE step = 40)),
dealt AS (
  SELECT d.doc_id, d.source, d.n_tokens, e.tokens AS source_tokens, e.epochs,
         CAST(('0x' || substr(md5('block:7:' || d.doc_id), 1, 15)) AS BIGINT) % e.n_blocks AS block
  FROM d JOIN e ON d.source IS NOT DISTINCT FROM e.source),
rows_in AS (SELECT *, unnest(range(0, CAST(ceil(epochs) AS BIGINT))) AS epoch FROM dealt),
blocks AS (
  SELECT source, epoch, block, row_number() OVER w - 1 AS block_rank, sum(k) OVER w - k AS tokens_before
  FROM (SELECT source, epoch, block, sum(n_tokens) AS k, md5('order:7:' || coalesce(source, '-') || ':' || epoch || ':' || block) AS code
        FROM rows_in GROUP BY source, epoch, block)
  WINDOW w AS (PARTITION BY source, epoch ORDER BY code, block ROWS UNBOUNDED PRECEDING)),
inside AS (
  SELECT *, row_number() OVER w - 1 AS slot, sum(n_tokens) OVER w - n_tokens AS ahead
  FROM (SELECT *, md5('row:7:' || doc_id || ':' || epoch) AS code FROM rows_in)
  WINDOW w AS (PARTITION BY source, epoch, block ORDER BY code, doc_id, n_tokens ROWS UNBOUNDED PRECEDING)),
placed AS (
  SELECT i.*, b.block_rank, i.epoch + CASE WHEN source_tokens > 0 THEN CAST(b.tokens_before + i.ahead AS DOUBLE) / source_tokens ELSE 0 END AS place
  FROM inside i JOIN blocks b ON i.source IS NOT DISTINCT FROM b.source AND i.epoch = b.epoch AND i.block = b.block)
SELECT doc_id, source, n_tokens, CAST(epoch AS INTEGER) AS epoch, CAST(block AS BIGINT) AS block, CAST(block_rank AS BIGINT) AS block_rank,
       CAST(slot AS BIGINT) AS slot, round(least(1.0, place / epochs), 9) AS position
FROM placed WHERE epoch + 1 <= epochs OR place < epochs
"""

#: CRC-32 byte by byte with its table built by the rule; MD5 order, exact byte positions.
SHARD_SQL = """
WITH tab AS (
  SELECT list_transform(range(256), lambda n: list_reduce(range(8), lambda c, k: CASE WHEN c % 2 = 1 THEN xor(c // 2, 3988292384) ELSE c // 2 END, n)) AS crc),
s AS (
  SELECT doc_id, CAST(octet_length(encode(coalesce(text, ''))) AS BIGINT) + 1 AS size, md5(coalesce(text, '')) AS code,
         list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda h: CAST('0x' || h AS BIGINT)) AS bytes
  FROM documents),
d AS (
  SELECT doc_id, size, code, xor(list_reduce(bytes, lambda c, b: xor(c // 256, crc[(xor(c, b) % 256) + 1]), CAST(4294967295 AS BIGINT)), 4294967295) AS text_crc32
  FROM s, tab),
p AS (SELECT *, sum(size) OVER (ORDER BY code, doc_id, size ROWS UNBOUNDED PRECEDING) - size AS before, sum(size) OVER () AS total FROM d),
q AS (SELECT *, CAST(least(before * 16 // total, 15) AS INTEGER) AS shard FROM p)
SELECT doc_id, size, CAST(text_crc32 AS BIGINT) AS text_crc32, 'bytes' AS law, shard,
       CAST(row_number() OVER (PARTITION BY shard ORDER BY code, doc_id, size) - 1 AS BIGINT) AS slot, CAST(NULL AS INTEGER) AS grown_shard
FROM q
"""
