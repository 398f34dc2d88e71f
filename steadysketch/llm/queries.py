"""The registered queries of this subpackage, one for each operator, and their SQL where SQL can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import bpe, exact_dedup, langid, licences, mixing, quality, simhash, token_counts, vectors
from .common import table


def public_file(name: str) -> tuple[str, str]:
    """Place of a published vocabulary file, and the pattern that goes with byte-level ones."""
    import public_tokenizers

    return public_tokenizers.path(name), public_tokenizers.PATTERN


def op1_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return langid.identify(docs, langid.learn_profiles(docs))


def op2_simhash_golay(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "fingerprint", "component_id")


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"), public_file("piece_bpe_32k.model")[0])


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    path, pattern = public_file("byte_bpe_50k.tiktoken")
    return bpe.encode_documents(table(spark, sf_dir, "documents"), path, pattern)


def op5_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan(table(spark, sf_dir, "documents"))


def op6_additive_quantisation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vectors.nearest(table(spark, sf_dir, "embeddings"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), ["doc_id"])


def op8_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = exact_dedup.duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def op9_cross_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.cross_entropy_difference(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


QUERIES = {
    "op1_language": op1_language,
    "op2_simhash_golay": op2_simhash_golay,
    "op3_token_counts": op3_token_counts,
    "op4_byte_bpe": op4_byte_bpe,
    "op5_licences": op5_licences,
    "op6_additive_quantisation": op6_additive_quantisation,
    "op7_quality": op7_quality,
    "op8_exact_dedup": op8_exact_dedup,
    "op9_cross_entropy": op9_cross_entropy,
    "op10_mixing": op10_mixing,
}

ORACLE_SQL: dict[str, str] = {
    "op10_mixing": r"""
        WITH base AS MATERIALIZED (
            SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
                   coalesce(CAST(doc_id AS VARCHAR), 'null/' || md5(coalesce(text, ''))) AS name FROM documents),
        sources AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, count(*) AS docs FROM base GROUP BY source),
        ranked AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS source_rank FROM sources),
        weighted AS (SELECT *, CAST([3, 1, 2][source_rank % 3 + 1] AS DOUBLE) AS weight FROM ranked),
        filled AS (
            SELECT *, sum(source_size) OVER () * CAST(1.5 AS DOUBLE) AS wanted, coalesce(sum(source_size * 2) OVER b, 0) AS full_before,
                   sum(weight) OVER () - coalesce(sum(weight) OVER b, 0) AS weight_left
            FROM weighted WINDOW b AS (ORDER BY CAST(2.0 AS DOUBLE) * source_size / weight, source_rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        levels AS (SELECT *, (wanted - full_before) / weight_left AS level FROM filled),
        stopped AS (SELECT *, source_size * 2 <= level * weight AS stops FROM levels),
        targets AS (SELECT source, source_rank, source_size, docs, CASE WHEN stops THEN CAST(source_size * 2 AS DOUBLE) ELSE max(CASE WHEN NOT stops THEN level END) OVER () * weight END AS target FROM stopped),
        blocks AS (SELECT *, CAST(greatest(1, least(64, floor(coalesce(min(CASE WHEN source_size > 0 THEN source_size END) OVER (), 0) / 64))) AS BIGINT) AS block FROM targets),
        seated AS MATERIALIZED (SELECT *, CAST(round(sum(target) OVER () / block) AS BIGINT) AS seats, CAST(ceil(docs / 4096) AS BIGINT) AS shards FROM blocks),
        offers AS (SELECT source_rank, seats, row_number() OVER (ORDER BY target / (2 * k + 1) DESC, source_rank, k) AS r FROM (SELECT *, unnest(range(0, seats)) AS k FROM seated WHERE target > 0)),
        won AS (SELECT s.*, coalesce(o.n, 0) AS source_seats FROM seated s LEFT JOIN (SELECT source_rank, count(*) AS n FROM offers WHERE r <= seats GROUP BY source_rank) o USING (source_rank)),
        placed AS MATERIALIZED (
            SELECT b.doc_id, b.size, w.source_rank, w.source_size, w.target, w.block, w.source_seats, md5('mix-1/' || b.name) AS place,
                   CAST('0x' || substr(md5('mix-1/' || b.name), 25, 8) AS BIGINT) % w.shards AS shard
            FROM base b JOIN won w ON b.source IS NOT DISTINCT FROM w.source),
        shards AS MATERIALIZED (SELECT source_rank, shard, source_seats, block, CAST(sum(size) AS BIGINT) AS words FROM placed GROUP BY ALL),
        shard_offers AS (
            SELECT source_rank, shard, source_seats, row_number() OVER (PARTITION BY source_rank ORDER BY words / (2 * k + 1) DESC, shard, k) AS r
            FROM (SELECT *, unnest(range(0, source_seats)) AS k FROM shards WHERE words > 0)),
        quotas AS (
            SELECT s.*, CAST(ceil(s.words / s.block) AS BIGINT) AS n, least(coalesce(o.q, 0), 2 * CAST(ceil(s.words / s.block) AS BIGINT)) AS quota
            FROM shards s LEFT JOIN (SELECT source_rank, shard, count(*) AS q FROM shard_offers WHERE r <= source_seats GROUP BY ALL) o USING (source_rank, shard)),
        runs AS (
            SELECT source_rank, shard, n, CASE WHEN n > 0 THEN quota // n ELSE 0 END AS whole, CASE WHEN n > 0 THEN quota % n ELSE quota END AS rest,
                   CAST('0x' || substr(md5(concat_ws('/', 'mix-1', source_rank, shard)), 1, 8) AS BIGINT) % greatest(n, 1) AS first FROM quotas),
        laid AS (
            SELECT p.*, coalesce(sum(size) OVER (PARTITION BY p.source_rank, p.shard ORDER BY place, doc_id NULLS FIRST, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS start FROM placed p)
        SELECT doc_id, size, source_size, target,
               CAST(whole * size + greatest(0, least(start + size, (first + rest) * block) - greatest(start, first * block))
                    + greatest(0, least(start + size, (first + rest - n) * block) - start) AS BIGINT) AS taken
        FROM laid JOIN runs USING (source_rank, shard)
    """,
    "op8_exact_dedup": r"""
        WITH t AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS norm FROM documents)
        SELECT doc_id,
               min(doc_id) OVER w AS keep_id,
               count(*) OVER w AS group_size,
               doc_id = min(doc_id) OVER w AS kept,
               sha256(norm) AS text_sha256
        FROM t WINDOW w AS (PARTITION BY norm)
    """,
}
