"""The registered queries of the training-data operators, with production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, extraction, langid, packing, quality, secrets, sharding, simhash, topk, toxicity
from .common import documents, fold


def op1_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extraction.extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(documents(spark, sf_dir), 24)


def op3_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_digests(documents(spark, sf_dir))


def op4_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    found = langid.identify(docs, langid.train(docs, fold("doc_id", 4) != 2))
    return found.select("doc_id", (fold("doc_id", 4) == 2).alias("held_out"), "lang_pred", "score", "rejected")


def op5_decontam(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.leaks(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"), width=5, share=0.8)


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), fold("doc_id", 4) != 2)
    return toxicity.score_documents(docs, model).withColumn("held_out", fold("doc_id", 4) == 2)


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"), 4096, end=1)


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = quality.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), fold("doc_id", 5) != 0)
    return quality.score_documents(docs, model).withColumn("held_out", fold("doc_id", 5) == 0)


def op9_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), F.pmod("vec_id", F.lit(50)) == 0, k=5, scale=256)


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(documents(spark, sf_dir), shingle=3, bits=2, seed=42)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_extraction, op2_sharding, op3_secrets, op4_langid, op5_decontam, op6_toxicity, op7_packing, op8_quality, op9_topk, op10_simhash)}


def _sharding_sql(shards: int = 24) -> str:
    """The law and the checksum in plain SQL; the checksum takes a text byte by byte through the table of CRC-32."""

    def rounds(x: str) -> str:
        for _ in range(2):
            x = f"((xor({x}, ({x}) >> 16) * 73244475) & 4294967295)"
        return f"xor({x}, ({x}) >> 16)"

    def best(n: int) -> str:
        scores = ", ".join(f"({rounds(f'((h + {(s + 1) * 2654435761 & 4294967295}) & 4294967295)')}) * 64 + {63 - s}" for s in range(n))
        return f"CAST(63 - greatest({scores}) % 64 AS INTEGER)"

    return f"""
    WITH RECURSIVE tbl(i, k, c) AS (
      SELECT i, 0, i FROM range(256) r(i)
      UNION ALL SELECT i, k + 1, CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END FROM tbl WHERE k < 8
    ), crc AS (SELECT list(c ORDER BY i) AS t FROM tbl WHERE k = 8),
    texts AS MATERIALIZED (
      SELECT doc_id, hex(encode(coalesce(text, ''))) AS x, octet_length(encode(coalesce(text, ''))) AS n,
             CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 8) AS BIGINT) AS h
      FROM documents
    ), summed AS MATERIALIZED (
      SELECT doc_id, n + 8 AS size, h,
             xor(list_reduce(list_prepend(CAST(4294967295 AS BIGINT), list_transform(range(n), lambda j: CAST('0x' || substr(x, 2 * j + 1, 2) AS BIGINT))),
                             lambda a, b: xor(a >> 8, t[(xor(a, b) & 255) + 1])), 4294967295) AS crc
      FROM texts, crc
    ), placed AS (SELECT *, {best(shards)} AS shard, {best(shards + 1)} AS grown_shard FROM summed)
    SELECT doc_id, size, crc AS text_crc32, 'key' AS law, shard, grown_shard,
           row_number() OVER (PARTITION BY shard ORDER BY ({rounds("xor(h, crc)")}) % {sharding.LANES}, doc_id NULLS FIRST, crc, size) - 1 AS slot
    FROM placed
    """


def _secrets_sql() -> str:
    """Spans from the pieces between matches: a match starts where the pieces and matches before it end."""
    kinds = []
    for order, rule in enumerate(secrets.BASE_RULES + secrets.MORE_RULES):
        quoted = rule.pattern.replace("'", "''")
        kinds.append(f"SELECT doc_id, {order} AS k, '{rule.kind}' AS kind, {rule.least} AS least, string_split_regex(text, '{quoted}') AS gaps, regexp_extract_all(text, '{quoted}') AS hits, regexp_extract_all(text, '{quoted}', {rule.group}) AS groups FROM texts WHERE regexp_matches(text, '{quoted}')")
    base = ", ".join(f"'{r.kind}'" for r in secrets.BASE_RULES)
    return f"""
    WITH texts AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
    found AS ({" UNION ALL ".join(kinds)}),
    each AS (SELECT *, unnest(range(1, len(hits) + 1)) AS i FROM found),
    placed AS (
      SELECT doc_id, k, kind, least, hits[i] AS hit, groups[i] AS g,
             CAST(coalesce(list_sum(list_transform(gaps[1:i], lambda x: length(x))), 0) + coalesce(list_sum(list_transform(hits[1:i - 1], lambda x: length(x))), 0) AS BIGINT) AS s
      FROM each
    ), kept AS (SELECT doc_id, k, kind, s, s + length(hit) AS e FROM placed WHERE length(g) >= least),
    joined AS (
      SELECT doc_id, count(*) FILTER (WHERE kind = 'assign') AS n_assign, count(*) FILTER (WHERE kind = 'access') AS n_access, count(*) FILTER (WHERE kind = 'hex') AS n_hex,
             string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, k) FILTER (WHERE kind IN ({base})) AS base,
             string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, k) AS spans
      FROM kept GROUP BY doc_id
    )
    SELECT d.doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
    FROM documents d LEFT JOIN joined USING (doc_id)
    """


ORACLES: dict[str, str] = {
    "op9_topk": """
    WITH v AS MATERIALIZED (
      SELECT row_number() OVER () AS r, vec_id, list_transform(embedding, lambda x: CAST(floor(256 * x::DOUBLE) AS BIGINT)) AS v FROM embeddings
      WHERE embedding IS NOT NULL AND vec_id IS NOT NULL AND len(embedding) > 0
        AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    ), s AS (
      SELECT q.r, q.vec_id AS query_id, c.vec_id,
             CAST(list_sum(list_transform(list_zip(q.v, c.v), lambda z: z[1] * z[2])) AS BIGINT) AS score
      FROM v q JOIN v c ON q.r <> c.r AND len(q.v) = len(c.v) WHERE q.vec_id % 50 = 0
    )
    SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
    FROM (SELECT *, row_number() OVER (PARTITION BY r ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 5
    """,
    "op2_sharding": _sharding_sql(),
    "op3_secrets": _secrets_sql(),
}
