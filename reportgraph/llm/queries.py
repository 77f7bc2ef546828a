"""One query for each operation, over its whole table, and its SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reportgraph.llm import fingerprints, mixing, packing, quality, simhash, substring_dedup, token_counts, topk, toxicity, warc
from reportgraph.sources.io import read_table


def tokenizer(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.document_fingerprints(read_table(spark, sf_dir, "documents"))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.learn(docs, read_table(spark, sf_dir, "labels")))


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(read_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = warc.archive_pages(read_table(spark, sf_dir, "pages"))
    return index.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "urlkey", "capture")


def op5_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.dedup_passages(read_table(spark, sf_dir, "documents")).select("doc_id", "text", "removed_spans")


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(read_table(spark, sf_dir, "documents"), tokenizer("byte_bpe_50k.json"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(read_table(spark, sf_dir, "documents"), tokenizer("word_bpe_49k.json"))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return quality.score(docs, quality.learn(docs, read_table(spark, sf_dir, "labels")))


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.simhash_components(read_table(spark, sf_dir, "documents"))


def op10_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = read_table(spark, sf_dir, "embeddings")
    return topk.top_k(vectors, vectors.where(F.col("vec_id") % 50 == 0))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (op1_fingerprints, op2_toxicity, op3_mixing, op4_warc, op5_substring_dedup, op6_token_counts, op7_packing, op8_quality, op9_simhash, op10_topk, pipeline)
    return {f.__name__: f for f in own}


#: Bits of a digest by fives, as letters.
_BASE32 = "array_to_string(list_transform(range(0, 8), lambda g: array_to_string(list_transform([15, 10, 5, 0], lambda s: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (((('0x' || substr(h, 5 * g + 1, 5))::BIGINT >> s::BIGINT) & 31) + 1)::BIGINT, 1)), '')), '')"


def oracle_sql() -> dict[str, str]:
    return {
        "op4_warc": f"""
            WITH p AS (SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha1(coalesce(html, '')) AS h, regexp_replace(regexp_extract(url, '^https?://([^/?#:]+)', 1), '^www[.]', '') AS host,
                regexp_extract(url, '^https?://[^/?#]+([^?#]*)', 1) AS place, regexp_extract(url, '[?]([^#]*)', 1) AS asked FROM pages),
            d AS (SELECT page_id, payload_bytes, {_BASE32} AS payload_digest, lower(array_to_string(list_reverse(string_split(host, '.')), ',') || ')' || CASE WHEN place = '' THEN '/' ELSE place END
                || CASE WHEN asked = '' THEN '' ELSE '?' || asked END) AS urlkey FROM p),
            k AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS kept, row_number() OVER (PARTITION BY urlkey ORDER BY page_id) AS capture FROM d)
            SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = kept THEN 'response' ELSE 'revisit' END AS record_type,
                CASE WHEN page_id = kept THEN NULL ELSE kept END AS refers_to, urlkey, capture FROM k""",
        "op10_topk": """
            WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(x::DOUBLE * 256)::BIGINT) AS q FROM embeddings
                WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
            s AS (SELECT a.vec_id AS query_id, b.vec_id, list_sum(list_transform(list_zip(a.q, b.q), lambda z: z[1] * z[2]))::BIGINT AS score
                FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id),
            r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
            SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM r WHERE rank <= 5""",
    }
