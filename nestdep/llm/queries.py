"""Registered queries of the operators for training data, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ._spark import table

WORD = r"[^\x20\x09-\x0D]+"


def vocabulary(name: str) -> str:
    """Place of a public vocabulary file; operators take any path."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .bpe import encode_texts

    out = encode_texts(table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"))
    return out.select("doc_id", "n_tokens", F.sha2("token_ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op2_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .neighbours import nearest

    return nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0, k=10)


def op3_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import plan_mix

    out = plan_mix(table(spark, sf_dir, "documents"))
    return out.select(F.col("id").alias("doc_id"), "size", "source_size", "target", "taken", "source", F.transform("draws", lambda d: d["shard"]).alias("shards"))


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .warc import archive_dir, read_archives, write_archives

    where = archive_dir(spark)
    write_archives(table(spark, sf_dir, "pages"), where)
    return read_archives(spark, where).select(F.col("id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", "refers_to")


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pii import BASE_KINDS, KINDS, find_pii, spans_text

    found = find_pii(table(spark, sf_dir, "documents"))
    of = lambda kind: F.filter("entities", lambda s: s["kind"] == kind)
    base = F.flatten(F.array(*[of(k) for k in BASE_KINDS]))
    every = F.flatten(F.array(*[of(k) for k in KINDS]))
    counts = [F.size(of(k)).cast("long").alias(f"n_{k}") for k in BASE_KINDS]
    digest = F.sha2(spans_text(base), 256).alias("base_sha256")
    return found.select("doc_id", *counts, digest, spans_text(every).alias("spans"), F.size("entities").cast("long").alias("n_entities"))


def op6_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .near_dedup import near_classes

    out = near_classes(table(spark, sf_dir, "documents"))
    return out.select(F.col("id").alias("doc_id"), "class_id", "class_size", "stays")


def op7_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .lm_scoring import held_out, score_texts, train

    docs = table(spark, sf_dir, "documents")
    return score_texts(docs, train(docs.where(~held_out(F.col("doc_id")))))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import fit, held_out, score_toxicity

    docs = table(spark, sf_dir, "documents")
    scored = score_toxicity(docs, fit(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality_rules import quality_measures, quality_verdict

    return quality_verdict(quality_measures(table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"), ranks=vocabulary("byte_bpe_50k.tiktoken")))


def op10_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .substring_dedup import remove_repeated_passages

    out = remove_repeated_passages(table(spark, sf_dir, "documents"), window=50)
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


QUERIES = {
    "op1_bpe": op1_bpe,
    "op2_neighbours": op2_neighbours,
    "op3_mix": op3_mix,
    "op4_warc": op4_warc,
    "op5_pii": op5_pii,
    "op6_near_dedup": op6_near_dedup,
    "op7_lm": op7_lm,
    "op8_toxicity": op8_toxicity,
    "op9_quality": op9_quality,
    "op10_substrings": op10_substrings,
}

SQL: dict[str, str] = {
    "op4_warc": """
        WITH p AS (SELECT page_id, coalesce(html, '') AS h, octet_length(encode(coalesce(html, '')))::BIGINT AS n, sha1(coalesce(html, '')) AS d FROM pages),
        b AS (SELECT d, max(page_id) AS best FROM p WHERE n >= 1000 GROUP BY d)
        SELECT page_id, n AS payload_bytes, d AS payload_digest,
               CASE WHEN page_id < best THEN 'revisit' ELSE 'response' END AS record_type,
               CASE WHEN page_id < best THEN best END AS refers_to
        FROM p LEFT JOIN b USING (d)""",
    "op10_substrings": rf"""
        WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{WORD}') AS ws FROM documents),
        s AS (SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS i FROM w WHERE len(ws) >= 50),
        h AS (SELECT doc_id, i, md5(array_to_string(ws[i:i + 49], ' ')) AS k FROM s),
        f AS (SELECT k, min(doc_id) AS lo FROM h GROUP BY k),
        b AS (SELECT DISTINCT doc_id, unnest(range(i, i + 50)) AS p FROM h JOIN f USING (k) WHERE doc_id > lo),
        g AS (SELECT doc_id, list(p) AS ps FROM b GROUP BY doc_id),
        k AS (SELECT doc_id, ws, coalesce(ps, []) AS ps FROM w LEFT JOIN g USING (doc_id))
        SELECT doc_id, len(ws)::BIGINT AS n_words, len(ps)::BIGINT AS n_removed,
               sha256(array_to_string(list_filter(ws, lambda x, j: NOT list_contains(ps, j)), ' ')) AS kept_sha256
        FROM k""",
}
