"""Queries opN_<name> over the whole tables, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table
from . import bpe, chat, lm, packing, quality_classifier, quality_rules, tiff, url_filters
from .simhash import near_duplicates
from .substring_dedup import remove_repeats


def op1_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = quality_classifier.fit(docs, table(spark, sf_dir, "labels"))
    out = quality_classifier.score(docs, model)
    return out.select("doc_id", quality_classifier.held_out().alias("held_out"), "score", (F.col("score") >= quality_classifier.THRESHOLD).cast("int").alias("predicted"))


def op2_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filters.judge_urls(table(spark, sf_dir, "pages")).withColumnRenamed("id", "page_id")


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"), min_words=13, longest=True)
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"), "longest_repeat")


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = near_duplicates(table(spark, sf_dir, "documents"), shingle=4, most=4)
    return out.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op4_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.render(table(spark, sf_dir, "conversations")).withColumnRenamed("id", "conv_id")


def op5_tiff(spark: SparkSession, sf_dir: str) -> DataFrame:
    stored = tiff.store_text(table(spark, sf_dir, "documents"))
    stored = stored.select("id", "n_bytes", F.length("media").cast("long").alias("media_bytes"), F.sha2("media", 256).alias("media_sha256"), "media")
    pages = tiff.tiff_pages(stored)
    return pages.select(
        F.col("id").alias("doc_id"),
        "n_bytes",
        F.length("pixels").cast("long").alias("payload_bytes"),
        F.sha2("pixels", 256).alias("payload_sha256"),
        F.crc32(F.expr("substring(pixels, -32)")).alias("tail_crc32"),
        "media_bytes",
        "media_sha256",
        "feature",
    )


def op6_byte_bpe(spark: SparkSession, sf_dir: str, vocabulary: str = "byte_bpe_50k.tiktoken") -> DataFrame:
    import public_tokenizers

    with open(public_tokenizers.path(vocabulary), "rb") as f:
        lines = f.read()
    ids = bpe.encode(table(spark, sf_dir, "documents").select("doc_id", "text"), lines, public_tokenizers.PATTERN)
    both = bpe.decode(ids.drop("text"), lines, public_tokenizers.PATTERN)
    return both.select("doc_id", (F.length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), capacity=2048)


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.verdicts(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


def op10_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.score_texts(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


QUERIES = {
    "op1_quality_classifier": op1_quality_classifier,
    "op2_url_filters": op2_url_filters,
    "op3_substring_dedup": op3_substring_dedup,
    "op4_chat_formatting": op4_chat_formatting,
    "op5_tiff": op5_tiff,
    "op6_byte_bpe": op6_byte_bpe,
    "op7_best_fit_packing": op7_best_fit_packing,
    "op8_quality_rules": op8_quality_rules,
    "op9_simhash": op9_simhash,
    "op10_lm_scoring": op10_lm_scoring,
}

#: DuckDB: the words of a text, and the SQL for the queries that have some.
_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

ORACLES = {
    "op4_chat_formatting": chat.ORACLE,
    "op8_quality_rules": quality_rules.oracle(),
    "op3_substring_dedup": rf"""
        WITH RECURSIVE d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
        l AS (SELECT doc_id, 13 AS size, [hash(array_to_string(w[i : i + 12], ' ')) FOR i IN range(1, len(w) - 11)] AS h FROM d WHERE len(w) >= 13
            UNION ALL SELECT doc_id, 2 * size, [hash(h[i], h[i + size]) FOR i IN range(1, len(h) - size + 1)] FROM l WHERE len(h) > size),
        s AS (SELECT size, doc_id, unnest(h) AS h FROM l),
        r AS (SELECT doc_id, max(size) AS longest FROM s JOIN (SELECT size, h FROM s GROUP BY ALL HAVING count(DISTINCT doc_id) > 1) USING (size, h) GROUP BY 1),
        p AS (SELECT doc_id, len(w) AS n, w, unnest(range(1, greatest(len(w) - 11, 1))) AS i FROM d),
        v AS (SELECT doc_id, i, array_to_string(w[i : i + 12], ' ') AS k FROM p),
        m AS (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY k) AS least FROM v),
        g AS (SELECT DISTINCT doc_id, i + unnest(range(13)) AS i FROM m WHERE least < doc_id),
        c AS (SELECT doc_id, list(i) AS gone FROM g GROUP BY doc_id)
        SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(len(gone), 0)::BIGINT AS n_removed,
            sha256(coalesce(array_to_string([x FOR x, i IN w IF gone IS NULL OR NOT list_contains(gone, i)], ' '), '')) AS kept_sha256, coalesce(longest, 0)::BIGINT AS longest_repeat
        FROM d LEFT JOIN c USING (doc_id) LEFT JOIN r USING (doc_id)""",
}
