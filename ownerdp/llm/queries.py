"""The driver's queries opN_<name>: thin forms of the operators with the columns that their contracts fix."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ownerdp.llm import bpe, decontaminate, exact_dedup, lm_scoring, packing, pii, quality, simhash, substring_dedup, url_filter
from ownerdp.llm.common import table


def tokenizer_path(name: str) -> str:
    """A vocabulary file: in the folder OWNERDP_TOKENIZERS, else where the public package has it. Only the driver reads it."""
    if folder := os.environ.get("OWNERDP_TOKENIZERS"):
        return os.path.join(folder, name)
    import public_tokenizers

    return public_tokenizers.path(name)


def split_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


def byte_vocabulary() -> list[bytes]:
    return bpe.read_ranks(tokenizer_path("byte_bpe_50k.tiktoken"))


def op1_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.score_documents(table(spark, sf_dir, "documents"), byte_vocabulary(), split_pattern())


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"), shingle=3, distance=2)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = quality.fit_quality(docs, table(spark, sf_dir, "labels"))
    scored = quality.score_documents(docs, model)
    return scored.select("doc_id", (~F.coalesce(quality.learnable("doc_id"), F.lit(True))).alias("held_out"), "score", "predicted")


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_documents(table(spark, sf_dir, "documents"), byte_vocabulary(), split_pattern())


def op7_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find_pii(table(spark, sf_dir, "documents"))
    count = lambda kind: F.size(F.filter("base", lambda x: x["kind"] == kind)).cast("long").alias(f"n_{kind}")
    text = lambda spans: F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"], x["end"])), ",")
    return found.select("doc_id", *map(count, pii.KINDS), F.sha2(text("base"), 256).alias("base_sha256"), text("spans").alias("spans"))


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.filter_urls(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict", "pattern")


def op9_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.remove_repeated_passages(table(spark, sf_dir, "documents"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Writes the matrices in the shared folder, reads them again and returns each row's segments and digests."""
    rows = packing.stored(packing.pack_documents(table(spark, sf_dir, "documents"), byte_vocabulary(), split_pattern()))
    return rows.select(
        "part", "row", "doc_ids", "starts", "cu_seqlens", F.element_at("cu_seqlens", -1).alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("positions", 256).alias("positions_sha256")
    )


QUERIES = {"op1_lm_score": op1_lm_score, "op2_decontaminate": op2_decontaminate, "op3_simhash": op3_simhash, "op4_exact_dedup": op4_exact_dedup, "op5_quality": op5_quality, "op6_byte_bpe": op6_byte_bpe, "op7_pii": op7_pii, "op8_url_filter": op8_url_filter, "op9_substring_dedup": op9_substring_dedup, "op10_packing": op10_packing}

ORACLES = {
    "op4_exact_dedup": """
SELECT doc_id, max(doc_id) OVER same AS keep_id, count(*) OVER same AS group_size, doc_id = max(doc_id) OVER same AS kept,
       sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW same AS (PARTITION BY coalesce(text, ''))""",
    "op8_url_filter": url_filter.oracle_sql(),
    "op9_substring_dedup": r"""
WITH w AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents),
starts AS (SELECT r, unnest(range(1, len(words) - 33)) AS s FROM w WHERE len(words) >= 35),
windows AS (SELECT r, s, array_to_string(words[s:s + 34], ' ') AS k FROM starts JOIN w USING (r)),
twice AS (SELECT k FROM windows GROUP BY k HAVING count(*) > 1),
gone AS (SELECT DISTINCT r, s + o AS p FROM windows SEMI JOIN twice USING (k), range(35) AS t(o)),
places AS (SELECT r, unnest(words) AS word, unnest(range(1, len(words) + 1)) AS p FROM w),
kept AS (SELECT r, string_agg(word, ' ' ORDER BY p) AS text, count(*) AS n FROM places ANTI JOIN gone USING (r, p) GROUP BY r)
SELECT doc_id, len(words) AS n_words, len(words) - coalesce(n, 0) AS n_removed, sha256(coalesce(kept.text, '')) AS kept_sha256
FROM w LEFT JOIN kept USING (r)""",
}
