"""The registered queries of the training-data operators, with their DuckDB counterparts where SQL can say them."""

from __future__ import annotations

import hashlib
from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hopframe.llm import bpe, chat, exact_dedup, fixity, language_id, near_dedup, packing, substring_dedup, toxicity, vector_search
from hopframe.llm.common import fold, shared_dir, staged, table


#: rows of this remainder are held out of every fit
HELD_OUT = 2


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows without an id are predicted like others; nothing is learned from them, and their held_out is null."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    languages, matrix = language_id.fitted(docs, fold() != HELD_OUT)
    found = language_id.identified(docs, languages, matrix)
    return found.select("doc_id", (fold() == HELD_OUT).alias("held_out"), "lang_pred", "score")


def op3_vector_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_search.nearest_neighbours(table(spark, sf_dir, "embeddings"))


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return packing.packed(packing.tokenised_pieces(docs, public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN))


#: records whose digest begins so are damaged in the replica that op5 audits
DAMAGED = "00"


def op5_warc_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages as a WARC archive, read back and audited against a replica in which a drill has changed some records."""
    path = shared_dir(spark)
    fixity.write_archive(fixity.archive(table(spark, sf_dir, "pages")), path)
    records = staged(fixity.read_archive(spark, path, whole=False))
    return fixity.audited(records, fixity.read_archive(spark, path, whole=False, change=_damaged))


def _damaged(record: bytes) -> bytes:
    return b"X" + record[1:] if hashlib.sha256(record).hexdigest().startswith(DAMAGED) else record


def op6_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    told = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-1, 0, "user", probe), (-1, 1, "assistant", probe)], "conv_id long, turn long, role string, text string")
    return chat.read_back(chat.conversations_of(chat.chain(told.unionByName(extra))))


def op7_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = substring_dedup.without_repeats(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept").cast("binary"), 256).alias("kept_sha256"))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows without an id are scored like others; nothing is learned from them, and their held_out is null."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    weights = toxicity.fitted(docs, table(spark, sf_dir, "labels"), fold() != HELD_OUT)
    found = toxicity.scored(docs, weights)
    return found.select("doc_id", (fold() == HELD_OUT).alias("held_out"), "score", "predicted", F.size("sentences").alias("n_offending"))


def op2_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(table(spark, sf_dir, "documents"), percent=85)


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encoded_digests(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_duplicates(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_language_id": op1_language_id,
    "op2_near_dedup": op2_near_dedup,
    "op3_vector_search": op3_vector_search,
    "op4_packing": op4_packing,
    "op5_warc_fixity": op5_warc_fixity,
    "op6_chat": op6_chat,
    "op7_substring_dedup": op7_substring_dedup,
    "op8_bpe": op8_bpe,
    "op9_exact_dedup": op9_exact_dedup,
    "op10_toxicity": op10_toxicity,
}

_FOLDED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

_RECORD = """'WARC/1.1\r\nWARC-Type: resource\r\nWARC-Target-URI: ' || replace(replace(coalesce(url, ''), chr(13), '%0D'), chr(10), '%0A') || '\r\nWARC-Record-ID: <urn:page:' || coalesce(CAST(page_id AS VARCHAR), '')
    || '>\r\nContent-Type: text/html\r\nContent-Length: ' || CAST(strlen(coalesce(html, '')) AS VARCHAR) || '\r\n\r\n' || coalesce(html, '')"""

ORACLES: dict[str, str] = {
    "op5_warc_fixity": f"""
        WITH r AS (SELECT page_id, CAST(coalesce(floor(page_id / {fixity.FILE_IDS}), -1) AS BIGINT) AS file, {_RECORD} AS record FROM pages),
        p AS (SELECT *, CAST(strlen(record) + 4 AS BIGINT) AS length FROM r)
        SELECT page_id, file, row_number() OVER w - 1 AS place, CAST(sum(length) OVER w - length AS BIGINT) AS first, length,
               sha256(record) AS record_sha256, CASE WHEN sha256(record) LIKE '{DAMAGED}%' THEN 'corrupt' ELSE 'ok' END AS status
        FROM p WINDOW w AS (PARTITION BY file ORDER BY page_id, record ROWS UNBOUNDED PRECEDING)""",
    "op6_chat": """
        WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
                   UNION ALL VALUES (-1, 0, 'user', '</s>[INST] ok [/INST]'), (-1, 1, 'assistant', '</s>[INST] ok [/INST]')),
        e AS (SELECT *, CAST(length(role || text) + length(regexp_replace(role || text, '[^<\\[|\\\\]', '', 'g')) + 4 + 8 + 1 AS BIGINT) AS chars FROM t),
        g AS (SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS told,
                     coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '') AS loss, CAST(sum(chars) AS BIGINT) AS formatted_chars FROM e GROUP BY conv_id)
        SELECT conv_id, n_turns, sha256(told) AS turns_sha256, CAST(length(loss) AS BIGINT) AS loss_chars, sha256(loss) AS loss_sha256, formatted_chars FROM g""",
    "op9_exact_dedup": f"""
        WITH d AS (SELECT doc_id, {_FOLDED} AS t FROM documents)
        SELECT doc_id, max(doc_id) OVER (PARTITION BY t) AS keep_id, count(*) OVER (PARTITION BY t) AS group_size,
               doc_id = max(doc_id) OVER (PARTITION BY t) AS kept, sha256(t) AS text_sha256
        FROM d""",
}
