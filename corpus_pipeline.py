"""The corpus pipeline: raw documents to packed training sequences, in five stages.

Each stage works on all that its predecessor kept. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from collections.abc import Callable
from string import ascii_lowercase, ascii_uppercase

import public_tokenizers
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from hopframe.llm import exact_dedup, language_id, near_dedup, packing, substring_dedup
from hopframe.llm.common import fold, staged, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: posterior below which a text's language counts as not found
LEAST_SCORE = 0.5
#: share of five-word shingles in common, in percent, from which texts are near-duplicates
NEAR_PERCENT = 80


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without letters, or whose language is not found, go."""
    languages, matrix = language_id.fitted(docs, fold() != 2)
    found = language_id.identified(docs.select(*COLUMNS), languages, matrix, keep=tuple(COLUMNS[1:]))
    return found.where((F.col("lang_pred") != language_id.UNKNOWN) & (F.col("score") >= LEAST_SCORE)).select(*COLUMNS)


def _content_key(digest: Column) -> Column:
    """Id and digest of a row as one string, which is never null."""
    return F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(":"), digest)


def without_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts one row stays, one with the largest id; a row without an id only where no equal one has any."""
    kept = exact_dedup.exact_duplicates(docs).where("kept").select(_content_key(F.col("text_sha256")).alias("key"))
    text = F.translate(F.coalesce("text", F.lit("")), ascii_uppercase, ascii_lowercase)
    rows = docs.select(*COLUMNS, _content_key(F.sha2(text.cast("binary"), 256)).alias("key")).join(kept, "key", "left_semi")
    place = F.row_number().over(W.partitionBy("key").orderBy(*COLUMNS[1:]))  # rows may share id and text
    return rows.withColumn("place", place).where("place = 1").select(*COLUMNS)


#: ids from here on stand for rows without an id
NO_ID = 1 << 62


def _with_ids(docs: DataFrame) -> DataFrame:
    """``docs`` with the own ids as ``own_id``; where there is none, doc_id becomes one made from the text.

    Equal texts have gone before, so these ids differ but for collisions of the hash; they are larger than usual ones.
    """
    made = F.lit(NO_ID) + F.xxhash64("text").bitwiseAND(F.lit(NO_ID - 1))
    return docs.select(F.col("doc_id").alias("own_id"), F.coalesce("doc_id", made).alias("doc_id"), *COLUMNS[1:])


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates the document with the smallest id stays; rows without an id come last."""
    docs = _with_ids(docs)
    kept = near_dedup.near_duplicates(docs, percent=NEAR_PERCENT).where("kept").select("doc_id").distinct()
    return docs.join(kept, "doc_id", "left_semi").select(F.col("own_id").alias("doc_id"), *COLUMNS[1:])


def without_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated passages go from the texts; a document of which nothing is left goes too."""
    found = substring_dedup.without_repeats(docs, keep=("lang", "source"))
    left = found.where("n_removed = 0 or n_removed < n_words")
    return left.select("doc_id", F.col("kept").alias("text"), "lang", "source", F.length("kept").cast("long").alias("n_chars"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents' tokens in sequences of at most 1024."""
    return packing.packed(packing.tokenised_pieces(docs, public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language", known_language),
    ("exact", without_copies),
    ("near", without_near_copies),
    ("substring", without_passages),
    ("packing", packed),
]

#: tokenisation and learned models are beyond SQL; tests hold the stages against brute force
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = staged(docs)
    return docs
