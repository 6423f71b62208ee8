"""Language identification: multinomial naive Bayes over hashed character n-grams.

Letters are lower-cased and everything else counts as one blank. Character n-grams of one to three characters are
hashed into a fixed number of features; counts by language come from a bounded sample of labelled rows and become a
matrix of log-probabilities that is broadcast. A text's score is the product of its sparse row of n-gram counts with
that matrix, gathered and summed in numpy for a batch of texts at once.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hopframe.llm.common import text_chunks, trimmed

FEATURES = 1 << 15
SMOOTHING = 0.5
#: labelled rows of each language from which the model is learned, at most about this many
SAMPLE_PER_LANGUAGE = 2500
UNKNOWN = "und"
#: bytes of text whose n-grams are held at once; a byte takes some 180 of a worker while it is counted
GRAM_BYTES = 1 << 18


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    """For each character of the basic plane its lower case, or a blank if it is no letter."""
    out = np.full(0x10000, 32, np.uint32)
    for i in range(0x10000):
        if (c := chr(i)).isalpha():
            out[i] = ord(low) if len(low := c.lower()) == 1 and ord(low) < 0x10000 else i
    return out


def _characters(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Folded characters of the texts with runs of blanks made one, and each character's row."""
    codes = np.frombuffer(data.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
    starts = np.concatenate(([0], np.cumsum((data & 0xC0) != 0x80)))[offsets]
    row = np.repeat(np.arange(len(offsets) - 1), np.diff(starts))
    high = codes >= 0x10000
    folded = _letters()[np.where(high, 32, codes)]
    if high.any():
        letters = {int(c): c if chr(c).isalpha() else 32 for c in np.unique(codes[high])}
        folded[high] = [letters[c] for c in codes[high].tolist()]
    blank = folded == 32
    keep = np.ones(len(folded), bool)
    keep[1:] = ~(blank[1:] & blank[:-1] & (row[1:] == row[:-1]))
    return folded[keep], row[keep]


def hashed_grams(folded: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Feature and row of every n-gram of one to three characters; blanks alone are none."""
    features, rows = [], []
    wide = folded.astype(np.uint64)
    value = np.zeros(len(wide), np.uint64)
    for n in (1, 2, 3):
        if len(wide) < n:
            break
        value = value[: len(wide) - n + 1] * np.uint64(0x100000001B3) + wide[n - 1 :]
        own = row[: len(value)] == row[n - 1 :]
        own &= (folded[: len(value)] != 32) | (n > 1)
        hashed = (value * np.uint64(0x9E3779B97F4A7C15) + np.uint64(n * 0xD6E8FEB86659FD93 % (1 << 64))) * np.uint64(0xFF51AFD7ED558CCD)
        features.append((hashed[own] >> np.uint64(64 - FEATURES.bit_length() + 1)).astype(np.int64))
        rows.append(row[: len(value)][own])
    if not features:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(features), np.concatenate(rows)


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: dict[str, np.ndarray] = {}
    for batch in batches:
        languages = np.array(batch.column(0).to_pylist(), object)
        for low, high, data, offsets in text_chunks(batch.column(1), GRAM_BYTES):
            features, rows = hashed_grams(*_characters(data, offsets))
            for language in set(languages[low:high]):
                own = features[(languages[low:high] == language)[rows]]
                held[language] = held.get(language, 0) + np.bincount(own, minlength=FEATURES)
    for language, counts in held.items():
        full = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array([language] * len(full)), pa.array(full), pa.array(counts[full].astype(np.int64))], ["lang", "feature", "n"])


def fitted(docs: DataFrame, usable: Column, text_col: str = "text", lang_col: str = "lang", per_language: int = SAMPLE_PER_LANGUAGE) -> tuple[list[str], np.ndarray]:
    """Languages and log-probability matrix (features x languages), from a bounded sample of the ``usable`` rows.

    What comes to the driver is at most features x languages counts, whatever the input.
    """
    labelled = docs.where(usable & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    sizes = {r[0]: r[1] for r in labelled.groupBy(lang_col).count().collect()}
    if not sizes:
        return [], np.zeros((FEATURES, 0), np.float32)
    share = F.create_map(*[F.lit(x) for k, n in sizes.items() for x in (k, min(1.0, per_language / n))])
    place = F.pmod(F.xxhash64(F.lit("sample"), text_col), F.lit(1_000_003)) / 1_000_003.0
    sample = labelled.where(place < share[F.col(lang_col)]).select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))
    counted = sample.mapInArrow(trimmed(_counts), "lang string, feature long, n long").groupBy("lang", "feature").agg(F.sum("n").alias("n")).toPandas()
    languages = sorted(sizes)
    matrix = np.full((FEATURES, len(languages)), SMOOTHING)
    matrix[counted["feature"].to_numpy(np.int64), counted["lang"].map({k: i for i, k in enumerate(languages)}).to_numpy(np.int64)] += counted["n"].to_numpy(float)
    return languages, (np.log(matrix) - np.log(matrix.sum(axis=0))).astype(np.float32)


def identified(docs: DataFrame, languages: list[str], matrix: np.ndarray, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, lang_pred, score and the columns named in ``keep`` for each row.

    ``score`` is the posterior of the language named. Texts that are null or have no letter are ``und`` with score
    0, and so is every text if nothing was learned. Equal posteriors go to the language that sorts first.
    """
    spark = docs.sparkSession
    model = spark.sparkContext.broadcast((languages, matrix))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, weights = model.value
        for batch in batches:
            for low, high, data, offsets in text_chunks(batch.column(1), GRAM_BYTES):
                folded, row = _characters(data, offsets)
                features, rows = hashed_grams(folded, row)
                total = np.stack([np.bincount(rows, weights[features, k], minlength=high - low) for k in range(len(names))], axis=1) if names else np.zeros((high - low, 0))
                lettered = np.bincount(row[folded != 32], minlength=high - low) > 0
                found, score = [UNKNOWN] * (high - low), np.zeros(high - low)
                if names:
                    best = total.argmax(axis=1)
                    odds = 1 / np.exp(total - total.max(axis=1, keepdims=True)).sum(axis=1)
                    found = [names[b] if ok else UNKNOWN for b, ok in zip(best, lettered)]
                    score = np.where(lettered, odds, 0.0)
                part = batch.slice(low, high - low)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(found, pa.string()), pa.array(score), *part.columns[2:]], ["doc_id", "lang_pred", "score", *(f"kept_{i}" for i in range(len(keep)))])

    chosen = [F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), *(F.col(c).alias(f"kept_{i}") for i, c in enumerate(keep))]
    slim = docs.select(*chosen)
    extra = "".join(f", kept_{i} {docs.schema[c].dataType.simpleString()}" for i, c in enumerate(keep))
    out = slim.mapInArrow(trimmed(run), f"doc_id long, lang_pred string, score double{extra}")
    return out.select("doc_id", "lang_pred", "score", *(F.col(f"kept_{i}").alias(c) for i, c in enumerate(keep)))
