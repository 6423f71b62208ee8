"""Toxicity by multiple-instance learning: sentences are scored, a noisy-or of them is the document's score.

A sentence's score is a logistic function of its hashed words and word beginnings. Only documents have labels, so the
weights are learned through the noisy-or: in a toxic document some sentence has to answer for the label, in a clean
one none may. The sentence scores then say where the offence is.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hopframe.llm.common import lowered, mixed, text_chunks

FEATURE_BITS = 18
#: labelled rows from which the model is learned, at most about this many
SAMPLE_ROWS = 6000
#: bytes of a word's beginning that are features of their own
BEGINNINGS = (4, 5)
BIAS = -6.0
#: documents of the sample that must hold a feature for it to have a weight
LEAST_DOCUMENTS = 4

_LETTER = np.zeros(256, bool)
_LETTER[97:123] = True
_LETTER[128:] = True
_STOP = np.zeros(256, bool)
_STOP[list(b".!?\n")] = True


def sentence_features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Features with their sentence, and each sentence's row, first and last byte (relative to its row)."""
    data = lowered(data)
    letter = _LETTER[data]
    n = len(data)
    first_of_row = np.zeros(n + 1, bool)
    first_of_row[offsets[:-1]] = True
    first_of_row = first_of_row[:n]
    # a sentence begins with a row and after each full stop
    begins = first_of_row.copy()
    begins[1:] |= _STOP[data[:-1]]
    starts = np.flatnonzero(begins)
    sentence = np.cumsum(begins) - 1
    row = np.searchsorted(offsets, starts, side="right") - 1
    stops = np.append(starts[1:], n)
    word_begins = letter.copy()
    if n:
        word_begins[1:] &= ~letter[:-1] | first_of_row[1:]
    at = np.flatnonzero(word_begins)
    if not len(at):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), row, starts - offsets[row], stops - offsets[row]
    ends = np.flatnonzero(letter & np.append(~letter[1:] | first_of_row[1:], True)) + 1
    length = ends - at
    features = []
    value = np.zeros(len(at), np.uint64)
    for k in range(int(min(length.max(), 24))):  # words by their first bytes; longer ones by these and their length
        live = length > k
        value[live] = (value[live] ^ data[at[live] + k].astype(np.uint64)) * np.uint64(0x100000001B3) + np.uint64(k + 1)
        if k + 1 in BEGINNINGS:
            own = length >= k + 1
            features.append((mixed(value[own] + np.uint64(k + 1 << 40)), sentence[at[own]]))
    features.append((mixed(value ^ (length.astype(np.uint64) << np.uint64(50))), sentence[at]))
    hashed = np.concatenate([f for f, _ in features])
    return (hashed >> np.uint64(64 - FEATURE_BITS)).astype(np.int64), np.concatenate([s for _, s in features]), row, starts - offsets[row], stops - offsets[row]


def _bags(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for low, high, data, offsets in text_chunks(batch.column(0)):
            features, owner, row, _, _ = sentence_features(data, offsets)
            order = np.argsort(owner, kind="stable")
            features, rows = features[order].astype("<i4"), row[owner[order]]
            local = (owner[order] - np.searchsorted(row, rows)).astype("<i4")
            cuts = np.searchsorted(rows, np.arange(high - low + 1))
            pairs = [(features[a:b].tobytes(), local[a:b].tobytes()) for a, b in zip(cuts[:-1], cuts[1:])]
            counts = np.bincount(row, minlength=high - low)
            yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in pairs], pa.binary()), pa.array([p[1] for p in pairs], pa.binary()), pa.array(counts.astype(np.int64)), batch.column(1).slice(low, high - low)], ["features", "owner", "sentences", "label"])


def fitted(docs: DataFrame, labels: DataFrame, usable: Column, label_col: str = "toxic", id_col: str = "doc_id", text_col: str = "text", rows: int = SAMPLE_ROWS, epochs: int = 14, seed: int = 7) -> np.ndarray:
    """Weights of all features and, last, the bias. The driver gets the features of at most about ``rows`` rows.

    An id with several labels counts as toxic if any of them says so. Null ids, texts and labels are left out;
    without any labelled row the bias alone speaks.
    """
    known = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).cast("long").alias("doc_id")).agg(F.max(F.col(label_col).cast("int")).alias("label")).where(usable)
    share = min(1.0, rows / max(1, known.count()))
    chosen = known.where(F.pmod(F.xxhash64(F.lit("sample"), "doc_id"), F.lit(1_000_003)) < share * 1_000_003)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).where("text is not null")
    sample = slim.join(F.broadcast(chosen), "doc_id").select("text", "label")  # at most about ``rows`` ids
    got = sample.mapInArrow(_bags, "features binary, owner binary, sentences long, label int").toPandas()
    return _learned([np.frombuffer(x, "<i4") for x in got["features"]], [np.frombuffer(x, "<i4") for x in got["owner"]], got["sentences"].to_numpy(), got["label"].to_numpy(), epochs, seed)


def _learned(features: list[np.ndarray], owners: list[np.ndarray], sentences: np.ndarray, labels: np.ndarray, epochs: int, seed: int) -> np.ndarray:
    """Adagrad on the noisy-or's likelihood, a few documents at a time."""
    weights, squares = np.zeros((1 << FEATURE_BITS) + 1), np.full((1 << FEATURE_BITS) + 1, 1e-2)
    weights[-1] = BIAS
    if not len(labels):
        return weights
    # features that few documents hold teach nothing about others; the rest start from their log-odds by document
    held = np.zeros((2, 1 << FEATURE_BITS))
    for f, label in zip(features, labels):
        held[int(label), np.unique(f)] += 1
    of = np.maximum(1, np.bincount(labels, minlength=2)[:2])
    rare = held.sum(axis=0) < LEAST_DOCUMENTS
    odds = np.log((held[1] + 0.05) / of[1]) - np.log((held[0] + 0.5) / of[0])
    weights[:-1] = np.where(rare, 0, np.clip(odds - 1, 0, 6) * 0.9)
    draw = np.random.default_rng(seed)
    for _ in range(epochs):
        order = draw.permutation(len(labels))
        for low in range(0, len(order), 32):
            part = order[low : low + 32]
            base = np.concatenate(([0], np.cumsum(sentences[part])))
            f = np.concatenate([features[i] for i in part])
            s = np.concatenate([owners[i] + b for i, b in zip(part, base[:-1])])
            z = np.bincount(s, weights[f], minlength=base[-1])[: base[-1]] + weights[-1]
            p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
            row = np.repeat(np.arange(len(part)), sentences[part])
            total = np.bincount(row, np.logaddexp(0, z), minlength=len(part))
            slope = np.where(labels[part] == 1, -1 / np.expm1(np.clip(total, 1e-6, 50)), 1.0)
            dz = np.clip(slope, -50, 1)[row] * p
            gradient = np.bincount(f, dz[s], minlength=len(weights))
            gradient[:-1][rare] = 0
            gradient[-1] = dz.sum() * 0.1
            touched = np.flatnonzero(gradient)
            squares[touched] += gradient[touched] ** 2
            weights[touched] -= 0.3 * gradient[touched] / np.sqrt(squares[touched])
    return weights


def scored(docs: DataFrame, weights: np.ndarray, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.3) -> DataFrame:
    """doc_id, score, predicted and the offending sentences of every row.

    ``sentences`` holds first byte, end byte and score of the sentences that reach ``threshold`` by themselves.
    Null and empty texts have one empty sentence. The weights (one number for each of a fixed number of features)
    are broadcast.
    """
    model = docs.sparkSession.sparkContext.broadcast(weights.astype(np.float32))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = model.value
        for batch in batches:
            for low, high, data, offsets in text_chunks(batch.column(1)):
                features, owner, row, starts, stops = sentence_features(data, offsets)
                z = np.bincount(owner, own[features], minlength=len(row))[: len(row)] + float(own[-1])
                loss = np.logaddexp(0, z)
                total = np.bincount(row, loss, minlength=high - low)
                total[np.bincount(row, minlength=high - low) == 0] = np.logaddexp(0, float(own[-1]))
                score = -np.expm1(-total)
                single = -np.expm1(-loss)
                hot = np.flatnonzero(single >= threshold)
                ends = np.searchsorted(row[hot], np.arange(high - low + 1)).astype(np.int32)
                where = pa.ListArray.from_arrays(pa.array(ends), pa.StructArray.from_arrays([pa.array(starts[hot]), pa.array(stops[hot]), pa.array(single[hot])], ["first", "stop", "score"]))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(low, high - low), pa.array(score), pa.array((score >= threshold).astype(np.int32)), where], ["doc_id", "score", "predicted", "sentences"])

    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return slim.mapInArrow(run, "doc_id long, score double, predicted int, sentences array<struct<first:long,stop:long,score:double>>")
