"""Learned operators against plain versions that know nothing of batches, and rows without an id."""

import math
from collections import Counter, defaultdict

import public_tokenizers
import pytest
from pyspark.sql import functions as F

from hopframe.llm import bpe, exact_dedup, language_id, packing, toxicity
from hopframe.llm.common import fold

MASK = (1 << 64) - 1


def gram_features(text):
    """Hashed character n-grams of one text."""
    chars = []
    for c in text or "":
        low = c.lower()
        one = (low if len(low) == 1 else c) if c.isalpha() else " "
        if one != " " or not chars or chars[-1] != " ":
            chars.append(one)
    out = Counter()
    for n in (1, 2, 3):
        for i in range(len(chars) - n + 1):
            if n == 1 and chars[i] == " ":
                continue
            value = 0
            for c in chars[i : i + n]:
                value = (value * 0x100000001B3 + ord(c)) & MASK
            hashed = (value * 0x9E3779B97F4A7C15 + n * 0xD6E8FEB86659FD93) * 0xFF51AFD7ED558CCD & MASK
            out[hashed >> (64 - language_id.FEATURES.bit_length() + 1)] += 1
    return out


def test_naive_bayes_equals_a_plain_one(documents):
    languages, matrix = language_id.fitted(documents, fold() != 2, per_language=10**9)
    got = {r.doc_id: (r.lang_pred, r.score) for r in language_id.identified(documents, languages, matrix).collect()}
    counts = defaultdict(Counter)
    for r in documents.where(fold() != 2).where("lang is not null and text is not null").collect():
        counts[r.lang] += gram_features(r.text)
    totals = {k: sum(c.values()) + language_id.SMOOTHING * language_id.FEATURES for k, c in counts.items()}
    for r in documents.limit(250).collect():
        grams = gram_features(r.text)
        said = {k: sum(n * math.log((counts[k][g] + language_id.SMOOTHING) / totals[k]) for g, n in grams.items()) for k in sorted(counts)}
        best = max(said, key=said.get)
        if any(c.isalpha() for c in r.text or ""):
            score = 1 / sum(math.exp(v - said[best]) for v in said.values())
            assert got[r.doc_id][1] == pytest.approx(score, abs=2e-3)
            assert got[r.doc_id][0] == best or score < 0.6
        else:
            assert got[r.doc_id] == ("und", 0.0)


def finished(x):
    x ^= x >> 30
    x = x * 0xBF58476D1CE4E5B9 & MASK
    x ^= x >> 27
    x = x * 0x94D049BB133111EB & MASK
    return x ^ x >> 31


def sentence_bags(text):
    """Hashed features of every sentence of one text."""
    data, sentences, words = (text or "").encode().lower(), [[]], []
    if not data:
        return []
    place = word = None
    for i, byte in enumerate(data):
        letter = 97 <= byte <= 122 or byte >= 128
        if i and data[i - 1] in b".!?\n":
            sentences.append([])
        if letter and place is None:
            place, word = len(sentences) - 1, b""
        if letter:
            word += bytes([byte])
        if place is not None and (not letter or i == len(data) - 1):
            words.append((place, word))
            place = None
    for place, word in words:
        value = 0
        for k, byte in enumerate(word[:24]):
            value = ((value ^ byte) * 0x100000001B3 + k + 1) & MASK
            if k + 1 in toxicity.BEGINNINGS:
                sentences[place].append(finished(value + (k + 1 << 40) & MASK))
        sentences[place].append(finished(value ^ (len(word) << 50) & MASK))
    return [[h >> (64 - toxicity.FEATURE_BITS) for h in s] for s in sentences]


def test_noisy_or_equals_a_plain_one(spark, documents):
    weights = toxicity.fitted(documents, spark.read.parquet("/root/testdata/sf0.01/labels.parquet"), fold() != 2).astype("float32")
    got = {r.doc_id: r for r in toxicity.scored(documents, weights).collect()}
    for r in documents.limit(300).collect():
        clean = 1.0
        singles = []
        for bag in sentence_bags(r.text) or [[]]:
            z = sum(float(weights[f]) for f in bag) + float(weights[-1])
            singles.append(1 / (1 + math.exp(-z)))
            clean *= 1 - singles[-1]
        assert got[r.doc_id].score == pytest.approx(1 - clean, abs=1e-6)
        assert [s.score for s in got[r.doc_id].sentences] == pytest.approx([s for s in singles if s >= 0.3], abs=1e-6)


@pytest.fixture()
def without_ids(docs_of):
    return docs_of([(None, "the words of a text"), (None, "the words of a text"), (None, None), (1, "other words"), (1, "the WORDS of a text"), (2, "other words")])


def test_rows_without_an_id(spark, documents, without_ids):
    languages, matrix = language_id.fitted(documents, fold() != 2)
    found = language_id.identified(without_ids, languages, matrix).collect()
    assert sorted((r.doc_id or 0, r.lang_pred == "und") for r in found) == [(0, False), (0, False), (0, True), (1, False), (1, False), (2, False)]
    assert without_ids.where(fold() != 2).where("doc_id is null").count() == 0  # nothing is learned from them
    scored = toxicity.scored(without_ids, toxicity.fitted(without_ids, spark.createDataFrame([(None, 1), (1, None)], "doc_id long, toxic int"), F.lit(True))).collect()
    assert sorted(r.doc_id or 0 for r in scored) == [0, 0, 0, 1, 1, 2]
    packed = packing.packed(packing.tokenised_pieces(without_ids, public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN)).collect()
    assert sorted(r.doc_id or 0 for r in packed) == [0, 0, 0, 1, 1, 2]
    coded = bpe.encoded_digests(without_ids, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN).collect()
    assert sorted((r.doc_id or 0, r.n_tokens > 0) for r in coded) == [(0, False), (0, True), (0, True), (1, True), (1, True), (2, True)]


def test_exact_groups_of_rows_without_an_id(without_ids):
    got = [(r.doc_id, r.keep_id, r.group_size, r.kept) for r in exact_dedup.exact_duplicates(without_ids).collect()]
    assert sorted(got, key=str) == sorted([(None, 1, 3, False), (None, 1, 3, False), (None, None, 1, True), (1, 2, 2, False), (1, 1, 3, True), (2, 2, 2, True)], key=str)


def test_rank_table_without_a_byte():
    coder = bpe.BytePairCoder({b"a": 0, b"b": 1, b"ab": 2}, "[a-z]+")
    assert coder.encode_piece(b"aba") == [2, 0]
    with pytest.raises(ValueError):
        coder.encode_piece(b"abx")
