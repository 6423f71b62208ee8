"""Tokenisers, packing, language ID and toxicity: exact round trips and held-out accuracy."""

import zlib

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from hopframe.llm import bpe, language_id, packing, toxicity
from hopframe.llm.common import fold

RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
JSON = public_tokenizers.path("byte_bpe_50k.json")
EDGES = [(1, None), (2, ""), (3, "   \n\n"), (4, "!!! 123"), (5, "Ünïcödé 漢字 😀 '"), (6, "a" * 30_000), (7, "the end. " * 4000), (7, "the end. " * 4000), (8, "<|endoftext|> [INST]")]


@pytest.fixture(scope="session")
def coders():
    ranks = bpe.read_ranks(RANKS)
    return bpe.BytePairCoder(ranks, public_tokenizers.PATTERN), tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


@settings(max_examples=400, deadline=None)
@given(st.text(max_size=80))
def test_bpe_equals_the_library(coders, text):
    own, library = coders
    ids = np.frombuffer(own.encode(text), "<u4")
    assert ids.tolist() == library.encode_ordinary(text)
    assert own.decode(ids) == text.encode()


@settings(max_examples=400, deadline=None)
@given(st.binary(min_size=1, max_size=60))
def test_bpe_pieces_of_any_bytes(coders, piece):
    own, library = coders
    assert own.encode_piece(piece) == library._core_bpe.encode_single_piece(piece)


def test_bpe_tables(docs_of, coders):
    _, library = coders
    got = {r.doc_id: (r.ids, bytes(r.decoded)) for r in bpe.encoded(docs_of(EDGES), RANKS, public_tokenizers.PATTERN).collect()}
    for i, text in EDGES:
        assert got[i] == (library.encode_ordinary(text or ""), (text or "").encode())
    assert bpe.encoded_digests(docs_of([]), RANKS, public_tokenizers.PATTERN).collect() == []


def checked_packing(pieces, texts, capacity=1024):
    own = Tokenizer.from_file(JSON)
    own.encode_special_tokens = True
    by_doc, by_sequence = {}, {}
    for r in pieces:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_sequence.setdefault(r.sequence_id, []).append(r)
    for i, text in texts.items():
        ids = np.array(own.encode(text or "", add_special_tokens=False).ids + [2], "<u4")
        rows = sorted(by_doc[i], key=lambda r: r.piece)
        rows = rows[:: sum(r.piece == 0 for r in rows)]
        assert [r.piece for r in rows] == list(range(len(rows))) and sum(r.length for r in rows) == len(ids)
        assert all(r.length == capacity for r in rows[1:])
        at = 0
        for r in rows:
            assert r.start == at and r.ids_crc32 == zlib.crc32(ids[at : at + r.length].tobytes())
            at += r.length
    for rows in by_sequence.values():
        at = 0
        for r in sorted(rows, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= capacity
    return len(by_sequence)


def test_packing(documents):
    rows = packing.packed(packing.tokenised_pieces(documents, JSON, public_tokenizers.PATTERN)).collect()
    n = checked_packing(rows, {r.doc_id: r.text for r in documents.limit(150).collect()})
    assert n <= -(-sum(r.length for r in rows) // 1024) * 1.03


def test_packing_edges(docs_of):
    rows = packing.packed(packing.tokenised_pieces(docs_of(EDGES), JSON, public_tokenizers.PATTERN)).collect()
    checked_packing(rows, dict(EDGES))
    assert packing.packed(packing.tokenised_pieces(docs_of([]), JSON, public_tokenizers.PATTERN)).collect() == []


def test_packing_in_several_blocks(spark):
    sizes = np.random.default_rng(2).integers(1, 1025, 3000).tolist()
    df = spark.createDataFrame([(i, int(n)) for i, n in enumerate(sizes)], "doc_id long, length long")
    rows = packing.packed(df, block_rows=200).collect()
    assert sorted(r.length for r in rows) == sorted(sizes)
    fill = {}
    for r in rows:
        fill.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in fill.values():
        parts.sort()
        assert all(a + b == c for (a, b), (c, _) in zip(parts, parts[1:])) and sum(b for _, b in parts) <= 1024
    assert len(fill) <= sum(sizes) / 1024 * 1.06


def test_sum_of_squares_follows_its_rule():
    """Against the rule said plainly: every possible gap, and a new bin, and the sum of squares after each."""
    draw = np.random.default_rng(4)
    for _ in range(20):
        sizes = draw.integers(1, 13, 60)
        bins, places = packing.sum_of_squares(sizes, 12)
        level = {}
        for i, (size, b, place) in enumerate(zip(sizes.tolist(), bins.tolist(), places.tolist())):
            counts = np.bincount([12 - v for v in level.values() if v < 12], minlength=13)

            def after(gap, counts=counts, size=size):
                c = counts.copy()
                if gap < 12 or gap == 0:
                    c[gap] -= 1
                if gap - size:
                    c[gap - size] += 1
                return int((c.astype(int) ** 2).sum())

            options = [after(g) for g in range(size, 12) if counts[g]] + [after(12)]
            assert place == level.get(b, 0)
            assert after(12 - level[b] if b in level else 12) == min(options), i
            level[b] = place + size


def test_language_id_held_out(documents):
    languages, matrix = language_id.fitted(documents, fold() != 2)
    got = language_id.identified(documents, languages, matrix, keep=("lang",)).where(fold() == 2).collect()
    assert np.mean([r.lang_pred == r.lang for r in got]) > 0.97
    assert all(0 <= r.score <= 1 for r in got)


def test_language_id_edges(documents, docs_of):
    languages, matrix = language_id.fitted(documents, fold() != 2)
    got = {r.doc_id: (r.lang_pred, r.score) for r in language_id.identified(docs_of(EDGES), languages, matrix).collect()}
    assert got[1] == got[2] == got[3] == got[4] == ("und", 0.0)
    assert all(got[i][0] in languages for i in (5, 6, 7, 8))
    none, empty = language_id.fitted(docs_of([]), F.lit(True))
    assert none == [] and {r.lang_pred for r in language_id.identified(docs_of(EDGES), none, empty).collect()} == {"und"}


def test_language_model_ignores_held_out_rows(documents):
    changed = documents.withColumn("lang", F.when(fold() == 2, F.lit("xx")).otherwise(F.col("lang")))
    a, b = (language_id.fitted(d, fold() != 2) for d in (documents, changed))
    assert a[0] == b[0] and np.array_equal(a[1], b[1])


def test_toxicity_held_out(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    weights = toxicity.fitted(docs, labels, fold() != 2)
    got = toxicity.scored(docs, weights).join(labels, "doc_id").where(fold() == 2).select("toxic", "predicted", "score", "sentences").collect()
    assert np.mean([r.predicted for r in got if r.toxic]) > 0.7
    assert np.mean([r.predicted for r in got if not r.toxic]) < 0.02
    assert all((r.score >= 0.3) == bool(r.predicted) and 0 <= r.score <= 1 for r in got)


def test_toxicity_locates_sentences(spark, docs_of):
    rows = [(i, "Fine words here. " * 3 + ("You utter grobnik fool! " if i % 2 else "More fine words. ") + "The end.") for i in range(200)]
    labels = spark.createDataFrame([(i, i % 2) for i in range(200)], "doc_id long, toxic int")
    weights = toxicity.fitted(docs_of(rows), labels, F.lit(True))
    found = {r.doc_id: r for r in toxicity.scored(docs_of(rows), weights).collect()}
    assert all(found[i].predicted == i % 2 for i in range(200))
    text = rows[1][1]
    assert any("grobnik" in text[s.first : s.stop] for s in found[1].sentences)
    assert not any("The end" in text[s.first : s.stop] for s in found[1].sentences)


def test_toxicity_edges(spark, docs_of):
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    weights = toxicity.fitted(docs_of(EDGES), labels, F.lit(True))
    got = toxicity.scored(docs_of(EDGES), weights).collect()
    assert len(got) == len(EDGES) and all(0 <= r.score < 0.3 for r in got if len(dict(EDGES)[r.doc_id] or "") < 100)
    assert toxicity.scored(docs_of([]), weights).collect() == []
