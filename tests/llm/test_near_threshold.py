"""Near dedup at thresholds other than op2's 85."""

import random

import pytest

import corpus_pipeline
from hopframe.llm import near_dedup
from tests.llm.test_dedup import near_brute, shingles


def pairs(count, edits, length=300, seed=5):
    """Pairs of texts of which the second has ``edits`` words changed, far enough apart to spoil five shingles each."""
    draw = random.Random(seed)
    rows = []
    for i in range(count):
        text = [f"w{draw.randrange(10**6)}" for _ in range(length)]
        other = list(text)
        for k in range(edits):
            other[10 + k * (length - 20) // edits] = f"e{draw.randrange(10**6)}"
        rows += [(2 * i, " ".join(text)), (2 * i + 1, " ".join(other))]
    return rows


def jaccard(a, b):
    return len(shingles(a) & shingles(b)) / len(shingles(a) | shingles(b))


def test_stage_takes_pairs_from_80(docs_of, spark):
    rows = pairs(40, 6)
    assert all(0.80 <= jaccard(rows[k][1], rows[k + 1][1]) < 0.85 for k in range(0, len(rows), 2))
    left = corpus_pipeline.without_near_copies(spark, docs_of(rows), "")
    assert sorted(r.doc_id for r in left.collect()) == [i for i, _ in rows if i % 2 == 0]


@pytest.mark.parametrize("percent, edits", [(50, 19), (65, 12)])
def test_low_thresholds_equal_brute_force(docs_of, percent, edits):
    rows = pairs(60, edits)
    assert all(percent / 100 <= jaccard(rows[k][1], rows[k + 1][1]) < percent / 100 + 0.04 for k in range(0, len(rows), 2))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dedup.near_duplicates(docs_of(rows), percent=percent).collect()}
    assert got == near_brute(rows, percent)


def test_documents_equal_brute_force_at_80(documents):
    rows = [(r.doc_id, r.text) for r in documents.select("doc_id", "text").collect()]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dedup.near_duplicates(documents, percent=80).collect()}
    assert got == near_brute(rows, 80)


@pytest.mark.parametrize("percent", range(1, 100))
def test_bands_miss_little(percent):
    rows = near_dedup.band_rows(percent)
    assert near_dedup.REGISTERS % rows == 0
    assert percent < 4 or (1 - (percent / 100) ** rows) ** (near_dedup.REGISTERS // rows) <= near_dedup.MISS
