"""The pipeline's stages on repeated rows and on rows without an id."""

import random

import corpus_pipeline

KINDS = "doc_id long, text string, lang string, source string, n_chars long"


def prose(seed, words=60):
    draw = random.Random(seed)
    return " ".join(f"w{draw.randrange(10**6)}" for _ in range(words))


def through(spark, pairs):
    """(doc_id, text) rows after the exact, near and substring stages."""
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in pairs], KINDS)
    for name, stage in corpus_pipeline.STAGES:
        if name in ("exact", "near", "substring"):
            docs = stage(spark, docs, "")
            assert docs.columns == corpus_pipeline.COLUMNS
    return sorted(((r.doc_id, r.text) for r in docs.collect()), key=str)


def test_repeated_rows_leave_one(spark):
    a, b = prose(1), prose(2)
    assert through(spark, [(1, a), (1, a), (2, b)]) == [(1, a), (2, b)]
    assert through(spark, [(1, a), (1, a.upper()), (1, a)]) == [(1, min(a, a.upper()))]


def test_only_the_kept_text_of_an_id_stays(spark):
    a, b = prose(1), prose(2)
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in [(5, a), (5, b), (9, a)]], KINDS)
    left = corpus_pipeline.without_copies(spark, docs, "")
    assert sorted((r.doc_id, r.text) for r in left.collect()) == sorted([(5, b), (9, a)])


def test_rows_without_id_are_documents(spark):
    a, b, c, d = (prose(k) for k in range(4))
    near_b = b.rsplit(" ", 1)[0] + " other"
    passage = prose(9, 40)
    rows = [(None, a), (None, a), (1, b), (None, near_b), (None, c), (2, c), (3, f"{passage} {d}"), (None, f"{passage} tail of its own")]
    want = [(None, a), (1, b), (2, c), (3, d), (None, "tail of its own")]
    assert through(spark, rows) == sorted(want, key=str)
    docs = spark.createDataFrame([(None, a, "en", "s", len(a))], KINDS)
    assert corpus_pipeline.packed(spark, docs, "").count() == 1
