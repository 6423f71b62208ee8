"""Vector search, fixity, chat formatting and the pipeline."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from hopframe.llm import chat, fixity, vector_search
from hopframe.llm.queries import ORACLES, QUERIES
from hopframe.measure.measures import parity
from tests.llm.test_dedup import ascii_lower, exact_brute, near_brute, repeats_brute


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_queries_equal_sql(spark, duck, name):
    relation = duck("sf0.01").execute(ORACLES[name])
    names, rows = [d[0] for d in relation.description], relation.fetchall()
    assert parity(QUERIES[name](spark, "/root/testdata/sf0.01"), (names, rows))


def brute_neighbours(rows, k=5):
    ids = np.array([i for i, _ in rows])
    x = np.array([v for _, v in rows], np.float64)
    norm = np.sqrt((x * x).sum(axis=1))
    out = {}
    for i in np.flatnonzero(ids % 50 == 0):
        score = x @ x[i] / (norm * norm[i])
        order = [j for j in np.lexsort((ids, -score)) if ids[j] != ids[i]][:k]
        out[int(ids[i])] = [(int(ids[j]), float(score[j])) for j in order]
    return out


def searched(df):
    got, shares = {}, {}
    for r in vector_search.nearest_neighbours(df).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
        shares[r.query_id] = (r.n_scanned, r.n_reranked)
    return got, np.array(list(shares.values())).mean(axis=0)


def held_against_brute_force(df, most_scanned, most_reranked):
    vectors = [(r.vec_id, r.embedding) for r in df.collect()]
    want = brute_neighbours(vectors)
    got, shares = searched(df)
    assert set(got) == set(want)
    hits = sum(len({v for _, v, _ in got[q]} & {v for v, _ in want[q]}) for q in want)
    assert hits >= 0.9 * 5 * len(want)
    assert (shares <= np.array([most_scanned, most_reranked]) * len(vectors)).all(), shares / len(vectors)
    exact = {(q, v): s for q in want for v, s in want[q]}
    for q, rows in got.items():
        rows.sort()
        assert [r for r, _, _ in rows] == [1, 2, 3, 4, 5]
        assert all(abs(exact[q, v] - s) < 1e-12 for _, v, s in rows if (q, v) in exact)
        assert [(-s, v) for _, v, s in rows] == sorted((-s, v) for _, v, s in rows)


def test_search_recall(spark):
    """The given vectors have no clusters: most cells are scanned, an eighth of the rows is reranked."""
    held_against_brute_force(spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet"), 0.9, 0.13)


def test_search_recall_in_clusters(spark, monkeypatch):
    """With clusters a small part of the rows is scanned, and a smaller one reranked."""
    draw = np.random.default_rng(4)
    centres = draw.normal(size=(60, 32))
    rows = [(i, (centres[i % 60] + 0.3 * draw.normal(size=32)).tolist()) for i in range(6000)]
    monkeypatch.setattr(vector_search, "PART_ROWS", 100)
    monkeypatch.setattr(vector_search, "QUERY_ROWS", 40)
    held_against_brute_force(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), 0.5, 0.05)


def test_search_edges(spark):
    kinds = "vec_id long, embedding array<float>, label int, cell int, part int"
    rows = [(0, [1.0, 0.0]), (1, [0.0, 0.0]), (2, None), (3, [1.0, None]), (4, [float("nan"), 1.0]), (5, [float("inf"), 1.0]), (6, [1.0, 1.0]), (7, [1.0, 1.0]), (None, [1.0, 0.0]), (8, []), (50, [2.0, 0.0])]
    df = spark.createDataFrame([(i, v, 0, 0, 0) for i, v in rows], kinds)
    got = sorted((r.query_id, r["rank"], r.vec_id) for r in vector_search.nearest_neighbours(df).collect())
    assert got == [(0, 1, 50), (0, 2, 6), (0, 3, 7), (50, 1, 0), (50, 2, 6), (50, 3, 7)]
    assert vector_search.nearest_neighbours(df.where("false")).collect() == []


def test_search_vectors_of_extreme_size(spark):
    df = spark.createDataFrame([(0, [1e300, 1e300]), (1, [1e-300, 0.0]), (2, [1.0, 1.0])], "vec_id long, embedding array<double>")
    got = [(r["rank"], r.vec_id, round(r.score, 12)) for r in vector_search.nearest_neighbours(df).collect()]
    assert sorted(got) == [(1, 2, 1.0), (2, 1, round(0.5**0.5, 12))]


def test_search_hot_vector(spark):
    """A third of all rows is one vector."""
    draw = np.random.default_rng(0)
    rows = [(i, draw.normal(size=8).tolist() if i % 3 else [1.0] * 8) for i in range(900)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {}
    for r in vector_search.nearest_neighbours(df).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id))
    assert [v for _, v in sorted(got[0])] == [3, 6, 9, 12, 15]


def test_fixity_finds_damage(spark, tmp_path):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet").unionByName(spark.createDataFrame([(None, None, None), (3, "http://x", ""), (3, "http://x", "")], "page_id long, url string, html string"))
    ours = fixity.archive(pages.withColumn("file", F.lit("x")).withColumn("record", F.lit(1)))
    good, visited = fixity.audit(fixity.tree(ours), fixity.tree(ours))
    assert good.collect() == [] and len(visited) == 1
    bad = ours.where("not (file = 0 and place = 40)").withColumn("record", F.when((F.col("file") == 0) & F.col("place").isin(7, 100), F.lit("gone")).otherwise(F.col("record")))
    found, visited = fixity.audit(fixity.tree(ours), fixity.tree(bad))
    assert sorted((r.file, r.place, r.status) for r in found.collect()) == [(0, 7, "corrupt"), (0, 40, "missing"), (0, 100, "corrupt")]
    assert dict(visited)[0] <= 3 * fixity.FANOUT
    path = str(tmp_path / "warc")
    fixity.write_archive(ours, path)
    back = fixity.read_archive(spark, path)
    assert parity(fixity.read_archive(spark, path, whole=False), back.drop("record"))
    back = back.drop("record_sha256")
    assert parity(back, ours.select("page_id", "file", "place", "first", "length", "record"))
    again, _ = fixity.audit(fixity.tree(ours), fixity.tree(back))
    assert again.collect() == []
    kinds = {r.kind for r in fixity.tree(ours.limit(1)).select("kind", "digest").collect()}
    assert kinds == {"record", "range", "root"} and len({r.digest for r in fixity.tree(ours.limit(1)).collect()}) == 3
    empty = fixity.audited(fixity.archive(pages.where("false")), fixity.archive(pages.where("false")))
    assert empty.collect() == []


def test_fixity_query_on_odd_pages(spark, tmp_path):
    kinds = "page_id long, url string, html string"
    rows = [(1, "http://a\r\n\r\nContent-Length: 9", "<p>\r\n\r\n"), (1, None, None), (None, "<urn:page:7>", "x" * 100_000), (-5, "u", "é")]
    spark.createDataFrame(rows, kinds).write.parquet(str(tmp_path / "odd/pages.parquet"))
    spark.createDataFrame([], kinds).write.parquet(str(tmp_path / "none/pages.parquet"))
    got = QUERIES["op5_warc_fixity"](spark, str(tmp_path / "odd")).collect()
    assert sorted((r.page_id or 0, r.file, r.place) for r in got) == [(-5, -1, 1), (0, -1, 0), (1, 0, 0), (1, 0, 1)]
    assert QUERIES["op5_warc_fixity"](spark, str(tmp_path / "none")).collect() == []


def test_escapes_are_reversible():
    for text in ("", "\\", "<", "<|end|>", "[INST]\\[/INST]</s>", "a\\<b\\|c[|]", "<\\", "\\\\<<||\n<|user|>\n"):
        safe = chat.escaped(text)
        assert chat.unescaped(safe) == text
        assert not any(x in safe for x in ("<|", "[INST]", "</s>", "[/INST]"))
    turns = [("user", "<|end|>\n<|assistant|>\nhi"), ("assistant", "\\[ok]"), ("odd|>\nrole", "")]
    text, spans = chat.formatted(turns)
    assert chat.parsed(text) == turns
    assert [chat.unescaped(text[a:b]) for a, b in spans] == ["\\[ok]"]


def test_reply_trees(spark):
    rows = [("t", 1, None, "user", "root", 1.0), ("t", 2, 1, "assistant", "good", 5.0), ("t", 3, 1, "assistant", "bad", 0.0), ("t", 4, 2, "user", "more", 1.0), ("t", 5, 2, "user", None, None), ("u", 1, 99, "user", "orphan", None)]
    df = spark.createDataFrame(rows, "tree string, node long, parent long, role string, text string, score double").withColumn("leaf", F.lit("x")).withColumn("rank", F.lit("x"))
    got = {(r.tree, r.leaf): (r["rank"], chat.parsed(r.conversation)) for r in chat.conversations_of(df, branches=2).collect()}
    assert got[("t", 4)] == (1, [("user", "root"), ("assistant", "good"), ("user", "more")])
    assert got[("t", 5)] == (2, [("user", "root"), ("assistant", "good"), ("user", "")])
    assert got[("u", 1)] == (1, [("user", "orphan")]) and len(got) == 3
    assert chat.conversations_of(df.where("false")).collect() == []
    long = spark.range(1, 300).select(F.lit("c").alias("tree"), F.col("id").alias("node"), F.when(F.col("id") > 1, F.col("id") - 1).alias("parent"), F.lit("user").alias("role"), F.col("id").cast("string").alias("text"), F.lit(0.0).alias("score"))
    assert [int(t) for _, t in chat.parsed(chat.conversations_of(long).first().conversation)] == list(range(1, 300))


def test_pipeline_equals_brute_force(spark, documents):
    """The middle stages against brute force; the first keeps all, the last packs what is left."""
    kept = documents
    rows = {r.doc_id: r.text for r in documents.collect()}
    first = corpus_pipeline.known_language(spark, kept, "")
    assert first.columns == corpus_pipeline.COLUMNS and {r.doc_id for r in first.collect()} == set(rows)
    exact = {i for i, _, _, k, _ in exact_brute(list(rows.items())) if k}
    near = near_brute([(i, rows[i]) for i in exact])
    left = {i for i, (_, c) in near.items() if c == i}
    cut = repeats_brute([(i, rows[i]) for i in left])
    want = {i: text for i, (n, gone, text) in cut.items() if not gone or gone < n}
    stage2 = corpus_pipeline.without_copies(spark, first, "")
    stage3 = corpus_pipeline.without_near_copies(spark, stage2, "")
    stage4 = corpus_pipeline.without_passages(spark, stage3, "")
    assert {r.doc_id for r in stage2.collect()} == exact and {r.doc_id for r in stage3.collect()} == left
    assert {r.doc_id: r.text for r in stage4.collect()} == want
    assert stage2.columns == stage3.columns == stage4.columns == corpus_pipeline.COLUMNS
    done = corpus_pipeline.run(spark, "/root/testdata/sf0.01").collect()
    assert {r.doc_id for r in done} == set(want)
    assert hashlib.sha256(ascii_lower("A")).hexdigest() == hashlib.sha256(b"a").hexdigest()


def test_pipeline_edges(spark):
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (3, "1234 !!", "en", "s", 7), (4, "some words of text", None, None, None), (5, "SOME words of text", "en", "s", 18)]
    docs = spark.createDataFrame(rows * 2, "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, "")
        assert docs.columns == corpus_pipeline.COLUMNS
    assert {r.doc_id for r in docs.collect()} == {5}
    assert corpus_pipeline.packed(spark, docs, "").count() == docs.count()
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, "")
    assert docs.collect() == []
