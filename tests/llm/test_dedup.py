"""Exact, near and substring deduplication against brute force, and their edge cases."""

import hashlib
import random
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest

from hopframe.llm import near_dedup, substring_dedup
from hopframe.llm.common import word_hashes, word_spans
from hopframe.llm.components import components
from hopframe.llm.exact_dedup import exact_duplicates


def ascii_lower(text):
    return (text or "").encode().lower()


def words_of(text):
    return (text or "").encode().split()


def exact_brute(rows):
    groups = defaultdict(list)
    for i, t in rows:
        groups[ascii_lower(t)].append(i)
    return sorted((i, max(groups[ascii_lower(t)]), len(groups[ascii_lower(t)]), i == max(groups[ascii_lower(t)]), hashlib.sha256(ascii_lower(t)).hexdigest()) for i, t in rows)


def shingles(text, width=5):
    w = ascii_lower(text).split()
    if not w:
        return frozenset()
    return frozenset([tuple(w)]) if len(w) < width else frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1))


def near_brute(rows, percent=80):
    sets = {i: shingles(t) for i, t in rows}
    ids, part = sorted(sets), {i: i for i in sets}

    def find(x):
        while part[x] != x:
            x = part[x]
        return x

    for k, a in enumerate(ids):
        for b in ids[:k]:
            x, y = sets[a], sets[b]
            if x and y and min(len(x), len(y)) * 100 >= percent * max(len(x), len(y)):
                shared = len(x & y)
                if 100 * shared >= percent * (len(x) + len(y) - shared):
                    p, q = sorted((find(a), find(b)))
                    part[q] = p
    return {i: (len(sets[i]), find(i)) for i in ids}


def repeats_brute(rows, window=35):
    counts = Counter(tuple(w[k : k + window]) for w in (words_of(t) for _, t in rows) for k in range(len(w) - window + 1))
    out = {}
    for i, t in rows:
        w = words_of(t)
        hit = [False] * len(w)
        for k in range(len(w) - window + 1):
            if counts[tuple(w[k : k + window])] > 1:
                hit[k : k + window] = [True] * window
        out[i] = (len(w), sum(hit), b" ".join(x for x, h in zip(w, hit) if not h).decode())
    return out


EDGES = [(1, None), (2, ""), (3, "   \t\n"), (4, "one"), (5, "ONE"), (6, "one two three four five"), (7, "One Two Three Four Five"), (8, "é É one"), (9, "é é one"), (10, "a b c d e f g h"), (11, "x" * 200_000), (12, "x" * 200_000)]


def test_exact_edges(docs_of):
    got = exact_duplicates(docs_of(EDGES)).collect()
    assert sorted((r.doc_id, r.keep_id, r.group_size, r.kept, r.text_sha256) for r in got) == exact_brute(EDGES)
    assert exact_duplicates(docs_of([])).collect() == []


def test_exact_runs_over_many_partitions(spark, docs_of):
    rows = [(i, "Same text") for i in range(400)] + [(1000 + i, f"text {i % 50}") for i in range(300)] + [(5000, "zz")]
    got = exact_duplicates(docs_of(rows).repartition(7)).collect()
    assert sorted((r.doc_id, r.keep_id, r.group_size, r.kept, r.text_sha256) for r in got) == exact_brute(rows)


def test_near_equals_brute_force(documents):
    rows = [(r.doc_id, r.text) for r in documents.select("doc_id", "text").collect()]
    got = near_dedup.near_duplicates(documents, percent=85).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == near_brute(rows, 85)
    assert all(r.kept == (r.doc_id == r.component_id) for r in got) and len(got) == len(rows)


def test_near_edges(docs_of):
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dedup.near_duplicates(docs_of(EDGES)).collect()}
    assert got == near_brute(EDGES)
    assert near_dedup.near_duplicates(docs_of([])).collect() == []


def test_near_hot_group_of_stars(docs_of, monkeypatch):
    """Many copies that are each near a base but not near each other, and passages shared by different texts."""
    draw = random.Random(3)
    base = [f"w{draw.randrange(10**6)}" for _ in range(120)]
    rows = [(0, " ".join(base))]
    for i in range(1, 150):
        text = list(base)
        for _ in range(draw.choice([1, 2, 2, 3, 4])):
            text[draw.randrange(len(text))] = f"e{draw.randrange(10**6)}"
        rows.append((i, " ".join(text)))
    rows += [(1000 + i, " ".join(base[:60] + [f"u{draw.randrange(10**6)}" for _ in range(60)])) for i in range(60)]
    monkeypatch.setattr(near_dedup, "PART_CLASSES", 40)
    for percent in (80, 85):
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dedup.near_duplicates(docs_of(rows), percent=percent).collect()}
        assert got == near_brute(rows, percent)


def test_registers_estimate_similarity():
    draw = np.random.default_rng(1)
    for share in (0.5, 0.85, 0.95):
        both = draw.integers(0, 1 << 63, 4000, dtype=np.uint64)
        k = int(4000 * share)
        a, b = both, np.concatenate([both[:k], draw.integers(0, 1 << 63, 4000 - k, dtype=np.uint64)])
        sketch = near_dedup.registers(np.concatenate([np.unique(a), np.unique(b)]), np.array([0, len(np.unique(a)), len(np.unique(a)) + len(np.unique(b))]))
        want = k / (8000 - k)
        assert abs((sketch[0] == sketch[1]).mean() - want) < 0.13


def test_components(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (103, 101), (200, 200)], "a long, b long")
    got = {r.node: r.component for r in components(links).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100, 103: 100}


@pytest.mark.parametrize("part_rows", [512, 2])
def test_substrings_equal_brute_force(documents, part_rows):
    rows = [(r.doc_id, r.text) for r in documents.select("doc_id", "text").collect()]
    got = substring_dedup.without_repeats(documents, part_rows=part_rows)
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept) for r in got.collect()} == repeats_brute(rows)


def test_substring_edges(docs_of):
    passage = " ".join(f"p{i}" for i in range(35))
    rows = [*EDGES, (20, passage), (21, f"before {passage} after"), (22, " ".join(["tick"] * 80)), (23, f"{passage} middle {passage}"), (24, " ".join(f"p{i}" for i in range(34))), (25, "a b c\u0085d " * 3)]
    got = substring_dedup.without_repeats(docs_of(rows), keep=("source",)).collect()
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept) for r in got} == repeats_brute(rows)
    assert {r.source for r in got} == {"x"}
    assert substring_dedup.without_repeats(docs_of([])).collect() == []


def doubled(length):
    """Two words over ab of which each is the other's complement; polynomials modulo powers of two confuse them."""
    word = "a"
    while len(word) < length:
        word += word.translate(str.maketrans("ab", "ba"))
    return word, word.translate(str.maketrans("ab", "ba"))


def prose(seed, words=60):
    draw = random.Random(seed)
    return [f"w{draw.randrange(10**6)}" for _ in range(words)]


def test_long_words_are_told_apart(docs_of):
    one, two = doubled(1024)
    words = prose(1, 35)
    rows = [(1, " ".join([one, *words[1:]])), (2, " ".join([two, *words[1:]])), (3, one), (4, two)]
    got = substring_dedup.without_repeats(docs_of(rows)).collect()
    assert {r.doc_id: r.n_removed for r in got} == {1: 0, 2: 0, 3: 0, 4: 0}
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dedup.near_duplicates(docs_of(rows)).collect()}
    assert got == near_brute(rows)


def test_substrings_of_words_of_any_length(docs_of):
    draw = random.Random(8)
    bag = ["".join(draw.choice("ab") for _ in range(draw.choice([1, 2, 7, 8, 9, 15, 16, 17, 40, 5000]))) for _ in range(60)]
    rows = [(i, draw.choice([" ", "\t", "\n "]).join(draw.choice(bag[:3]) if i % 3 else draw.choice(bag) for _ in range(draw.choice([30, 36, 80])))) for i in range(40)]
    rows += [(100 + i, rows[i][1] + " tail") for i in range(0, 40, 5)]
    for part_rows in (512, 2):
        got = substring_dedup.without_repeats(docs_of(rows), part_rows=part_rows).collect()
        assert {r.doc_id: (r.n_words, r.n_removed, r.kept) for r in got} == repeats_brute(rows)


@pytest.mark.parametrize("bits", [0, 2])
def test_windows_of_equal_fingerprints_are_compared(monkeypatch, bits):
    """Inside a part nothing rests on fingerprints: with almost none, the result is the same."""
    draw = random.Random(2)
    texts = [" ".join(draw.choice("abc") for _ in range(12)).encode() for _ in range(50)]
    monkeypatch.setattr(substring_dedup, "window_hashes", lambda words, width: words & np.uint64((1 << bits) - 1))
    rows = pa.table({"words": pa.array(texts, pa.binary())})
    windows = substring_dedup._Windows(rows, 6)
    order, same = windows.order(np.zeros(len(windows.at), np.uint64))
    again = {int(x) for k in np.flatnonzero(same) for x in (order[k], order[k + 1])}
    every = [tuple(t.split()[k : k + 6]) for t in texts for k in range(7)]
    counts = Counter(every)
    assert again == {k for k, w in enumerate(every) if counts[w] > 1}


def test_near_rows_that_share_an_id(docs_of):
    a, b = prose(1), prose(2)
    near = [[*x[:-1], "other"] for x in (a, b)]
    rows = [(1, " ".join(a)), (1, " ".join(b)), (2, " ".join(near[0])), (3, " ".join(near[1])), (4, " ".join(prose(3))), (1, "")]
    got = sorted((r.doc_id, r.n_shingles, r.component_id, r.kept) for r in near_dedup.near_duplicates(docs_of(rows)).collect())
    assert got == [(1, 0, 1, True), (1, 56, 1, True), (1, 56, 1, True), (2, 56, 1, False), (3, 56, 1, False), (4, 56, 4, True)]


def test_near_rows_without_an_id(docs_of):
    a, b, c = prose(1), prose(2), prose(3)
    rows = [(None, " ".join(a)), (7, " ".join([*a[:-1], "other"])), (None, " ".join(b)), (None, " ".join([*b[:-1], "other"])), (None, " ".join(c)), (None, None)]
    got = near_dedup.near_duplicates(docs_of(rows)).collect()
    assert sorted((r.doc_id or 0, r.component_id or 0, r.kept) for r in got) == [(0, 0, False), (0, 0, True), (0, 0, True), (0, 0, True), (0, 7, False), (7, 7, True)]


@pytest.mark.parametrize("part_rows", [512, 1])
def test_substrings_of_repeated_and_missing_ids(docs_of, part_rows):
    a, b, c, d = (" ".join(prose(k, 40)) for k in range(4))
    rows = [(1, a), (1, f"{b} own"), (None, a), (None, b), (2, c), (2, c), (None, d), (None, None), (3, " ".join(prose(9)))]
    got = substring_dedup.without_repeats(docs_of(rows), part_rows=part_rows, keep=("text",)).collect()
    assert sorted((r.doc_id or 0, r.text or "", r.n_words, r.n_removed) for r in got) == sorted((i or 0, t or "", len((t or "").split()), 0 if t is None or t in (d, rows[-1][1]) else 40) for i, t in rows)


def test_words_hash_alike_wherever_they_stand():
    data = np.frombuffer(b"alpha beta alpha\tgamma beta", np.uint8)
    starts, stops, first = word_spans(data, np.array([0, len(data)]))
    h = word_hashes(data, starts, stops)
    assert h[0] == h[2] and h[1] == h[4] and len(set(h.tolist())) == 3 and first.tolist() == [0, 5]
