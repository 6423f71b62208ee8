"""Substring deduplication by super-k-mer partitioning.

A window is a number of consecutive words of one text. Its minimiser is the least hash of the shorter word grams
inside it; consecutive windows that share their minimiser form a super-k-mer, which travels as one packed string to
the minimiser's bucket. Equal windows have equal minimisers, so a bucket holds every place of its windows. There the
windows are sorted and counted.

Minimisers are counted first, without text: a super-k-mer whose minimiser is found once cannot repeat and stays at
home. Inside a part of a bucket, windows are sorted by fingerprints and neighbours compared word by word. Buckets of
very common minimisers are dealt into parts of bounded size; what is found once in its part is compared across the
parts by BLAKE2b digests of the windows' words, whose counts are pre-aggregated.

A row is known by its id and a hash of its text, so null and repeated ids need no special care.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopframe.llm.common import mixed, row_chunks, staged, string_buffers, text_chunks, trimmed, window_hashes, word_codes, word_hashes, word_spans

WINDOW = 35
GRAM = 6
#: low bits of a gram's rank that hold its place
PLACE_MASK = (1 << 28) - 1
#: super-k-mers of one minimiser that one part of its bucket takes
PART_ROWS = 512


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Least of every ``width`` neighbours, by first place; shorter by ``width - 1``."""
    span = 1
    while span * 2 <= width:
        x = np.minimum(x[:-span], x[span:])
        span *= 2
    if rest := width - span:
        x = np.minimum(x[:-rest], x[rest:])
    return x


def super_kmers(words: np.ndarray, first: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Minimiser, row, first window and number of windows of every super-k-mer of word-hash sequences."""
    empty = np.zeros(0, np.int64)
    if len(words) < window:
        return np.zeros(0, np.uint64), empty, empty, empty
    grams = mixed(window_hashes(words, gram)[: len(words) - gram + 1])
    # the least hash, leftmost first: a repeat inside one text then stands at two places
    ranked = grams & np.uint64(~PLACE_MASK % (1 << 64)) | np.arange(len(grams), dtype=np.uint64)
    least = (_sliding_min(ranked, window - gram + 1) & np.uint64(PLACE_MASK)).astype(np.int64)  # by first word of a window
    row = np.repeat(np.arange(len(first) - 1), np.diff(first))
    own = row[: len(least)] == row[window - 1 :]
    place = np.flatnonzero(own)
    if not len(place):
        return np.zeros(0, np.uint64), empty, empty, empty
    chosen, at = least[place], row[place]
    begins = np.ones(len(place), bool)
    begins[1:] = (chosen[1:] != chosen[:-1]) | (at[1:] != at[:-1])
    starts = np.flatnonzero(begins)
    return grams[chosen[starts]], at[starts], place[starts] - first[at[starts]], np.diff(np.append(starts, len(place)))


def _minimisers(window: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low, high, data, offsets in text_chunks(batch.column(2)):
                starts, stops, first = word_spans(data, offsets)
                value, row, _, _ = super_kmers(word_hashes(data, starts, stops), first, window, gram)
                # a row of the text table may hold a minimiser several times
                order = np.lexsort((value, row))
                value, row = value[order], row[order]
                fresh = np.ones(len(value), bool)
                fresh[1:] = (value[1:] != value[:-1]) | (row[1:] != row[:-1])
                at = np.flatnonzero(fresh)
                own = [batch.column(k).slice(low, high - low).take(pa.array(row[at])) for k in (0, 1)]
                yield pa.RecordBatch.from_arrays([pa.array(value[at].view(np.int64)), *own, pa.array(np.diff(np.append(at, len(value))).astype(np.int32))], ["mini", "id", "print", "times"])

    return run


def _compressed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts as zstd frames, for the way through a shuffle."""
    own = zstandard.ZstdCompressor(level=1)
    for batch in batches:
        for low, high, data, offsets in text_chunks(batch.column(2)):
            raw, ends = data.tobytes(), offsets.tolist()
            frames = pa.array([own.compress(raw[a:b]) for a, b in zip(ends[:-1], ends[1:])], pa.binary())
            part = batch.slice(low, high - low)
            yield pa.RecordBatch.from_arrays([*part.columns[:2], frames, *part.columns[3:]], batch.schema.names)


def _expanded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches with plain texts again, a few MB at a time."""
    own = zstandard.ZstdDecompressor()
    for batch in batches:
        _, offsets = string_buffers(batch.column(2))
        for low, high in row_chunks(offsets, 1 << 20):
            part = batch.slice(low, high - low)
            texts = pa.array([own.decompress(x.as_py()) for x in part.column(2)], pa.binary()).view(pa.string())
            yield pa.RecordBatch.from_arrays([*part.columns[:2], texts, *part.columns[3:]], batch.schema.names)


def _packed(window: int, gram: int):
    """Super-k-mers whose minimisers are among the row's repeated ones, as packed strings of words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _expanded(batches):
            for low, high, data, offsets in text_chunks(batch.column(2)):
                starts, stops, first = word_spans(data, offsets)
                value, row, begin, runs = super_kmers(word_hashes(data, starts, stops), first, window, gram)
                lists = batch.column(3).slice(low, high - low)
                minis = lists.flatten()
                sizes = np.diff(np.asarray(lists.offsets))[: high - low]
                keys = np.asarray(minis.field(0)).view(np.uint64)
                parts = np.asarray(minis.field(1))
                owner = np.repeat(np.arange(high - low), sizes)
                # (row, minimiser) pairs of both sides, met by sorting
                both = mixed(value ^ mixed(row.astype(np.uint64)))
                wanted = mixed(keys ^ mixed(owner.astype(np.uint64)))
                order = np.argsort(wanted, kind="stable")
                near = np.minimum(np.searchsorted(wanted[order], both), max(0, len(wanted) - 1))
                hit = order[near] if len(order) else np.zeros(len(both), np.int64)
                keep = np.flatnonzero((keys[hit] == value) & (owner[hit] == row)) if len(order) else np.zeros(0, np.int64)
                value, row, begin, runs, cut = value[keep], row[keep], begin[keep], runs[keep], parts[hit[keep]]
                word0 = first[row] + begin
                a, b = starts[word0], stops[word0 + runs + window - 2]
                raw = data.tobytes()
                texts = [raw[i:j] for i, j in zip(a.tolist(), b.tolist())]
                own = [batch.column(k).slice(low, high - low).take(pa.array(row)) for k in (0, 1)]
                yield pa.RecordBatch.from_arrays([pa.array(value.view(np.int64)), pa.array(cut.astype(np.int32)), *own, pa.array(begin.astype(np.int64)), pa.array(texts, pa.binary())], ["mini", "parts", "id", "print", "begin", "words"])

    return run


class _Windows:
    """The windows of packed strings: two fingerprints, the first word of each, and its string."""

    def __init__(self, rows: pa.Table, window: int):
        texts = rows.column("words").combine_chunks() if isinstance(rows.column("words"), pa.ChunkedArray) else rows.column("words")
        offsets = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
        self.data = np.frombuffer(texts.buffers()[2], np.uint8)[offsets[0] : offsets[-1]]
        self.starts, self.stops, first = word_spans(self.data, offsets - offsets[0])
        self.window = window
        row = np.repeat(np.arange(len(texts)), np.diff(first))
        self.at = np.flatnonzero(row[: max(0, len(row) - window + 1)] == row[window - 1 :]) if len(row) >= window else np.zeros(0, np.int64)
        self.row = row[self.at]
        self.one, self.two = (window_hashes(word_hashes(self.data, self.starts, self.stops, seed), window)[self.at] for seed in (0, 1))

    def order(self, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Windows sorted by ``key`` and words, and which of them equal the one before, word by word."""
        order = np.lexsort((self.two, self.one, key))
        same = self._alike(order, key, self.one, self.two)
        codes = word_codes(self.data, self.starts, self.stops)
        hit = np.flatnonzero(same)
        left, right = self.at[order[hit]], self.at[order[hit + 1]]
        equal = np.ones(len(hit), bool)
        for k in range(self.window):
            equal &= codes[left + k] == codes[right + k]
        if equal.all():
            return order, same
        # other words under the same fingerprints: the words themselves number the windows
        _, name = np.unique(codes[self.at[:, None] + np.arange(self.window)], axis=0, return_inverse=True)
        name = name.ravel()
        order = np.lexsort((name, key))
        return order, self._alike(order, key, name)

    @staticmethod
    def _alike(order: np.ndarray, *columns: np.ndarray) -> np.ndarray:
        return np.logical_and.reduce([c[order][1:] == c[order][:-1] for c in columns])

    def digests(self, some: np.ndarray) -> np.ndarray:
        """Two integers of a cryptographic digest of each of these windows' words."""
        after = np.append(self.starts[1:], len(self.data)) > self.stops  # a separator, which becomes a space
        keep = np.zeros(len(self.data), bool)
        edges = np.zeros(len(self.data) + 1, np.int32)
        np.add.at(edges, self.starts, 1)
        np.add.at(edges, self.stops, -1)
        keep[:] = np.cumsum(edges[:-1]) > 0
        letters = self.data.copy()
        spaces = self.stops[after]
        letters[spaces], keep[spaces] = 32, True
        text = letters[keep].tobytes()
        place = np.concatenate(([0], np.cumsum(keep)))
        low, high = place[self.starts[self.at[some]]], place[self.stops[self.at[some] + self.window - 1]]
        found = b"".join([blake2b(text[a:b], digest_size=16).digest() for a, b in zip(low.tolist(), high.tolist())])
        return np.frombuffer(found, np.int64).reshape(-1, 2)


def _counted(window: int):
    """Sorts each bucket part's windows and counts neighbours. Buckets arrive sorted, and may span batches."""
    names = ["id", "print", "low", "high", "one", "two"]

    def settle(rows: pa.Table) -> Iterator[pa.RecordBatch]:
        windows = _Windows(rows, window)
        at = windows.row
        key = np.asarray(rows.column("mini")).view(np.uint64)[at] ^ mixed(np.asarray(rows.column("part")).astype(np.uint64))[at]
        order, same = windows.order(key)
        again = np.zeros(len(order), bool)
        again[order[1:]] |= same
        again[order[:-1]] |= same
        # windows' words, by their place in the text
        firsts = np.searchsorted(at, np.arange(len(rows)))
        word = np.asarray(rows.column("begin"))[at] + np.arange(len(at)) - firsts[at]
        wide = np.asarray(rows.column("parts"))[at] > 1
        own = [c.combine_chunks() if isinstance(c, pa.ChunkedArray) else c for c in (rows.column("id"), rows.column("print"))]
        hit = np.flatnonzero(again)
        joined = np.ones(len(hit), bool)
        joined[1:] = (np.diff(hit) != 1) | (at[hit][1:] != at[hit][:-1])
        head = np.flatnonzero(joined)
        tail = np.append(head[1:], len(hit)) - 1
        nothing = pa.nulls(len(head), pa.int64())
        if len(head):
            which = pa.array(at[hit[head]])
            yield pa.RecordBatch.from_arrays([*(c.take(which) for c in own), pa.array(word[hit[head]]), pa.array(word[hit[tail]] + window), nothing, nothing], names)
        # every window of a bucket in several parts is told once by each part, and each single one with its place
        loose = np.flatnonzero(wide & ~again)
        sure = order[np.append(True, ~same)] if len(order) else order
        sure = sure[(wide & again)[sure]]
        if len(loose):
            which, told = pa.array(at[loose]), windows.digests(loose)
            yield pa.RecordBatch.from_arrays([*(c.take(which) for c in own), pa.array(word[loose]), pa.array(word[loose] + window), pa.array(told[:, 0]), pa.array(told[:, 1])], names)
        if len(sure):
            gone, told = pa.nulls(len(sure), pa.int64()), windows.digests(sure)
            yield pa.RecordBatch.from_arrays([gone, gone, gone, gone, pa.array(told[:, 0]), pa.array(told[:, 1])], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None
        for batch in batches:
            rows = pa.Table.from_batches([batch])
            rows = rows if held is None else pa.concat_tables([held, rows])
            held = None
            mini, part = np.asarray(rows.column("mini")), np.asarray(rows.column("part"))
            last = np.flatnonzero((mini != mini[-1]) | (part != part[-1])) if len(rows) else []
            cut = int(last[-1]) + 1 if len(last) else 0
            if cut:
                for low in range_cuts(mini[:cut], part[:cut]):
                    yield from settle(rows.slice(low[0], low[1] - low[0]).combine_chunks())
            held = rows.slice(cut)
        if held is not None and len(held):
            yield from settle(held.combine_chunks())

    return run


def range_cuts(mini: np.ndarray, part: np.ndarray, rows: int = 4000) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``rows`` rows that end where a bucket part ends."""
    ends = np.append(np.flatnonzero((mini[1:] != mini[:-1]) | (part[1:] != part[:-1])) + 1, len(mini))
    low = 0
    while low < len(mini):
        k = int(np.searchsorted(ends, low + rows))
        high = int(ends[min(k, len(ends) - 1)])
        yield low, high
        low = high


def _cleaned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in _expanded(batches):
        for low in range(0, len(batch), 256):
            part = batch.slice(low, 256)
            out: list[list] = [[], [], []]
            for text, spans in zip(part.column(2).fill_null("").to_pylist(), part.column(3).to_pylist()):
                words = text.encode("utf-8").split()
                total = len(words)
                if spans:
                    covered = np.zeros(total + 1, np.int32)
                    lows, highs = np.array([(s["low"], s["high"]) for s in spans], np.int64).T
                    np.add.at(covered, lows, 1)
                    np.add.at(covered, highs, -1)
                    words = [words[i] for i in np.flatnonzero(np.cumsum(covered[:-1]) == 0).tolist()]
                out[0].append(total)
                out[1].append(total - len(words))
                out[2].append(b" ".join(words).decode("utf-8"))
            columns = [part.column(1), pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.string())]
            yield pa.RecordBatch.from_arrays([*columns, *part.columns[4:]], ["doc_id", "n_words", "n_removed", "kept", *part.schema.names[4:]])


def without_repeats(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, id_col: str = "doc_id", text_col: str = "text", part_rows: int = PART_ROWS, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, n_words, n_removed, kept (the words that stay, joined by a space) and the columns ``keep`` of every row.

    A word goes if a window over it has words that also start anywhere else, in the same text included; every window
    is judged on the input. Words are runs of bytes other than space and tab to carriage return, unchanged. Null and
    empty texts have no words; texts shorter than a window lose nothing. Every row is a text of its own, whatever its
    id: two rows of one id and text are two places of each of their windows. Null ids stay null.
    """
    doc_id, text = F.col(id_col).cast("long"), F.col(text_col).cast("string")
    row = [F.coalesce(doc_id, F.lit(0)).alias("id"), F.xxhash64(doc_id.isNull(), text).alias("print")]
    slim = docs.select(*row, text.alias("text"))
    minis = slim.mapInArrow(trimmed(_minimisers(window, gram)), "mini long, id long, print long, times int")
    often = minis.groupBy("mini").agg(F.sum("times").alias("n")).where("n > 1")
    common = minis.drop("times").join(often, "mini").groupBy("id", "print").agg(F.collect_set(F.struct("mini", F.ceil(F.col("n") / part_rows).cast("int").alias("parts"))).alias("minis"))
    small = slim.mapInArrow(trimmed(_compressed), "id long, print long, text binary")
    strings = small.join(common, ["id", "print"]).mapInArrow(trimmed(_packed(window, gram)), "mini long, parts int, id long, print long, begin long, words binary")
    part = F.pmod(F.xxhash64("id", "print", "begin"), F.col("parts")).cast("int")
    buckets = strings.withColumn("part", part).repartition("mini", "part").sortWithinPartitions("mini", "part")
    told = staged(buckets.mapInArrow(trimmed(_counted(window)), "id long, print long, low long, high long, one long, two long"))
    loose = told.where("one is not null")
    twice = loose.groupBy("one", "two").agg(F.count("*").alias("n")).where("n > 1")
    across = loose.where("id is not null").join(twice, ["one", "two"], "left_semi")
    spans = told.where("one is null").unionByName(across).groupBy("id", "print").agg(F.collect_set(F.struct("low", "high")).alias("spans"))
    own = [F.col(c).alias(f"kept_{i}") for i, c in enumerate(keep)]
    extra = "".join(f", kept_{i} {docs.schema[c].dataType.simpleString()}" for i, c in enumerate(keep))
    wide = docs.select(*row, text.alias("text"), doc_id.alias("doc_id"), *own).mapInArrow(trimmed(_compressed), f"id long, print long, text binary, doc_id long{extra}")
    found = wide.join(spans, ["id", "print"], "left").select("id", "doc_id", "text", "spans", *(f"kept_{i}" for i in range(len(keep))))
    found = found.mapInArrow(trimmed(_cleaned), f"doc_id long, n_words long, n_removed long, kept string{extra}")
    return found.select("doc_id", "n_words", "n_removed", "kept", *(F.col(f"kept_{i}").alias(c) for i, c in enumerate(keep)))
