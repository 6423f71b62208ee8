"""Exact byte-level BPE in linear time: longest matches with backtracking over adjacent-token compatibility.

Bytes are mapped to Latin-1 characters so that an Aho-Corasick automaton over the whole vocabulary can scan them.
From the matches that start at a position the longest is tried first; when a token does not go with the one before
it, the next shorter match is taken, or the encoder steps back. Two tokens go together if merging by rank would
keep the border between them, which is found by undoing their merges and remembered for each pair.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from functools import lru_cache
from itertools import islice

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark import SparkFiles
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopframe.llm.common import Remembered

#: token pairs whose compatibility is remembered, some 100 MB in a worker
PAIRS_KEPT = 1_000_000


class BytePairCoder:
    """Encoder and decoder for a rank table ``{token bytes: rank}`` and a splitting pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.split = regex.compile(pattern)
        self.rank = ranks
        self.bytes_of = {i: t for t, i in ranks.items()}
        self.parts: dict[int, tuple[int, int]] = {}
        self.joined: dict[tuple[int, int], int] = {}
        self.fits: dict[tuple[int, int], bool] = {}
        self.shorter: dict[int, int] = {}
        self._learn_merges()
        self.words = Remembered(self._word)

    def _learn_merges(self) -> None:
        """Which two tokens each token is merged from; tokens that no merge yields stay out of the automaton."""
        latin = {t: t.decode("latin-1") for t in self.rank}
        self.automaton = ahocorasick.Automaton()
        for token, rank in sorted(self.rank.items(), key=lambda x: x[1]):
            if len(token) == 1:
                self.parts[rank] = (rank, rank)
                self.automaton.add_word(latin[token], rank)
                continue
            for cut in range(len(token) - 1, 0, -1):
                left, right = self.rank.get(token[:cut]), self.rank.get(token[cut:])
                if left is None or right is None or left not in self.parts or right not in self.parts:
                    continue
                if left < rank and right < rank and self._compatible(left, right):
                    self.parts[rank] = (left, right)
                    self.joined[left, right] = rank
                    self.automaton.add_word(latin[token], rank)
                    break
        self.automaton.make_automaton()
        self.fits.clear()

    def _compatible(self, left: int, right: int) -> bool:
        """Whether merging by rank leaves a border between the two, had they been adjacent."""
        key = left << 32 | right
        if key in self.fits:
            return self.fits[key]
        limit, good = 1 << 62, True
        while True:
            merged = self.joined.get((left, right))
            if merged is not None and merged < limit:
                good = False
                break
            if left > right:
                limit = left
                left = self.parts[left][1]
                if left == limit:
                    limit = right + 1
                    right = self.parts[right][0]
                    if right + 1 == limit:
                        break
            else:
                limit = right + 1
                right = self.parts[right][0]
                if right + 1 == limit:
                    limit = left
                    left = self.parts[left][1]
                    if left == limit:
                        break
        if len(self.fits) >= PAIRS_KEPT:
            self.fits.clear()
        self.fits[key] = good
        return good

    def encode_piece(self, piece: bytes) -> list[int]:
        """Ids of one match of the splitting pattern."""
        whole = self.rank.get(piece)
        if whole is not None:
            return [whole]
        n = len(piece)
        options: list[list[int]] = [[] for _ in range(n)]  # by start, shortest first
        lengths = self.bytes_of
        for end, rank in self.automaton.iter(piece.decode("latin-1")):
            options[end + 1 - len(lengths[rank])].append(rank)
        tried = [len(o) for o in options]
        out: list[int] = []
        at: list[int] = [0]
        open_ends = bytearray(b"\x01") * (n + 1)
        while at[-1] < n:
            here = at[-1]
            while tried[here]:
                tried[here] -= 1
                token = options[here][tried[here]]
                end = here + len(lengths[token])
                if open_ends[end] and (not out or self._compatible(out[-1], token)):
                    out.append(token)
                    at.append(end)
                    break
            else:  # nothing goes from here after this token: never come here again
                open_ends[here] = 0
                tried[here] = len(options[here])
                if not out:
                    raise ValueError(f"the rank table cannot spell {piece[:32]!r}")
                out.pop()
                at.pop()
        return out

    def _word(self, word: str) -> bytes:
        return np.array(self.encode_piece(word.encode("utf-8")), "<u4").tobytes()

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers. Words of long texts are taken in blocks."""
        if len(text) <= 1 << 20:
            return b"".join(map(self.words.__getitem__, self.split.findall(text)))
        matches, out = self.split.finditer(text), []
        while block := [m.group() for m in islice(matches, 50_000)]:
            out.append(b"".join(map(self.words.__getitem__, block)))
        return b"".join(out)

    def decode(self, ids: np.ndarray) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids.tolist()))


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}


@lru_cache(maxsize=2)
def coder(path: str, pattern: str) -> BytePairCoder:
    return BytePairCoder(read_ranks(path), pattern)


def encoded(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", shipped: bool = False) -> DataFrame:
    """doc_id, ids (array<int>) and decoded (binary) for every row. Null counts as empty.

    ``ranks_path`` is a file that every worker can open, or, with ``shipped``, the name of one sent with addFile.
    """
    return _mapped(docs, ranks_path, pattern, id_col, text_col, shipped, False)


def encoded_digests(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", shipped: bool = False) -> DataFrame:
    """As ``encoded``, but number and SHA-256 of the ids and SHA-256 of what they decode to."""
    return _mapped(docs, ranks_path, pattern, id_col, text_col, shipped, True)


def _mapped(docs: DataFrame, ranks_path: str, pattern: str, id_col: str, text_col: str, shipped: bool, digests: bool) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = coder(SparkFiles.get(ranks_path) if shipped else ranks_path, pattern)
        for batch in batches:
            for low in range(0, len(batch), 256):
                part = batch.slice(low, 256)
                ids = [own.encode(t) for t in part.column(1).fill_null("").to_pylist()]
                whole = [own.decode(np.frombuffer(i, "<u4")) for i in ids]
                if digests:
                    columns = [pa.array([len(i) // 4 for i in ids], pa.int64()), pa.array([hashlib.sha256(i).hexdigest() for i in ids]), pa.array([hashlib.sha256(w).hexdigest() for w in whole])]
                    yield pa.RecordBatch.from_arrays([part.column(0), *columns], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
                else:
                    yield pa.RecordBatch.from_arrays([part.column(0), pa.array([np.frombuffer(i, "<u4").astype(np.int32) for i in ids], pa.list_(pa.int32())), pa.array(whole, pa.binary())], ["doc_id", "ids", "decoded"])

    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return slim.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" if digests else "doc_id long, ids array<int>, decoded binary")
