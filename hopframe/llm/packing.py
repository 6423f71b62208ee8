"""Sum-of-squares packing of token sequences.

A document becomes its token ids and an end mark; longer ones are cut so that all pieces but the first are full.
Full pieces are sequences of their own. The others are dealt into blocks of bounded size; in a block each piece is
placed, longest first, where the squared counts of open bins per residual gap become smallest. The pieces of bins
that stay open are packed again by the same rule, a few times in their block and then over several blocks together,
where bins with a growing gap are let go.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator
from functools import cached_property, lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopframe.llm.common import staged, trimmed

CAPACITY = 1024
END_ID = 2
BLOCK_ROWS = 100_000
#: blocks whose left-over pieces are packed together
BLOCKS_TOGETHER = 8
#: gap up to which a bin stays closed, in each round over a block, and over several blocks together
IN_BLOCK, TOGETHER = (0, 0, 0), (0, 2, 4, 8, 16, 64, CAPACITY)


def sum_of_squares(sizes: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of every item, in order, by the sum-of-squares rule."""
    counts = np.zeros(capacity + 1, np.int64)  # open bins by gap; gap 0 is closed and counts nothing
    stacks: list[list[int]] = [[] for _ in range(capacity + 1)]
    bins, places = np.empty(len(sizes), np.int64), np.empty(len(sizes), np.int64)
    opened = 0
    never = np.int64(1) << 40
    for i, size in enumerate(sizes.tolist()):
        own = counts[size:]
        change = 2 * (counts[: capacity + 1 - size] - own) + 2  # by gap, from ``size`` upwards
        change[0] = 1 - 2 * own[0]
        change[own == 0] = never
        k = int(change.argmin())
        fresh = 2 * counts[capacity - size] + 1 if size < capacity else 0
        if change[k] <= fresh:
            gap = size + k
            target = stacks[gap].pop()
            counts[gap] -= 1
        else:
            gap, target = capacity, opened
            opened += 1
        bins[i], places[i] = target, capacity - gap
        rest = gap - size
        if rest:
            stacks[rest].append(target)
            counts[rest] += 1
    return bins, places


def rounds(sizes: np.ndarray, gaps: tuple[int, ...], capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of items in falling order, by the rule applied again to what bins with larger gaps held.

    Items whose bin was never closed have bin -1.
    """
    bins, places = np.full(len(sizes), -1, np.int64), np.zeros(len(sizes), np.int64)
    left, opened = np.arange(len(sizes)), 0
    for gap in gaps:
        own, at = sum_of_squares(sizes[left], capacity)
        closed = (np.bincount(own, sizes[left], minlength=1) >= capacity - gap)[own] if len(left) else np.zeros(0, bool)
        bins[left[closed]], places[left[closed]] = opened + own[closed], at[closed]
        opened += int(own.max()) + 1 if len(own) else 0
        left = left[~closed]
    return bins, places


class JsonTokenizer:
    """Ids as the tokenizers library gives them for a JSON file, without special tokens.

    A plain byte-level BPE whose ids follow its merges is the same as a rank table, which is encoded faster; any
    other file, and a text that the fast encoder refuses, goes through the library itself.
    """

    def __init__(self, path: str, pattern: str):
        self.path = path
        self.fast = self._ranked(path, pattern)

    @cached_property
    def library(self):
        """The library's own tokenizer, some 100 MB, where it is needed."""
        from tokenizers import Tokenizer

        own = Tokenizer.from_file(self.path)
        own.encode_special_tokens = True  # the special strings are ordinary text
        return own

    @staticmethod
    def _ranked(path: str, pattern: str) -> tiktoken.Encoding | None:
        with open(path, encoding="utf-8") as lines:
            raw = json.load(lines)
        model, split = raw["model"], raw.get("pre_tokenizer") or {}
        plain = model.get("type") == "BPE" and not raw.get("normalizer") and split.get("type") == "ByteLevel" and not split.get("add_prefix_space") and split.get("use_regex")
        plain = plain and not any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges"))
        if not plain:
            return None
        merges = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        ids = [model["vocab"].get(a + b) for a, b in merges]
        if None in ids or any(x >= y for x, y in zip(ids, ids[1:])) or len(model["vocab"]) != len(ids) + 256:
            return None
        shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
        byte = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(sorted(set(range(256)) - set(shown)))}
        ranks = {bytes(byte[c] for c in token): i for token, i in model["vocab"].items()}
        return tiktoken.Encoding("json", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})

    def __call__(self, text: str) -> np.ndarray:
        if self.fast is not None:
            try:
                return self.fast.encode_to_numpy(text, disallowed_special=())
            except BaseException as e:  # its Rust code may panic on extreme texts, which is no Exception
                if isinstance(e, KeyboardInterrupt | SystemExit | MemoryError):
                    raise
        return np.array(self.library.encode(text, add_special_tokens=False).ids, np.uint32)


@lru_cache(maxsize=2)
def tokenizer(path: str, pattern: str) -> JsonTokenizer:
    return JsonTokenizer(path, pattern)


def _pieces(path: str, pattern: str, capacity: int, end_id: int):
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = tokenizer(path, pattern)
        for batch in batches:
            for low in range(0, len(batch), 512):
                part = batch.slice(low, 512)
                out: list[list[int]] = [[], [], [], [], []]
                for doc_id, text in zip(part.column(0).to_pylist(), part.column(1).fill_null("").to_pylist()):
                    ids = encode(text).astype("<u4").tobytes() + end
                    n, start, piece = len(ids) // 4, 0, 0
                    length = (n - 1) % capacity + 1
                    while start < n:
                        for column, value in zip(out, (doc_id, piece, start, length, zlib.crc32(ids[4 * start : 4 * (start + length)]))):
                            column.append(value)
                        start, piece, length = start + length, piece + 1, capacity
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return run


def tokenised_pieces(docs: DataFrame, tokenizer_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every piece of every row. Null and empty texts are their end mark.

    ``pattern`` must cut a text as the tokenizer's own pre-tokenizer does.
    """
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return slim.mapInArrow(trimmed(_pieces(tokenizer_path, pattern, capacity, end_id)), "doc_id long, piece long, start long, length long, ids_crc32 long")


def packed(pieces: DataFrame, capacity: int = CAPACITY, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """``pieces`` (any columns with an int column ``length``) with sequence_id and offset.

    Repeated rows are packed each for itself; an empty table gives an empty result. ``sequence_id`` and ``offset``
    of the input, if any, are replaced.
    """
    pieces = staged(pieces.drop("sequence_id", "offset").withColumn("row_id", F.monotonically_increasing_id()))
    whole = pieces.where(F.col("length") >= capacity).withColumn("sequence_id", -1 - F.col("row_id")).withColumn("offset", F.lit(0).cast("long"))
    short = pieces.where(F.col("length") < capacity)
    blocks = max(1, -(-short.count() // block_rows))

    def place(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["length", "row_id"], ascending=[False, True], kind="stable")
        bins, offsets = rounds(frame["length"].to_numpy(np.int64), IN_BLOCK, capacity)
        return frame.assign(bin=bins, offset=offsets)

    def gather(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["length", "row_id"], ascending=[False, True], kind="stable")
        bins, offsets = rounds(frame["length"].to_numpy(np.int64), (*TOGETHER, capacity), capacity)
        return frame.assign(bin=bins, offset=offsets)

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema.fields)
    dealt = short.withColumn("block", F.pmod(F.xxhash64("row_id"), F.lit(blocks)))
    first = staged(dealt.groupBy("block").applyInPandas(place, f"{kinds}, block long, bin long, offset long"))
    closed = first.where("bin >= 0").withColumn("sequence_id", F.col("block") * (1 << 33) + F.col("bin")).drop("block", "bin")
    left = first.where("bin < 0").withColumn("block", F.floor(F.col("block") / BLOCKS_TOGETHER))
    again = left.groupBy("block").applyInPandas(gather, f"{kinds}, block long, bin long, offset long")
    again = again.withColumn("sequence_id", (F.col("block") * 2 + 1) * (1 << 32) + F.col("bin")).drop("block", "bin")
    return whole.unionByName(closed).unionByName(again).drop("row_id")
