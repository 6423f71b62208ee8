"""Exact deduplication by content sort.

Texts are normalised (A-Z lower-cased), sampled splitters range-partition them, an external sort places equals
next to each other, and full comparisons of neighbours find the runs of equal texts. The range key is the text's
first bytes, then a hash, then the id: samples stay small, texts with a common head spread, and a run of many
equal texts is cut over several partitions. Runs that touch a partition's border (two in each partition at most)
are put together in a table as large as the number of partitions.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopframe.llm.common import lowered, staged, text_chunks

HEAD_BYTES = 48


def _normalise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch, (first, last, data, offsets) in ((b, c) for b in batches for c in text_chunks(b.column(1))):
        low = lowered(data).tobytes()
        bounds = offsets.tolist()
        texts = [low[a:b] for a, b in zip(bounds[:-1], bounds[1:])]
        digests = [hashlib.sha256(t).digest() for t in texts]
        yield pa.RecordBatch.from_arrays(
            [batch.column(0).slice(first, last - first), pa.array([t[:HEAD_BYTES] for t in texts], pa.binary()), pa.array([int.from_bytes(d[:8], "little", signed=True) for d in digests], pa.int64()), pa.array(digests, pa.binary()), pa.array(texts, pa.binary())],
            ["doc_id", "head", "spread", "digest", "body"],
        )


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Numbers the runs of equal neighbours of one sorted partition; one text is held at a time."""
    before, run = None, -1
    for batch in batches:
        numbers = []
        for body in batch.column("body"):
            text = body.as_buffer()
            if before is None or not text.equals(before):
                run += 1
                before = text
            numbers.append(run)
        if before is not None:
            before = pa.py_buffer(before.to_pybytes())  # do not hold on to the batch
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("digest"), batch.column("part"), pa.array(numbers, pa.int64())], ["doc_id", "digest", "part", "run"])


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for every input row: doc_id, keep_id (largest id of the equal texts), group_size, kept, text_sha256.

    Null counts as the empty text. Repeated rows of one id count each in group_size and are all kept or all
    dropped. Other columns are ignored, whatever their names; an empty table gives an empty result.
    """
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    normal = slim.mapInArrow(_normalise, "doc_id long, head binary, spread long, digest binary, body binary")
    ordered = normal.repartitionByRange("head", "spread", "doc_id").sortWithinPartitions("head", "spread", "body", "doc_id")
    rows = staged(ordered.withColumn("part", F.spark_partition_id().cast("long")).select("doc_id", "digest", "part", "body").mapInArrow(_runs, "doc_id long, digest binary, part long, run long"))
    return _stitched(rows)


def _stitched(rows: DataFrame) -> DataFrame:
    """Keeps and counts of each run; runs cut by a partition's border are joined by their digest."""
    runs = rows.groupBy("part", "run").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"), F.first("digest").alias("digest"))
    runs = staged(runs)
    last = runs.groupBy("part").agg(F.max("run").alias("last"))
    border = runs.join(F.broadcast(last), "part").where((F.col("run") == 0) | (F.col("run") == F.col("last")))  # a row for each partition
    cut = border.groupBy("digest").agg(F.max("keep_id").alias("all_keep"), F.sum("group_size").alias("all_size"), F.count("*").alias("pieces")).where("pieces > 1")
    wide = border.join(cut, "digest").select("part", "run", "all_keep", "all_size")
    named = runs.drop("digest").join(F.broadcast(wide), ["part", "run"], "left")  # two rows for each partition at most
    named = named.select("part", "run", F.coalesce("all_keep", "keep_id").alias("keep_id"), F.coalesce("all_size", "group_size").alias("group_size"))
    out = rows.join(named, ["part", "run"])
    return out.select("doc_id", "keep_id", "group_size", (F.col("doc_id").eqNullSafe(F.col("keep_id"))).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"))
