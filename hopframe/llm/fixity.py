"""Fixity audit of WARC archives with Merkle trees.

Every record has a digest over its bytes and its place in the file; ordered offset ranges have digests over their
bounds and their parts, up to a root for each archive file and one root over all files. Leaves, ranges and roots are
marked apart, so that no node can stand for one of another kind. Two replicas are compared at the root, and only
branches that differ are followed down to the damaged records.

Records are compared by file and place: a record that is inserted or lost, or changes its length, moves all later ones
of its file, which then count as corrupt too.
"""

from __future__ import annotations

import gzip
import hashlib
import logging
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from hopframe.llm.common import staged

log = logging.getLogger(__name__)

#: page ids of one archive file, and branches of a tree node
FILE_IDS, FANOUT = 128, 16


def record_text(page_id: Column, url: Column, html: Column) -> Column:
    """A WARC record without its closing empty lines. Line breaks in a URL are percent-encoded, lest they end its header."""
    url, html = F.coalesce(url, F.lit("")), F.coalesce(html, F.lit(""))
    url = F.replace(F.replace(url, F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A"))
    number = F.coalesce(page_id.cast("string"), F.lit(""))
    return F.concat(F.lit("WARC/1.1\r\nWARC-Type: resource\r\nWARC-Target-URI: "), url, F.lit("\r\nWARC-Record-ID: <urn:page:"), number, F.lit(">\r\nContent-Type: text/html\r\nContent-Length: "), F.octet_length(html).cast("string"), F.lit("\r\n\r\n"), html)


RECORD_END = "\r\n\r\n"


def archive(pages: DataFrame) -> DataFrame:
    """page_id, file, place, first (byte offset in the file), length, record of every page.

    A file holds the pages of ``FILE_IDS`` consecutive ids, ordered by id, url and content; null ids are in file -1,
    null urls and contents count as empty. Repeated rows are records of their own. Other columns are ignored.
    """
    rows = pages.select("page_id", record_text(F.col("page_id"), F.col("url"), F.col("html")).alias("record"))
    rows = rows.withColumn("file", F.coalesce(F.floor(F.col("page_id") / FILE_IDS), F.lit(-1))).withColumn("length", (F.octet_length("record") + len(RECORD_END)).cast("long"))
    order = W.partitionBy("file").orderBy("page_id", "record")
    return rows.select("page_id", "file", (F.row_number().over(order) - 1).cast("long").alias("place"), (F.sum("length").over(order.rowsBetween(W.unboundedPreceding, 0)) - F.col("length")).alias("first"), "length", "record")


def write_archive(records: DataFrame, path: str) -> None:
    """The archive as compressed WARC text, a folder for each file (``file=...``)."""
    rows = records.select("file", "place", "record").repartition("file").sortWithinPartitions("file", "place")
    rows.select("file", "record").write.partitionBy("file").option("lineSep", RECORD_END).option("compression", "gzip").option("zlib.compress.level", "BEST_SPEED").text(path)


def read_archive(spark, path: str, whole: bool = True, change: Callable[[bytes], bytes] | None = None) -> DataFrame:
    """page_id, file, place, first, length, record and record_sha256 of what ``write_archive`` wrote.

    Records are cut by their own lengths. Without ``whole`` there are digests only. ``change`` is a drill: it gets every
    record's bytes and gives what is to be read in their place, of the same length.
    """
    names = ["page_id", "file", "place", "first", "length", *(["record"] if whole else []), "record_sha256"]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for file, content in zip(frame["file"], frame["content"]):
                content = gzip.decompress(content) if content[:2] == b"\x1f\x8b" else content
                at, place, out = 0, 0, []
                while at < len(content):
                    head = content.index(b"\r\n\r\n", at)
                    size = int(content[content.rindex(b"Content-Length: ", at, head) + 16 : head])
                    named = content.rindex(b"<urn:page:", at, head) + 10
                    stop = head + 4 + size
                    record = content[at:stop] if change is None else change(content[at:stop])
                    told = [record.decode("utf-8")] if whole else []
                    out.append((content[named : content.index(b">", named)].decode(), file, place, at, stop + len(RECORD_END) - at, *told, hashlib.sha256(record).hexdigest()))
                    at, place = stop + len(RECORD_END), place + 1
                yield pd.DataFrame(out, columns=names)

    raw = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "part-*").load(path)
    files = raw.select(F.regexp_extract("path", "file=(-?[0-9]+)", 1).cast("long").alias("file"), "content")
    found = files.mapInPandas(run, f"page_id string, file long, place long, first long, length long, {'record string, ' if whole else ''}record_sha256 string")
    return found.withColumn("page_id", F.when(F.col("page_id") != "", F.col("page_id")).cast("long"))


def _digest(records: DataFrame) -> Column:
    """The record's digest, read or taken."""
    return F.col("record_sha256") if "record_sha256" in records.columns else F.sha2(F.col("record").cast("binary"), 256)


def tree(records: DataFrame) -> DataFrame:
    """All nodes of the tree over (file, place, first, length, record or record_sha256): kind, level, file, place, digest.

    Kinds are 'record', 'range' (in the tree of one file) and 'root' (in that over the files, whose level counts on).
    """
    stop = F.col("first") + F.col("length")
    leaf = F.concat_ws("|", F.lit("record"), "first", stop, _digest(records))
    leaves = staged(records.select("file", "place", "first", stop.alias("stop"), F.sha2(leaf, 256).alias("digest")))
    level, below, nodes = 0, leaves, leaves.select(F.lit("record").alias("kind"), F.lit(0).alias("level"), "file", "place", "digest")
    widest = leaves.agg(F.max("place")).first()[0]
    while widest is not None and (widest > 0 or level == 0):
        level, widest = level + 1, widest // FANOUT
        below = _above(below, ["file"], "place", "range")
        nodes = nodes.unionByName(below.select(F.lit("range").alias("kind"), F.lit(level).alias("level"), "file", "place", "digest"))
    roots = below.where("place = 0").select(F.lit(0).cast("long").alias("place"), "file", "first", "stop", "digest")
    span = leaves.agg(F.max("file"), F.min("file")).first()
    while span[0] is not None:
        level += 1
        roots = _above(roots, ["place"], "file", "root")
        nodes = nodes.unionByName(roots.select(F.lit("root").alias("kind"), F.lit(level).alias("level"), "file", "place", "digest"))
        span = (span[0] // FANOUT, span[1] // FANOUT)
        if span[0] == span[1] or (span[0], span[1]) == (0, -1):  # files below zero keep a root of their own
            break
    return staged(nodes)


def _above(nodes: DataFrame, same: list[str], along: str, kind: str) -> DataFrame:
    """Parents of ordered nodes: the digest of their bounds and of ``FANOUT`` neighbours' digests, in order."""
    up = F.floor(F.col(along) / FANOUT)
    joined = nodes.groupBy(*same, up.alias("up")).agg(F.min("first").alias("first"), F.max("stop").alias("stop"), F.sort_array(F.collect_list(F.struct(along, "digest"))).alias("parts"))
    digest = F.sha2(F.concat_ws("|", F.lit(kind), "first", "stop", F.col("parts.digest")), 256)
    return joined.select(*same, F.col("up").alias(along), "first", "stop", digest.alias("digest"))


def audit(ours: DataFrame, theirs: DataFrame) -> tuple[DataFrame, list[tuple[int, int]]]:
    """Records that differ between two trees: file, place, status; and the (level, nodes compared) of the descent.

    ``status`` is 'corrupt', 'missing' (not in the second tree) or 'extra' (in the second only).
    """
    top = max((t.agg(F.max("level")).first()[0] or 0) for t in (ours, theirs))
    file_top = max((t.where("kind = 'range'").agg(F.max("level")).first()[0] or 0) for t in (ours, theirs))
    suspects, visited = None, []
    for level in range(top, -1, -1):
        a, b = (t.where(F.col("level") == level).select("file", "place", F.col("digest").alias(name)) for t, name in ((ours, "a"), (theirs, "b")))
        if suspects is not None:
            inside = level < file_top
            key = ["file", F.floor(F.col("place") / FANOUT).alias("up")] if inside else [F.floor(F.col("file") / FANOUT).alias("up"), "place"] if level > file_top else [F.floor(F.col("file") / FANOUT).alias("up"), "place"]
            names = ["file", "up"] if inside else ["up", "place"]
            wanted = suspects.select("file", F.col("place").alias("up")) if inside else suspects.select(F.col("file").alias("up"), "place")
            a, b = (x.select("*", [k for k in key if not isinstance(k, str)][0]).join(wanted, names, "left_semi") for x in (a, b))
        met = a.select("file", "place", "a").join(b.select("file", "place", "b"), ["file", "place"], "full")
        compared = staged(met)
        visited.append((level, compared.count()))
        suspects = compared.where(~F.col("a").eqNullSafe(F.col("b")))
        if suspects.isEmpty():
            break
    status = F.when(F.col("b").isNull(), "missing").when(F.col("a").isNull(), "extra").otherwise("corrupt")
    if not visited or visited[-1][0] != 0:  # the roots agree: no record differs
        suspects = suspects.where("false") if suspects is not None else ours.where("false").select("file", "place", F.col("digest").alias("a"), F.col("digest").alias("b"))
    return suspects.select("file", "place", status.alias("status")), visited


def audited(records: DataFrame, replica: DataFrame) -> DataFrame:
    """Every record with its place in the archive, its digest and what the audit says of it.

    The nodes that the descent compared on each level are logged.
    """
    found, visited = audit(tree(records), tree(replica))
    log.info("fixity audit: nodes compared by level %s", visited)
    rows = records.select("page_id", "file", "place", "first", "length", _digest(records).alias("record_sha256"))
    return rows.join(found, ["file", "place"], "left").withColumn("status", F.coalesce("status", F.lit("ok")))
