"""Near-duplicate grouping with HyperMinHash registers, register bands and exact confirmation.

1. Every text becomes its set of distinct word shingles (A-Z lower-cased). Equal sets are one class at once.
2. Each set is compressed into registers: per bucket the leading-zero count and the first mantissa bits of the
   bucket's least hash. Bands of registers name candidate buckets; the lower the threshold, the narrower the bands.
3. Among the candidates a shingle held by one class only can be in no intersection. A class with more than
   ``1 - threshold`` of such shingles has no partner at all and leaves, whatever its buckets hold.
4. In each bucket every class meets the best connected one; pairs whose collision-corrected estimate is far below
   the threshold go, the rest are confirmed on the full sets. Groups of copies become one component here, in a
   number of pairs linear in the bucket's size.
5. What is left are pairs of one bucket whose classes are in different components. A shingle that few of these classes
   hold is rare: pairs that share rare shingles are counted by them, in a number linear in the shingles. Any other pair
   can have its common shingles only in its intersection, and is looked at where these still reach the threshold.
   A pair at the threshold shares no bucket with a probability of ``MISS`` at most, and is thrown out by its estimate
   only beyond five deviations.

Sets hold 64-bit hashes; words up to 16 bytes enter them byte by byte, longer ones by a cryptographic digest.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hopframe.llm.common import lowered, mixed, staged, text_chunks, trimmed, window_hashes, word_hashes, word_spans
from hopframe.llm.components import components

REGISTERS = 256
#: probability, at most, that a pair exactly at the threshold meets in no band
MISS = 1e-4
MANTISSA_BITS = 18
HASH_BITS = 52
#: times that shingles held by one candidate only are counted among those that stay
UNIQUE_ROUNDS = 3
#: classes of a bucket that meet in one task
PART_CLASSES = 4096
EMPTY = np.uint64(1 << 63)
#: expected equal registers of disjoint sets: constant of the published HyperMinHash estimator
COLLISION_CONSTANT = 0.169919487159739


def shingle_sets(data: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of every row, end to end, and their offsets."""
    data = lowered(data)
    starts, stops, first = word_spans(data, offsets)
    words = word_hashes(data, starts, stops)
    windows = window_hashes(words, width)
    parts = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
        if b - a >= width:
            parts.append(np.unique(windows[a : b - width + 1]))
        elif b > a:
            places = np.arange(1, b - a + 1, dtype=np.uint64) * np.uint64(0x9FB21C651E98DF25)
            parts.append(mixed((mixed(words[a:b] ^ places)).sum(keepdims=True, dtype=np.uint64)))
        else:
            parts.append(np.zeros(0, np.uint64))
    sizes = np.array([len(p) for p in parts], np.int64)
    return np.concatenate(parts) if parts else np.zeros(0, np.uint64), np.concatenate(([0], np.cumsum(sizes)))


def registers(hashes: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """HyperMinHash registers of every row; 0 is an empty register."""
    rows = len(offsets) - 1
    least = np.full(rows * REGISTERS, EMPTY)
    row = np.repeat(np.arange(rows), np.diff(offsets))
    bucket = (hashes & np.uint64(REGISTERS - 1)).astype(np.int64)
    np.minimum.at(least, row * REGISTERS + bucket, hashes >> np.uint64(64 - HASH_BITS))
    full = least != EMPTY
    value = least[full]
    zeros = HASH_BITS - np.frexp(value.astype(np.float64))[1]
    mantissa = (value << zeros.astype(np.uint64)) >> np.uint64(HASH_BITS - 1 - MANTISSA_BITS)
    mantissa &= np.uint64((1 << MANTISSA_BITS) - 1)
    out = np.zeros(rows * REGISTERS, np.int32)
    out[full] = ((zeros + 1).astype(np.int64) << MANTISSA_BITS | mantissa.astype(np.int64)).astype(np.int32)
    return out.reshape(rows, REGISTERS)


def band_rows(percent: int) -> int:
    """Registers of a band: as many as leave the chance of missing a pair at the threshold at ``MISS`` or less."""
    for rows in (8, 4, 2):
        if (1 - (percent / 100) ** rows) ** (REGISTERS // rows) <= MISS:
            return rows
    return 1


def least_bands(percent: int) -> int:
    """Bands that a pair at the threshold has in common, but for a probability of ``MISS`` at most."""
    rows = band_rows(percent)
    bands, p, least, below = REGISTERS // rows, (percent / 100) ** rows, 0, 0.0
    while (below := below + comb(bands, least) * p**least * (1 - p) ** (bands - least)) <= MISS:
        least += 1
    return max(1, least)


def band_keys(sketch: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """One 64-bit key for each band of ``rows`` registers, and whether the band holds anything."""
    bands = sketch.reshape(len(sketch), REGISTERS // rows, rows).astype(np.uint64)
    key = np.zeros(bands.shape[:2], np.uint64)
    for k in range(bands.shape[2]):
        key = mixed(key + bands[:, :, k] + np.uint64(k + 1))
    return key.view(np.int64), (bands != 0).any(axis=2)


def _lists(values: np.ndarray, offsets: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(values))


def _sums(hashes: np.ndarray, ends: np.ndarray) -> list[pa.Array]:
    """Two 64-bit fingerprints of every set."""
    sums = [np.concatenate(([np.uint64(0)], np.cumsum(mixed(hashes ^ np.uint64(salt)), dtype=np.uint64))) for salt in (0x5851F42D4C957F2D, 0x2545F4914F6CDD1D)]
    return [pa.array((x[ends[1:]] - x[ends[:-1]]).view(np.int64)) for x in sums]


def _sketches(width: int, rows: int):
    """(doc_id, key, text) to doc_id, key, size, fingerprints and band keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low, high, data, offsets in text_chunks(batch.column(2)):
                hashes, ends = shingle_sets(data, offsets, width)
                keys, full = band_keys(registers(hashes, ends), rows)
                flat = pa.array(keys.ravel(), mask=~full.ravel())
                bands = pa.ListArray.from_arrays(pa.array(np.arange(len(keys) + 1, dtype=np.int32) * (REGISTERS // rows)), flat)
                own = [batch.column(k).slice(low, high - low) for k in (0, 1)]
                yield pa.RecordBatch.from_arrays([*own, pa.array(np.diff(ends)), *_sums(hashes, ends), bands], ["doc_id", "key", "n", "f1", "f2", "bands"])

    return run


def _full_sets(width: int):
    """(rep, text, want1, want2) to rep, size, registers and set, where the set has these fingerprints."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low, high, data, offsets in text_chunks(batch.column(1)):
                hashes, ends = shingle_sets(data, offsets, width)
                sketch = registers(hashes, ends)
                regs = _lists(sketch.ravel(), np.arange(len(sketch) + 1) * REGISTERS)
                made = pa.RecordBatch.from_arrays([batch.column(0).slice(low, high - low), pa.array(np.diff(ends)), regs, _lists(hashes.view(np.int64), ends)], ["rep", "n", "regs", "grams"])
                own = [np.asarray(x) == np.asarray(batch.column(k).slice(low, high - low)) for k, x in enumerate(_sums(hashes, ends), 2)]
                yield made.filter(pa.array(own[0] & own[1]))  # a key may have several texts

    return run


def estimated(regs_a: Column, regs_b: Column, n_a: Column, n_b: Column) -> tuple[Column, Column]:
    """Collision-corrected Jaccard estimate, and the registers it rests on."""
    same = F.size(F.filter(F.zip_with(regs_a, regs_b, lambda x, y: (x == y) & (x != 0)), lambda z: z))
    used = F.size(F.filter(F.zip_with(regs_a, regs_b, lambda x, y: (x != 0) | (y != 0)), lambda z: z))
    ratio = F.greatest(n_a, n_b) / F.least(n_a, n_b)
    chance = F.lit(COLLISION_CONSTANT * REGISTERS / 2**MANTISSA_BITS) * 4 * ratio / ((1 + ratio) * (1 + ratio))
    return (same - chance) / used, used


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets reach the threshold. Sketches thin them out before sets are moved."""
    slim = sets.select("rep", "n", "regs")
    a, b = (slim.select(F.col("rep").alias(x), F.col("n").alias(f"n_{x}"), F.col("regs").alias(f"regs_{x}")) for x in "ab")
    both = pairs.join(a, "a").join(b, "b")
    guess, used = estimated(F.col("regs_a"), F.col("regs_b"), F.col("n_a"), F.col("n_b"))
    slack = 5 * F.sqrt(F.lit(percent / 100 * (1 - percent / 100)) / used)
    close = both.where(guess >= percent / 100 - slack).select("a", "b", "n_a", "n_b")
    a, b = (sets.select(F.col("rep").alias(x), F.col("grams").alias(f"grams_{x}")) for x in "ab")
    shared = F.size(F.array_intersect("grams_a", "grams_b")).cast("long")
    full = close.join(a, "a").join(b, "b").withColumn("shared", shared)
    return full.where(100 * F.col("shared") >= percent * (F.col("n_a") + F.col("n_b") - F.col("shared"))).select("a", "b")


def _reach(percent: int, n_a: str, u_a: str, n_b: str, u_b: str, more: str | None = None) -> Column:
    """Whether two sets can still reach the threshold, if none of their ``u`` shingles is in both but ``more``."""
    most = F.least(F.col(n_a) - F.col(u_a), F.col(n_b) - F.col(u_b))
    most = most if more is None else most + F.col(more)
    return 100 * most >= percent * (F.col(n_a) + F.col(n_b) - most)


def _same_ids(seen: DataFrame, classes: DataFrame) -> DataFrame:
    """Pairs (a, b) of classes that rows of one id are in."""
    apart = F.lit(False)
    for c in ("f1", "f2", "n"):
        apart = apart | (F.col(f"low_{c}") != F.col(f"high_{c}"))
    bounds = [f(c).alias(f"{name}_{c}") for c in ("f1", "f2", "n") for name, f in (("low", F.min), ("high", F.max))]
    told = seen.where("n > 0 and doc_id is not null").select("doc_id", "f1", "f2", "n")
    several = told.groupBy("doc_id").agg(*bounds).where(apart).select("doc_id")
    held = told.join(several, "doc_id").join(classes.select("f1", "f2", "n", "rep"), ["f1", "f2", "n"]).select("doc_id", "rep").distinct()
    return held.join(held.groupBy("doc_id").agg(F.min("rep").alias("a")), "doc_id").where("a < rep").select("a", F.col("rep").alias("b"))


def _across(met: DataFrame, classes: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) of classes in different components that share a bucket and can still reach the threshold."""
    torn = met.groupBy("band", "key").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.count("*").alias("members")).where("low < high").select("band", "key", "members")
    torn = met.join(torn, ["band", "key"]).select("band", "key", "members", "rep", "n", "component")
    reps = staged(torn.select("rep", "n", "component").distinct())
    grams = sets.join(reps.select("rep"), "rep", "left_semi").select("rep", F.explode("grams").alias("g"))
    rare = staged(grams.groupBy("g").agg(F.count("*").alias("c"), F.min("rep").alias("a"), F.max("rep").alias("b")).where("c <= 2").groupBy("a", "b").agg(F.count("*").alias("shared")))
    held = rare.select(F.explode(F.array_distinct(F.array("a", "b"))).alias("rep"), "shared").groupBy("rep").agg(F.sum("shared").alias("r"))
    reps = staged(reps.join(held, "rep", "left").fillna(0, ["r"]))

    left, right = (reps.select(*(F.col(c).alias(f"{c}_{x}" if c != "rep" else x) for c in ("rep", "n", "r", "component"))) for x in "ab")
    counted = rare.where("a < b").join(left, "a").join(right, "b")
    by_rare = counted.where((F.col("component_a") != F.col("component_b")) & _reach(percent, "n_a", "r_a", "n_b", "r_b", "shared")).select("a", "b")

    # a bucket of many classes is cut into parts, and its classes go to every part on the other side
    parts = F.ceil(F.col("members") / PART_CLASSES).cast("int")
    short = F.transform("bands", lambda x: x.bitwiseAND(F.lit(0x7FFFFFFF)).cast("int"))  # keys as told here; buckets go by whole ones
    able = reps.where(_reach(percent, "n", "r", "n", "r"))
    wide = torn.select("band", "key", "rep", parts.alias("parts")).join(able, "rep").join(classes.select("rep", short.alias("bands")), "rep")
    left = wide.withColumn("part", F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int"))
    right = wide.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    left, right = (side.select("band", "key", "part", *(F.col(c).alias(f"{c}_{x}") for c in ("rep", "n", "r", "component", "bands"))) for side, x in ((left, "a"), (right, "b")))
    alike = F.zip_with("bands_a", "bands_b", lambda x, y: F.coalesce(x == y, F.lit(False)))
    enough = (F.array_position(alike, True) == F.col("band") + 1) & (F.size(F.filter(alike, lambda z: z)) >= least_bands(percent))
    met_in = left.join(right, ["band", "key", "part"])
    by_bucket = met_in.where((F.col("rep_a") < F.col("rep_b")) & (F.col("component_a") != F.col("component_b")) & _reach(percent, "n_a", "r_a", "n_b", "r_b") & enough)
    return by_rare.unionByName(by_bucket.select(F.col("rep_a").alias("a"), F.col("rep_b").alias("b"))).distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = 80) -> DataFrame:
    """Groups of texts whose shingle sets have at least ``percent`` of their union in common.

    Returns doc_id, n_shingles, component_id (smallest id reachable) and kept, a row for each input row. Null and
    empty texts have no shingles and stay alone; texts of fewer than ``width`` words count as one shingle. Rows that
    share an id are one document: all their texts are in one component. Rows without an id are linked like others;
    a component without any id has a null component_id, and one of its rows is kept. ``percent`` is 1 to 99. Other
    columns are ignored, whatever their names.
    """
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    slim = slim.select("doc_id", F.coalesce("doc_id", F.xxhash64("text")).alias("key"), "text")
    sketched = slim.mapInArrow(trimmed(_sketches(width, band_rows(percent))), "doc_id long, key long, n long, f1 long, f2 long, bands array<long>")
    seen = staged(sketched.withColumn("row", F.monotonically_increasing_id()))
    classes = seen.where("n > 0").groupBy("f1", "f2", "n").agg(F.min("doc_id").alias("least"), F.min("row").alias("row"), F.min("key").alias("key"), F.first("bands").alias("bands"))
    classes = staged(classes.withColumn("rep", F.monotonically_increasing_id()))

    # sets so small that one shingle more or less misses the threshold have equal partners only
    least = -(-percent // (100 - percent))
    rows = classes.where(F.col("n") >= least).select("rep", "n", F.posexplode("bands").alias("band", "key")).where("key is not null")
    shared = rows.groupBy("band", "key").agg(F.count("*").alias("c")).where("c > 1").select("band", "key")
    members = staged(rows.join(shared, ["band", "key"], "left_semi"))
    candidates = classes.join(members.select("rep").distinct(), "rep", "left_semi").select("key", "rep", F.col("f1").alias("want1"), F.col("f2").alias("want2"))
    texts = slim.select("key", "text").join(candidates, "key").select("rep", "text", "want1", "want2")
    sets = staged(texts.mapInArrow(trimmed(_full_sets(width)), "rep long, n long, regs array<int>, grams array<long>").dropDuplicates(["rep"]))

    able = sets.select("rep", "n")
    for _ in range(UNIQUE_ROUNDS):  # who leaves makes more shingles unique among those who stay
        grams = sets.join(able.select("rep"), "rep", "left_semi").select("rep", F.explode("grams").alias("g"))
        alone = grams.groupBy("g").agg(F.count("*").alias("c"), F.min("rep").alias("rep")).where("c = 1").groupBy("rep").agg(F.count("*").alias("u"))
        able = staged(able.select("rep", "n").join(alone, "rep", "left").fillna(0, ["u"]).where(100 * (F.col("n") - F.col("u")) >= percent * F.col("n")))
    met = members.drop("n").join(able, "rep")
    size = met.groupBy("band", "key").agg(F.count("*").alias("c")).where("c > 1")
    met = staged(met.join(size, ["band", "key"]))

    degree = met.groupBy("rep").agg(F.sum("c").alias("degree"))
    hub = met.join(degree, "rep").groupBy("band", "key").agg(F.max(F.struct("degree", (-F.col("rep")).alias("m"), F.struct("rep", "n", "u").alias("hub"))).alias("best")).select("band", "key", "best.hub")
    star = met.join(hub, ["band", "key"]).select("rep", "n", "u", F.col("hub.rep").alias("hub"), F.col("hub.n").alias("hub_n"), F.col("hub.u").alias("hub_u"))
    star = star.where((F.col("rep") != F.col("hub")) & _reach(percent, "n", "u", "hub_n", "hub_u"))
    star = star.select(F.least("rep", "hub").alias("a"), F.greatest("rep", "hub").alias("b")).distinct()
    links = staged(_confirmed(star, sets, percent).unionByName(_same_ids(seen, classes)))
    found = components(links)

    met = met.join(found.withColumnRenamed("node", "rep"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
    more = staged(_confirmed(_across(staged(met), classes, sets, percent), sets, percent))
    if not more.isEmpty():
        found = components(links.unionByName(more))

    joined = classes.select("rep", "least", "row").join(found.withColumnRenamed("node", "rep"), "rep")
    lowest = joined.groupBy("component").agg(F.min("least").alias("least"), F.min("row").alias("row"))
    linked = joined.select("rep", "component").join(lowest, "component").select("rep", F.col("least").alias("component_id"), F.col("row").alias("first"), F.lit(True).alias("linked"))
    named = classes.join(linked, "rep", "left").select("f1", "f2", "n", F.when(F.col("linked"), F.col("component_id")).otherwise(F.col("least")).alias("component_id"), F.coalesce("first", "row").alias("first"))
    grouped = seen.select("doc_id", "n", "f1", "f2", "row").join(named, ["f1", "f2", "n"], "left")
    out = grouped.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"), F.coalesce("first", "row").alias("first"), "row")
    kept = F.when(F.col("component_id").isNull(), F.col("row") == F.col("first")).otherwise(F.col("doc_id").eqNullSafe(F.col("component_id")))
    return out.select("doc_id", "n_shingles", "component_id", kept.alias("kept"))
