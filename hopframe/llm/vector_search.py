"""Approximate nearest neighbours: inverted file with product-quantised residuals and exact reranking.

Coarse centroids and the sub-quantisers of the residuals are fitted on a bounded sample; every vector is indexed. A
query goes to its nearest cells and scores their codes by tables of asymmetric distances. Over all visited cells a
fixed number of rows with the least asymmetric distances is chosen, and these alone are reranked by exact cosine on
the original vectors. Cells are cut into parts and queries into slices of bounded size, so a cell that holds a third
of all rows, or that all queries visit, is no single task. Codes and identifiers travel to the search; original
vectors travel for the chosen rows only.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from hopframe.llm.common import staged

#: vectors on which centroids and codebooks are fitted, at most about this many
SAMPLE_ROWS = 16_000
#: share of the sample's true neighbours whose cells are to be searched; this sets the number of cells a query goes to
CELL_RECALL, PROBE_LEAST = 0.95, 8
TUNING_QUERIES = 300
#: rows of each query whose exact cosine is taken
RERANKED = 256
PART_ROWS, QUERY_ROWS = 4096, 2048
SUBSPACES, CODES = 16, 256


def _kmeans(x: np.ndarray, k: int, draw: np.random.Generator, rounds: int = 10) -> np.ndarray:
    centres = x[draw.choice(len(x), k, replace=len(x) < k)].astype(np.float64)
    for _ in range(rounds):
        near = _nearest(x, centres)
        counts = np.bincount(near, minlength=k)
        sums = np.stack([np.bincount(near, x[:, d], minlength=k) for d in range(x.shape[1])], axis=1)
        full = counts > 0
        centres[full] = sums[full] / counts[full, None]
    return centres


def _nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return ((centres**2).sum(axis=1) - 2 * x @ centres.T).argmin(axis=1)


class Quantiser:
    """Coarse centroids and one codebook for each subspace of the residuals, on vectors of length one."""

    def __init__(self, sample: np.ndarray, cells: int, seed: int = 5):
        draw = np.random.default_rng(seed)
        self.centres = _kmeans(sample, cells, draw)
        residual = sample - self.centres[_nearest(sample, self.centres)]
        self.parts = np.array_split(np.arange(sample.shape[1]), min(SUBSPACES, sample.shape[1]))
        self.books = [_kmeans(residual[:, p], min(CODES, max(1, len(sample))), draw, 6) for p in self.parts]
        cell, codes = self.encode(sample)
        self.seen = (self.centres[cell] + np.hstack([book[codes[:, i]] for i, book in enumerate(self.books)])).astype(np.float32)

    def radius(self, queries: np.ndarray, rows: int, reranked: int) -> np.ndarray:
        """An asymmetric distance within which about twice ``reranked`` of ``rows`` rows lie, by the sample's codes."""
        place = min(len(self.seen) - 1, 2 * reranked * len(self.seen) // rows + 2)
        far = (queries**2).sum(axis=1)[:, None] + (self.seen**2).sum(axis=1) - 2 * queries.astype(np.float32) @ self.seen.T
        return np.partition(far, place, axis=1)[:, place].astype(np.float64)

    def probes(self, sample: np.ndarray, k: int) -> int:
        """Cells that a query has to visit for the sample's own neighbours, by brute force on a few queries."""
        asked = sample[:TUNING_QUERIES]
        near = asked @ sample.T
        near[np.arange(len(asked)), np.arange(len(asked))] = -np.inf
        best = np.argpartition(-near, min(k, near.shape[1] - 1), axis=1)[:, :k]
        order = np.argsort((self.centres**2).sum(axis=1) - 2 * asked @ self.centres.T, axis=1, kind="stable")
        place = np.argsort(order, axis=1)
        ranks = np.take_along_axis(place, _nearest(sample, self.centres)[best], axis=1)
        return int(np.quantile(ranks, CELL_RECALL, method="higher")) + 1

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        cell = _nearest(x, self.centres)
        residual = x - self.centres[cell]
        return cell, np.stack([_nearest(residual[:, p], b) for p, b in zip(self.parts, self.books)], axis=1).astype(np.uint8)

    def tables(self, query: np.ndarray, cell: int) -> np.ndarray:
        """Squared distances from a query's residual to every code of every subspace."""
        residual = query - self.centres[cell]
        return np.stack([((b - residual[p]) ** 2).sum(axis=1) for p, b in zip(self.parts, [np.resize(b, (CODES, b.shape[1])) for b in self.books])])


def matrix(column) -> np.ndarray:
    """Vectors in double precision; those of extreme size are scaled, which leaves their cosines as they are."""
    x = np.array([np.asarray(v, np.float64) for v in column]).reshape(len(column), -1)
    top = np.abs(x).max(axis=1, keepdims=True)
    extreme = (top > 1e100) | (top < 1e-100)
    return np.where(extreme, x / top, x) if extreme.any() else x


def unit_rows(column) -> np.ndarray:
    x = matrix(column)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def nearest_neighbours(vectors: DataFrame, query_every: int = 50, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", sample_rows: int = SAMPLE_ROWS, reranked: int = RERANKED) -> DataFrame:
    """The ``k`` nearest rows found for every row whose id is divisible by ``query_every``.

    Returns query_id, rank, vec_id, score, n_scanned and n_reranked: score is the cosine in double precision on the
    original vectors, ties go to the smaller id; n_scanned rows had their codes scored for the query, n_reranked their
    vectors. Rows whose id or vector is null, or whose vector is empty, zero, or has null or non-finite parts, take no
    part, nor do those whose length is not that of most rows of the sample. Rows that share an id are each a
    candidate, but for the queries of that id. An empty table gives an empty result.
    """
    spark = vectors.sparkSession
    kinds = "query_id long, rank int, vec_id long, score double, n_scanned long, n_reranked int"
    whole = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).alias("v"))
    fine = whole.where("vec_id is not null and v is not null and size(v) > 0").where(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))).where(F.exists("v", lambda x: x != 0))
    rows = fine.count()
    if not rows:
        return spark.createDataFrame([], kinds)
    share = min(1.0, sample_rows / rows)
    sample = fine.where(F.pmod(F.xxhash64(F.lit("sample"), "vec_id"), F.lit(1_000_003)) <= share * 1_000_003).select("v").toPandas()["v"]
    width = int(sample.map(len).mode()[0]) if len(sample) else len(fine.select("v").first()[0])
    sample = sample[sample.map(len) == width] if len(sample) else fine.where(F.size("v") == width).limit(1).toPandas()["v"]
    cells = int(min(4096, max(1, min(len(sample) // 40, rows**0.5 / 3))))
    units = unit_rows(sample)
    quantiser = Quantiser(units, cells)
    model = spark.sparkContext.broadcast(quantiser)  # fixed numbers of centroids, codes and sampled rows

    def index(frames):
        for frame in frames:
            if len(frame):
                cell, codes = model.value.encode(unit_rows(frame["v"]))
                yield pd.DataFrame({"cell": cell, "vec_id": frame["vec_id"], "codes": [c.tobytes() for c in codes], "v": frame["v"]})

    filed = fine.where(F.size("v") == width).mapInPandas(index, f"cell int, vec_id long, codes binary, v {fine.schema['v'].dataType.simpleString()}")
    indexed = staged(filed.withColumn("row", F.monotonically_increasing_id()))
    asking = F.col("vec_id") % query_every == 0
    sizes = {r["cell"]: (r["n"], r["asked"]) for r in indexed.groupBy("cell").agg(F.count("*").alias("n"), F.count_if(asking).alias("asked")).collect()}  # a row for each cell
    counts = np.array([sizes.get(c, (0, 0))[0] for c in range(cells)])
    cuts = -(-counts // PART_ROWS)
    slices = max(1, -(-sum(n for _, n in sizes.values()) // QUERY_ROWS))
    probes = min(cells, max(PROBE_LEAST, quantiser.probes(units, k)))

    def spread(frames):
        centres = model.value.centres
        for frame in frames:
            if not len(frame):
                continue
            x = unit_rows(frame["v"])
            order = np.argsort((centres**2).sum(axis=1) - 2 * x @ centres.T, axis=1, kind="stable")
            seen = np.cumsum(counts[order], axis=1)
            radius, out, scanned = model.value.radius(x, rows, reranked), [], np.zeros(len(frame), np.int64)
            for i in range(len(frame)):
                # nearest cells, more of them until they hold several times what is asked for
                enough = min(cells, max(probes, int(np.searchsorted(seen[i], 20 * k)) + 1))
                scanned[i] = seen[i, enough - 1]
                out += [(i, int(c), p) for c in order[i, :enough] for p in range(cuts[c])]
            at, cell, part = (np.array(z, np.int64) for z in zip(*out))
            for low in range(0, len(at), 4000):
                i, some = at[low : low + 4000], slice(low, low + 4000)
                yield pd.DataFrame({"cell": cell[some].astype(np.int32), "part": part[some].astype(np.int32), "query_id": frame["vec_id"].to_numpy()[i], "unit": [x[j].tolist() for j in i], "radius": radius[i], "scanned": scanned[i]})

    queries = indexed.where(asking).select("vec_id", "v", "row").dropDuplicates(["vec_id"])
    queries = staged(queries)
    asked = queries.mapInPandas(spread, "cell int, part int, query_id long, unit array<double>, radius double, scanned long")
    asked = asked.withColumn("slice", F.pmod(F.xxhash64("query_id"), F.lit(slices)).cast("int"))
    cut = F.element_at(F.array(*[F.lit(int(max(1, c))) for c in cuts]), F.col("cell") + 1)
    codes = indexed.select("cell", "vec_id", "codes", "row", F.pmod(F.xxhash64("row"), cut).cast("int").alias("part"))
    codes = codes.withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(slices - 1))))

    def search(key, theirs: pd.DataFrame, ours: pd.DataFrame) -> pd.DataFrame:
        out = [pd.DataFrame({"query_id": pd.Series(dtype="int64"), "vec_id": pd.Series(dtype="int64"), "row": pd.Series(dtype="int64"), "far": pd.Series(dtype="float64"), "scanned": pd.Series(dtype="int64")})]
        if not len(theirs) or not len(ours):
            return out[0]
        own, cell = model.value, int(key[0])
        theirs = theirs.sort_values(["vec_id", "row"])
        ids, row = theirs["vec_id"].to_numpy(), theirs["row"].to_numpy()
        codes = np.frombuffer(b"".join(theirs["codes"]), np.uint8).reshape(len(theirs), -1)
        spaces = np.arange(codes.shape[1])
        for query_id, unit, radius, scanned in zip(ours["query_id"], ours["unit"], ours["radius"], ours["scanned"]):
            far = own.tables(np.asarray(unit), cell)[spaces, codes].sum(axis=1)
            far[ids == query_id] = np.inf
            near = max(2 * k, min(reranked, int((far <= radius).sum())))
            best = np.argsort(far, kind="stable")[:near]  # ties to the smaller id
            best = best[np.isfinite(far[best])]
            out.append(pd.DataFrame({"query_id": query_id, "vec_id": ids[best], "row": row[best], "far": far[best], "scanned": scanned}))
        return pd.concat(out)

    found = codes.groupBy("cell", "part", "slice").cogroup(asked.groupBy("cell", "part", "slice")).applyInPandas(search, "query_id long, vec_id long, row long, far double, scanned long")
    place = F.row_number().over(W.partitionBy("query_id").orderBy("far", "vec_id", "row"))
    chosen = found.withColumn("place", place).where(F.col("place") <= reranked).select("query_id", "row", "scanned")
    lists = chosen.join(indexed.select("row", "vec_id", "v"), "row").groupBy("query_id").agg(F.max("scanned").alias("scanned"), F.collect_list(F.struct("vec_id", "v")).alias("near"))  # ``reranked`` at most
    pairs = queries.select(F.col("vec_id").alias("query_id"), F.col("v").alias("q")).join(lists, "query_id")

    def rerank(frames):
        for frame in frames:
            out = []
            for query_id, q, scanned, near in zip(frame["query_id"], frame["q"], frame["scanned"], frame["near"]):
                raw, ids, theirs = matrix([q])[0], np.array([x["vec_id"] for x in near], np.int64), matrix([x["v"] for x in near])
                score = (theirs * raw).sum(axis=1) / (np.sqrt((theirs * theirs).sum(axis=1)) * np.sqrt((raw * raw).sum()))
                top = np.lexsort((ids, -score))[:k]
                out += [(query_id, r, int(ids[i]), float(score[i]), scanned, len(near)) for r, i in enumerate(top, 1)]
            yield pd.DataFrame(out, columns=["query_id", "rank", "vec_id", "score", "n_scanned", "n_reranked"])

    return pairs.mapInPandas(rerank, kinds)
