"""Approximate nearest neighbours by collision counting over single-projection sorted arrays.

Each block of vectors keeps, for every random projection, its vectors sorted by that one value. A
query opens a window round its own value in each array and widens all windows together (virtual
rehashing); a vector found in at least ``threshold`` of the windows is a candidate and is verified
against the original vectors. Widening stops once a block has given enough candidates.

For the largest inner product every vector gets one more component that makes all lengths equal, so
that the nearest in distance has the largest product. Vectors meet queries block by block, so memory
is bounded by the block sizes, whatever the tables hold.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilesieve.llm.common import frugal, ship

ship(__name__)

#: Fewest and most projections; between, one full orthogonal set is drawn.
PROJECTIONS = (32, 128)
#: Share of the windows in which a vector must be found.
THRESHOLD = 0.86
#: Share of a block that must become candidates, besides ``k``, before its windows stop widening.
ENOUGH = 0.10
#: Factor by which windows widen.
WIDEN = 1.12
BLOCK_VECTORS = 8192
BLOCK_QUERIES = 1024
QUERY_EVERY = 20


def projections(dim: int, seed: int) -> np.ndarray:
    """Random directions in dim + 1 components, in orthogonal sets, so that few of them repeat one another."""
    count, rng = min(max(dim + 1, PROJECTIONS[0]), PROJECTIONS[1]), np.random.default_rng(seed)
    sets = [np.linalg.qr(rng.standard_normal((dim + 1, dim + 1)))[0] for _ in range(-(-count // (dim + 1)))]
    return np.hstack(sets)[:, :count]


class Arrays:
    """Sorted arrays of one block."""

    def __init__(self, x: np.ndarray, longest: float, a: np.ndarray):
        extra = np.sqrt(np.maximum(longest**2 - (x * x).sum(1), 0.0))
        values = x @ a[:-1] + extra[:, None] * a[-1]
        self.size = len(x)
        self.order = np.argsort(values, axis=0, kind="stable").T.copy()
        self.values = np.sort(values, axis=0).T.copy()

    def windows(self, at: np.ndarray, width: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the windows of all queries (rows of ``at``) begin and end, by query and projection."""
        lo, hi = (np.empty(at.shape, np.int64) for _ in range(2))
        for i, v in enumerate(self.values):
            lo[:, i] = np.searchsorted(v, at[:, i] - width, "left")
            hi[:, i] = np.searchsorted(v, at[:, i] + width, "right")
        return lo, hi

    def _tally(self, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        """How often each vector stands in the given stretches, one for each array."""
        parts = [self.order[i, b:e] for i, (b, e) in enumerate(zip(begin.tolist(), end.tolist(), strict=True)) if e > b]
        return np.bincount(np.concatenate(parts), minlength=self.size) if parts else np.zeros(self.size, np.int64)

    def candidates(self, at: np.ndarray, threshold: int, enough: int, width: float) -> Iterator[np.ndarray]:
        """For each query the vectors that collide with it in ``threshold`` windows or more.

        What is counted is where a vector is missed, outside the windows, which is less to visit; a
        wider window gives back what it newly holds.
        """
        n, arrays = self.size, len(self.values)
        if n <= enough:
            yield from (np.arange(n) for _ in at)
            return
        first = self.windows(at, np.full(len(at), width))
        for j in range(len(at)):
            lo, hi, w = first[0][j], first[1][j], width
            missed = self._tally(np.zeros(arrays, np.int64), lo) + self._tally(hi, np.full(arrays, n))
            while len(found := np.flatnonzero(missed <= arrays - threshold)) < enough:
                w *= WIDEN
                lo2, hi2 = (x[0] for x in self.windows(at[j : j + 1], np.array([w])))
                missed -= self._tally(lo2, lo) + self._tally(hi, hi2)
                lo, hi = lo2, hi2
            yield found

    def usual_width(self, at: np.ndarray, threshold: int, enough: int) -> float:
        """Half width of windows that suffice for about half of the given queries."""
        if self.size <= enough or not len(at):
            return 1.0
        values = np.empty_like(self.values)
        np.put_along_axis(values, self.order, self.values, 1)
        need = [np.partition(np.partition(np.abs(values - q[:, None]), threshold - 1, axis=0)[threshold - 1], enough - 1)[enough - 1] for q in at]
        return float(max(np.median(need), 1e-12))


def top(ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best: largest score first, ties to the smaller id."""
    if len(ids) > 4 * k:
        cut = np.partition(scores, len(scores) - k)[len(scores) - k]
        keep = np.flatnonzero(scores >= cut)
        return keep[np.lexsort((ids[keep], -scores[keep]))[:k]]
    return np.lexsort((ids, -scores))[:k]


def usable(df: DataFrame, key: str, vector: str) -> DataFrame:
    """(vec_id, v, norm2) of the vectors that take part: not null, not zero, all components finite."""
    v = F.col(vector).cast("array<double>")
    rows = df.select(F.col(key).cast("bigint").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & (F.size("v") > 0))
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return rows.where(finite).withColumn("norm2", F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)).where("norm2 > 0")


def _blocks(rows: DataFrame, blocks: int, dim: int) -> DataFrame:
    """One row for each hash block: ids and the matrix as bytes."""

    def packed(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("vec_id", kind="stable")
        x = np.array(part["v"].tolist(), np.float64).reshape(len(part), dim)
        return pd.DataFrame({"block": [int(part["block"].iloc[0])], "ids": [part["vec_id"].to_numpy(np.int64).tobytes()], "data": [x.tobytes()]})

    dealt = rows.select(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("block"), "vec_id", "v")
    return dealt.groupBy("block").applyInPandas(packed, "block int, ids binary, data binary")


NEAREST = "query_id bigint, rank int, vec_id bigint, score double"


def nearest(df: DataFrame, *, k: int = 20, every: int = QUERY_EVERY, key: str = "vec_id", vector: str = "embedding", seed: int = 5, threshold: float = THRESHOLD, enough: float = ENOUGH) -> DataFrame:
    """The ``k`` nearest found of each query, a row with an id divisible by ``every``, among all other rows.

    Returns ``query_id``, ``rank`` from 1, ``vec_id`` and ``score``, the inner product of the original
    vectors in double precision; ties go to the smaller id. Null ids and vectors, zero vectors and those
    with null or non-finite components take no part, nor do vectors of another length than the most
    common one. Rows that repeat an id count each, but never for their own id as a query. Fewer than
    ``k`` other rows give all of them; an empty table gives no rows.
    """
    spark = df.sparkSession
    rows = usable(df, key, vector)
    shape = rows.groupBy(F.size("v").alias("dim")).agg(F.count("*").alias("n"), F.sum((F.col("vec_id") % every == 0).cast("bigint")).alias("q"), F.max("norm2").alias("longest")).orderBy(F.desc("n"), "dim").limit(1).collect()
    if not shape:
        return spark.createDataFrame([], NEAREST)
    dim, n, q, longest = shape[0]["dim"], shape[0]["n"], shape[0]["q"], float(np.sqrt(shape[0]["longest"]))
    rows = rows.where(F.size("v") == dim)
    vectors = _blocks(rows, -(-n // BLOCK_VECTORS), dim)
    lanes = max(1, -(-q // BLOCK_QUERIES))
    asked = _blocks(rows.where(F.col("vec_id") % every == 0), lanes, dim)
    # every block of vectors meets every block of queries: rows are whole blocks here
    spread = vectors.withColumn("lane", F.explode(F.sequence(F.lit(0), F.lit(lanes - 1))))
    met = spread.join(asked.select(F.col("block").alias("lane"), F.col("ids").alias("q_ids"), F.col("data").alias("q_data")), "lane").select("ids", "data", "q_ids", "q_data").repartition(max(1, -(-n // BLOCK_VECTORS)) * lanes)

    @frugal
    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a = projections(dim, seed)
        hits = int(np.ceil(threshold * a.shape[1]))
        for batch in batches:
            for r in range(batch.num_rows):
                ids, q_ids = (np.frombuffer(batch.column(c)[r].as_py(), np.int64) for c in (0, 2))
                x, qs = (np.frombuffer(batch.column(c)[r].as_py(), np.float64).reshape(-1, dim) for c in (1, 3))
                arrays = Arrays(x, longest, a)
                need = 3 * k + int(np.ceil(enough * len(ids)))
                # a longer or shorter query asks the same: only its direction matters to the order
                at = (qs @ a[:-1]) * (longest / np.sqrt((qs * qs).sum(1)))[:, None]
                width = arrays.usual_width(at[:: max(1, len(at) // 16)], hits, need)
                out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
                for j, found in enumerate(arrays.candidates(at, hits, need, width)):
                    found = found[ids[found] != q_ids[j]]
                    # a first cut by matrix product, then each product summed alike, so equal vectors score alike
                    rough = x[found] @ qs[j]
                    if len(found) > 4 * k:
                        cut = np.partition(rough, len(rough) - k)[len(rough) - k]
                        found = found[rough >= cut - 1e-9 * (1 + abs(cut))]
                    score = (x[found] * qs[j]).sum(1)
                    best = top(ids[found], score, k)
                    out.append((np.full(len(best), q_ids[j]), ids[found][best], score[best]))
                a0, a1, a2 = (np.concatenate(c) for c in zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(a0), pa.array(a1), pa.array(a2)], names=["query_id", "vec_id", "score"])

    found = met.mapInArrow(search, "query_id bigint, vec_id bigint, score double")
    # ranks are cut to k before the shuffle and after it, so no query gathers more than k rows of each task
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
