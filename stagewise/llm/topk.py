"""Exact top-k search by distributed histogram selection.

Every candidate is scored against every query, several times over but never stored. Each pass counts scores into histograms, which
narrow the range that holds each query's k-th best value until the value is known; a last pass lets through what reaches it, and
ties go to the smaller id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import small_batches, stash, table, tidied

K, SCALE, QUERY_STEP = 5, 256, 50
#: Queries that are sent to the executors at once, and bins of a histogram. Both are fixed, whatever the input.
QUERY_BLOCK, BINS = 4_096, 1_024
_LEAST = -(1 << 62)


def quantised(vectors: DataFrame, key: str, vector: str, scale: int = SCALE) -> DataFrame:
    """(vec_id, v array<long>): floor(scale * x) of each component x as double. Rows that are null or hold a null or non-finite component are left out, as are null ids."""
    x = F.col(vector)
    sound = x.isNotNull() & F.col(key).isNotNull() & F.coalesce(F.forall(x, lambda c: c.isNotNull() & (F.abs(c.cast("double")) < float("inf"))), F.lit(False))
    return vectors.where(sound).select(F.col(key).cast("long").alias("vec_id"), F.transform(x, lambda c: F.floor(c.cast("double") * scale)).alias("v"))


def _matrix(values: pa.Array, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows of the given width as a matrix, and which rows those are."""
    lengths = np.asarray(pc.list_value_length(values))
    fit = np.flatnonzero(lengths == width)
    flat = np.asarray(values.take(pa.array(fit)).flatten()).reshape(len(fit), width)
    return flat, fit


def _scores(candidates: np.ndarray, queries: np.ndarray) -> np.ndarray:
    """Integer inner products; in floating point where that is exact, modulo 2**64 beyond."""
    most = float(np.abs(candidates.astype(float)).max(initial=0)) * float(np.abs(queries.astype(float)).max(initial=0)) * max(1, queries.shape[1])
    if most < 2**24:
        return (candidates.astype(np.float32) @ queries.T.astype(np.float32)).astype(np.int64)
    if most < 2**53:
        return (candidates.astype(np.float64) @ queries.T.astype(np.float64)).astype(np.int64)
    return candidates @ queries.T


def _each_block(batches: Iterator[pa.RecordBatch], ids: np.ndarray, queries: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, scores query x candidate) block by block; a query's own rows score least of all."""
    step = max(1, (1 << 22) // max(1, len(ids)))
    for batch in batches:
        for lo in range(0, batch.num_rows, step):
            part = batch.slice(lo, step)
            rows, at = _matrix(part.column(1), queries.shape[1])
            own = np.asarray(part.column(0))[at]
            if len(own):
                scores = _scores(rows, queries).T.copy()
                scores[ids[:, None] == own[None, :]] = _LEAST
                yield own, scores


def _best(ids: np.ndarray, scores: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k best of each row by score, then by smaller id."""
    order = np.lexsort((np.broadcast_to(ids, scores.shape), -scores), axis=1)[:, :k]
    return np.take_along_axis(np.broadcast_to(ids, scores.shape), order, 1), np.take_along_axis(scores, order, 1)


def _histogram(candidates: DataFrame, block, low: np.ndarray, high: np.ndarray, need: np.ndarray) -> DataFrame:
    """(q, bin, n): how many scores fall into each bin of the query's range ``low..high``; bin ``BINS`` stands for all above.

    A task leaves out the bins below its own ``need``-th best score: the value sought is at least that.
    """
    ids, queries = block
    width = np.maximum(1, -((low - high - 1) // BINS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((len(ids), BINS + 2), np.int64)
        base = (np.arange(len(ids)) * (BINS + 2))[:, None]
        for _, scores in _each_block(batches, ids, queries):
            b = np.clip((scores - low[:, None]) // width[:, None], -1, BINS)
            b[scores > high[:, None]] = BINS
            counts += np.bincount((base + b + 1).ravel(), minlength=counts.size).reshape(counts.shape)
        above = np.cumsum(counts[:, ::-1], 1)[:, ::-1] - counts
        q, b = np.nonzero((counts > 0) & (above < need[:, None]))
        keep = b > 0
        yield pa.record_batch([pa.array(q[keep], pa.int32()), pa.array((b[keep] - 1).astype(np.int32)), pa.array(counts[q[keep], b[keep]])], names=["q", "bin", "n"])

    return candidates.transform(small_batches).mapInArrow(tidied(run), "q int, bin int, n long")


def _reached(candidates: DataFrame, block, floor: np.ndarray, k: int) -> DataFrame:
    """(query_id, q, vec_id, score) of what reaches the query's k-th value; of ties a task sends the k smallest ids."""
    ids, queries = block

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, values = np.zeros((len(ids), 0), np.int64), np.zeros((len(ids), 0), np.int64)
        for own, scores in _each_block(batches, ids, queries):
            hit = np.flatnonzero((scores >= floor[:, None]).any(0))
            if len(hit):
                both = np.concatenate([names, np.broadcast_to(own[hit], (len(ids), len(hit)))], 1)
                score = np.concatenate([values, np.where(scores[:, hit] >= floor[:, None], scores[:, hit], _LEAST)], 1)
                order = np.lexsort((both, -score), axis=1)[:, :k]
                names, values = np.take_along_axis(both, order, 1), np.take_along_axis(score, order, 1)
        q, c = np.nonzero(values > _LEAST)
        yield pa.record_batch([pa.array(ids[q]), pa.array(q.astype(np.int32)), pa.array(names[q, c]), pa.array(values[q, c])], names=["query_id", "q", "vec_id", "score"])

    return candidates.transform(small_batches).mapInArrow(tidied(run), "query_id long, q int, vec_id long, score long")


def _kth_values(candidates: DataFrame, block, k: int, bound: np.ndarray) -> np.ndarray:
    """Each query's k-th best score; the least possible one where there are fewer candidates."""
    n = len(block[0])
    low, high, need = -bound, bound.copy(), np.full(n, k, np.int64)
    found = np.full(n, _LEAST + 1)
    open_ = np.ones(n, bool)
    while open_.any():
        width = np.maximum(1, -((low - high - 1) // BINS))
        got = _histogram(candidates, block, low, high, np.full(n, k, np.int64)).groupBy("q", "bin").agg(F.sum("n").alias("n"))
        # best first: the bin where the running count reaches k
        order = Window.partitionBy("q").orderBy(F.desc("bin"))
        hit = got.withColumn("sum", F.sum("n").over(order)).where(F.col("sum") >= k).groupBy("q").agg(F.max("bin").alias("bin")).toArrow()  # a row a query of the block
        bins = np.full(n, -1, np.int64)
        bins[np.asarray(hit["q"])] = np.asarray(hit["bin"])
        fewer = open_ & (bins < 0)
        open_ &= ~fewer
        low = np.where(open_, low + bins * width, low)
        high = np.where(open_, np.minimum(high, low + width - 1), high)
        done = open_ & (low == high)
        found[done] = low[done]
        open_ &= ~done
    return found


def top_k(vectors: DataFrame, is_query, k: int = K, key: str = "vec_id", vector: str = "embedding", scale: int = SCALE) -> DataFrame:
    """(query_id, rank, vec_id, score): the k best candidates of each query row by integer inner product, ties to the smaller id.

    Candidates are all sound rows of the query's own length but those of the query's own id; all of them come back if they are
    fewer than k. Identical query rows are asked once. Vectors whose scores could leave 64 bits are refused. An empty table
    gives an empty result.
    """
    spark = vectors.sparkSession
    rows = stash(quantised(vectors, key, vector, scale))
    asked = stash(rows.where(is_query(F.col("vec_id"))).distinct().withColumn("width", F.size("v")))
    none = spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    # the widest reach of any vector bounds every score (Cauchy-Schwarz)
    reach = {r["width"]: r["norm"] for r in rows.groupBy(F.size("v").alias("width")).agg(F.max(F.aggregate("v", F.lit(0.0), lambda a, c: a + c.cast("double") * c)).alias("norm")).collect()}
    parts = []
    for width in sorted(w for w in reach if w > 0):
        of_width = asked.where(F.col("width") == width)
        last = None
        while True:  # one block of queries after another, in the order of their ids
            more = of_width if last is None else of_width.where(F.struct("vec_id", "v") > F.struct(F.lit(last[0]).cast("long").alias("vec_id"), F.lit(last[1]).cast("array<bigint>").alias("v")))
            block = more.orderBy("vec_id", "v").limit(QUERY_BLOCK).select("vec_id", "v").toArrow()
            if not block.num_rows:
                break
            ids, (queries, _) = np.asarray(block["vec_id"]), _matrix(block["v"].combine_chunks(), width)
            last = (int(ids[-1]), [int(x) for x in queries[-1]])
            norms = np.sqrt((queries.astype(float) ** 2).sum(1) * reach[width])
            if norms.max() >= 1 << 60:
                raise OverflowError("vectors this long have scores beyond 64 bits")
            bound = (norms + 1 + norms / (1 << 40)).astype(np.int64)  # a little more than the rounded root
            kth = _kth_values(rows, (ids, queries), k, bound)
            ranked = F.row_number().over(Window.partitionBy("q").orderBy(F.desc("score"), "vec_id"))
            parts.append(stash(_reached(rows, (ids, queries), kth, k).withColumn("rank", ranked).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")))
            if block.num_rows < QUERY_BLOCK:
                break
    for p in parts:
        none = none.unionByName(p)
    return none


def op5_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), lambda vec_id: vec_id % QUERY_STEP == 0)


OP5_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS e
  FROM embeddings
  WHERE embedding IS NOT NULL AND vec_id IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(range(1, len(q.e) + 1), lambda i: q.e[i] * c.e[i])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e)
  WHERE q.vec_id % 50 = 0
), r AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
