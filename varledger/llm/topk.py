"""Exact top-k inner-product search by a three-phase uniform threshold.

The dimensions are cut into slices; a task's vectors and one slice make one
local list of partial scores.  For each block of queries:

1. every list names its best entries; their whole scores, gathered from the
   lists, give each query a k-th best score so far, and the lists their lowest
   and highest partial scores;
2. the cutoff that follows is broadcast: an entry of which every slice stays
   below its share of the gap cannot reach the k-th best, so each list keeps
   only the entries at or above its share;
3. slice by slice, widest first, an entry is dropped once it cannot reach the
   cutoff even with the best of the slices to come; rows that no query of a
   tile still wants are not multiplied again, and what is left is resolved
   pair by pair.

The vectors are quantised and written once.  Only entries that reach the
cutoff leave a task, at least k for each query.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import written

QUERY_TILE, ROW_TILE = 256, 2048
#: Share of a tile's pairs below which the rest is resolved pair by pair.
SPARSE = 0.05


def quantised(embedding: str, scale: int) -> F.Column:
    return F.transform(F.col(embedding), lambda x: F.floor(F.lit(float(scale)) * x.cast("double")))


def usable(embedding: str) -> F.Column:
    """Vectors that take part: no null and no non-finite component."""
    bad = F.exists(
        F.col(embedding), lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) == float("inf"))
    )
    return F.col(embedding).isNotNull() & ~F.coalesce(bad, F.lit(True))


def _fitted(vector: str, width: int) -> F.Column:
    """The vector cut or filled with zeros to a length."""
    lacking = F.greatest(F.lit(width) - F.size(vector), F.lit(0))
    other = F.concat(F.slice(vector, 1, width), F.array_repeat(F.lit(0).cast("long"), lacking))
    return F.when(F.size(vector) == width, F.col(vector)).otherwise(other)


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1).astype(np.float64)


def _slices(width: int, count: int) -> list[tuple[int, int]]:
    edges = np.linspace(0, width, min(count, max(width, 1)) + 1).astype(int)
    return list(zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True))


def _tiles(batches: Iterator[pa.RecordBatch], queries: np.ndarray):
    """(ids, vectors, first query, queries) of bounded size."""
    for batch in batches:
        ids = batch.column(0).to_numpy(zero_copy_only=False)
        vectors = _matrix(batch.column(1))
        for lo in range(0, len(ids), ROW_TILE):
            for q in range(0, len(queries), QUERY_TILE):
                yield ids[lo : lo + ROW_TILE], vectors[lo : lo + ROW_TILE], q, queries[q : q + QUERY_TILE]


def _gather(shared, k: int, count: int):
    """Phase 1: per query the k best whole scores named by any list, and each
    list's lowest and highest partial score."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, queries = shared.value
        cuts = _slices(queries.shape[1], count)
        best = np.full((len(qid), k), -np.inf)
        low = np.full((len(qid), len(cuts)), np.inf)
        high = np.full((len(qid), len(cuts)), -np.inf)
        for ids, vectors, q, block in _tiles(batches, queries):
            own = slice(q, q + len(block))
            parts = [block[:, a:b] @ vectors[:, a:b].T for a, b in cuts]
            same = qid[own][:, None] == ids[None, :]
            named = []
            for s, part in enumerate(parts):
                low[own, s] = np.minimum(low[own, s], part.min(1))
                high[own, s] = np.maximum(high[own, s], part.max(1))
                part[same] = -np.inf
                top = min(k, part.shape[1])
                named.append(np.argpartition(part, part.shape[1] - top, axis=1)[:, part.shape[1] - top :])
            named = np.sort(np.concatenate(named, axis=1), axis=1)
            score = sum(np.take_along_axis(part, named, axis=1) for part in parts)
            score[:, 1:][named[:, 1:] == named[:, :-1]] = -np.inf  # named by two lists
            both = np.concatenate([best[own], score], axis=1)
            best[own] = np.sort(both, axis=1)[:, -k:]
        seen = np.isfinite(low[:, 0])
        yield pa.RecordBatch.from_pydict(
            {
                "query_id": pa.array(qid[seen]),
                "best": pa.array([[x for x in b if x > -np.inf] for b in best[seen].tolist()], pa.list_(pa.float64())),
                "low": pa.array(low[seen].tolist(), pa.list_(pa.float64())),
                "high": pa.array(high[seen].tolist(), pa.list_(pa.float64())),
            }
        )

    return run


def _survivors(
    block: np.ndarray, vectors: np.ndarray, cuts: list[tuple[int, int]], order: list[int], cutoff: np.ndarray, share: np.ndarray, high: np.ndarray
) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Query and row numbers and whole scores of the pairs that reach the cutoff.

    ``share`` and ``high`` (query, slice): the partial score that a list must
    see of an entry, and the best that it holds."""
    rows = np.arange(len(vectors))
    total = np.zeros((len(block), len(rows)))
    reach = np.zeros(total.shape, dtype=bool)
    rest = high.sum(1)
    for done, s in enumerate(order):
        a, b = cuts[s]
        part = block[:, a:b] @ vectors[rows, a:b].T
        total += part
        reach |= part >= share[:, s][:, None]
        rest = rest - high[:, s]
        alive = total + rest[:, None] >= cutoff[:, None]
        if done + 1 < len(order) and alive.mean() < SPARSE:
            q, r = np.nonzero(alive)
            score, seen = total[q, r], reach[q, r]
            for t in order[done + 1 :]:
                a, b = cuts[t]
                part = np.einsum("ij,ij->i", block[q, a:b], vectors[rows[r], a:b])
                score, seen = score + part, seen | (part >= share[q, t])
            fit = seen & (score >= cutoff[q])
            return q[fit], rows[r[fit]], score[fit]
        used = alive.any(0)
        if not used.all():
            rows, total, reach = rows[used], total[:, used], reach[:, used]
    q, r = np.nonzero(reach & (total >= cutoff[:, None]))
    return q, rows[r], total[q, r]


def _resolve(shared, limits, count: int):
    """Phases 2 and 3: entries whose whole score reaches the query's cutoff."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, queries = shared.value
        cutoff, low, high = limits.value
        cuts = _slices(queries.shape[1], count)
        order = np.argsort(low.sum(0) - high.sum(0)).tolist() if len(qid) else list(range(len(cuts)))
        share = ((cutoff - low.sum(1)) / len(cuts))[:, None] + low
        for ids, vectors, q, block in _tiles(batches, queries):
            own = slice(q, q + len(block))
            row, col, score = _survivors(block, vectors, cuts, order, cutoff[own], share[own], high[own])
            other = qid[own][row] != ids[col]
            row, col, score = row[other], col[other], score[other]
            if len(row):
                yield pa.RecordBatch.from_pydict(
                    {
                        "query_id": pa.array(qid[own][row]),
                        "vec_id": pa.array(ids[col]),
                        "score": pa.array(score.astype(np.int64)),
                    }
                )

    return run


def top_k(
    vectors: DataFrame,
    queries: DataFrame,
    *,
    k: int = 5,
    id_col: str = "vec_id",
    vector_col: str = "embedding",
    scale: int = 256,
    slices: int = 4,
    block: int = 16_384,
) -> DataFrame:
    """query_id, rank (from 1), vec_id, score: the k best inner products of
    floor(scale * x) over all rows but those with the query's own id.

    Ties go to the smaller id.  Rows with a null id, a null or empty vector or
    a null or non-finite component take no part.  Of vectors of two lengths the
    components that both have count; the search runs once for each length of
    queries.  Ids that repeat: each row is a candidate, and the query is asked
    once, with its smallest vector.  Fewer candidates than k: all.  Scores
    below 2**53 are exact.  Queries go in blocks of about ``block``; what is
    broadcast is one block's vectors and cutoffs.
    """
    spark = vectors.sparkSession
    ready = lambda df: df.where(F.col(id_col).isNotNull() & usable(vector_col) & (F.size(vector_col) > 0)).select(
        F.col(id_col).cast("long").alias("vec_id"), quantised(vector_col, scale).alias("v")
    )
    asked = written(ready(queries).groupBy("vec_id").agg(F.min("v").alias("v")), "topk-queries")
    sizes = asked.groupBy(F.size("v").alias("width")).count().orderBy("width").collect()
    if not sizes:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    rows = written(ready(vectors), "topk-rows")
    out = None
    for width, n in sizes:
        like = rows.withColumn("v", _fitted("v", width))
        blocks = math.ceil(n / block)
        for b in range(blocks):
            part = asked.where(F.size("v") == width).where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b).toArrow()
            order = np.argsort(part.column("vec_id").to_numpy(), kind="stable")
            qid = part.column("vec_id").to_numpy()[order]
            matrix = _matrix(part.column("v").combine_chunks())[order] if len(qid) else np.zeros((0, width))
            if not len(qid):
                continue
            shared = spark.sparkContext.broadcast((qid, matrix))
            each = like.mapInArrow(
                _gather(shared, k, slices), "query_id long, best array<double>, low array<double>, high array<double>"
            )
            count = len(_slices(width, slices))
            bounds = [F.min(F.col("low")[s]).alias(f"low{s}") for s in range(count)]
            bounds += [F.max(F.col("high")[s]).alias(f"high{s}") for s in range(count)]
            edge = each.groupBy("query_id").agg(*bounds)
            # The k-th best of what the lists named: ranks within a query, of which
            # each task contributed at most k.
            named = each.select("query_id", F.explode("best").alias("score"))
            place = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score")))
            kth = named.withColumn("r", place).where(F.col("r") == k).select("query_id", F.col("score").alias("kth"))
            got = {r.query_id: r for r in edge.join(kth, "query_id", "left").toLocalIterator()}
            cutoff = np.array([-np.inf if (r := got.get(i)) is None or r.kth is None else r.kth for i in qid.tolist()])
            low = np.array([[got[i][f"low{s}"] if i in got else 0.0 for s in range(count)] for i in qid.tolist()])
            high = np.array([[got[i][f"high{s}"] if i in got else 0.0 for s in range(count)] for i in qid.tolist()])
            limits = spark.sparkContext.broadcast((cutoff, low, high))
            reached = like.mapInArrow(_resolve(shared, limits, slices), "query_id long, vec_id long, score long")
            rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
            found = reached.withColumn("rank", rank.cast("int")).where(F.col("rank") <= k).select(
                "query_id", "rank", "vec_id", "score"
            )
            if blocks > 1 or len(sizes) > 1:
                found = written(found, "topk-block")
            out = found if out is None else out.union(found)
    return out
