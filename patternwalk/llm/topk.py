"""Operator 3: exact top-k inner products by the threshold algorithm.

Each block of candidates has one sorted list per dimension. A query walks the lists
of the dimensions in which it is not zero, from the top where its weight is positive
and from the bottom where it is negative, and scores what it meets. What it has not
met cannot score more than the sum of its weights times the values at which the
lists stand; once that bound is below the k-th score so far, the block is done.
The k-th score goes on from block to block, so later blocks stop sooner.

Walks advance in steps of doubling depth, and a step's new candidates are scored by
one matrix product. Queries come in blocks of ``QUERY_BLOCK`` rows: one block at a
time is broadcast (at most ``QUERY_BLOCK`` rows of the vectors' width, whatever the
corpus), and every candidate partition answers it. Only each partition's k best per
query leave it.

Defined results: a null vector, or one holding a null, NaN or infinity, takes no
part; vectors of another length than the query's have no score with it; a row is
never its own candidate, nor are rows that share its id; ties go to the smaller id;
repeated rows count each for itself. Fewer than k candidates: all of them. An empty
table gives an empty result. Extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from patternwalk.plans.scratch import cut, drop

QUERY_BLOCK = 8192
BLOCK = 4096
_FIRST_DEPTH = 64
_EMPTY = np.iinfo(np.int64).min


def quantised(batch: pa.RecordBatch, scale: int = 256) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """``(ids, floor(scale * x))`` of the usable vectors, one pair for each length of vector."""
    ids, lists = batch.column(0), batch.column(1)
    ok = np.ones(len(lists), bool) if not lists.null_count else np.asarray(lists.is_valid().to_numpy(zero_copy_only=False), bool)
    ok &= np.asarray(ids.is_valid().to_numpy(zero_copy_only=False), bool)
    lengths = np.where(ok, np.asarray(lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), np.int64), 0)
    offsets = np.asarray(lists.offsets.to_numpy(), np.int64)[:-1]
    values = lists.values.to_numpy(zero_copy_only=False).astype(np.float64)  # a null becomes NaN
    numbers = np.asarray(ids.fill_null(0).to_numpy(zero_copy_only=False), np.int64)
    for n in np.unique(lengths[ok & (lengths > 0)]).tolist():
        rows = np.flatnonzero(ok & (lengths == n))
        block = values[offsets[rows][:, None] + np.arange(n)]
        fine = np.isfinite(block).all(axis=1)
        yield numbers[rows[fine]], np.floor(scale * block[fine])


class Best:
    """The k best so far of each query, in order."""

    def __init__(self, n: int, k: int) -> None:
        self.scores, self.ids, self.k = np.full((n, k), _EMPTY), np.full((n, k), -1, np.int64), k

    def offer(self, q: int, scores: np.ndarray, ids: np.ndarray) -> None:
        floor = self.scores[q, -1]
        good = scores >= floor
        if not good.any():
            return
        s, i = np.concatenate((self.scores[q], scores[good])), np.concatenate((self.ids[q], ids[good]))
        order = np.lexsort((i, -s, s == _EMPTY))[: self.k]
        self.scores[q], self.ids[q] = s[order], i[order]


def _score(block: np.ndarray, query: np.ndarray) -> np.ndarray:
    """Exact integers: floats where every partial sum is below 2**53, else Python's."""
    reach = np.abs(block).max(initial=0.0) * np.abs(query).max(initial=0.0) * len(query)
    if reach < 2.0**53:
        return (block @ query).astype(np.int64)
    whole = np.array([[int(x) for x in row] for row in block], object) @ np.array([int(x) for x in query], object)
    return np.array([max(min(x, 2**63 - 1), -(2**63) + 1) for x in whole], np.int64)


def search_block(ids: np.ndarray, block: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, best: Best, which: np.ndarray) -> int:
    """Offer a block's candidates to ``best``; returns how many were scored."""
    n, scored = len(ids), 0
    order = np.argsort(block, axis=0, kind="stable")
    ranked = np.take_along_axis(block, order, axis=0)
    for row, (own, query) in enumerate(zip(query_ids, queries)):
        q, up, down = int(which[row]), np.flatnonzero(query > 0), np.flatnonzero(query < 0)
        met = np.zeros(n, bool)
        depth, reached = min(_FIRST_DEPTH, n), 0
        while True:
            fresh = np.concatenate((order[n - depth : n - reached][:, up].ravel(), order[reached:depth][:, down].ravel()))
            if len(up) + len(down) == 0:
                fresh = np.arange(n)
                depth = n
            new = np.zeros(n, bool)
            new[fresh] = True
            new &= ~met
            met |= new
            at = np.flatnonzero(new)
            scored += len(at)
            scores = _score(block[at], query)
            other = ids[at] != own
            best.offer(q, scores[other], ids[at][other])
            if depth >= n or met.all():
                break
            bound = ranked[n - depth][up] @ query[up] + ranked[depth - 1][down] @ query[down]
            if best.scores[q, -1] != _EMPTY and bound < best.scores[q, -1]:
                break
            reached, depth = depth, min(n, 2 * depth)
    return scored


def top_k(candidates: DataFrame, queries: DataFrame, k: int = 5, scale: int = 256, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """``(query_id, rank, vec_id, score)``; queries and candidates have the same two columns."""
    spark = candidates.sparkSession
    pick = lambda d: d.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("v"))
    numbered = cut(pick(queries).withColumn("part", F.spark_partition_id()).withColumn("nth", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)), "queries")
    per_part = numbered.groupBy("part").count()
    base = per_part.withColumn("base", F.coalesce(F.sum("count").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select(F.col("part").alias("p"), "base")
    numbered = cut(numbered.join(F.broadcast(base), F.col("part") == F.col("p")).select("id", "v", F.floor((F.col("base") + F.col("nth")) / QUERY_BLOCK).alias("block")), "query-blocks")
    last = numbered.agg(F.max("block")).first()[0]
    out_schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])
    schema = "query_id long, vec_id long, score long"
    if last is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    answers, order = [], Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    for nth in range(last + 1):
        held = [pair for b in numbered.where(F.col("block") == nth).select("id", "v").toArrow().to_batches() for pair in quantised(b, scale)]  # at most QUERY_BLOCK rows
        shared = spark.sparkContext.broadcast(held)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            groups = shared.value
            total = sum(len(i) for i, _ in groups)
            best, starts, at = Best(total, k), [], 0
            for i, _ in groups:
                starts.append(at)
                at += len(i)
            waiting: dict[int, list] = {}

            def work(n: int) -> None:
                ids, block = (np.concatenate(x) for x in zip(*waiting.pop(n)))
                for start, (query_ids, queries) in zip(starts, groups):
                    if queries.shape[1] == n:
                        search_block(ids, block, query_ids, queries, best, start + np.arange(len(query_ids)))

            for batch in batches:
                for ids, block in quantised(batch, scale):
                    for a in range(0, len(ids), BLOCK):
                        waiting.setdefault(block.shape[1], []).append((ids[a : a + BLOCK], block[a : a + BLOCK]))
                        if sum(len(i) for i, _ in waiting[block.shape[1]]) >= BLOCK:
                            work(block.shape[1])
            for n in list(waiting):
                work(n)
            if total:
                query_ids = np.repeat(np.concatenate([i for i, _ in groups]), k)
                found = (best.scores != _EMPTY).ravel()
                yield pa.RecordBatch.from_arrays([pa.array(query_ids[found]), pa.array(best.ids.ravel()[found]), pa.array(best.scores.ravel()[found])], schema=out_schema)

        found = pick(candidates).mapInArrow(run, schema)
        answers.append(cut(found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k), "answers"))
        shared.destroy()
    drop(numbered)
    return reduce(DataFrame.unionByName, answers).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def query(spark, sf_dir: str) -> DataFrame:
    from patternwalk.sources.tables import table

    vectors = table(spark, sf_dir, "embeddings")
    return top_k(vectors, vectors.where(F.col("vec_id") % 50 == 0))


ORACLE = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.e::DOUBLE[], c.e::DOUBLE[])::BIGINT AS score
  FROM v q JOIN v c ON c.vec_id <> q.vec_id WHERE q.vec_id % 50 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, rank::INT AS rank, vec_id, score FROM r WHERE rank <= 5
"""
