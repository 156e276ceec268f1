"""The miner: schedule, walk, name, queue, read out."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from patternwalk.model import GraphDB
from patternwalk.operators.queue import QueuePolicy, lossless_queue, queue_order, replay_queue, sharded_queue
from patternwalk.operators.sampler import run_walks


def ranked(queue: DataFrame, k: int, by: tuple[str, ...] = ()) -> DataFrame:
    """The first ``k`` of each group in queue order. Spark keeps ``k`` rows a partition before it moves any."""
    place = F.row_number().over(Window.partitionBy(*(by or [F.lit(0)])).orderBy(*queue_order()))
    if not by:
        queue = queue.orderBy(*queue_order()).limit(k)
    return queue.withColumn("rank", place).where(F.col("rank") <= k)


def mine_top_k(db: GraphDB, p: int, k: int = 500, m: int = 10_000, score: str = "s2", induced: bool = True, queue: QueuePolicy | None = None, emit: str = "accepted", seed: int = 0, chains: int = 1, mode: str = "counter", shards: int = 0, types: DataFrame | None = None, naming: str = "dfs", scores=None) -> DataFrame:
    """``chain, rank, code, exp_support, score, last_time``: the ``k`` patterns sampled from the most graphs.

    ``queue=None`` aggregates without a bound; a policy replays the bounded queue, in
    ``shards`` parts if given (one chain then). ``naming``: which canonical string ``code`` is. ``scores``: as of :func:`run_walks`.
    """
    samples = run_walks(db, p, m, score, seed, chains, induced, emit, mode, types=types, scores=scores)
    if queue is None:
        found = lossless_queue(samples, ("chain",), naming=naming)
    elif shards:
        found = sharded_queue(samples, queue, shards, naming=naming).withColumn("chain", F.lit(0))
    else:
        found = replay_queue(samples, queue, naming=naming)
    return ranked(found, k, ("chain",)).select("chain", "rank", "code", "exp_support", "score", "last_time")


def mine_sizes(db: GraphDB, sizes: list[int], **options) -> DataFrame:
    """A session per size."""
    return reduce(DataFrame.unionByName, [mine_top_k(db, p, **options).withColumn("p", F.lit(p)) for p in sizes])
