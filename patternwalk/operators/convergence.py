"""When to stop: chains that agree."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from patternwalk.functions.accuracy import chain_jaccard, gelman_rubin
from patternwalk.model import GraphDB
from patternwalk.operators.canon import with_code
from patternwalk.operators.mine import ranked
from patternwalk.operators.queue import expected_support
from patternwalk.operators.sampler import run_walks
from patternwalk.operators.support import edge_support
from patternwalk.plans.scratch import cut


def run_until(db: GraphDB, p: int, k: int = 100, epsilon: float = 0.2, r_hat: float = 1.1, first: int = 1000, most: int = 64_000, chains: int = 10, score: str = "s2", seed: int = 0) -> tuple[DataFrame, list[dict]]:
    """Samples of all chains and the trace of each checkpoint, doubling the iterations until the chains agree twice running.

    The chains are rows of one job. An epoch starts from the states that the last one left
    in a cut table; two numbers come to the driver per checkpoint.
    """
    types = edge_support(db)
    state, at, every, trace, good = None, 0, None, [], 0
    step = first
    while at < most:
        samples, moved = run_walks(db, p, step, score, seed, chains, first=at + 1, state=state, types=types, want_state=True)
        own = cut(with_code(samples, method="inline").select("chain", "iter", "gid", "score", "code"), "samples")
        state = cut(moved, "state")
        every = own if every is None else every.unionByName(own)
        at += step
        top = ranked(expected_support(every, ("chain",)), k, ("chain",))
        distance = chain_jaccard(top).first().distance
        rhat = gelman_rubin(every).first().r_hat
        trace.append({"iters": at, "distance": distance, "r_hat": rhat})
        good = good + 1 if distance is not None and distance <= epsilon and (rhat or 0.0) <= r_hat else 0
        if good == 2:
            break
        step = at
    return every, trace


def stage_times(db: GraphDB, p: int, m: int, score: str = "s2", seed: int = 0) -> DataFrame:
    """``stage, rows, seconds``: sampling, naming and queueing, each timed where it runs, one after another in one process."""
    import time

    from patternwalk.operators.canon import dfs_code
    from patternwalk.operators.queue import PatternQueue, QueuePolicy

    spark = db.spark
    t0 = time.perf_counter()
    rows = run_walks(db, p, m, score, seed).select("iter", "gid", "raw", "score").orderBy("iter").collect()  # m rows of a timing run
    t1 = time.perf_counter()
    codes = [dfs_code(r.raw) for r in rows]
    t2 = time.perf_counter()
    queue = PatternQueue(QueuePolicy())
    for r, code in zip(rows, codes):
        queue.offer(lambda code=code: code, r.gid, r.score, r.iter)
    t3 = time.perf_counter()
    return spark.createDataFrame([("sampling", len(rows), t1 - t0), ("naming", len(set(codes)), t2 - t1), ("queueing", len(queue.entries), t3 - t2)], "stage string, rows long, seconds double").withColumn("p", F.lit(p))
