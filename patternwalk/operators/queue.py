"""The pattern queue: bounded, ordered, gated; and its forms for many machines."""

from __future__ import annotations

from bisect import bisect_left, insort
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from patternwalk.operators.canon import NAMINGS, with_code
from patternwalk.plans.scratch import cut

ENTRY = "code string, exp_support int, score double, last_time long, idset array<long>"


@dataclass(frozen=True)
class QueuePolicy:
    """``gate``: ``before_lookup`` (saves the code of what it refuses), ``after_lookup`` (stored patterns are always updated) or ``off``. ``ties``: whether a score equal to the tail's mean is let in."""

    capacity: int = 100_000
    gate: str = "before_lookup"
    ties: str = "admit"


class _Blocks:
    """A sorted list of keys with a number each: inserts and removals touch one block, sums of the tail a row of blocks."""

    def __init__(self, most: int = 512) -> None:
        self.blocks: list[list[tuple]] = [[]]
        self.sums = [0.0]
        self.most, self.n = most, 0

    def _block(self, key: tuple) -> int:
        lo, hi = 0, len(self.blocks) - 1
        while lo < hi:
            mid = (lo + hi) // 2
            if self.blocks[mid] and self.blocks[mid][-1] >= key:
                hi = mid
            else:
                lo = mid + 1
        return lo

    def add(self, key: tuple, value: float) -> None:
        k = self._block(key)
        insort(self.blocks[k], key)
        self.sums[k] += value
        self.n += 1
        if len(self.blocks[k]) > self.most:
            half = len(self.blocks[k]) // 2
            tail = self.blocks[k][half:]
            del self.blocks[k][half:]
            self.blocks.insert(k + 1, tail)
            self.sums[k : k + 1] = [sum(-x[1] for x in self.blocks[k]), sum(-x[1] for x in tail)]

    def remove(self, key: tuple, value: float) -> None:
        k = self._block(key)
        del self.blocks[k][bisect_left(self.blocks[k], key)]
        self.sums[k] -= value
        self.n -= 1
        if not self.blocks[k] and len(self.blocks) > 1:
            del self.blocks[k], self.sums[k]

    def last(self) -> tuple:
        return self.blocks[-1][-1]

    def tail_mean(self) -> float:
        want = left = max(1, self.n // 2)
        total = 0.0
        for block, s in zip(reversed(self.blocks), reversed(self.sums)):
            if len(block) <= left:
                total += s
                left -= len(block)
            else:
                total += sum(-x[1] for x in block[len(block) - left :])
                left = 0
            if not left:
                break
        return total / want


class PatternQueue:
    """Unique by code, ordered by support, score and time of last growth, all descending, then code."""

    def __init__(self, policy: QueuePolicy) -> None:
        self.policy = policy
        self.entries: dict[str, list] = {}  # code -> [ids, score, time]
        self.order = _Blocks()
        self.gated = self.evicted = self.coded = 0

    def _key(self, code: str, entry: list) -> tuple:
        return (-len(entry[0]), -entry[1], -entry[2], code)

    @property
    def full(self) -> bool:
        return len(self.entries) >= self.policy.capacity

    def passes(self, score: float) -> bool:
        if self.policy.gate == "off" or not self.full:
            return True
        mean = self.order.tail_mean()
        return score >= mean if self.policy.ties == "admit" else score > mean

    def offer(self, code_of, gid: int, score: float, time: int) -> None:
        """One sample; ``code_of()`` names its pattern and is called only if the gate needs it."""
        if self.policy.gate == "before_lookup" and not self.passes(score):
            self.gated += 1
            return
        self.coded += 1
        code = code_of()
        entry = self.entries.get(code)
        if entry is not None:
            self.touch(code, entry, gid, time)
        elif self.policy.gate == "after_lookup" and not self.passes(score):
            self.gated += 1
        else:
            self.admit(code, gid, score, time)

    def touch(self, code: str, entry: list, gid: int, time: int) -> None:
        if gid not in entry[0]:
            self.order.remove(self._key(code, entry), entry[1])
            entry[0].add(gid)
            entry[2] = time
            self.order.add(self._key(code, entry), entry[1])

    def admit(self, code: str, gid: int, score: float, time: int) -> None:
        if self.full:
            victim = self.order.last()
            self.order.remove(victim, -victim[1])
            del self.entries[victim[3]]
            self.evicted += 1
        entry = [{gid}, score, time]
        self.entries[code] = entry
        self.order.add(self._key(code, entry), score)

    def restore(self, code: str, ids, score: float, time: int) -> None:
        entry = [set(int(x) for x in ids), score, time]
        self.entries[code] = entry
        self.order.add(self._key(code, entry), score)

    def rows(self) -> list[tuple]:
        out = []
        for block in self.order.blocks:
            out += [(key[3], len(self.entries[key[3]][0]), self.entries[key[3]][1], self.entries[key[3]][2], sorted(self.entries[key[3]][0])) for key in block]
        return out


def queue_order() -> list[Column]:
    return [F.desc("exp_support"), F.desc("score"), F.desc("last_time"), F.asc("code")]


def top_k(queue: DataFrame, k: int) -> DataFrame:
    return queue.orderBy(*queue_order()).limit(k)


def replay_queue(samples: DataFrame, policy: QueuePolicy, by: tuple[str, ...] = ("chain",), codes: str = "lazy", naming: str = "dfs") -> DataFrame:
    """The reference semantics: each chain's samples offered in order of iteration; chains run side by side.

    A chain is one task: this is the sequential form, for samples that one worker can read
    through. ``codes='lazy'`` names only what the gate lets through; ``'eager'`` expects a ``code`` column.
    """
    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        queue, name = PatternQueue(policy), NAMINGS[naming]
        frame = frame.sort_values("iter", kind="stable")
        for raw, gid, score, i in zip(frame["name"], frame["gid"], frame["score"], frame["iter"]):
            queue.offer((lambda raw=raw: name(raw)) if codes == "lazy" else (lambda raw=raw: raw), int(gid), float(score), int(i))
        rows = pd.DataFrame(queue.rows(), columns=["code", "exp_support", "score", "last_time", "idset"], dtype=object)
        for c, v in zip(by, key):
            rows.insert(0, c, v)
        rows["gated"], rows["evicted"], rows["coded"] = queue.gated, queue.evicted, queue.coded
        return rows

    kinds = {f.name: f.dataType.simpleString() for f in samples.schema.fields}
    narrow = samples.select(*by, "iter", "gid", "score", F.col("raw" if codes == "lazy" else "code").alias("name"))
    return narrow.groupBy(*by).applyInPandas(run, ", ".join(f"{c} {kinds[c]}" for c in reversed(by)) + f", {ENTRY}, gated long, evicted long, coded long")


def expected_support(samples: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Distinct graphs that each pattern was sampled from, and when that number last grew; ``samples`` has ``code``.

    Per pattern and graph first, so a common pattern's samples are combined where they are.
    """
    first = samples.groupBy(*by, "code", "gid").agg(F.min("iter").alias("t0"), F.min("score").alias("score"))
    return first.groupBy(*by, "code").agg(F.count("*").cast("int").alias("exp_support"), F.min("score").alias("score"), F.max("t0").alias("last_time"))


def lossless_queue(samples: DataFrame, by: tuple[str, ...] = (), method: str = "inline", naming: str = "dfs") -> DataFrame:
    """The queue without a bound: an aggregation that spills instead of forgetting."""
    coded = samples if "code" in samples.columns else with_code(samples, method=method, naming=naming)
    return expected_support(coded, by)


def sketch_queue(samples: DataFrame, precision: int = 12, naming: str = "dfs") -> DataFrame:
    """Supports by a fixed-size sketch per pattern, for streams that cannot keep id sets."""
    coded = samples if "code" in samples.columns else with_code(samples, method="inline", naming=naming)
    return coded.groupBy("code").agg(F.hll_sketch_estimate(F.hll_sketch_agg("gid", F.lit(precision))).alias("exp_support"), F.max("score").alias("score"))


def sharded_queue(samples: DataFrame, policy: QueuePolicy, shards: int = 8, epochs: int = 4, naming: str = "dfs") -> DataFrame:
    """A bounded queue in ``shards`` parts by code, ``capacity / shards`` entries each.

    Within an epoch all shards work at once. The gate before coding needs a global tail
    mean: it is the mean of the last epoch's shards, one number that goes into the plan as a literal below the coding step.
    """
    spark = samples.sparkSession
    part = QueuePolicy(max(1, policy.capacity // shards), "off" if policy.gate == "off" else "after_lookup", policy.ties)
    span = samples.agg(F.min("iter"), F.max("iter")).first()
    state = spark.createDataFrame([], f"shard int, {ENTRY}, tail double, n long")
    if span[0] is None:
        return state.select("code", "exp_support", "score", "last_time", "idset")
    step = -(-(span[1] - span[0] + 1) // epochs)
    gate = None
    schema = f"shard int, {ENTRY}, tail double, n long"

    def run(key: tuple, new: pd.DataFrame, old: pd.DataFrame) -> pd.DataFrame:
        queue = PatternQueue(part)
        for r in old.itertuples():
            queue.restore(r.code, r.idset, r.score, r.last_time)
        new = new.sort_values(["iter", "gid"], kind="stable")
        for code, gid, score, i in zip(new["code"], new["gid"], new["score"], new["iter"]):
            queue.offer(lambda code=code: code, int(gid), float(score), int(i))
        out = pd.DataFrame(queue.rows(), columns=["code", "exp_support", "score", "last_time", "idset"], dtype=object)
        out.insert(0, "shard", int(key[0]))
        out["tail"], out["n"] = queue.order.tail_mean() if queue.full else None, len(queue.entries)
        return out

    for e in range(epochs):
        a = span[0] + e * step
        own = samples.where((F.col("iter") >= a) & (F.col("iter") < a + step))
        if gate is not None and policy.gate == "before_lookup":
            own = own.where(F.col("score") >= gate if policy.ties == "admit" else F.col("score") > gate)
        coded = with_code(own, method="inline", naming=naming).select(F.pmod(F.xxhash64("code"), F.lit(shards)).cast("int").alias("shard"), "code", "gid", "score", "iter")
        state = cut(coded.groupBy("shard").cogroup(state.groupBy("shard")).applyInPandas(run, schema), "queue")
        gate = state.select("shard", "tail").distinct().agg(F.avg("tail")).first()[0]
    return state.select("code", "exp_support", "score", "last_time", "idset")


def merge_queues(*queues: DataFrame) -> DataFrame:
    """Id sets united, latest time kept: any order, any grouping, the same result."""
    every = queues[0].select("code", "score", "last_time", "idset")
    for q in queues[1:]:
        every = every.unionByName(q.select("code", "score", "last_time", "idset"))
    ids = every.select("code", F.explode("idset").alias("gid")).distinct().groupBy("code").agg(F.sort_array(F.collect_list("gid")).alias("idset"))
    facts = every.groupBy("code").agg(F.max("score").alias("score"), F.max("last_time").alias("last_time"))
    return facts.join(ids, "code").select("code", F.size("idset").alias("exp_support"), "score", "last_time", "idset")


def queue_stats(queue: DataFrame) -> DataFrame:
    """Size, least support, mean score of the lower half, and a measure of memory."""
    from pyspark.sql import Window

    n = queue.count()
    place = F.row_number().over(Window.orderBy(*queue_order()))  # a queue is bounded by its capacity
    half = max(1, n // 2)
    ranked = queue.withColumn("place", place)
    return ranked.agg(F.count("*").alias("size"), F.min("exp_support").alias("least_support"), F.avg(F.when(F.col("place") > n - half, F.col("score"))).alias("tail_mean"), F.sum(F.length("code") + 8 * F.size("idset") + 24).alias("bytes"))


def iterate(rows: Iterator[tuple[str, int, float, int]], policy: QueuePolicy) -> PatternQueue:
    """A queue over ``(code, gid, score, iter)`` in the order given."""
    queue = PatternQueue(policy)
    for code, gid, score, i in rows:
        queue.offer(lambda code=code: code, gid, score, i)
    return queue
