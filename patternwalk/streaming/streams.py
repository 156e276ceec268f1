"""Streams: edges as they arrive, incremental supports, windows, and a pattern queue that never ends."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from patternwalk.operators.queue import PatternQueue, QueuePolicy
from patternwalk.sources.builders import NEAR, RADIUS, event_label

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A file stream of events; ``ts`` becomes a timestamp that watermarks understand."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def edge_stream(events: DataFrame, alphabet: str = "coarse", watermark: str = "2 days") -> DataFrame:
    """``gid, src, dst, elabel, la, lb, ts`` of each new event with the user's events of the last radius, and with the one before.

    The state of a user is the events that can still get an edge. Events later than the
    watermark are dropped before they reach the state.
    """
    labelled = events.withWatermark("ts", watermark).select(F.col("user_id").alias("gid"), F.col("event_id").alias("vid"), F.unix_micros("ts").alias("t"), "ts", event_label(alphabet).alias("vlabel"))

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = [tuple(x) for x in state.get[0]] if state.exists else []
        new = sorted((int(t), int(v), str(x)) for f in frames for t, v, x in zip(f["t"], f["vid"], f["vlabel"]))
        rows, every = [], sorted([*held, *new])
        fresh = set(new)
        for i, (t, v, x) in enumerate(every):
            for j in range(i - 1, -1, -1):
                u, w, y = every[j]
                if t - u > RADIUS and j < i - 1:
                    break
                if (t, v, x) in fresh or (u, w, y) in fresh:
                    gap = t - u
                    rows.append((int(key[0]), min(v, w), max(v, w), "1" if gap <= NEAR else "2" if gap <= RADIUS else "3", min(x, y), max(x, y)))
        if every:
            last = every[-1][0]
            keep = [e for e in every if last - e[0] <= 2 * RADIUS] or every[-1:]
            state.update(([{"t": t, "v": v, "x": x} for t, v, x in keep],))
        yield pd.DataFrame(rows, columns=["gid", "src", "dst", "elabel", "la", "lb"], dtype=object)

    return labelled.groupBy("gid").applyInPandasWithState(step, "gid long, src long, dst long, elabel string, la string, lb string", "held array<struct<t:long,v:long,x:string>>", "append", GroupStateTimeout.NoTimeout)


def running_type_counts(events: DataFrame, alphabet: str = "coarse") -> DataFrame:
    """Users by label so far: a streaming aggregate, complete or update mode."""
    return events.select(F.col("user_id").alias("gid"), event_label(alphabet).alias("vlabel")).groupBy("vlabel").agg(F.approx_count_distinct("gid").alias("graphs"), F.count("*").alias("events"))


def windowed_activity(events: DataFrame, width: str = "1 day", slide: str | None = None, watermark: str = "2 days") -> DataFrame:
    """Events by type in tumbling or sliding windows; late rows beyond the watermark are left out."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", watermark).groupBy(w, "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "43 hours", watermark: str = "2 days") -> DataFrame:
    """A user's runs of events with no gap beyond the radius: the connected parts before far edges."""
    return events.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "n")


def once_per_event(events: DataFrame, watermark: str = "2 days") -> DataFrame:
    """Repeated deliveries of an event dropped within the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def with_dictionary(events: DataFrame, labels: DataFrame) -> DataFrame:
    """Stream-static join: events with the row of a small label table."""
    return events.join(F.broadcast(labels), "event_type", "left")


def queue_stream(samples: DataFrame, policy: QueuePolicy, shards: int = 8) -> DataFrame:
    """The bounded queue, in shards by code, over a stream of ``code, gid, score, iter``; emits each shard's queue as it stands after a batch (update mode)."""
    part = QueuePolicy(max(1, policy.capacity // shards), "off" if policy.gate == "off" else "after_lookup", policy.ties)

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        queue = PatternQueue(part)
        for code, ids, score, time in state.get[0] if state.exists else []:
            queue.restore(code, ids, score, time)
        new = pd.concat(list(frames)).sort_values(["iter", "gid"], kind="stable")
        for code, gid, score, i in zip(new["code"], new["gid"], new["score"], new["iter"]):
            queue.offer(lambda code=code: str(code), int(gid), float(score), int(i))
        rows = queue.rows()
        state.update(([{"code": c, "ids": ids, "score": s, "time": t} for c, _, s, t, ids in rows],))
        yield pd.DataFrame([(int(key[0]), c, n, s, t) for c, n, s, t, _ in rows], columns=["shard", "code", "exp_support", "score", "last_time"], dtype=object)

    sharded = samples.select(F.pmod(F.xxhash64("code"), F.lit(shards)).cast("int").alias("shard"), "code", "gid", "score", "iter")
    return sharded.groupBy("shard").applyInPandasWithState(step, "shard int, code string, exp_support int, score double, last_time long", "entries array<struct<code:string,ids:array<long>,score:double,time:long>>", "update", GroupStateTimeout.NoTimeout)


def drain(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over what is there and return what it wrote (to memory: for tests and small reports)."""
    writer = stream.writeStream.format("memory").queryName(name).outputMode(mode)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    q = writer.trigger(availableNow=True).start()
    try:
        q.awaitTermination()
    finally:
        q.stop()
    return stream.sparkSession.table(name)
