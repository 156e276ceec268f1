from pyspark.sql import functions as F

from patternwalk.operators import queue as Q
from patternwalk.operators import sampler as W
from patternwalk.operators.canon import with_code
from patternwalk.sources import builders
from patternwalk.streaming import streams

SF = "/root/testdata/sf0.001"


def days(spark, path, late=True):
    """Events by day as files in time order; some held back two days where ``late``."""
    e = spark.read.parquet(f"{SF}/events.parquet")
    day = F.date_trunc("day", "ts")
    e = e.withColumn("day", F.when((F.col("event_id") % 97 == 0) & F.lit(late), day + F.expr("INTERVAL 2 DAYS")).otherwise(day))
    for i, d in enumerate(r.day for r in e.select("day").distinct().orderBy("day").collect()):
        e.where(F.col("day") == d).drop("day").coalesce(1).write.mode("append").parquet(f"{path}/in")
    return f"{path}/in"


def test_edges_of_the_stream_equal_the_batch(spark, tmp_path):
    path = days(spark, str(tmp_path), late=False)
    got = streams.drain(streams.edge_stream(streams.event_stream(spark, path, 1000)), "edges_seen")
    want = builders.proximity(spark, SF, "coarse").edges
    key = lambda d: sorted(tuple(r) for r in d.select("gid", "src", "dst", "elabel").distinct().collect())
    assert key(got) == key(want)


def test_windows_sessions_and_repeats(spark, tmp_path):
    path = days(spark, str(tmp_path))
    e = streams.event_stream(spark, path, 1000)
    n = streams.drain(streams.windowed_activity(e), "activity", "complete").agg(F.sum("n")).first()[0]
    assert n == spark.read.parquet(f"{SF}/events.parquet").count()
    assert streams.drain(streams.once_per_event(e), "once").count() == n
    assert streams.drain(streams.running_type_counts(e), "types", "complete").count() == 5


def test_queue_of_the_stream_equals_the_shards(spark, tmp_path):
    db = builders.proximity(spark, SF, "coarse").stored()
    coded = with_code(W.run_walks(db, 3, 500)).select("code", "gid", "score", "iter")
    coded.write.parquet(str(tmp_path / "samples"))
    stream = spark.readStream.schema(coded.schema).parquet(str(tmp_path / "samples"))
    got = streams.drain(streams.queue_stream(stream, Q.QueuePolicy(10**6, "off"), 3), "queue_seen", "update")
    want = Q.lossless_queue(coded)
    key = lambda d: sorted(tuple(r) for r in d.select("code", "exp_support", "last_time").collect())
    assert key(got) == key(want)
