"""Headline queries at ``$BENCH_SF_DIR`` on ``local[$BENCH_CPUS]``; prints one line of JSON."""

import json
import os
import sys
import time

os.environ.setdefault("OMP_NUM_THREADS", "1")


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from patternwalk.functions import accuracy as A
    from patternwalk.operators import enumerate as E
    from patternwalk.operators import queue as Q
    from patternwalk.operators import sampler as W
    from patternwalk.operators import support as S
    from patternwalk.operators.mine import mine_top_k
    from patternwalk.plans.scratch import cut
    from patternwalk.sources import builders

    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times, facts = {}, {}

    def timed(name, f):
        t = time.perf_counter()
        out = f()
        times[name] = round(time.perf_counter() - t, 3)
        return out

    noop = lambda df: df.write.format("noop").mode("overwrite").save()
    db = timed("build_proximity", lambda: builders.proximity(spark, sf, "skewed").stored())
    types = timed("edge_support", lambda: cut(S.edge_support(db), "types"))
    m = 60_000
    for p in (3, 5, 8):
        timed(f"walk_s2_p{p}", lambda p=p: noop(W.run_walks(db, p, m, "s2", types=types)))
        facts[f"samples_per_s_p{p}"] = round(m / times[f"walk_s2_p{p}"])
    for s in ("uniform", "s1"):
        timed(f"walk_{s}_p5", lambda s=s: noop(W.run_walks(db, 5, m, s, types=types)))
    timed("mine_lossless_p5", lambda: mine_top_k(db, 5, k=500, m=m, types=types).collect())
    timed("mine_bounded_p5", lambda: mine_top_k(db, 5, k=500, m=m, queue=Q.QueuePolicy(10_000), types=types).collect())
    timed("mine_plain_p4", lambda: mine_top_k(db, 4, k=500, m=10_000, induced=False, types=types).collect())
    truth = timed("ground_truth_p3", lambda: E.ground_truth(db, 3, types=types).toPandas())
    found = mine_top_k(db, 3, k=500, m=m, types=types)
    facts["precision_at_500_p3"] = A.precision_at_k(spark.createDataFrame(truth), found, 500).first().precision
    timed("pieces_p4_kernel", lambda: E.space_size(db, 4).agg(F.sum("n")).collect())
    star = timed("build_order_star", lambda: builders.order_star(spark, sf, every=10).stored())
    timed("walk_order_star_p6", lambda: noop(W.run_walks(star, 6, m)))
    print(json.dumps({"metric": "headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(sf.rstrip("/")), "facts": facts}))
    spark.stop()


if __name__ == "__main__":
    sys.exit(main())
