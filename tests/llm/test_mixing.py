import itertools
import random

import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from patternwalk.llm import mixing

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("source", T.StringType()), T.StructField("size", T.IntegerType()), T.StructField("taken", T.StringType())])


def reshared(sizes, weights, ratio=1.5, most=2.0):
    """The rule in words: share by weight, hold the overfull at their most, share the excess again."""
    out, free = [0.0] * len(sizes), set(range(len(sizes)))
    left = ratio * sum(sizes)
    while free:
        w = sum(weights[i] for i in free)
        over = {i for i in free if left * weights[i] / w > most * sizes[i]}
        if not over:
            for i in free:
                out[i] = left * weights[i] / w
            break
        for i in over:
            out[i] = most * sizes[i]
            left -= out[i]
        free -= over
    return out


@pytest.mark.parametrize("seed", range(6))
def test_quotas(seed):
    rng = random.Random(seed)
    sizes = [rng.randrange(1, 1000) for _ in range(12)]
    weights = mixing.cycled_weights(12)
    assert mixing.quotas(sizes, weights) == pytest.approx(reshared(sizes, weights))


@pytest.mark.parametrize("seed", range(8))
def test_route_costs_no_more_than_any_other(seed):
    """Small whole-word cases against every possible division."""
    rng = random.Random(seed)
    patterns = [("a",), ("a", "b"), ("b", "c")]
    supply = {p: rng.randrange(1, 4) for p in patterns}
    quota = {s: rng.randrange(0, 4) for s in "abc"}
    flow = mixing.route(supply, quota)
    arcs = [(p, s) for p in patterns for s in p]

    def cost(use):
        return sum(max(0, use[p] - supply[p]) for p in patterns)

    best = None
    for x in itertools.product(range(5), repeat=len(arcs)):
        use, got = dict.fromkeys(patterns, 0), dict.fromkeys("abc", 0)
        for (p, s), n in zip(arcs, x):
            use[p] += n
            got[s] += n
        if all(use[p] <= 2 * supply[p] for p in patterns) and all(got[s] <= quota[s] for s in "abc"):
            key = (-sum(got.values()), cost(use))
            best = key if best is None else min(best, key)
    use = dict.fromkeys(patterns, 0)
    for (p, _), n in flow.items():
        use[p] += n
    assert (-sum(flow.values()), cost(use)) == pytest.approx(best)


def docs(spark):
    rng = random.Random(1)
    rows = []
    for i in range(300):
        source = "hot" if i % 3 == 0 else rng.choice(["a", "b", None, "z"])
        rows.append((i, " ".join("w" * rng.randrange(1, 5) for _ in range(rng.randrange(40))), source, 1, "x"))
    rows += [(900, None, "a", 1, "x"), (901, "", "only-empty", 1, "x"), (902, "v " * 3000, "z", 1, "x"), (7, "again and again", "a", 1, "x"), (None, "no id", "b", 1, "x")]
    return spark.createDataFrame(rows, SCHEMA)


def test_mix_reaches_targets_and_reruns_agree(spark):
    d = docs(spark)
    got = mixing.mix(d, F.array("source")).collect()
    again = mixing.mix(d.repartition(7), F.array("source")).collect()
    key = lambda r: (r.doc_id is None, r.doc_id or 0, r.size, r.taken)
    assert sorted(map(key, got)) == sorted(map(key, again))
    assert len(got) == 305
    by = {}
    for r in got:
        assert 0 <= r.taken <= 2 * r.size
        x = by.setdefault(r.first_source, [0, r.target, 0, r.source_size])
        x[0] += r.taken
        x[2] = max(x[2], r.size)
    assert list(by) and set(by) == {"hot", "a", "b", None, "z", "only-empty"}
    names = sorted(by, key=lambda s: (s is None, s or ""))
    assert [by[s][1] for s in names] == pytest.approx(reshared([by[s][3] for s in names], mixing.cycled_weights(len(names))))
    assert all(abs(taken - target) <= most / 2 + 1 for taken, target, most, _ in by.values())


def test_overlapping_sources_and_an_empty_table(spark):
    d = docs(spark).withColumn("m", F.when(F.col("doc_id") % 2 == 0, F.array(F.lit("even"), F.lit("all"))).otherwise(F.array(F.lit("all"))))
    got = mixing.mix(d, F.col("m"), weights=lambda n: [1.0] * n, ratio=1.0).collect()
    assert len(got) == 305 and sum(r.taken for r in got) == pytest.approx(sum(r.size for r in got), rel=0.2)
    assert mixing.mix(d.limit(0), F.array("source")).count() == 0
