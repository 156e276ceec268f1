import math
import random

import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from patternwalk.llm import topk

SCHEMA = T.StructType([T.StructField("vec_id", T.LongType()), T.StructField("embedding", T.ArrayType(T.FloatType())), T.StructField("score", T.StringType()), T.StructField("rank", T.StringType())])


def brute(rows, k=5, every=50):
    import numpy as np

    whole = {}
    for i, (vec_id, v, *_) in enumerate(rows):
        if vec_id is not None and v and all(x is not None and math.isfinite(x) for x in v):
            whole[i] = (vec_id, [math.floor(256 * float(np.float32(x))) for x in v])
    out = []
    for q, a in whole.values():
        if q % every:
            continue
        scores = sorted((-sum(x * y for x, y in zip(a, b)), c) for c, b in whole.values() if c != q and len(a) == len(b))[:k]
        out += [(q, n + 1, c, -s) for n, (s, c) in enumerate(scores)]
    return sorted(out)


@pytest.mark.parametrize("block", [8, 4096])
def test_top_k_against_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(topk, "BLOCK", block)
    monkeypatch.setattr(topk, "_FIRST_DEPTH", 2)
    monkeypatch.setattr(topk, "QUERY_BLOCK", 4)
    rng = random.Random(2)
    rows = [(i, [rng.gauss(0, 1) if rng.random() < 0.7 else 0.0 for _ in range(8)], "", "") for i in range(400)]
    rows += [(1000 + i, rows[50][1], "", "") for i in range(8)]  # ties
    rows += [(1100, None, "", ""), (1150, [1.0, None], "", ""), (1200, [float("nan")] * 8, "", ""), (1250, [float("inf")] * 8, "", ""), (1300, [0.0] * 8, "", ""), (1350, [1.0, 2.0], "", ""), (1351, [1.0, 2.0], "", ""), (None, [1.0] * 8, "", ""), (1400, [], "", ""), (1450, [1e9] * 8, "", "")]
    df = spark.createDataFrame(rows, SCHEMA).repartition(5)
    got = topk.top_k(df, df.where(F.col("vec_id") % 50 == 0)).collect()
    assert sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in got) == brute(rows)


def test_the_walk_stops_early_on_skewed_lists():
    import numpy as np

    rng = np.random.default_rng(1)
    block = np.floor(np.exp(3 * rng.standard_normal((4000, 4))))
    best = topk.Best(1, 5)
    query = np.array([[1.0, 1.0, 0.0, 0.0]])
    scored = topk.search_block(np.arange(4000), block, np.array([-1]), query, best, np.array([0]))
    assert scored < 1000
    assert best.ids[0].tolist() == np.lexsort((np.arange(4000), -(block @ query[0])))[:5].tolist()


def test_empty_table(spark):
    df = spark.createDataFrame([], SCHEMA)
    assert topk.top_k(df, df).count() == 0
