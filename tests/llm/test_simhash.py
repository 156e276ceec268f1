import random

import numpy as np
import pytest
import xxhash
from pyspark.sql import types as T

from patternwalk.llm import simhash

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("fp", T.StringType()), T.StructField("root", T.IntegerType())])


def plain(text, width=4):
    import re

    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if c.isascii() else c for c in text or ""))
    if not words:
        return 0
    hashes = [xxhash.xxh64_intdigest(" ".join(words[i : i + width]).encode(), 42) for i in range(max(1, len(words) - width + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute(prints, radius=4):
    root = list(range(len(prints)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(prints)):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= radius:
                a, b = sorted((top(i), top(j)))
                root[b] = a
    return [top(i) for i in range(len(prints))]


@pytest.mark.parametrize("text", [None, "", " \t\n", "One", "A b C", "A b c d", "É a\x0bÀ b c  d e\x85f g", "x " * 500, "the quick brown fox jumps over the lazy dog"])
def test_fingerprint_against_the_definition(text):
    assert simhash.fingerprint(text) == plain(text)


@pytest.mark.parametrize("n", [5, 40, 300])
def test_small_and_large_trees_find_the_components(n):
    rng = random.Random(n)
    base = [rng.getrandbits(64) for _ in range(6)]
    values = list({b ^ sum(1 << rng.randrange(64) for _ in range(rng.randrange(6))) & (2**64 - 1) for b in base for _ in range(n // 5)})
    assert simhash.linked(np.array(values, np.uint64), 4).tolist() == brute(values)


def test_groups_against_brute_force(spark):
    rng = random.Random(3)
    words = [f"w{i}" for i in range(50)]
    texts = [None, "", " ", "solo"]
    for _ in range(12):
        t = [rng.choice(words) for _ in range(rng.choice([3, 60, 400]))]
        texts.append(" ".join(t))
        for _ in range(rng.randrange(6)):
            u = list(t)
            u[rng.randrange(len(u))] = rng.choice(words)
            texts.append(" ".join(u))
    texts += ["long " * 60_000, "long " * 60_000]
    rows = [(i, t, "clash", 7) for i, t in enumerate(texts)]
    got = {r.doc_id: (r.fp & (2**64 - 1), r.component_id) for r in simhash.near_duplicate_groups(spark.createDataFrame(rows, SCHEMA)).collect()}
    prints = [plain(t) for t in texts]
    assert got == {i: (p, c) for i, (p, c) in enumerate(zip(prints, brute(prints)))}


def test_empty_table_null_ids_and_repeated_rows(spark):
    assert simhash.near_duplicate_groups(spark.createDataFrame([], SCHEMA)).count() == 0
    rows = [(None, "a b c d e", "", 1), (4, "a b c d e", "", 1), (4, "a b c d e", "", 1)]
    got = simhash.near_duplicate_groups(spark.createDataFrame(rows, SCHEMA)).collect()
    assert sorted((r.doc_id or -1, r.component_id) for r in got) == [(-1, 4), (4, 4), (4, 4)]


def test_components_of_a_long_path_and_a_star(spark):
    path = [(i, i + 1) for i in range(0, 60)] + [(100, i) for i in range(101, 140)]
    got = {r.node: r.root for r in simhash.components(spark.createDataFrame(path, "u long, v long")).collect()}
    assert got == {i: 0 for i in range(61)} | {i: 100 for i in range(100, 140)}
