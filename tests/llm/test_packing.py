import itertools
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import types as T

from patternwalk.llm import packing

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("length", T.StringType()), T.StructField("rank", T.StringType())])


def reference_ids(text):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(str(public_tokenizers.path(packing.VOCABULARY)))
    return t.encode(text or "", add_special_tokens=False).ids + [2]


def test_word_ids_equal_the_tokenizers():
    texts = ["", " a  b\n\nc", "It's don't 12,345 é ÀÉ x<|endoftext|>y", "tab\there\r\nand  nbsp em", "İstanbul ΣΑΣ ́ combining é", "Hello, World!! " * 50, "x" * 500 + " tail", "a\x1cb\x85c\xa0d", "½²ª_snake_ O'Neill'LL 'tis", "ŉ ǅ Ǆ"]
    own = packing.tokenizer(packing.VOCABULARY).encode(texts)
    assert [np.frombuffer(x, "<u4").tolist() + [2] for x in own] == [reference_ids(t) for t in texts]


@pytest.mark.parametrize("seed", range(5))
def test_knapsack_against_every_multiset(seed):
    rng = random.Random(seed)
    sizes = np.array(sorted(rng.sample(range(2, 12), 4)))
    prices = np.array([rng.random() for _ in sizes])
    value, count = packing.best_pattern(sizes, prices, 20)
    best = max(sum(n * p for n, p in zip(x, prices)) for x in itertools.product(range(11), repeat=4) if sum(n * s for n, s in zip(x, sizes)) <= 20)
    assert value == pytest.approx(best) and (count * sizes).sum() <= 20 and count @ prices == pytest.approx(best)


def test_the_program_reaches_a_known_optimum():
    """Rolls of 9: a full roll needs an odd number of threes, so ten rolls can be full and seven and a half hold eight."""
    sizes, demand = np.array([2, 3, 4]), np.array([20.0, 10.0, 20.0])
    _, uses = packing.solve(sizes, demand, 9, gap=0)
    assert uses.sum() == pytest.approx(17.5)


@pytest.mark.parametrize("seed", range(4))
def test_plan_holds_every_piece_and_little_air(seed):
    rng = np.random.default_rng(seed)
    counts = {int(g): int(n) for g, n in zip(rng.choice(np.arange(1, 513), 200, replace=False), rng.integers(1, 400, 200))}
    got, room = {}, 0
    for n, held in packing.plan(counts, 512):
        assert n > 0 and sum(g * k for g, k in held) <= 512
        room += n
        for g, k in held:
            got[g] = got.get(g, 0) + n * k
    assert got == counts
    sizes = np.array(sorted(counts))
    _, uses = packing.solve(sizes, np.array([counts[int(g)] for g in sizes], float), 512)
    assert uses.sum() * (1 - 2e-4) - 1e-6 <= room <= 1.02 * uses.sum() + 1


def test_pack(spark):
    rng = random.Random(5)
    texts = [None, "", " ", "word " * 9000] + [" ".join(rng.choice(["alpha", "beta!", "Γάμμα", "12"]) for _ in range(rng.randrange(1, 900))) for _ in range(300)]
    rows = [(i, t, "clash", "clash") for i, t in enumerate(texts)] + [(5, "same row", "", ""), (5, "same row", "", ""), (None, "no id", "", "")]
    got = packing.pack(spark.createDataFrame(rows, SCHEMA)).collect()
    by_doc, by_seq = {}, {}
    for r in got:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_seq.setdefault(r.sequence_id, []).append(r)
    assert len(by_doc[5]) == 3 and len(by_doc[None]) == 1
    for i, t in enumerate(texts):
        if i == 5:
            continue
        ids, at = reference_ids(t), 0
        for r in sorted(by_doc[i], key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids)
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    padded = 0
    for own in by_seq.values():
        at = 0
        for r in sorted(own, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 4096 and own[0].sequence_tokens == at
        padded += own[0].padded_tokens
    assert padded <= 1.05 * sum(r.length for r in got)
    assert packing.pack(spark.createDataFrame([], SCHEMA)).count() == 0
