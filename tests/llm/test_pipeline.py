import random
import zlib

import numpy as np
from pyspark.sql import functions as F
from pyspark.sql import types as T

import corpus_pipeline as C
from patternwalk.llm import near_texts, packing
from patternwalk.plans.scratch import cut
from tests.llm.test_line_dedup import brute as brute_lines
from tests.llm.test_mixing import reshared
from tests.llm.test_near_texts import brute as brute_groups
from tests.llm.test_packing import reference_ids

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())])


def corpus():
    rng = random.Random(9)
    say = {"aa": "the and of to in that was with for on".split(), "bb": "der die und das nicht ein auf mit von zu".split()}
    rows = []
    for i in range(160):
        lang = "aa" if i % 3 else "bb"
        lines = [" ".join(rng.choice(say[lang]) + rng.choice(["", "ing", "ung", "er"]) for _ in range(rng.randrange(3, 60))) for _ in range(rng.randrange(1, 4))]
        rows.append((i, "\n".join(lines), lang, f"s{i % 4}", 0))
    rows += [(300 + i, rows[i][1], "aa", "s0", 0) for i in range(10)]  # copies
    rows += [(400, None, None, None, 0), (401, "123 456", None, "s1", 0), (402, "", "aa", None, 0), (403, rows[3][1] + " more", None, None, 0)]
    return rows


def test_each_stage_against_brute_force(spark):
    rows = corpus()
    docs = spark.createDataFrame(rows, SCHEMA)
    first = C.language(spark, docs, "")
    kept = sorted(tuple(r) for r in first.collect())
    assert [r[0] for r in kept] == sorted(r[0] for r in rows if r[0] not in (400, 401, 402))
    second = C.lines(spark, spark.createDataFrame(kept, SCHEMA), "")
    got = sorted(tuple(r) for r in second.collect())
    assert second.columns == C.COLUMNS
    assert [(d, t) for d, t, *_ in got] == sorted((d, t) for d, t, _ in brute_lines(kept)) and all(len(t) == n for _, t, _, _, n in got)
    third = sorted(tuple(r) for r in C.near_copies(spark, spark.createDataFrame(got, SCHEMA), "").collect())
    groups = brute_groups([t for _, t, *_ in got])
    assert third == [r for i, r in enumerate(got) if groups[i] == i]
    fourth = [tuple(r) for r in C.mixture(spark, spark.createDataFrame(third, SCHEMA), "").collect()]
    names = sorted({r[3] for r in third}, key=lambda s: (s is None, s or ""))
    sizes = [sum(len(r[1].split()) for r in third if r[3] == s) for s in names]
    for s, target in zip(names, reshared(sizes, [[3, 1, 2][i % 3] for i in range(len(names))])):
        own = [len(r[1].split()) for r in fourth if r[3] == s]
        assert abs(sum(own) - target) <= max(own) and set(r[:3] for r in fourth) <= set(r[:3] for r in third)
    last = C.packed(spark, spark.createDataFrame(fourth, SCHEMA), "").collect()
    text = {r[0]: r[1] for r in fourth}
    assert sum(r.length for r in last) == sum(len(reference_ids(r[1])) for r in fourth)
    for r in last:
        ids = reference_ids(text[r.doc_id])[r.start : r.start + r.length]
        assert r.ids_crc32 == zlib.crc32(np.array(ids, "<u4").tobytes())


def test_language_keeps_short_texts_and_rejects_unlearned_ones(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    odd = [
        (900001, "A", None, "s", 1), (900002, "OK", "en", "s", 2), (900003, "Hello world", "en", "s", 11), (900004, "\U00020000\U00020001", None, "s", 2),
        (900010, "Det var en g\u00e5ng en liten flicka som bodde i en stuga i skogen och hon hette R\u00f6dluvan", "sv", "s", 0),
        (900014, "Egyszer volt hol nem volt egy kis l\u00e1ny aki az erd\u0151 sz\u00e9l\u00e9n lakott az anyj\u00e1val", "hu", "s", 0),
    ]
    odd = [r if r[2] in (None, "en") else (r[0], r[1], None, *r[3:]) for r in odd]
    kept = {r.doc_id for r in C.language(spark, docs.unionByName(spark.createDataFrame(odd, SCHEMA)), "").select("doc_id").collect()}
    assert kept >= {900001, 900002, 900003, 900004} and not kept & {900010, 900014}
    lost = docs.where(~F.col("doc_id").isin(list(kept)) & F.col("text").rlike("\\p{L}")).count()
    assert lost == 0


def test_stages_with_odd_rows(spark):
    nothing = spark.createDataFrame([], SCHEMA)
    long = " ".join(f"w{i % 5000}" for i in range(60_000))
    rows = [(1, None, None, None, None), (None, "one two three four five six", "aa", "s", 0), (2, "same text here " * 5, "aa", "s", 0), (2, "same text here " * 5, "aa", "s", 0), (3, long, "aa", "s", 0), (4, "", "aa", None, 0)]
    docs = spark.createDataFrame(rows, SCHEMA).withColumns({"fp": F.lit("x"), "component_id": F.lit("y"), "line_no": F.lit("z"), "sequence_id": F.lit("w")})
    for name, stage in C.STAGES:
        assert stage(spark, nothing, "").count() == 0, name
        out = stage(spark, docs, "")
        assert name == "packed" or out.columns == C.COLUMNS
        assert out.count() >= 1


def test_run_over_the_smallest_tables(spark):
    got = C.run(spark, "/root/testdata/sf0.001")
    assert {"doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"} <= set(got.columns)
    assert got.count() > 50
    assert packing.CAPACITY == 4096


def test_texts_and_sets_go_to_workers_in_small_batches(spark, monkeypatch):
    """Packing and near-copies hold few rows at once in a worker, and leave the session's setting as it was."""
    setting = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before, seen = spark.conf.get(setting), {}

    def noted(df, name, *args, **options):
        seen[name] = int(spark.conf.get(setting))
        return cut(df, name, *args, **options)

    monkeypatch.setattr(packing, "cut", noted)
    monkeypatch.setattr(near_texts, "cut", noted)
    docs = spark.createDataFrame([(i, "a b c d e f g", "aa", "s", 0) for i in range(3)], SCHEMA)
    assert packing.pack(docs).count() == 3 and C.near_copies(spark, docs, "").count() == 1
    assert all(seen[name] <= 1024 for name in ("pieces", "sigs", "shared", "sets")) and spark.conf.get(setting) == before
