import zlib

import numpy as np
from pyspark.sql import types as T

from patternwalk.llm import quality

DOCS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("x", T.StringType()), T.StructField("score", T.StringType())])
SF = "/root/testdata/sf0.01"


def test_scores_equal_plain_log_densities():
    rng = np.random.default_rng(0)
    x = [rng.normal(0, 1, (200, 3)) @ np.diag([1, 2, 0.5]), rng.normal(1, 1, (300, 3))]
    d = quality.Discriminant(np.array([200.0, 300.0]), np.array([a.sum(0) for a in x]), np.array([a.T @ a for a in x]))
    every = np.concatenate(x)
    z = [(a - every.mean(0)) / every.std(0) for a in x]
    at = (every - every.mean(0)) / every.std(0)
    log = []
    for a in z:
        cov = np.cov(a.T)
        cov = 0.9 * cov + 0.1 * np.trace(cov) / 3 * np.eye(3)
        e = at - a.mean(0)
        log.append(np.log(len(a) / 500) - 0.5 * np.linalg.slogdet(cov)[1] - 0.5 * np.einsum("ij,jk,ik->i", e, np.linalg.inv(cov), e))
    assert np.allclose(d.score(every), 1 / (1 + np.exp(log[0] - log[1])))


def test_held_out_accuracy_and_edge_rows(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    measured = quality.measure(docs)
    model = quality.fit(measured, labels)
    truth = {r.doc_id: r.quality for r in labels.collect()}
    got = {r.doc_id: r for r in quality.score(measured, model).collect()}
    assert len(got) == docs.count()
    own = [i for i in truth if zlib.crc32(str(i).encode()) % 4 == 2]
    assert sum(got[i].predicted == truth[i] for i in own) >= 0.95 * len(own)
    odd = [(1, None, "", ""), (2, "", "", ""), (None, "no id", "", ""), (4, "long " * 200_000, "", ""), (4, "long " * 200_000, "", "")]
    rows = quality.score(quality.measure(spark.createDataFrame(odd, DOCS)), model).collect()
    by = {r.doc_id: r.score for r in rows}
    assert len(rows) == 5 and all(0 <= r.score <= 1 for r in rows) and by[1] == by[2]


def test_nothing_labelled_and_an_empty_table(spark):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    docs = spark.createDataFrame([(1, "a b", "", "")], DOCS)
    measured = quality.measure(docs)
    assert quality.score(measured, quality.fit(measured, labels)).first().score == 0.5
    none = quality.measure(docs.limit(0))
    assert quality.score(none, quality.fit(none, labels)).count() == 0
