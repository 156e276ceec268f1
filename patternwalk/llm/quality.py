"""Operator 1: document quality by a regularised quadratic discriminant.

Each text is read once and becomes a dozen transformed statistics (logarithms of
shares, ratios of distinct words). The classes' counts, sums and sums of products
are gathered over every labelled row that may be learned from: sums per partition,
then one aggregate, so the driver sees a few hundred numbers whatever the corpus.
Each class covariance is shrunk towards a multiple of the identity; its Cholesky
factor's inverse is worked out once, so a row's log-density is one product. The score is
the posterior probability of label 1.

Defined results: null text counts as empty; an empty text has statistics like any
other and gets a score. Rows whose label is null or other than 0 and 1, or whose
id is null, are not learned from. If a class has fewer than two rows, every score is
the learned share of label 1 (0.5 if nothing is labelled). Repeated rows get equal scores; a label that is
repeated counts as often. Extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from patternwalk.llm.langid import held_out
from patternwalk.plans.scratch import cut

NAMES = ("words", "word_bytes", "upper", "marks", "stops", "digits", "distinct", "commonest", "lines", "bars", "shouts")
SHRINK = 0.1
THRESHOLD = 0.7


def statistics(text: str | None) -> list[float]:
    """The transformed statistics of a whole text."""
    text = text or ""
    seen = np.bincount(np.frombuffer(text.encode("utf-8", "replace"), np.uint8), minlength=256)
    words = text.split()
    n, k = int(seen.sum()), max(1, len(words))
    counts: dict[str, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    upper, lower, high = seen[65:91].sum(), seen[97:123].sum(), seen[128:].sum()
    stops = seen[44] + seen[46]
    marks = seen[33:48].sum() + seen[58:65].sum() + seen[91:97].sum() + seen[123:127].sum() - stops
    share = lambda x: np.log((x + 0.5) / (n + 10))
    return [
        np.log1p(len(words)),
        np.log1p(n / k),
        np.log((upper + 1) / (upper + lower + high + 10)),
        share(marks),
        share(stops),
        share(seen[48:58].sum()),
        len(counts) / k,
        max(counts.values(), default=0) / k,
        np.log1p(10 * (seen[10] + 1) / k),
        share(seen[124]),
        share(seen[33]),
    ]


def measure(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id`` and an array of the statistics, in the order of ``NAMES``."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [statistics(t.as_py()) for t in b.column(1)]
            flat = pa.array(np.array(rows, np.float64).ravel())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(np.arange(0, len(rows) * len(NAMES) + 1, len(NAMES)), pa.int32()), flat)], names=["doc_id", "x"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, x array<double>")


class Discriminant:
    """Class means and Cholesky factors over standardised statistics."""

    def __init__(self, counts: np.ndarray, sums: np.ndarray, products: np.ndarray, shrink: float = SHRINK) -> None:
        total = counts.sum()
        self.prior = float(counts[1] / total) if total else 0.5
        self.usable = bool((counts >= 2).all())
        if not self.usable:
            return
        self.centre = sums.sum(axis=0) / total
        spread = np.sqrt(np.maximum(np.diag(products.sum(axis=0)) / total - self.centre**2, 0.0))
        self.scale = np.where(spread > 1e-9, spread, 1.0)
        self.classes = []
        for k in (0, 1):
            mean = sums[k] / counts[k]
            cov = (products[k] / counts[k] - np.outer(mean, mean)) / np.outer(self.scale, self.scale) * counts[k] / (counts[k] - 1)
            d = len(mean)
            cov = (1 - shrink) * cov + (shrink * max(np.trace(cov) / d, 1e-6)) * np.eye(d)
            factor = np.linalg.cholesky(cov)
            self.classes.append(((mean - self.centre) / self.scale, np.linalg.inv(factor), float(np.log(np.diag(factor)).sum()), float(np.log(counts[k] / total))))

    def score(self, x: np.ndarray) -> np.ndarray:
        if not self.usable:
            return np.full(len(x), self.prior)
        z = (x - self.centre) / self.scale
        log = [prior - half - 0.5 * (((z - mean) @ inverse.T) ** 2).sum(axis=1) for mean, inverse, half, prior in self.classes]
        return 1.0 / (1.0 + np.exp(-np.clip(log[1] - log[0], -500, 500)))


def fit(measured: DataFrame, labels: DataFrame, id_col: str = "doc_id", label_col: str = "quality") -> Discriminant:
    """Learn from every labelled row that is not held out."""
    d = len(NAMES)
    own = labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).alias("y")).where(F.col("y").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out("doc_id"))
    known = measured.join(own, "doc_id").select("x", F.col("y").cast("int").alias("y"))
    upper = np.triu_indices(d)

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = np.zeros((2, 1 + d + len(upper[0])))
        for b in batches:
            x, y = b.column(0).flatten().to_numpy().reshape(-1, d), b.column(1).to_numpy()
            for k in (0, 1):
                z = x[y == k]
                kept[k] += np.concatenate(([len(z)], z.sum(axis=0), (z.T @ z)[upper]))
        n = kept.shape[1]
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat([0, 1], n), pa.int32()), pa.array(np.tile(np.arange(n), 2), pa.int32()), pa.array(kept.ravel())], names=["y", "i", "v"])

    whole = np.zeros((2, 1 + d + len(upper[0])))
    for r in known.mapInArrow(sums, "y int, i int, v double").groupBy("y", "i").agg(F.sum("v").alias("v")).collect():
        whole[r.y, r.i] = r.v
    products = np.zeros((2, d, d))
    for k in (0, 1):
        products[k][upper] = whole[k, 1 + d :]
        products[k] = products[k] + np.triu(products[k], 1).T
    return Discriminant(whole[:, 0], whole[:, 1 : 1 + d], products)


def score(measured: DataFrame, model: Discriminant, threshold: float = THRESHOLD) -> DataFrame:
    """``doc_id, score, predicted``."""
    shared = measured.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = shared.value.score(b.column(1).flatten().to_numpy().reshape(-1, len(NAMES)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found)], names=["doc_id", "score"])

    return measured.mapInArrow(run, "doc_id long, score double").withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def query(spark, sf_dir: str) -> DataFrame:
    from patternwalk.sources.tables import table

    measured = cut(measure(table(spark, sf_dir, "documents")), "measured")
    found = score(measured, fit(measured, table(spark, sf_dir, "labels")))
    return found.select("doc_id", held_out().alias("held_out"), "score", "predicted")
