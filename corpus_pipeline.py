"""A training corpus from ``documents``: language, repeated lines, near-copies, mix, packing.

Each stage takes all that its predecessor kept and applies one operator of
``patternwalk.llm``; :func:`run` writes and rereads each stage's rows as Parquet in the
shared folder. All stages but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patternwalk.llm import langid, line_dedup, mixing, packing, simhash
from patternwalk.plans.scratch import cut, drop
from patternwalk.sources.tables import table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Text that needs this many times the phrases of a language's own text is in none of the learned languages: no text
#: of ``SHORT`` characters or more of the labelled rows of the given tables does. Shorter texts are not judged.
FOREIGN, SHORT = 2.2, 40


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, or long enough to judge and foreign to every learned language, go."""
    found = langid.identify(docs, langid.fit(docs), keep=COLUMNS[1:])
    return found.where((F.col("lang_pred") != "und") & ((F.col("rate") <= FOREIGN) | (F.char_length("text") < SHORT))).select(*COLUMNS)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that an earlier document or line has go from the texts; a document stays even if little of it is left."""
    return line_dedup.dedup_lines(docs.select(*COLUMNS)).withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-copies, of a Jaccard similarity of 0.8 on shingles of five words, the document of the smallest id stays; of equal ids, one row. Rows without an id stay."""
    groups = simhash.near_duplicate_groups(docs, width=5, threshold=0.8)
    kept = groups.where(F.col("doc_id") == F.col("component_id")).select(F.col("doc_id").alias("kept_id")).distinct()
    own = docs.select(*COLUMNS)
    named = own.join(kept, F.col("doc_id") == F.col("kept_id"), "left_semi").dropDuplicates(["doc_id"])
    return named.unionByName(own.where(F.col("doc_id").isNull()))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix holds it: not at all, once or twice."""
    mixed = mixing.mix(docs, F.array("source"), keep=COLUMNS[1:])
    return mixed.where("copies > 0").withColumn("_nth", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select(*COLUMNS)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents and their places in sequences."""
    return packing.pack(docs)


STAGES = [("language", language), ("lines", lines), ("near_copies", near_copies), ("mixture", mixture), ("packed", packed)]

#: Tokens and hashes of this pipeline are beyond SQL; tests/llm/test_pipeline.py holds it against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES[:-1]):
        before, docs = docs, cut(stage(spark, docs, sf_dir), f"stage-{name}")
        if k:
            drop(before)
    return STAGES[-1][1](spark, docs, sf_dir)
