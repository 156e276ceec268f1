"""Groups of near-copies: texts whose word shingles have a Jaccard similarity of at least a threshold, by an exact join.

1. *Equal sets* of shingles collapse to one node, so that copies of any number are compared once.
2. *Fingerprints.* Texts whose SimHash fingerprints the BK-trees of operator 10 link are compared; most copies meet here.
3. *Prefixes.* Similar sets of ``n`` shingles share one of the first ``n - ceil(t n) + 1`` of a global order. The
   order is rarity, then hash: any order finds all pairs. The shingles of all texts are counted, by hash bucket.
4. *Stars.* All sets that share a prefix shingle are compared with the least of them, at one comparison a set,
   which settles most groups of many near-copies.
5. *Pairs.* What shares a prefix shingle and is not yet in one component is compared pair by pair, unless lengths
   and places rule out the overlap. The smaller of two sets needs to have the shingle among its first
   ``n - ceil(2 t n / (1 + t)) + 1`` only.
6. *Sketches.* The parities of a set's shingles in ``SKETCH`` hash classes: two sketches differ in no more bits than the
   sets in shingles, so a pair whose sketches differ in more than similar sets can is dropped without its texts.
7. *Verify.* A pair links only if its sets, worked out from the texts again, are similar enough. Groups are connected components.

Defined results: a text without a word has the empty text's one shingle, fewer words than a shingle are one shingle.
Rows without an id take no part. An empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patternwalk.llm.lean import tidily
from patternwalk.llm.line_dedup import bounded
from patternwalk.llm.simhash import components, links, majority, shingle_hashes
from patternwalk.plans.scratch import cut, drop

THRESHOLD = 0.8
#: One text in so many is counted for the order: every one. Only a test sets it.
SAMPLE = 1
#: Buckets of shingle counts: the size of a table that every worker holds. So many partial tables reach the driver at most.
COUNTED, TABLES = 1 << 20, 32
#: Bits of a sketch; sets of more than about twice so many shingles pass it unseen.
SKETCH = 2048


def shingles(text: str | None, width: int = 5) -> np.ndarray:
    """The distinct hashes of a text's shingles, ascending."""
    return np.unique(shingle_hashes(text, width))


def _sig(own: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(own.tobytes(), len(own)) - (1 << 63)


def _sketch(own: np.ndarray) -> bytes:
    return np.packbits(np.bincount((own & np.uint64(SKETCH - 1)).astype(np.int64), minlength=SKETCH) & 1).tobytes()


def _per_text(docs: DataFrame, of_text, schema: str, types: list[pa.DataType]) -> DataFrame:
    """A row or more for each ``doc_id, text``; ``of_text`` gives an array for each column after ``doc_id``."""
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                batch = whole.slice(at, 256)
                found = [of_text(t.as_py()) for t in batch.column(1)]
                ids = np.repeat(batch.column(0).to_numpy(zero_copy_only=False), [len(x[0]) for x in found])
                columns = [pa.array(np.concatenate([x[k] for x in found]) if t != pa.binary() else [b for x in found for b in x[k]], t) for k, t in enumerate(types)]
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), *columns], names=names)

    return docs.select("doc_id", "text").mapInArrow(tidily(run), schema)


def _least(t: float, n):
    """``ceil(t * n)`` with room for the floats."""
    return np.ceil(t * n - 1e-9).astype(np.int64) if isinstance(n, np.ndarray) else int(np.ceil(t * n - 1e-9))


def _facts(docs: DataFrame, width: int) -> DataFrame:
    """``doc_id, sig, n, fp, sketch, counts``: a row for each text, and for each task one without ``sig`` whose ``counts`` are those of its texts' shingles by bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, types = ["doc_id", "sig", "n", "fp", "sketch", "counts"], [pa.int64()] * 4 + [pa.binary()] * 2
        counts, any_text = np.zeros(COUNTED, np.int64), False
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                batch, rows = whole.slice(at, 256), []
                for text in batch.column(1):
                    hashes = shingle_hashes(text.as_py(), width)
                    own = np.unique(hashes)
                    np.add.at(counts, _bucket(own), 1)
                    rows.append((_sig(own), len(own), majority(hashes), _sketch(own)))
                any_text = True
                sig, n, fp, sketch = zip(*rows)
                columns = [sig, n, np.array(fp, np.uint64).view(np.int64), sketch, [None] * len(rows)]
                yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), *(pa.array(c, t) for c, t in zip(columns, types[1:]))], names=names)
        if any_text:
            yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip([None] * 5 + [zlib.compress(counts.tobytes(), 1)], types)], names=names)

    return docs.select("doc_id", "text").mapInArrow(tidily(run), "doc_id long, sig long, n long, fp long, sketch binary, counts binary")


def _bucket(own: np.ndarray) -> np.ndarray:
    return (own & np.uint64(COUNTED - 1)).astype(np.int64)


def _total(tables) -> np.ndarray:
    total = np.zeros(COUNTED, np.int64)
    for t in tables:
        total += np.frombuffer(zlib.decompress(t), np.int64)
    return total


def _counts(facts: DataFrame) -> np.ndarray:
    """In how many texts the shingles of each bucket are, all told."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield pa.RecordBatch.from_arrays([pa.array([zlib.compress(_total(t.as_py() for b in batches for t in b.column(0)).tobytes(), 1)], pa.binary())], names=["counts"])

    parts = facts.where("counts IS NOT NULL").select("counts").coalesce(TABLES).mapInArrow(tidily(run), "counts binary")
    return _total(bytes(r.counts) for r in parts.collect())


def _prefixes(docs: DataFrame, width: int, threshold: float, counts) -> DataFrame:
    """``doc_id, key, sig, n, at``: the prefix shingles of each text, those of the least of the broadcast counts. Sets of so few shingles that only equal ones are similar have none."""
    def of_text(text: str | None):
        own = shingles(text, width)
        n = len(own)
        length = n - _least(threshold, n) + 1 if _least(threshold, n + 1) <= n else 0
        key = own[np.lexsort((own, counts.value[_bucket(own)]))[:length]]
        return key.view(np.int64), np.full(length, _sig(own)), np.full(length, n), np.arange(length)

    return _per_text(docs, of_text, "doc_id long, key long, sig long, n int, at int", [pa.int64(), pa.int64(), pa.int32(), pa.int32()])


def _fits(x: str, y: str, threshold: float) -> Column:
    """Lengths and places leave room for the overlap of similar sets."""
    c = lambda t, name: F.col(f"{t}.{name}")
    left = F.least(c(x, "n") - c(x, "at"), c(y, "n") - c(y, "at")) + F.least(c(x, "at"), c(y, "at"))
    return (F.least(c(x, "n"), c(y, "n")) >= F.lit(threshold) * F.greatest(c(x, "n"), c(y, "n")) - 1e-9) & (left >= F.lit(threshold / (1 + threshold)) * (c(x, "n") + c(y, "n")) - 1e-9)


def _similar(pairs: DataFrame, docs: DataFrame, firsts: DataFrame, width: int, threshold: float) -> DataFrame:
    """``u, v`` of the pairs whose sets are similar, as a cut table; the sets come from one text each."""
    facts = firsts.select("sig", "n", "sketch")
    one, two = (facts.select(F.col("sig").alias(e), F.col("n").alias(f"n{e}"), F.col("sketch").alias(f"s{e}")) for e in "uv")

    def alike(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (np.frombuffer(b"".join(batch.column(k).to_pylist()), np.uint64).reshape(-1, SKETCH // 64) for k in (4, 5))
            n = batch.column(2).to_numpy() + batch.column(3).to_numpy()
            differ = np.bitwise_count(a ^ b).sum(axis=1, dtype=np.int64)
            yield batch.select([0, 1]).filter(pa.array(differ <= n - 2 * _least(threshold / (1 + threshold), n)))

    pairs = cut(pairs.join(one, "u").join(two, "v").select("u", "v", "nu", "nv", "su", "sv").mapInArrow(alike, "u long, v long"), "alike")
    ends = pairs.select(F.col("u").alias("sig")).unionByName(pairs.select(F.col("v").alias("sig"))).distinct()
    wanted = cut(ends.join(firsts, "sig").select(F.col("first_id").alias("wanted_id")).distinct(), "wanted")
    texts = docs.join(bounded(wanted), docs.doc_id == wanted.wanted_id, "left_semi")

    def of_text(text: str | None):
        own = shingles(text, width)
        return np.array([_sig(own)]), [own.tobytes()]

    held = cut(_per_text(texts, of_text, "doc_id long, sig long, own binary", [pa.int64(), pa.binary()]).drop("doc_id"), "sets")
    sets = held.dropDuplicates(["sig"])
    both = pairs.join(sets.select(F.col("sig").alias("u"), F.col("own").alias("a")), "u").join(sets.select(F.col("sig").alias("v"), F.col("own").alias("b")), "v")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for a, b in zip(batch.column(2), batch.column(3)):
                a, b = (np.frombuffer(x.as_buffer(), np.uint64) for x in (a, b))
                shared = len(np.intersect1d(a, b, assume_unique=True))
                good.append(shared >= threshold * (len(a) + len(b) - shared) - 1e-9)
            yield batch.select([0, 1]).filter(pa.array(good, pa.bool_()))

    out = cut(both.select("u", "v", "a", "b").mapInArrow(run, "u long, v long"), "similar")
    drop(pairs, wanted, held)
    return out


def near_copy_groups(docs: DataFrame, width: int = 5, threshold: float = THRESHOLD, radius: int = 4) -> DataFrame:
    """``doc_id, fp, component_id`` for each row of ``docs`` with an id; ``component_id`` is the group's smallest id."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where("doc_id IS NOT NULL")

    facts = cut(_facts(docs, width), "sigs")
    rows = facts.where("sig IS NOT NULL").drop("counts")
    firsts = cut(rows.groupBy("sig").agg(F.min("doc_id").alias("first_id"), F.first("n").alias("n"), F.min("fp").alias("fp"), F.first("sketch").alias("sketch")), "first-texts")

    by_print = firsts.groupBy("fp").agg(F.min("sig").alias("head"))
    same = firsts.join(by_print, "fp").where("sig != head").select(F.col("head").alias("u"), F.col("sig").alias("v"))
    found = cut(links(by_print.select("fp"), radius), "print-links")
    heads = lambda end: by_print.select(F.col("fp").alias(end), F.col("head").alias(f"{end}_sig"))
    met = found.join(heads("u"), "u").join(heads("v"), "v").select(F.col("u_sig").alias("u"), F.col("v_sig").alias("v"))
    met = cut(same.unionByName(met).distinct(), "prints-met")
    near = _similar(met, docs, firsts, width, threshold)
    drop(found, met)

    copies = cut(rows.select("doc_id").distinct().join(firsts.select(F.col("first_id").alias("doc_id")), "doc_id", "left_anti"), "copies")
    own = docs.join(bounded(copies), "doc_id", "left_anti")
    by_key = Window.partitionBy("key")
    whole = by_key.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    # Two columns travel as one: this is the stage's largest exchange.
    both = F.shiftleft(F.col("n").cast("long"), 32).bitwiseOR(F.col("at").cast("long"))
    n, at = (lambda c: F.shiftright(c, 32).cast("int")), (lambda c: F.col(c).bitwiseAND((1 << 32) - 1).cast("int"))
    counts = docs.sparkSession.sparkContext.broadcast(_counts(facts))
    postings = _prefixes(own, width, threshold, counts).select("key", "sig", both.alias("both"))
    met = postings.select("*", F.min(F.struct("sig", "both")).over(whole).alias("first"), F.max("sig").over(whole).alias("last")).where(F.col("first.sig") != F.col("last"))
    shared = met.select("key", "sig", n("both").alias("n"), at("both").alias("at"), F.struct(F.col("first.sig").alias("sig"), n("first.both").alias("n"), at("first.both").alias("at")).alias("head"))
    shared = cut(shared, "shared", hashes=True)
    counts.destroy()
    drop(copies)

    roots = components(near)
    named = shared.join(roots, shared.sig == roots.node, "left").select(*shared.columns, F.coalesce("root", "sig").alias("root"))
    head_root = roots.select(F.col("node").alias("head_node"), F.col("root").alias("head_root"))
    apart = named.join(head_root, named["head.sig"] == head_root.head_node, "left").where(F.coalesce("head_root", "head.sig") != F.col("root"))
    meeting = apart.select(F.struct("sig", "n", "at").alias("x"), F.col("head").alias("y")).where((F.col("x.sig") != F.col("y.sig")) & _fits("x", "y", threshold))
    stars = cut(meeting.select(F.col("y.sig").alias("u"), F.col("x.sig").alias("v")).distinct(), "stars")
    starred = _similar(stars, docs, firsts, width, threshold)
    drop(roots)
    roots = components(near.unionByName(starred))

    named = shared.join(roots, shared.sig == roots.node, "left").select("key", "sig", "n", "at", F.coalesce("root", "sig").alias("root"))
    open_keys = cut(named.select("*", F.min("root").over(whole).alias("low"), F.max("root").over(whole).alias("high")).where("low != high").drop("low", "high"), "open")
    x, y = open_keys.alias("x"), open_keys.alias("y")
    y = y.where(F.col("n") - F.col("at") >= F.lit(2 * threshold / (1 + threshold)) * F.col("n") - 1e-9)
    smaller = (F.col("y.n") < F.col("x.n")) | ((F.col("y.n") == F.col("x.n")) & (F.col("y.sig") < F.col("x.sig")))
    meet = (F.col("x.key") == F.col("y.key")) & smaller & (F.col("x.root") != F.col("y.root")) & _fits("x", "y", threshold)
    pairs = cut(x.join(y, meet).select(F.least("x.sig", "y.sig").alias("u"), F.greatest("x.sig", "y.sig").alias("v")).distinct().join(stars, ["u", "v"], "left_anti"), "pairs")
    drop(shared, open_keys, stars, roots)
    rest = _similar(pairs, docs, firsts, width, threshold)
    roots = components(near.unionByName(starred).unionByName(rest))
    drop(pairs, near, starred, rest)
    member = firsts.join(roots, firsts.sig == roots.node, "left").select("sig", "first_id", F.coalesce("root", "sig").alias("root"))
    group = member.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = member.join(group, "root").select(F.col("sig").alias("node"), "component_id")
    groups = cut(rows.join(named, rows.sig == named.node).select("doc_id", "fp", "component_id"), "groups")
    drop(facts, firsts, roots)
    return groups
