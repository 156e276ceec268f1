"""Operator 10: near-duplicates by SimHash fingerprints and BK-trees.

A fingerprint has one bit for each of the 64 bits of the shingles' XXH64 values;
the bit is set if it is set in over half of them. Two fingerprints link if they
differ in at most ``radius`` bits, and a group is a connected component of links.

How the whole corpus is searched without comparing everything with everything:

* Equal fingerprints collapse first (``groupBy`` with map-side combine), so that
  a group of copies of any size is one node.
* The 64 bits are cut into ``radius + 2`` blocks. ``radius`` changed bits leave at
  least two blocks whole, so two linked fingerprints agree on a pair of blocks.
  Each pair of blocks names a shard; a fingerprint goes to one shard per pair.
* A shard's fingerprints form a BK-tree: the children of a node are keyed by
  their Hamming distance to it. All members descend the tree at once and follow
  only edges within ``radius`` of their own distance to the node.
* A shard returns a spanning star of each component that it finds, never its
  pairs, so ``m`` close fingerprints give at most ``m - 1`` links.
* Links of all shards meet in :func:`components`, alternating star contraction
  on a distributed edge table that is cut after each round.

The trees travel to the shards' tasks by shuffle, not by broadcast: their total
grows with the corpus and has no bound that a broadcast could rely on.

Defined results: a null or empty text has no word, hence fingerprint zero, and is
linked like any other. Fewer words than a shingle: the whole sequence is the one
shingle. Repeated rows and ties share a fingerprint and a component. An empty
table gives an empty result. Only the id and text columns are read, so extra
columns with any name do no harm; a null id stays a row and is never a
component's smallest id unless all ids of the component are null.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from patternwalk.llm.lean import small_batches
from patternwalk.plans.scratch import cut, drop

#: The bits of each byte value, most significant first.
_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).astype(np.int64)
_SEED = 42
#: Shards up to this many members use the plain tree; larger ones descend it with arrays. Same links either way.
_SMALL = 48


def shingle_hashes(text: str | None, width: int = 4) -> np.ndarray:
    """The hash of each shingle of a text, repeats included; of fewer words than a shingle, that of the whole sequence."""
    words = (text or "").encode("utf-8", "replace").lower().split()
    joined = b" ".join(words)
    digest = xxhash.xxh64_intdigest
    if len(words) <= width:
        return np.array([digest(joined, _SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1)).tolist()
    return np.fromiter((digest(joined[a:b], _SEED) for a, b in zip(starts, ends[width - 1 :].tolist())), np.uint64)


def fingerprint(text: str | None, width: int = 4) -> int:
    """The unsigned 64-bit fingerprint of a text."""
    if text is None or not text.encode("utf-8", "replace").split():
        return 0
    return majority(shingle_hashes(text, width))


def majority(hashes: np.ndarray) -> int:
    """The bits that are set in over half of the hashes."""
    if len(hashes) == 1:
        return int(hashes[0])
    columns = hashes.astype(">u8").view(np.uint8).reshape(-1, 8) + np.arange(0, 2048, 256, dtype=np.int64)
    seen = np.bincount(columns.ravel(), minlength=2048).reshape(8, 256)
    return int.from_bytes(np.packbits((seen @ _BITS).ravel() * 2 > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, width: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fp)`` for each row; ``fp`` holds the 64 bits as a signed long."""
    schema = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = np.fromiter((fingerprint(t.as_py(), width) for t in batch.column(1)), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found.view(np.int64))], schema=schema)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, fp long")


class BKTree:
    """A tree of distinct 64-bit values whose children are keyed by their Hamming distance to the parent."""

    def __init__(self) -> None:
        self.root: tuple[int, dict] | None = None

    def add(self, value: int) -> None:
        if self.root is None:
            self.root = (value, {})
            return
        node = self.root
        while d := (value ^ node[0]).bit_count():
            below = node[1].get(d)
            if below is None:
                node[1][d] = (value, {})
                return
            node = below

    def within(self, value: int, radius: int) -> list[int]:
        found, todo = [], [self.root] if self.root else []
        while todo:
            own, children = todo.pop()
            d = (value ^ own).bit_count()
            if d <= radius:
                found.append(own)
            todo += [child for edge, child in children.items() if abs(edge - d) <= radius]
        return found


def linked(values: np.ndarray, radius: int) -> np.ndarray:
    """For distinct values, the position of the first member of each one's component."""
    n = len(values)
    label = np.arange(n)
    if n <= _SMALL:
        tree, where, root = BKTree(), {}, list(range(n))

        def top(i: int) -> int:
            while root[i] != i:
                root[i] = i = root[root[i]]
            return i

        for i, value in enumerate(values.tolist()):
            for other in tree.within(value, radius):
                a, b = sorted((top(i), top(where[other])))
                root[b] = a
            tree.add(value)
            where[value] = i
        return np.array([top(i) for i in range(n)])
    # The same tree, built and searched by levels: below a node are the members of its subtree and those still searching it.
    todo = [(np.arange(n), np.arange(n))]
    while todo:
        members, asking = todo.pop()
        node, rest = members[0], members[1:]
        d = np.bitwise_count(values[asking] ^ values[node])
        near = label[asking[d <= radius]]
        if len(near) and len(others := np.unique(near[near != label[node]])):
            group = np.append(others, label[node])
            label[np.isin(label, group)] = group.min()
        if not len(rest):
            continue
        edge = np.bitwise_count(values[rest] ^ values[node])
        for k in np.unique(edge).tolist():
            follow = asking[np.abs(d.astype(np.int16) - k) <= radius]
            if len(follow):
                todo.append((rest[edge == k], follow))
    return label


def _blocks(radius: int) -> list[tuple[int, int]]:
    """``(shift, bits)`` of ``radius + 2`` blocks that cover 64 bits."""
    n, at, out = radius + 2, 0, []
    for i in range(n):
        bits = 64 // n + (i < 64 % n)
        out.append((at, bits))
        at += bits
    return out


def links(nodes: DataFrame, radius: int = 4) -> DataFrame:
    """``(u, v)`` with ``v`` before ``u``: links that join all fingerprints within ``radius`` of each other, directly or by others."""
    blocks = _blocks(radius)
    part = lambda s, b: F.shiftrightunsigned("fp", s).bitwiseAND(F.lit((1 << b) - 1))
    keys = []
    for i, (s, b) in enumerate(blocks):
        for j, (t, c) in enumerate(blocks[i + 1 :], i + 1):
            keys.append(F.shiftleft(F.lit(i * len(blocks) + j).cast("long"), 48).bitwiseOR(F.shiftleft(part(s, b), c)).bitwiseOR(part(t, c)))
    shards = nodes.select("fp", F.explode(F.array(*keys)).alias("shard")).repartition("shard").sortWithinPartitions("shard", "fp")

    def stars(shard_of: np.ndarray, fps: np.ndarray) -> pd.DataFrame:
        cuts = np.flatnonzero(np.diff(shard_of)) + 1
        starts, ends = np.concatenate(([0], cuts)), np.concatenate((cuts, [len(fps)]))
        u, v = [], []
        several = ends - starts > 1
        for a, b in zip(starts[several].tolist(), ends[several].tolist()):
            own = fps[a:b]
            first = linked(own.view(np.uint64), radius)
            off = np.flatnonzero(first != np.arange(b - a))
            u.append(own[off])
            v.append(own[first[off]])
        return pd.DataFrame({"u": np.concatenate(u), "v": np.concatenate(v)} if u else {"u": np.array([], np.int64), "v": np.array([], np.int64)})

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held_s, held_f = [], []  # the last shard may go on in the next batch
        for frame in frames:
            if not len(frame):
                continue
            shard, fps = frame["shard"].to_numpy(), frame["fp"].to_numpy()
            last = int(np.searchsorted(shard, shard[-1]))
            if last == 0 and held_s and held_s[-1][-1] == shard[0]:
                held_s.append(shard)
                held_f.append(fps)
                continue
            done_s, done_f = np.concatenate([*held_s, shard[:last]]), np.concatenate([*held_f, fps[:last]])
            held_s, held_f = [shard[last:]], [fps[last:]]
            if len(done_s):
                yield stars(done_s, done_f)
        if held_s:
            yield stars(np.concatenate(held_s), np.concatenate(held_f))

    return shards.mapInPandas(run, "u long, v long").distinct()


def components(edges: DataFrame, u: str = "u", v: str = "v") -> DataFrame:
    """``(node, root)`` for each node of an undirected edge table, as a cut table; ``root`` is the component's smallest node.

    Each round points the larger neighbours of a node at its smallest one, then the
    smaller ones too, until nothing moves: a number of rounds about the logarithm
    of the longest path. Only minima are gathered per node, so a node of any degree is safe.
    """
    edges = cut(edges.select(F.greatest(u, v).alias("a"), F.least(u, v).alias("b")).where("a != b").distinct(), "links")

    def mark(e: DataFrame):
        return e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()

    before = mark(edges)
    while before[0]:
        both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("k"), F.least("a", "m").alias("m"))
        large = both.join(least, both.a == least.k).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a != b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m")).withColumnRenamed("a", "k")
        small = large.join(low, large.a == low.k)
        small = small.select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e")).select("e.a", "e.b").where("a != b").distinct()
        last, edges = edges, cut(small, "links")
        drop(last)
        after = mark(edges)
        if after == before:
            break
        before = after
    named = edges.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("root")))
    roots = cut(named.distinct(), "roots")
    drop(edges)
    return roots


def near_duplicate_groups(docs: DataFrame, width: int = 4, radius: int = 4, id_col: str = "doc_id", text_col: str = "text", threshold: float | None = None) -> DataFrame:
    """``(doc_id, fp, component_id)`` for each row of ``docs``.

    With a ``threshold``, groups are of texts whose sets of shingles have at least that Jaccard
    similarity: links of fingerprints are then held against the sets, and
    :mod:`~patternwalk.llm.near_texts` adds the links that fingerprints miss. Rows without an id take no part in that.
    """
    if threshold is not None:
        from patternwalk.llm.near_texts import near_copy_groups

        with small_batches(docs.sparkSession):  # its result is a cut table, so all of it runs in here
            return near_copy_groups(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), width, threshold, radius)
    prints = cut(fingerprints(docs, width, id_col, text_col), "prints")
    nodes = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "nodes")
    roots = components(links(nodes, radius))
    member = nodes.join(roots, nodes.fp == roots.node, "left").select("fp", "first_id", F.coalesce("root", "fp").alias("root"))
    group = member.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = member.join(group, "root").select(F.col("fp").alias("node_fp"), "component_id")
    return prints.join(named, prints.fp == named.node_fp).select("doc_id", "fp", "component_id")


def query(spark, sf_dir: str) -> DataFrame:
    from patternwalk.sources.tables import table

    found = near_duplicate_groups(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
