"""Operator 2: pack token pieces into sequences by cutting-stock column generation.

1. Each text is tokenised once. A document longer than a sequence is cut at
   multiples of the capacity; whole sequences need no packing, rests do.
2. Pieces are counted by length class (``GRAIN`` tokens wide, so at most
   ``capacity / GRAIN`` rows reach the driver, whatever the corpus).
3. On the driver a linear program over patterns (how many pieces of each class a
   sequence holds) is solved by column generation: a knapsack dynamic program over the
   dual prices finds the best new pattern, until Farley's bound says that the
   program is within ``gap`` of its optimum.
4. The solution is rounded down; what demand remains is packed largest piece first,
   each sequence with the others that fill it best.
   Where even so over 1 % would be padding, because most pieces exceed half a
   sequence, rests are cut at halves, quarters or eighths of it and planned again.
5. Pieces are ranked within their class in a seeded order, and ranks are dealt to
   the slots of the patterns. Ranks come from counts by class and hash bucket plus
   a ``row_number`` within a bucket, so no class is ever sorted in one task.

A sequence is padded to the capacity, unless its tokens are a power of two.

Defined results: null and empty texts have only the end id, one piece of length 1.
Repeated rows are packed each for itself. An empty table gives an empty result.
Only the id and text columns are read, so extra columns do no harm. A text of any
length is tokenised as a whole.
"""

from __future__ import annotations

import re
import sys
import zlib
from array import array
from collections import Counter
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from patternwalk.llm.lean import keeps, small_batches, tidily
from patternwalk.llm.mixing import place
from patternwalk.plans.scratch import cut

CAPACITY = 4096
GRAIN = 8
END_ID = 2
VOCABULARY = "word_bpe_49k.json"
#: Distinct words whose ids a worker remembers, and the longest of them.
MEMO, MEMO_CHARS = 200_000, 40
#: Pieces of the most common class that are ranked in one task, about.
BUCKET = 20_000
#: A rest may also be cut at multiples of the capacity halved so often; used only where sequences would hold too much padding without.
LEVELS = 4
ENOUGH = 1.01
_PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, levels long"


#: Texts of characters up to U+024F are split here as the vocabulary file's normaliser and pattern would: they are
#: composed already, and lower case goes character by character. All others go through the tokenizer as a whole.
_BEYOND = re.compile("[^\x00-\u024f]")
_LETTER, _NUMBER, _SPACE = "a-z\u00aa\u00b5\u00ba\u00df-\u00f6\u00f8-\u024f", "0-9\u00b2\u00b3\u00b9\u00bc-\u00be", " \\t-\\r\x85\xa0"
_WORDS = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{_LETTER}]+|[{_NUMBER}]|[^{_SPACE}{_LETTER}{_NUMBER}]+")


def pack_ids(ids: list[int]) -> bytes:
    """Little-endian unsigned 32-bit numbers."""
    out = array("I", ids)
    if sys.byteorder == "big":
        out.byteswap()
    return out.tobytes()


class WordTokenizer:
    """The tokenizer's ids as little-endian unsigned 32-bit bytes. No token spans two words, so words are encoded once and remembered."""

    def __init__(self, vocabulary: str) -> None:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        import public_tokenizers
        from tokenizers import Tokenizer, pre_tokenizers

        path = vocabulary if "/" in vocabulary else public_tokenizers.path(vocabulary)
        self.whole = Tokenizer.from_file(str(path))
        self.word = Tokenizer(self.whole.model)
        self.word.pre_tokenizer = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        self.memo: dict[str, bytes] = {}
        self.passed = 0

    def encode(self, texts: list[str]) -> list[bytes]:
        split = [None if _BEYOND.search(t) or "<|" in t else _WORDS.findall(t.lower()) for t in texts]
        memo, passing = self.memo, {}
        if self.passed > 8 * MEMO:
            memo.clear()
            self.passed = 0
        fresh = list(set(chain.from_iterable(filter(None, split))).difference(memo))
        for i in range(0, len(fresh), 4096):
            some = fresh[i : i + 4096]
            for word, found in zip(some, self.word.encode_batch_fast(some, add_special_tokens=False)):
                (memo if len(word) <= MEMO_CHARS and len(memo) < MEMO else passing)[word] = pack_ids(found.ids)
        self.passed += len(passing)
        memo.update(passing)  # for this call
        out = [pack_ids(self.whole.encode(t, add_special_tokens=False).ids) if words is None else b"".join(map(memo.__getitem__, words)) for t, words in zip(texts, split)]
        for word in passing:
            del memo[word]
        return out


_LOADED: dict[str, WordTokenizer] = {}
keeps("packing", _LOADED.clear)


def tokenizer(vocabulary: str) -> WordTokenizer:
    if vocabulary not in _LOADED:
        _LOADED[vocabulary] = WordTokenizer(vocabulary)
    return _LOADED[vocabulary]


def cut_levels(n: int, capacity: int) -> list[tuple[int, int, int]]:
    """``(start, length, levels)``: whole sequences at every level, and the rest as level ``k`` cuts it, by ``capacity >> k``."""
    if n <= capacity >> LEVELS - 1:
        return [(0, n, (1 << LEVELS) - 1)]
    whole = n // capacity * capacity
    found: dict[tuple[int, int], int] = {(s, capacity): (1 << LEVELS) - 1 for s in range(0, whole, capacity)}
    for k in range(LEVELS):
        step = capacity >> k
        for s in range(whole, n, step):
            key = (s, min(step, n - s))
            found[key] = found.get(key, 0) | 1 << k
    return [(s, size, levels) for (s, size), levels in found.items()]


def pieces(docs: DataFrame, capacity: int = CAPACITY, vocabulary: str = VOCABULARY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: ``doc_id, start, length, ids_crc32, doc_tokens`` and ``levels``, the cutting levels that have this piece as bits."""
    schema = pa.schema([(c, pa.int64()) for c in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "levels")])
    end = END_ID.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = tokenizer(vocabulary).encode
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                batch = whole.slice(at, 256)
                rows = []
                for doc, ids in zip(batch.column(0).to_pylist(), encode([t or "" for t in batch.column(1).to_pylist()])):
                    ids += end
                    n = len(ids) // 4
                    rows += [(doc, s, size, zlib.crc32(ids[4 * s : 4 * (s + size)]), n, levels) for s, size, levels in cut_levels(n, capacity)]
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*rows)] if rows else [pa.array([], pa.int64())] * 6, schema=schema)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tidily(run, "packing"), _PIECE)


def best_pattern(sizes: np.ndarray, prices: np.ndarray, room: int) -> tuple[float, np.ndarray]:
    """The most valuable multiset of sizes that fits ``room``: an unbounded knapsack, by capacity."""
    value, choice = np.zeros(room + 1), np.full(room + 1, -1)
    fits = np.searchsorted(sizes, np.arange(room + 1), side="right")
    for c in range(int(sizes[0]), room + 1):
        value[c] = value[c - 1]
        own = value[c - sizes[: fits[c]]] + prices[: fits[c]]
        k = int(own.argmax())
        if own[k] > value[c]:
            value[c], choice[c] = own[k], k
    count, c = np.zeros(len(sizes), np.int64), room
    while c > 0:
        if choice[c] < 0:
            c -= 1
        else:
            count[choice[c]] += 1
            c -= int(sizes[choice[c]])
    return float(value[room]), count


def solve(sizes: np.ndarray, demand: np.ndarray, room: int, gap: float = 2e-4, rounds: int = 1200) -> tuple[np.ndarray, np.ndarray]:
    """Patterns (a column each) and their fractional uses whose sum is least, by column generation with a revised simplex."""
    n = len(sizes)
    basis = np.diag(room // sizes).astype(np.float64)
    inverse = np.diag(1.0 / basis.diagonal())
    uses = inverse @ demand
    for step in range(rounds):
        prices = np.maximum(inverse.sum(axis=0), 0.0)
        value, pattern = best_pattern(sizes, prices, room)
        if value <= 1 + 1e-9 or uses.sum() * (1 - 1 / value) <= gap * uses.sum():
            break
        held = np.flatnonzero(pattern)
        column = (inverse[:, held] * pattern[held]).sum(axis=1)
        up = column > 1e-9
        if not up.any():
            break
        ratio = np.where(up, uses / np.where(up, column, 1.0), np.inf)
        out = int(ratio.argmin())
        basis[:, out] = pattern
        if step % 400 == 399:
            inverse = np.linalg.inv(basis)
            uses = np.maximum(inverse @ demand, 0.0)
        else:
            uses = np.maximum(uses - ratio[out] * column, 0.0)
            uses[out] = ratio[out]
            pivot = inverse[out] / column[out]
            inverse -= np.outer(column, pivot)
            inverse[out] = pivot
    return basis.astype(np.int64), uses


def plan(counts: dict[int, int], room: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """``(uses, [(class, pieces of it)])`` for each pattern; together they hold exactly the counted pieces."""
    if not counts:
        return []
    sizes = np.array(sorted(counts), np.int64)
    demand = np.array([counts[int(s)] for s in sizes], np.int64)
    columns, uses = solve(sizes, demand.astype(np.float64), room)
    out = []
    left = demand.copy()
    for j in np.argsort(-uses, kind="stable"):
        held = np.flatnonzero(columns[:, j])
        n = int(min(uses[j] + 1e-6, (left[held] // columns[held, j]).min()))
        if n > 0:
            left -= n * columns[:, j]
            out.append((n, [(int(sizes[i]), int(columns[i, j])) for i in held[::-1]]))
    while left.any():
        took = fullest(sizes, left, room)
        held = np.flatnonzero(took)
        n = int((left[held] // took[held]).min())
        left -= n * took
        out.append((n, [(int(sizes[i]), int(took[i])) for i in held[::-1]]))
    return out


def fullest(sizes: np.ndarray, left: np.ndarray, room: int) -> np.ndarray:
    """The largest piece left and those others that fill its sequence best: a subset sum with counts."""
    took = np.zeros_like(left)
    first = int(np.flatnonzero(left)[-1])
    took[first] = 1
    free = room - int(sizes[first])
    by = np.full(free + 1, -1)  # the class whose piece completed a sum, larger classes first
    by[0] = len(sizes)
    for i in np.flatnonzero(left)[::-1]:
        size, reach = int(sizes[i]), by >= 0
        for _ in range(min(int(left[i] - took[i]), free // size)):
            more = np.zeros_like(reach)
            more[size:] = reach[:-size]
            more &= by < 0
            if not more.any():
                break
            by[more] = i
            reach = more
        if by[free] >= 0:
            break
    c = int(np.flatnonzero(by >= 0)[-1])
    while c > 0:
        i = int(by[c])
        took[i] += 1
        c -= int(sizes[i])
    return took


def pack(docs: DataFrame, capacity: int = CAPACITY, vocabulary: str = VOCABULARY, seed: int = 17, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, sequence_tokens, padded_tokens`` for each piece."""
    spark = docs.sparkSession
    grade = F.ceil(F.col("length") / F.lit(GRAIN)).cast("int")
    with small_batches(spark):
        held = cut(pieces(docs, capacity, vocabulary, id_col, text_col), "pieces")
    every = held.withColumn("grade", grade).withColumn("place", place("doc_id", seed))
    sums = every.groupBy("grade", "levels").agg(F.count("*").alias("n"), F.sum("length").alias("tokens")).collect()
    room, best = capacity // GRAIN, None
    for level in range(LEVELS):
        own = [r for r in sums if r.levels >> level & 1]
        counted = dict(sum((Counter({r.grade: r.n}) for r in own), Counter()))
        found = plan(counted, room)
        padded = sum(uses for uses, _ in found) * capacity
        if best is None or padded < 0.99 * best[0]:
            best = padded, level, counted, found
        if padded <= ENOUGH * sum(r.tokens for r in own) + capacity:
            break
    _, level, counted, patterns = best
    cuts = every.where(F.col("levels").bitwiseAND(1 << level) != 0)
    buckets = max(1, max(counted.values(), default=0) // BUCKET)  # seeded
    bucketed = cuts.withColumn("bucket", (F.col("place") % F.lit(buckets)).cast("int"))
    base = bucketed.groupBy("grade", "bucket").count().select(F.col("grade").alias("g"), F.col("bucket").alias("b"), F.coalesce(F.sum("count").over(Window.partitionBy("grade").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    order = Window.partitionBy("grade", "bucket").orderBy("place", "doc_id", "start")
    ranked = bucketed.join(base, (F.col("grade") == F.col("g")) & (F.col("bucket") == F.col("b"))).withColumn("rank", F.col("base") + F.row_number().over(order) - 1)

    # The slots: from which rank on a class's pieces go to which pattern.
    at, first_rank, slots = 0, dict.fromkeys(counted, 0), []
    for uses, held in patterns:
        before = 0
        for g, each in held:
            slots.append((g << 44 | first_rank[g], at, each, before))
            first_rank[g] += uses * each
            before += each
        at += uses
    slots.sort()
    starts, firsts, each, before = (np.array(x, np.int64) for x in (zip(*slots) if slots else ([], [], [], [])))
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "slot"]
    schema = pa.schema([(c, pa.int64()) for c in names])

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            key = (b.column("grade").to_numpy().astype(np.int64) << 44) | b.column("rank").to_numpy()
            k = np.searchsorted(starts, key, side="right") - 1
            nth = key - starts[k]
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in names[:5]), pa.array(firsts[k] + nth // each[k]), pa.array(before[k] + nth % each[k])], schema=schema)

    dealt = ranked.select(*names[:5], "grade", "rank").mapInArrow(deal, ", ".join(f"{c} long" for c in names))
    one = Window.partitionBy("sequence_id")
    placed = dealt.withColumn("offset", F.sum("length").over(one.orderBy("slot")) - F.col("length")).withColumn("sequence_tokens", F.sum("length").over(one))
    exact = F.col("sequence_tokens").bitwiseAND(F.col("sequence_tokens") - 1) == 0
    return placed.withColumn("padded_tokens", F.when(exact, F.col("sequence_tokens")).otherwise(F.lit(capacity))).drop("slot")


def query(spark, sf_dir: str) -> DataFrame:
    from patternwalk.sources.tables import table

    return pack(table(spark, sf_dir, "documents"))
