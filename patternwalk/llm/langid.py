"""Operator 5: language identification by cross-parsing.

For each language a suffix automaton is built from a bounded sample of labelled
text. A text is then parsed once per language: the phrase at hand grows as long as
the automaton knows it, and a new phrase starts where it does not. The fewer phrases a
language needs for the text, the more of it that language has already said. Counts are
normalised by the language's own rate on held-back labelled text, and the language
with the least normalised count wins.

An automaton becomes one dense table: next state for each state and letter class,
with the restart after a mismatch folded in and marked by the sign. A batch of texts
is parsed in lockstep, one lane per text and language, so that a step is a table
lookup for all lanes; lanes are sorted by length and drop out as they end. Texts are
parsed whole.

The model is fitted on at most ``SAMPLE_CHARS`` characters a language, and at most
``MAX_LANGUAGES`` languages, taken in a hash order of ids from the rows that may be
learned from; scoring covers every row.

Defined results: null text, empty text and text without a letter give ``und`` with score
0. Rows with a null id are never learned from. With no labelled row at all, every
text is ``und``. Ties go to the first language by name. Only text is read to predict.
Repeated rows get equal results.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patternwalk.llm.lean import tidily

SAMPLE_CHARS = 12_000
#: Labelled characters a language, beyond those, on which its own rate of phrases is measured.
RATE_CHARS = 6_000
#: Rows looked at per language to fill the sample.
SAMPLE_ROWS = 64
MAX_LANGUAGES = 256
CLASSES = 48
_BREAK, _OTHER = 0, 1
#: Code points there are.
_SPACE = 0x110000


def held_out(id_col: str = "doc_id") -> Column:
    """Rows that may not be learned from: the CRC-32 of the id as text leaves 2 when divided by 4."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2, F.lit(False))


@lru_cache(maxsize=1)
def _letters() -> tuple[np.ndarray, np.ndarray]:
    """For each code point: its lower case, and whether it is a letter."""
    lower, letter = np.arange(_SPACE, dtype=np.uint32), np.zeros(_SPACE, bool)
    for i in range(_SPACE):
        c = chr(i)
        if unicodedata.category(c)[0] == "L":
            letter[i] = True
            low = c.lower()
            if len(low) == 1:
                lower[i] = ord(low)
    return lower, letter


class Automaton:
    """All substrings of a text over small integers, by states of equal end positions."""

    def __init__(self, symbols: list[int]) -> None:
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]
        last = 0
        for c in symbols:
            last = self._extend(last, c)

    def _extend(self, last: int, c: int) -> int:
        new = len(self.next)
        self.next.append({})
        self.length.append(self.length[last] + 1)
        self.link.append(0)
        p = last
        while p >= 0 and c not in self.next[p]:
            self.next[p][c] = new
            p = self.link[p]
        if p >= 0:
            q = self.next[p][c]
            if self.length[q] == self.length[p] + 1:
                self.link[new] = q
            else:
                twin = len(self.next)
                self.next.append(dict(self.next[q]))
                self.length.append(self.length[p] + 1)
                self.link.append(self.link[q])
                while p >= 0 and self.next[p].get(c) == q:
                    self.next[p][c] = twin
                    p = self.link[p]
                self.link[q] = self.link[new] = twin
        return new

    def table(self, classes: int) -> np.ndarray:
        """``[state, class]`` to the next state; a new phrase is the bitwise complement of the state after its first symbol."""
        out = np.full((len(self.next), classes), 0, np.int32)
        start = np.zeros(classes, np.int32)
        for c, to in self.next[0].items():
            start[c] = to
        out[:] = ~start
        for s, steps in enumerate(self.next[1:], 1):  # the first state is that of no phrase: whatever follows starts one
            for c, to in steps.items():
                out[s, c] = to
        return out


def phrases(symbols: list[int], automaton: Automaton) -> int:
    """The cross-parse of one text, step by step: what the tables do for many."""
    state, count = 0, 0
    for c in symbols:
        if state and c in automaton.next[state]:
            state = automaton.next[state][c]
        else:
            count += 1
            state = automaton.next[0].get(c, 0)
    return count


class Model:
    """Letter classes, one table for all languages, and each language's own phrase rate."""

    def __init__(self, samples: dict[str, list[str]], sample_chars: int = SAMPLE_CHARS, rate_chars: int = RATE_CHARS) -> None:
        self.languages = sorted(samples)
        lower, letter = _letters()
        seen = np.zeros(_SPACE, np.int64)
        raw = {lang: np.concatenate([self._points(t) for t in texts] or [np.zeros(0, np.uint32)]) for lang, texts in samples.items()}
        for points in raw.values():
            seen += np.bincount(lower[points], minlength=_SPACE)
        seen[~letter[np.arange(_SPACE)]] = 0
        known = np.argsort(-seen, kind="stable")[: CLASSES - 2]
        known = known[seen[known] > 0]
        self.class_of = np.where(letter, _OTHER, _BREAK).astype(np.uint8)
        of_lower = np.full(_SPACE, _OTHER, np.uint8)
        of_lower[known] = np.arange(2, 2 + len(known))
        self.class_of[letter] = of_lower[lower[letter]]
        tables, base, self.rates = [], 0, []
        self.roots = []
        for lang in self.languages:
            symbols = self._squeeze(self.class_of[raw[lang]])
            learned, rest = symbols[:sample_chars], symbols[sample_chars : sample_chars + rate_chars]
            if len(rest) < 500:  # little text: measure the rate on a part that is not learned from
                k = len(symbols) * 3 // 4
                learned, rest = symbols[:k], symbols[k:]
            automaton = Automaton(learned.tolist())
            table = automaton.table(CLASSES)
            tables.append(np.where(table >= 0, (table + base) * CLASSES, ~((~table + base) * CLASSES)).astype(np.int32))
            self.roots.append(base * CLASSES)
            base += len(table)
            self.rates.append(max(phrases(rest.tolist(), automaton) / max(1, len(rest)), 1e-3))
        self.table = np.concatenate(tables).ravel() if tables else np.zeros(0, np.int32)

    @staticmethod
    def _points(text: str) -> np.ndarray:
        return np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)

    @staticmethod
    def _squeeze(symbols: np.ndarray) -> np.ndarray:
        """Runs of breaks become one."""
        if not len(symbols):
            return symbols
        keep = np.ones(len(symbols), bool)
        keep[1:] = (symbols[1:] != _BREAK) | (symbols[:-1] != _BREAK)
        return symbols[keep]

    def counts(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Phrases by text and language, and the symbols of each text; zero symbols where there is no letter."""
        symbols = [self._squeeze(self.class_of[self._points(t)]) for t in texts]
        length = np.array([len(s) if s.any() else 0 for s in symbols], np.int64)
        n, k = len(texts), len(self.languages)
        found = np.zeros((n, k), np.int64)
        order = np.argsort(-length, kind="stable")
        order = order[length[order] > 0]
        if not len(order) or not k:
            return found, length
        flat = np.concatenate([symbols[i] for i in order]).astype(np.int32)
        ends = np.cumsum(length[order])
        at = (ends - length[order]).astype(np.int64)
        state = np.repeat(np.array(self.roots, np.int32)[:, None], len(order), axis=1)
        restarts = np.zeros(state.shape, np.int32)
        alive = np.searchsorted(-length[order], -np.arange(int(length[order[0]])), side="left")  # lanes longer than each step
        m = len(order)
        table = self.table
        for step in range(int(length[order[0]])):
            if alive[step] != m:
                m = int(alive[step])
                found[order[m : state.shape[1]]] = restarts[:, m:].T
                state, restarts, at = state[:, :m].copy(), restarts[:, :m].copy(), at[:m]
            state = table.take(state + flat.take(at + step))
            back = state >> 31
            restarts -= back
            state ^= back
        found[order[:m]] = restarts.T
        return found, length

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, score and the winner's normalised count: about 1 for text like the language's own, more for text that none knows."""
        found, length = self.counts(texts)
        if not self.languages:
            return ["und"] * len(texts), np.zeros(len(texts)), np.full(len(texts), np.inf)
        rate = found / np.maximum(length, 1)[:, None] / np.array(self.rates)
        best = rate.argmin(axis=1)
        top = rate[np.arange(len(texts)), best]
        rest = np.where(np.arange(len(self.languages))[None, :] == best[:, None], np.inf, rate).min(axis=1)
        score = np.where(np.isinf(rest), 1.0, 1.0 / (1.0 + np.exp(-12.0 * (1.0 - top / np.where(np.isinf(rest), 1.0, rest)))))
        none = length == 0
        return ["und" if x else self.languages[b] for x, b in zip(none, best)], np.where(none, 0.0, score), np.where(none, np.inf, top)


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang") -> Model:
    """A model of the rows that may be learned from; a bounded number of rows and characters reaches the driver."""
    d = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"), F.col(label_col).alias("l"))
    usable = d.where((F.length("t") > 0) & F.col("l").isNotNull() & F.col("id").isNotNull() & ~held_out("id")).withColumn("h", F.xxhash64(F.col("id").cast("string")))
    # First the least hashes of each language, on narrow rows; then the texts of those alone.
    order = Window.partitionBy("l").orderBy("h")
    least = usable.select("l", "h").withColumn("r", F.row_number().over(order)).where(F.col("r") <= SAMPLE_ROWS).groupBy("l").agg(F.max("h").alias("top")).limit(MAX_LANGUAGES + 1).collect()
    if len(least) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} languages")
    if not least:
        return Model({})
    tops = docs.sparkSession.createDataFrame([(r.l, r.top) for r in least], "l string, top long")
    near = usable.join(F.broadcast(tops), "l").where("h <= top").select("l", "h", F.substring("t", 1, SAMPLE_CHARS + RATE_CHARS).alias("t"))
    rows = near.withColumn("r", F.row_number().over(Window.partitionBy("l").orderBy("h", "t"))).where(F.col("r") <= SAMPLE_ROWS)
    samples: dict[str, list[str]] = {}
    for r in rows.orderBy("l", "r").toLocalIterator():
        texts = samples.setdefault(r.l, [])
        if sum(map(len, texts)) < SAMPLE_CHARS + RATE_CHARS:
            texts.append(r.t + "\n")
    return Model(samples)


def identify(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``lang_pred, score, rate`` beside the id and the columns to keep."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = list(dict.fromkeys([id_col, *(keep or [])]))
    kept = docs.select(*dict.fromkeys([*names, text_col]))  # texts are what fills a batch: a kept text travels once
    at_text = kept.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for whole in batches:
            for at in range(0, max(1, whole.num_rows), 1024):
                b = whole.slice(at, 1024)
                langs, score, rate = own.predict([t or "" for t in b.column(at_text).to_pylist()])
                yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(names))), pa.array(langs, pa.string()), pa.array(score, pa.float64()), pa.array(rate, pa.float64())], names=[*names, "lang_pred", "score", "rate"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields[: len(names)])
    return kept.mapInArrow(tidily(run, "langid"), f"{fields}, lang_pred string, score double, rate double")


def query(spark, sf_dir: str) -> DataFrame:
    from patternwalk.sources.tables import table

    docs = table(spark, sf_dir, "documents")
    found = identify(docs, fit(docs))
    return found.select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
