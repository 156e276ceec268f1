"""Operator 8: near-duplicate lines by an exact set-similarity join, in DataFrame functions only.

A line is the set of its lower-cased words. A line is removed if an earlier line, by
``(doc_id, line number)``, has a word set with Jaccard similarity of at least
``threshold`` to its own. How:

1. *Rarity.* The words of all lines are counted, as they are compared, by hash bucket; the logarithm of a
   bucket's count is its level. A set's words are sorted by level, then hash, so every set
   follows one global order, rarest first. (Any such order is exact; rarity only makes it fast.)
2. *Equal sets* collapse to their first line; only first lines go on.
3. *Prefixes.* Similar sets of ``n`` words share one of the first ``n - ceil(t n) + 1``. The smaller of the two, or
   either if they are equal, has it among its first ``n - ceil(2 t n / (1 + t)) + 1`` even: its short prefix.
4. *Join.* Lines meet where a short prefix of the smaller has a prefix word of the larger. The first word that two similar sets have in
   common has no common word before it, so what each set has from there on must hold the
   whole overlap: this joins the length and the position filter. A sketch of a set
   (parities of its words by hash bit) bounds the difference from below.
5. *Verify.* Pairs are compared word by word, a line's likeliest partner first.
6. *Heads.* Before all that, a line meets the ``HEADS`` earliest of those that share one of its first ``LEADING`` words
   with it, at any size of a family a few comparisons each. Lines that are settled so meet no earlier line any more.
7. *Crowds.* On a word that more than ``CROWD`` lines have in their short prefixes, a line again meets the ``HEADS``
   earliest of those that have it in their prefixes first; those not settled then meet all the others.

Defined results: null text stays null; rows with a null id are returned as they are
and remove nothing. Lines without a word are kept. Sets of fewer than four words match equal sets only, which
follows from a threshold of 0.8. Rows that repeat an id count as one document at the
same places: equal texts lose the same lines. A text that loses all lines becomes empty. An
empty table gives an empty result. Extra columns are kept, whatever their names;
the columns that this operator adds to them are ``n_lines`` and ``n_removed``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patternwalk.plans.scratch import cut, drop

THRESHOLD = 0.8
#: Buckets of word counts: the size of a table that every task holds.
COUNTED = 1 << 18
#: A word in the short prefixes of more lines than this is crowded; of a crowd, so many earliest lines are met before all others.
CROWD, HEADS = 1000, 8
#: So many of a line's rarest words name the heads that it meets first.
LEADING = 3
#: So many documents' places are broadcast at most; more of them meet their texts by shuffle.
BROADCAST_DOCS = 500_000
#: Sketches of sets of this size on have 128 bits, of smaller ones 64.
LONG = 90
#: Levels of rarity; with the 59 bits of a word's hash they fill a positive long.
_LEVELS, _BITS = 16, 59


def _spaced(text: str) -> Column:
    """Lower-cased, with every white space of a line as a blank: one character splits faster than a pattern."""
    lower = F.lower(text)
    out, other = lower, F.lit(False)
    for mark in "\t\x0b\f\r":
        out, other = F.replace(out, F.lit(mark), F.lit(" ")), other | F.contains(F.col(text), F.lit(mark))
    return F.when(other, out).otherwise(lower)


def rarity(docs: DataFrame) -> DataFrame:
    """One row, one array: the level of each bucket of words, by the occurrences of all of its words."""
    each = F.explode(F.split(F.replace(_spaced("text"), F.lit("\n"), F.lit(" ")), " ")).alias("w")
    counts = docs.select(each).where("w <> ''").groupBy(F.xxhash64("w").bitwiseAND(COUNTED - 1).alias("slot")).count()
    every = counts.unionByName(docs.sparkSession.range(COUNTED).select(F.col("id").alias("slot"), F.lit(1).cast("long").alias("count"))).groupBy("slot").agg(F.max("count").alias("count"))
    level = F.least(F.floor(F.log2("count")), F.lit(_LEVELS - 1)).cast("tinyint")
    each = every.select("slot", level.alias("level")).agg(F.array_sort(F.collect_list(F.struct("slot", "level"))).alias("all"))
    return each.select(F.col("all.level").alias("levels"))


def words(line: str) -> Column:
    """The set of the hashes of a line's words; white space is blanks only."""
    return F.array_distinct(F.transform(F.array_remove(F.split(line, " "), ""), lambda w: F.xxhash64(w)))


def _least(t: float, n: Column) -> Column:
    """Rounded up with room for the floats: ``ceil(t * n)``."""
    return F.ceil(n * F.lit(t) - 1e-9).cast("int")


def _parity(r: str, each) -> Column:
    return F.aggregate(r, F.lit(0).cast("long"), lambda a, x: a.bitwiseXOR(F.call_function("shiftleft", each(x), x.bitwiseAND(63).cast("int"))))


def later_matches(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """``(doc_id, line_no)`` of each line that an earlier line matches, some more than once, as a cut table; ``docs`` has ``doc_id`` and ``text``."""
    split = docs.select("doc_id", F.posexplode(F.split(_spaced("text"), "\n")).alias("line_no", "line"))
    held = split.select("doc_id", "line_no", words("line").alias("words"), rarity(docs).scalar().alias("levels"))
    level = lambda h: F.shiftleft(F.get("levels", h.bitwiseAND(COUNTED - 1).cast("int")).cast("long"), _BITS)
    sets = held.select("doc_id", "line_no", F.sort_array(F.transform("words", lambda h: level(h).bitwiseOR(F.shiftrightunsigned(h, 64 - _BITS)))).alias("r"))
    n = F.size("r")
    upper = F.when(n >= LONG, _parity("r", lambda x: F.shiftright(x, 6).bitwiseAND(1))).otherwise(F.lit(0).cast("long"))
    prefix = F.when(_least(threshold, n + 1) <= n, F.slice("r", 1, n - _least(threshold, n) + 1))
    lines = sets.select("doc_id", "line_no", F.xxhash64("r").alias("sig"), F.xxhash64(F.lit(1), "r").alias("sig2"), n.alias("n"), _parity("r", lambda x: F.lit(1).cast("long")).alias("s0"), upper.alias("s1"), prefix.alias("prefix"))
    held = cut(lines, "lines", hashes=True)  # a filter before the cut would be pushed below "r" and work it out twice
    lines = held.where("n > 0")
    place = F.row_number().over(Window.partitionBy("sig", "sig2").orderBy("doc_id", "line_no"))
    firsts = cut(lines.select("*", place.alias("nth")).where("nth = 1").select(F.col("doc_id").alias("d"), F.col("line_no").alias("l"), "n", "s0", "s1", "prefix"), "firsts", hashes=True)
    own = firsts.select("d", "l")
    again = cut(lines.select("doc_id", "line_no").join(own, (F.col("doc_id") == F.col("d")) & (F.col("line_no") == F.col("l")), "left_anti"), "again")
    drop(held)

    def postings(lines: DataFrame, *more: str, words="prefix") -> DataFrame:
        each = lines.select("d", "l", "n", "s0", "s1", *more, F.posexplode(words).alias("k", "w"))
        return each.select("w", "d", "l", "n", (F.col("n") - F.col("k")).alias("m"), "s0", "s1", *more)

    def compared(pairs: DataFrame) -> DataFrame:
        """``(d, l)`` of the lines with a similar partner among their pairs ``(d, l, od, ol, differ)``: each is held against its likeliest partner first, and only if that fails against the others."""
        held = cut(pairs, "pairs")
        places = held.select("d", "l").unionByName(held.select(F.col("od").alias("d"), F.col("ol").alias("l"))).groupBy("d").agg(F.collect_set("l").alias("wanted"))
        places = cut(places, "places")
        every = docs.join(bounded(places), docs.doc_id == places.d).select("d", "wanted", F.split(_spaced("text"), "\n").alias("every"))
        picked = every.select("d", F.explode(F.transform("wanted", lambda l: F.struct(l.alias("l"), F.get("every", l).alias("line")))).alias("at"))
        r = cut(picked.select("d", "at.l", words("at.line").alias("r")).dropDuplicates(["d", "l"]), "tokens")

        def similar(some: DataFrame) -> DataFrame:
            both = some.join(r.withColumnRenamed("r", "ra"), ["d", "l"]).join(r.select(F.col("d").alias("od"), F.col("l").alias("ol"), F.col("r").alias("rb")), ["od", "ol"])
            shared = F.size(F.array_intersect("ra", "rb"))
            return both.where(shared >= F.lit(threshold) * (F.size("ra") + F.size("rb") - shared) - 1e-9).select("d", "l")

        best = cut(similar(held.groupBy("d", "l").agg(F.min(F.struct("differ", "od", "ol")).alias("b")).select("d", "l", "b.od", "b.ol")), "best")
        rest = held.drop("differ").join(best, ["d", "l"], "left_anti")
        out = cut(best.unionByName(similar(rest).distinct()), "matched")
        drop(held, places, r, best)
        return out

    c = lambda t, name: F.col(f"{t}.{name}")

    def differ(x: str, y: str) -> Column:
        """Bits in which the sketches differ."""
        wide = F.bit_count(c(x, "s0").bitwiseXOR(c(y, "s0")).bitwiseXOR(c(x, "s1")).bitwiseXOR(c(y, "s1"))) + F.bit_count(c(x, "s1").bitwiseXOR(c(y, "s1")))
        narrow = F.bit_count(c(x, "s0").bitwiseXOR(c(y, "s0")))
        return F.when(F.least(c(x, "n"), c(y, "n")) >= LONG, wide).otherwise(narrow)

    def fits(x: str, y: str) -> Column:
        """The rest of each set from the shared word on holds the overlap of similar sets of these sizes, and the sketches differ in no more bits than they may in words."""
        overlap = F.lit(threshold / (1 + threshold)) * (c(x, "n") + c(y, "n")) - 1e-9
        return (F.least(c(x, "m"), c(y, "m")) >= overlap) & (differ(x, y) <= c(x, "n") + c(y, "n") - 2 * F.ceil(overlap))

    earlier = lambda y, x: (F.col(f"{y}.d") < F.col(f"{x}.d")) | ((F.col(f"{y}.d") == F.col(f"{x}.d")) & (F.col(f"{y}.l") < F.col(f"{x}.l")))
    smaller = (F.col("y.n") < F.col("x.n")) | ((F.col("y.n") == F.col("x.n")) & earlier("y", "x"))
    place_of = lambda late, early: F.struct(*(c(late, k).alias(k) for k in "dl"), *(c(early, k).alias(f"o{k}") for k in "dl"))
    pair = [F.when(earlier("y", "x"), place_of("x", "y")).otherwise(place_of("y", "x")).alias("of"), differ("x", "y").alias("differ")]
    columns = ["of.d", "of.l", "of.od", "of.ol", "differ"]

    def headed(lines: DataFrame) -> DataFrame:
        """Each line with the earliest of its word that it fits."""
        heads = lines.withColumn("nth", F.row_number().over(Window.partitionBy("w").orderBy("d", "l"))).where(F.col("nth") <= HEADS)
        return lines.alias("x").join(heads.alias("y"), (F.col("x.w") == F.col("y.w")) & earlier("y", "x") & fits("x", "y")).select(*pair).select(*columns)

    def marked(settled: DataFrame) -> DataFrame:
        """All first lines, and which of them are still to be settled."""
        done = bounded(settled.select(F.col("d").alias("dd"), F.col("l").alias("dl")).distinct())
        return firsts.join(done, (F.col("d") == F.col("dd")) & (F.col("l") == F.col("dl")), "left").select(*firsts.columns, F.col("dd").isNull().alias("open"))

    def meet(lines: DataFrame, others: DataFrame) -> DataFrame:
        """Pairs of a line and a smaller one whose later is still to be settled."""
        wanted = F.when(earlier("y", "x"), F.col("x.open")).otherwise(F.col("y.open"))
        return lines.alias("x").join(others.alias("y"), (F.col("x.w") == F.col("y.w")) & wanted & smaller & fits("x", "y")).select(*pair).select(*columns)

    led = compared(headed(postings(firsts, words=F.slice("prefix", 1, LEADING))).distinct())
    each = postings(marked(led), "open")
    in_short = F.col("m") >= _least(2 * threshold / (1 + threshold), F.col("n"))
    crowds = cut(postings(firsts).where(in_short).groupBy("w").count().where(F.col("count") > CROWD).select("w"), "crowds")
    small = bounded(crowds)
    met = meet(each.join(small, "w", "left_anti"), each.where(in_short).join(small, "w", "left_anti"))
    more = compared(met.unionByName(headed(each.join(small, "w", "left_semi"))).distinct())
    settled = cut(led.unionByName(more), "settled")

    last = postings(marked(settled), "open").join(small, "w", "left_semi")
    joined = compared(meet(last, last.where(in_short)).distinct())
    drop(firsts, crowds, led, more)
    gone = cut(again.unionByName(settled.unionByName(joined).toDF("doc_id", "line_no")), "gone")
    drop(again, settled, joined)
    return gone


def bounded(keys: DataFrame) -> DataFrame:
    """Marked for broadcast where there are at most ``BROADCAST_DOCS`` rows."""
    return F.broadcast(keys) if keys.limit(BROADCAST_DOCS + 1).count() <= BROADCAST_DOCS else keys


def dedup_lines(docs: DataFrame, threshold: float = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with the lines left in its texts, and ``n_lines`` and ``n_removed``."""
    usable = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).where(F.col("doc_id").isNotNull() & F.col("text").isNotNull())
    gone = bounded(later_matches(usable, threshold).groupBy("doc_id").agg(F.collect_set("line_no").alias("_gone_lines")).withColumnRenamed("doc_id", "_gone_id"))
    own = docs.drop("n_lines", "n_removed", "_gone_lines", "_gone_id")
    joined = own.join(gone, F.col(id_col) == F.col("_gone_id"), "left")
    every = F.split(F.col(text_col), "\n")
    left = F.array_except(F.sequence(F.lit(0), F.size(every) - 1), "_gone_lines")
    kept = F.array_join(F.transform(left, lambda i: F.get(F.col("_every"), i)), "\n")
    columns = [F.when(F.col("_gone_lines").isNull(), F.col(text_col)).otherwise(kept).alias(c) if c == text_col else F.col(f"`{c}`") for c in own.columns]
    n_lines = F.when(F.col(text_col).isNull(), 0).otherwise(F.size("_every"))
    return joined.withColumn("_every", every).select(*columns, n_lines.alias("n_lines"), F.coalesce(F.size("_gone_lines"), F.lit(0)).alias("n_removed"))


def query(spark, sf_dir: str) -> DataFrame:
    from patternwalk.sources.tables import table

    return dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "text", F.col("n_lines").cast("long").alias("n_lines"), F.greatest("n_removed", F.lit(0)).cast("long").alias("n_removed"))


ORACLE = r"""
WITH raw AS (SELECT doc_id, text, string_split(text, chr(10)) AS ls FROM documents),
lines AS (SELECT doc_id, i - 1 AS line_no, list_sort(list_distinct(list_filter(string_split_regex(lower(ls[i]), '[ \t\x0B\f\r]+'), lambda w: w <> ''))) AS ws
  FROM (SELECT doc_id, ls, unnest(range(1, len(ls) + 1)) AS i FROM raw WHERE doc_id IS NOT NULL AND text IS NOT NULL)),
sets AS (SELECT *, row_number() OVER (ORDER BY doc_id, line_no) AS pos, len(ws) AS n FROM lines WHERE len(ws) > 0),
first AS (SELECT ws, n, min(pos) AS pos FROM sets GROUP BY ws, n),
w AS (SELECT pos, n, unnest(ws) AS word FROM first WHERE n > 3),
near AS (SELECT a.pos FROM w a JOIN w b ON a.word = b.word AND b.pos < a.pos AND least(a.n, b.n) >= 0.8 * greatest(a.n, b.n)
  GROUP BY a.pos, b.pos, a.n, b.n HAVING count(*) >= 0.8 * (a.n + b.n - count(*)) - 1e-9),
gone AS (SELECT DISTINCT s.doc_id, s.line_no FROM sets s JOIN first f ON s.ws = f.ws WHERE s.pos > f.pos OR f.pos IN (SELECT pos FROM near)),
lost AS (SELECT doc_id, list(line_no) AS ns FROM gone GROUP BY doc_id)
SELECT r.doc_id, CASE WHEN l.ns IS NULL THEN r.text ELSE coalesce(array_to_string(list_filter(r.ls, lambda x, i: NOT list_contains(l.ns, i - 1)), chr(10)), '') END AS text,
       CASE WHEN r.text IS NULL THEN 0 ELSE len(r.ls) END::BIGINT AS n_lines, coalesce(len(l.ns), 0)::BIGINT AS n_removed
FROM raw r LEFT JOIN lost l ON r.doc_id = l.doc_id
"""
