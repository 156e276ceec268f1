import random
import re

from pyspark.sql import types as T

from patternwalk.llm import line_dedup

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("line_no", T.StringType()), T.StructField("sig", T.StringType()), T.StructField("n_lines", T.StringType())])


def brute(rows, t=0.8):
    places, out = {}, []
    for d, text, *_ in rows:
        if d is not None and text is not None:
            for i, line in enumerate(text.split("\n")):
                places[d, i] = frozenset(w for w in re.split(r"[ \t\x0b\f\r]+", line.lower()) if w)
    order = sorted(places)
    gone = set()
    for k, at in enumerate(order):
        a = places[at]
        if a and any(b and len(a & b) >= t * len(a | b) - 1e-9 for b in (places[o] for o in order[:k])):
            gone.add(at)
    for d, text, *_ in rows:
        if d is None or text is None:
            out.append((d, text, 0))
        else:
            ls = text.split("\n")
            out.append((d, "\n".join(x for i, x in enumerate(ls) if (d, i) not in gone), sum((d, i) in gone for i in range(len(ls)))))
    return out


def test_against_brute_force(spark):
    rng = random.Random(4)
    vocabulary = [f"w{i}" for i in range(400)] + ["the", "of"] * 40
    base = [[rng.choice(vocabulary) for _ in range(rng.choice([1, 2, 3, 4, 5, 9, 20, 45]))] for _ in range(60)]
    rows = []
    for d in range(120):
        lines = []
        for _ in range(rng.randrange(1, 5)):
            line = list(rng.choice(base))
            for _ in range(rng.choice([0, 0, 1, 1, 2, 5])):
                line[rng.randrange(len(line))] = rng.choice(vocabulary)
            rng.shuffle(line)
            lines.append(" ".join(line) if rng.random() < 0.9 else "  \t")
        rows.append((d, "\n".join(lines), "clash", "clash", "clash"))
    hot = base[7] * 3
    for d in range(200, 260):  # one line with many near-copies
        line = list(hot)
        line[rng.randrange(len(line))] = f"x{d}"
        rows.append((d, " ".join(line).upper(), "", "", ""))
    for d in range(300, 340):  # long lines about the border between the two indexes
        line = [f"y{i}" for i in range(95 + d - 300)] if d % 2 else [f"z{i}" for i in range(150)]
        for _ in range(rng.randrange(20)):
            line[rng.randrange(len(line))] = f"q{rng.randrange(1000)}"
        rows.append((d, " ".join(line), "", "", ""))
    rows += [(900, None, "", "", ""), (901, "", "", "", ""), (902, "long " + " ".join(f"v{i}" for i in range(20_000)), "", "", ""), (None, "w1 w2 w3", "", "", "")]
    got = line_dedup.dedup_lines(spark.createDataFrame(rows, SCHEMA).repartition(3)).collect()
    key = lambda x: (x[0] is None, x[0] or 0, x[1] or "")
    assert sorted([(r.doc_id, r.text, r.n_removed) for r in got], key=key) == sorted(brute(rows), key=key)
    assert got[0].sig is not None


def test_empty_table_and_repeated_rows(spark):
    assert line_dedup.dedup_lines(spark.createDataFrame([], SCHEMA)).count() == 0
    rows = [(1, "a b c\na b c", "", "", "")] * 2 + [(2, "c b a\nd", "", "", "")]
    got = sorted((r.doc_id, r.text, r.n_removed) for r in line_dedup.dedup_lines(spark.createDataFrame(rows, SCHEMA)).collect())
    assert got == [(1, "a b c", 1), (1, "a b c", 1), (2, "d", 1)]


def test_crowds(spark, monkeypatch):
    monkeypatch.setattr(line_dedup, "CROWD", 5)
    monkeypatch.setattr(line_dedup, "HEADS", 2)
    rng = random.Random(6)
    base = [f"b{i}" for i in range(30)]
    rows = []
    for d in range(90):  # one family, many of whose lines are about as far apart as may be
        line = list(base)
        for _ in range(rng.randrange(7)):
            line[rng.randrange(30)] = rng.choice([f"m{rng.randrange(12)}", f"x{d}"])
        rows.append((d, " ".join(line), "", "", ""))
    got = line_dedup.dedup_lines(spark.createDataFrame(rows, SCHEMA)).collect()
    assert sorted((r.doc_id, r.text, r.n_removed) for r in got) == sorted(brute(rows))


def test_pairs_of_a_family_grow_with_its_lines(spark, monkeypatch):
    """A family of near-copies below a thousand lines is not compared pair by pair."""
    rng = random.Random(11)
    base = [f"w{i}" for i in range(24)]
    rows = [(d, " ".join(base[:-1] + [f"own{d}"]) + "\n" + " ".join(f"x{rng.randrange(3000)}" for _ in range(12)), "", "", "") for d in range(600)]
    made, cut = [], line_dedup.cut

    def counted(df, name, **how):
        held = cut(df, name, **how)
        if name == "pairs":
            made.append(held.count())
        return held

    monkeypatch.setattr(line_dedup, "cut", counted)
    got = line_dedup.dedup_lines(spark.createDataFrame(rows, SCHEMA)).collect()
    assert sorted((r.doc_id, r.text, r.n_removed) for r in got) == sorted(brute(rows))
    assert sum(made) < 20 * len(rows)  # all pairs: 179,700


def test_every_word_of_every_document_is_counted(spark):
    """Whatever its case, line, white space or document's id."""
    texts = ["Common word", "one\ncommon\ttwo", "COMMON", "three\ncommon\nfour"] * 16
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    levels = line_dedup.rarity(docs).first().levels
    slot = lambda w: spark.sql(f"SELECT xxhash64('{w}')").first()[0] & (line_dedup.COUNTED - 1)
    assert [levels[slot(w)] for w in ("common", "word", "one", "two", "three", "four")] == [6, 4, 4, 4, 4, 4]
