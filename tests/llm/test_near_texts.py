import random

from pyspark.sql import types as T

import corpus_pipeline as C
from patternwalk.llm import near_texts as N

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())])


def shingle_set(text, width=5):
    words = (text or "").lower().split()
    return {tuple(words[i : i + width]) for i in range(max(1, len(words) - width + 1))}


def similarity(a, b):
    a, b = shingle_set(a), shingle_set(b)
    return len(a & b) / len(a | b)


def brute(texts):
    """For each text the first of its component of pairs of similarity 0.8."""
    root = list(range(len(texts)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            if similarity(texts[i], texts[j]) >= 0.8:
                a, b = sorted((top(i), top(j)))
                root[b] = a
    return [top(i) for i in range(len(texts))]


def corpus():
    rng = random.Random(4)
    word = lambda: f"w{int(rng.paretovariate(0.6)) % 3000}"
    texts = [" ".join(word() for _ in range(rng.choice([3, 8, 40, 200, 900]))) for _ in range(60)]
    for i in range(60):  # copies with one to many changed words
        words = texts[i].split()
        for _ in range(rng.randrange(1, 2 + len(words) // 45)):
            words[rng.randrange(len(words))] = word()
        texts.append(" \n".join(words))
    texts += [texts[3], texts[3].upper(), "", None, "a b c d e f g h", "a b c d e f g h i"]
    return texts


def test_stage_against_brute_force_jaccard(spark):
    texts = corpus()
    close = [similarity(a, b) for k, a in enumerate(texts[:120]) for b in texts[:k]]
    assert all(sum(low <= s < low + 0.05 for s in close) >= 2 for low in (0.8, 0.85, 0.9, 0.95))
    rows = [(i, t, "aa", "s", 0) for i, t in enumerate(texts)] + [(None, texts[0], "aa", "s", 0)]
    root = brute(texts)
    got = C.near_copies(spark, spark.createDataFrame(rows, SCHEMA), "").collect()
    assert sorted(r.doc_id for r in got if r.doc_id is not None) == [i for i, r in enumerate(root) if i == r]
    assert sum(r.doc_id is None for r in got) == 1


def test_many_near_copies_and_common_shingles(spark, monkeypatch):
    monkeypatch.setattr(N, "SAMPLE", 1)
    rng = random.Random(5)
    base, phrase = [f"b{i}" for i in range(100)], "one phrase that very many of the texts have in common"
    texts = [" ".join([*base[:k], "x", *base[k + 1 :]]) for k in rng.choices(range(100), k=80)]
    texts += [f"{phrase} " + " ".join(f"c{rng.randrange(10**6)}" for _ in range(30)) for _ in range(80)]
    got = {r.doc_id: r.component_id for r in N.near_copy_groups(spark.createDataFrame([(i, t, "", "", 0) for i, t in enumerate(texts)], SCHEMA)).collect()}
    assert [got[i] for i in range(len(texts))] == brute(texts)


def test_nothing(spark):
    assert N.near_copy_groups(spark.createDataFrame([], SCHEMA)).count() == 0


def test_shingles_of_every_text_are_counted(spark):
    """The order is by rarity among all texts, whatever their ids and however few have a shingle."""
    phrase, own = "a phrase that is common here", "b phrase that two have"
    texts = [f"{phrase} {own if i in (7, 23) else f'and x{i} y{i} z{i} w{i}'}" for i in range(40)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    counts = N._counts(N._facts(docs, 5))
    of = lambda text: counts[N._bucket(N.shingles(text))].tolist()
    assert of("a phrase that is common") == [40] and of(own) == [2] and of("and x3 y3 z3 w3") == [1]
    assert counts.sum() == sum(len(N.shingles(t)) for t in texts)
