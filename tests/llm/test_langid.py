import random
import zlib

import numpy as np
import pytest
from pyspark.sql import types as T

from patternwalk.llm import langid

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("score", T.StringType()), T.StructField("rate", T.StringType())])


def longest_matches(text, learned):
    """Phrases by searching the learned text itself."""
    count, i = 0, 0
    while i < len(text):
        n = 1
        while i + n < len(text) and text[i : i + n + 1] in learned and text[i : i + n] in learned:
            n += 1
        count += 1
        i += n
    return count


@pytest.mark.parametrize("seed", range(4))
def test_automaton_and_tables_against_search(seed):
    rng = random.Random(seed)
    learned = "".join(rng.choice("abcd ") for _ in range(300))
    automaton = langid.Automaton([ord(c) for c in learned])
    for n in (0, 1, 7, 200):
        text = "".join(rng.choice("abcde ") for _ in range(n))
        assert langid.phrases([ord(c) for c in text], automaton) == longest_matches(text, learned)
    every = {learned[i:j] for i in range(60) for j in range(i + 1, 61)}
    for s in every:
        state = 0
        for c in s:
            state = automaton.next[state][ord(c)]


def test_lanes_equal_one_text_at_a_time():
    rng = random.Random(1)
    say = {"aa": "ab ba abba baba ", "zz": "xyz zyx yyz xxz "}
    model = langid.Model({k: ["".join(rng.sample(v, len(v))) for _ in range(200)] for k, v in say.items()})
    texts = ["", "...", "a", "Abba BABA!", "xyz zyx é", "x" * 5000, "ab xy " * 700, "\U0001f600 ab"]
    found, length = model.counts(texts)
    table, roots = model.table.reshape(-1, langid.CLASSES), [r // langid.CLASSES for r in model.roots]
    for i, t in enumerate(texts):
        symbols = model._squeeze(model.class_of[model._points(t)]).tolist()
        for k, root in enumerate(roots):
            state, count = root, 0
            for c in symbols:
                to = int(table[state, c])
                count += to < 0
                state = (to if to >= 0 else ~to) // langid.CLASSES
            assert found[i, k] == (count if length[i] else 0)


def test_held_out_accuracy_and_edge_rows(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = langid.identify(docs, langid.fit(docs), keep=["lang"]).collect()
    own = [r for r in rows if zlib.crc32(str(r.doc_id).encode()) % 4 == 2]
    assert len(rows) == docs.count() and sum(r.lang == r.lang_pred for r in own) >= 0.98 * len(own)
    odd = [(1, None, "en", "", ""), (2, "", "en", "", ""), (3, "123 !!", None, "", ""), (None, "text of no id", "en", "", ""), (5, "the and of " * 30000, None, "", ""), (5, "the and of " * 30000, None, "", "")]
    got = {r.doc_id: r for r in langid.identify(spark.createDataFrame(odd, SCHEMA), langid.fit(docs)).collect()}
    assert [got[i].lang_pred for i in (1, 2, 3, 5)] == ["und", "und", "und", "en"] and got[1].score == 0.0
    assert all(0 <= r.score <= 1 for r in got.values())


def test_empty_table_and_nothing_to_learn(spark):
    empty = spark.createDataFrame([], SCHEMA)
    assert langid.identify(empty, langid.fit(empty)).count() == 0
    one = spark.createDataFrame([(1, "words", None, "", "")], SCHEMA)
    assert langid.identify(one, langid.fit(one)).first().lang_pred == "und"


def test_a_kept_text_travels_once(spark):
    docs = spark.createDataFrame([(1, "one and two", "en", "", "")], SCHEMA)
    found = langid.identify(docs, langid.Model({}), keep=["text", "lang"])
    assert found.columns == ["doc_id", "text", "lang", "lang_pred", "score", "rate"] and found.first().text == "one and two"
    assert "_parsed_text" not in found._jdf.queryExecution().toString()


def test_workers_drop_what_other_operators_keep():
    from patternwalk.llm import lean, packing

    packing._LOADED["kept"] = None
    list(lean.tidily(lambda batches: batches, "packing")(iter([])))
    assert "kept" in packing._LOADED
    list(lean.tidily(lambda batches: batches, "langid")(iter([])))
    assert not packing._LOADED
