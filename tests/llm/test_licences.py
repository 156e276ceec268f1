from pyspark.sql import types as T

from patternwalk.llm import licences as L

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("seq", T.StringType()), T.StructField("left", T.StringType())])


def test_tables_hold_together():
    assert all(any(a in s for a in L.ANCHORS) for s in L.SENTENCES.values())
    assert len(set(L.SENTENCES.values())) == len(L.SENTENCES)
    assert all(x in L.SENTENCES for _, run in L.RULES for x in run)
    for k, (_, early) in enumerate(L.RULES):  # a run is never hidden by an earlier part of itself
        for _, late in L.RULES[k + 1 :]:
            assert not any(late[i : i + len(early)] == early for i in range(len(late) - len(early) + 1)) or late == early


def test_statements(spark):
    mit = "\n".join(f"  * {L.SENTENCES[k].upper()}." for k in ("mit-grant", "mit-notice", "mit-as-is", "mit-liable"))
    texts = {
        1: (None, "", "", 0),
        2: ("", "", "", 0),
        3: ("No licence here. None.", "", "", 0),
        4: ("Some code.\nReleased under the MIT License. Then text.", "mit-by", "MIT", 0),
        5: (f"Head\n{mit}\nTail", "mit-grant mit-notice mit-as-is mit-liable", "MIT", 0),
        6: ("Licensed under CC BY-NC 4.0.\nThis work is licensed under the GNU General Public License, version 3.", "cc-by-nc-4 gpl-by-3", "CC-BY-NC-4.0, GPL-3.0", 0),
        7: (L.SENTENCES["mit-notice"], "mit-notice", "", 1),
        8: (f"{L.SENTENCES['mit-grant']}. An unknown one. {L.SENTENCES['mit-notice']}.", "mit-grant mit-notice", "", 2),
        9: ("word " * 400_000 + "\nLicensed under the Apache License, Version 2.0.", "apache-by", "Apache-2.0", 0),
        10: ("{MIT} <mit-by> license", "", "", 0),
    }
    rows = [(k, t, "", "") for k, (t, *_) in texts.items()] + [(4, texts[4][0], "", "")]
    got = L.scan(spark.createDataFrame(rows, SCHEMA)).collect()
    assert len(got) == 11
    for r in got:
        assert (r.sentence_ids, r.licences, r.n_unmatched) == texts[r.doc_id][1:], r.doc_id
    assert L.scan(spark.createDataFrame([], SCHEMA)).count() == 0


def test_the_plan_has_no_exchange_and_no_python(spark):
    plan = L.query(spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Python" not in plan and "Arrow" not in plan


MIT = """MIT License

Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE
SOFTWARE.
"""
BSD = """Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice,
   this list of conditions and the following disclaimer.
2) Redistributions in binary form must reproduce the above copyright
   notice, this list of conditions and the following disclaimer in the
   documentation and/or other materials provided with the distribution.
"""
GPL = """This {} is free software{} you can redistribute it and/or modify
it under the terms of the GNU {}General Public License as published by
the Free Software Foundation{} either version {} of the License, or
(at your option) any later version.

This {} is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the
GNU General Public License for more details.
"""
APACHE = """Licensed under the Apache License, Version 2.0 (the "License");
you may not use this file except in compliance with the License.
You may obtain a copy of the License at

    http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software
distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
See the License for the specific language governing permissions and
limitations under the License.
"""
ISC = """Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.
"""


def test_genuine_notices_wrapped_and_commented(spark):
    notices = {
        "MIT": MIT,
        "BSD-2-Clause": BSD,
        "GPL-2.0-or-later": GPL.format("program", ";", "", ";", "2", "program"),
        "GPL-3.0-or-later": GPL.format("program", ":", "", ",", "3", "program"),
        "LGPL-2.1-or-later": GPL.format("library", ";", "Lesser ", ";", "2.1", "library"),
        "AGPL-3.0-or-later": GPL.format("program", ":", "Affero ", ",", "3", "program"),
        "Apache-2.0": APACHE,
        "ISC": ISC,
    }
    styles = [lambda t: t, lambda t: " ".join(t.removeprefix("MIT License").split()), lambda t: t.replace("\n", "\r\n"), *(lambda t, p=p: "x = 1\n" + "".join(f"{p}{line}\n" for line in t.split("\n")) + "y = 2" for p in ("# ", "// ", " * "))]
    rows = [(k, style(t), name, "") for name, t in notices.items() for k, style in enumerate(styles)]
    docs = spark.createDataFrame([(100 * n + k, t, "", "") for n, (k, t, _, _) in enumerate(rows)], SCHEMA)
    got = {r.doc_id: (r.licences, r.n_unmatched) for r in L.scan(docs).collect()}
    assert [got[100 * n + k] for n, (k, *_) in enumerate(rows)] == [(name, 0) for _, _, name, _ in rows]
