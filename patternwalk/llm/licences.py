"""Operator 7: licence statements by sentence rules, in DataFrame functions only.

A text is cut into pieces, each is normalised to lower-case letters and digits,
and runs of pieces that make a known licence sentence are mapped to short identifiers. The identifiers in order,
with unknown sentences between them shown as a gap, are matched against an
ordered list of rules: each rule names a run of identifiers and the licence that it
states, and takes the run out of the sequence before the next rule is tried. Longer
runs come first, so a full notice is not read as several short ones.

Only texts with one of the words that every known sentence has (``ANCHORS``, checked by
a test) are cut at all. There is no join and no shuffle: the tables of sentences and
rules are fixed and small.

Defined results: null and empty texts state no licence: empty strings and zeros. Texts
of any length are read whole. Repeated rows get equal results; an empty table gives an
empty result; only the id and text columns are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Public licences' own sentences, normalised, with their identifiers.
SENTENCES = {
    "apache-by": "licensed under the apache license version 2 0",
    "apache-the": "licensed under the apache license version 2 0 the license",
    "apache-use": "you may not use this file except in compliance with the license",
    "apache-get": "you may obtain a copy of the license at http www apache org licenses license 2 0",
    "apache-as-is": "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    "apache-see": "see the license for the specific language governing permissions and limitations under the license",
    "mit-by": "released under the mit license",
    "mit-licensed": "licensed under the mit license",
    "mit-grant": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    "mit-notice": "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    "mit-as-is": "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement",
    "mit-liable": "in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
    "bsd-grant": "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    "bsd-source": "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    "bsd-binary": "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
    "bsd-name": "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    "isc-grant": "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    "gpl-warranty": "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    "mpl-form": "this source code form is subject to the terms of the mozilla public license v 2 0",
    "unlicense-free": "this is free and unencumbered software released into the public domain",
} | {
    f"{short}-{version}{later and '+'}": f"this {what} is free software you can redistribute it and or modify it under the terms of the gnu {name}general public license as published by the free software foundation either version {version} of the license{later}"
    for short, what, name, versions in (("gpl", "program", "", "23"), ("lgpl", "library", "lesser ", "23"), ("agpl", "program", "affero ", "3"))
    for version in versions
    for later in ("", " or at your option any later version")
} | {
    f"{short}-by-{version}": f"this work is licensed under the gnu {name}general public license version {version}" for short, name in (("gpl", ""), ("lgpl", "lesser "), ("agpl", "affero ")) for version in "23"
} | {
    f"cc-{kind.replace(' ', '-')}-{version}": f"licensed under cc {kind} {version} 0" for kind in ("by", "by sa", "by nc", "by nd", "by nc sa", "by nc nd") for version in "34"
}

#: Rules in order: the licence and the run of identifiers that states it.
RULES: list[tuple[str, tuple[str, ...]]] = [
    ("Apache-2.0", ("apache-the", "apache-use", "apache-get", "apache-as-is", "apache-see")),
    ("Apache-2.0", ("apache-the", "apache-use", "apache-get")),
    ("MIT", ("mit-grant", "mit-notice", "mit-as-is", "mit-liable")),
    ("MIT", ("mit-grant", "mit-notice", "mit-as-is")),
    ("MIT-no-disclaimer", ("mit-grant", "mit-notice")),
    ("BSD-3-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-name")),
    ("BSD-2-Clause", ("bsd-grant", "bsd-source", "bsd-binary")),
    ("BSD-1-Clause", ("bsd-grant", "bsd-source")),
    *((f"{s.upper()}-{v}.0{end}", (f"{s}-{v}{plus}", "gpl-warranty")) for s, vs in (("gpl", "23"), ("lgpl", "23"), ("agpl", "3")) for v in vs for plus, end in (("+", "-or-later"), ("", "-only"))),
    *((f"{s.upper()}-{v}.0{end}", (f"{s}-{v}{plus}",)) for s, vs in (("gpl", "23"), ("lgpl", "23"), ("agpl", "3")) for v in vs for plus, end in (("+", "-or-later"), ("", "-only"))),
    *((f"{s.upper()}-{v}.0", (f"{s}-by-{v}",)) for s in ("gpl", "lgpl", "agpl") for v in "23"),
    ("Apache-2.0", ("apache-the",)),
    ("Apache-2.0", ("apache-by",)),
    ("MIT", ("mit-by",)),
    ("MIT", ("mit-licensed",)),
    ("ISC", ("isc-grant",)),
    ("MPL-2.0", ("mpl-form",)),
    ("Unlicense", ("unlicense-free",)),
    *((f"CC-{k[3:-2].upper()}-{k[-1]}.0", (k,)) for k in SENTENCES if k.startswith("cc-")),
]
#: Rules of the further wordings, before the others.
MORE_RULES = [(f"LGPL-2.1{end}", (f"lgpl-2.1{plus}", *more)) for more in (("gpl-warranty",), ()) for plus, end in (("+", "-or-later"), ("", "-only"))]
ANCHORS = ("license", "permission", "redistribut", "copyright", "liable", "warrant", "unencumbered")
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Where a piece ends: at a full stop, mark, colon or semicolon before white space, and at the end of a line.
_ENDS = r"[.!?;:]+[ \t\r\n]+|\n+"


#: Genuine wordings besides those of ``SENTENCES``, with the identifiers that they count as.
WORDINGS = [
    *((s, i) for i, s in SENTENCES.items()),
    *((SENTENCES["gpl-warranty"].replace("this program", f"this {what}"), "gpl-warranty") for what in ("library", "software")),
    *((f"this {what} is free software you can redistribute it and or modify it under the terms of the gnu {name}general public license version {version} as published by the free software foundation", f"{short}-{version}") for short, what, name, versions in (("gpl", "program", "", "23"), ("lgpl", "library", "lesser ", "3"), ("agpl", "program", "affero ", "3")) for version in versions),
    *((f"this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2 1 of the license{later}", f"lgpl-2.1{later and '+'}") for later in ("", " or at your option any later version")),
    (SENTENCES["apache-get"].replace("http ", "https "), "apache-get"),
    *((f"{SENTENCES['apache-get'].replace('http ', f'{scheme} ')} {SENTENCES['apache-as-is']}", "apache-get><apache-as-is") for scheme in ("http", "https")),  # an address has no full stop
    (SENTENCES["isc-grant"].replace("and or distribute", "and distribute"), "isc-grant"),
]


def recognise(text: Column) -> Column:
    """The sequence of identifiers of a text: ``<id>`` each, ``<->`` for a gap.

    The text becomes its pieces between line ends and marks, each in lower-case letters and digits. A known sentence is
    a run of whole pieces, so it may be wrapped, commented or have marks of its own; a list's number or letter
    before it belongs to it. Longer sentences are taken first.
    """
    low = F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER)
    anchored = F.lit(False)
    for a in ANCHORS:
        anchored = anchored | low.contains(a)
    pieces = F.regexp_replace(F.regexp_replace(low, _ENDS, "\n"), "[^a-z0-9\n]+", " ")
    seq = F.concat(F.lit("|"), F.regexp_replace(pieces, " ?\n[ \n]*", "|"), F.lit("|"))
    seq = F.regexp_replace(F.regexp_replace(seq, r"\| ", "|"), r" \|", "|")
    for sentence, i in sorted(WORDINGS, key=lambda x: (-len(x[0]), x[0])):
        run = sentence.replace(" ", "[ |]")
        seq = F.regexp_replace(seq, rf"(?<=\|)(?:(?:[0-9]{{1,2}}|[a-z])[ |])?{run}(?=\|)", f"<{i}>")
    seq = F.replace(F.regexp_replace(seq, r"\|[a-z0-9 ]+(?=\|)", "|<->"), F.lit("|"), F.lit(""))
    return F.when(anchored, F.regexp_replace(seq, "(<->)+", "<->")).otherwise(F.lit(""))


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, sentence_ids, licences, n_unmatched``: the known sentences, the licences stated, and known sentences that no rule took."""
    found = docs.select(F.col(id_col).alias("doc_id"), recognise(F.col(text_col)).alias("seq"))
    left = F.col("seq")
    for licence, run in [*MORE_RULES, *RULES]:
        left = F.replace(left, F.lit("".join(f"<{x}>" for x in run)), F.lit(f"{{{licence}}}"))
    return found.withColumn("left", left).select(
        "doc_id",
        F.array_join(F.regexp_extract_all("seq", F.lit("<([^->][^>]*)>"), F.lit(1)), " ").alias("sentence_ids"),
        F.array_join(F.array_distinct(F.regexp_extract_all("left", F.lit(r"\{([^}]*)\}"), F.lit(1))), ", ").alias("licences"),
        F.regexp_count("left", F.lit("<[^->]")).cast("long").alias("n_unmatched"),
    )


def query(spark, sf_dir: str) -> DataFrame:
    from patternwalk.sources.tables import table

    return scan(table(spark, sf_dir, "documents"))


def _oracle() -> str:
    values = ", ".join(f"('{s}', '{i}')" for i, s in SENTENCES.items())
    left = "seq"
    for licence, run in RULES:
        left = f"replace({left}, '{''.join(f'<{x}>' for x in run)}', '{{{licence}}}')"
    return rf"""
WITH known(s, i) AS (VALUES {values}),
cut AS (SELECT doc_id, row_number() OVER () AS row, string_split_regex(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '{_ENDS}') AS ss FROM documents),
each AS (SELECT row, k, trim(regexp_replace(ss[k], '[^a-z0-9]+', ' ', 'g')) AS s FROM (SELECT row, ss, unnest(range(1, len(ss) + 1)) AS k FROM cut)),
seqs AS (SELECT row, regexp_replace(string_agg('<' || coalesce(i, '-') || '>', '' ORDER BY k), '(<->)+', '<->', 'g') AS seq FROM each LEFT JOIN known USING (s) WHERE s <> '' GROUP BY row),
done AS (SELECT row, seq, {left} AS rest FROM seqs WHERE regexp_matches(seq, '<[^-]'))
SELECT c.doc_id, coalesce(array_to_string(regexp_extract_all(seq, '<([^->][^>]*)>', 1), ' '), '') AS sentence_ids,
       coalesce((SELECT string_agg(x, ', ' ORDER BY n) FROM (SELECT x, min(n) AS n FROM (SELECT unnest(regexp_extract_all(rest, '\{{([^}}]*)\}}', 1)) AS x, generate_subscripts(regexp_extract_all(rest, '\{{([^}}]*)\}}', 1), 1) AS n) GROUP BY x)), '') AS licences,
       coalesce(len(regexp_extract_all(rest, '<[^->]')), 0)::BIGINT AS n_unmatched
FROM cut c LEFT JOIN done d ON c.row = d.row
"""


ORACLE = _oracle()
