"""Licence scans by sentence rules.

Texts are cut into sentences, twice: by lines, and with wrapped lines joined. A sentence is lower-cased and reduced to its letters and digits; known sentences have identifiers.
A licence is found where a text's sequence of identifiers holds the identifiers of one of its rules in order. Everything is built-in functions; the tables are literals of fixed size.
Every known sentence holds one of the ANCHORS, so texts without any are settled by one search.

Defined results: a null or empty text, or one without known sentences, has no licence and an empty sequence; repeated sentences repeat in the sequence; repeated rows give repeated rows; an empty table gives an empty table; other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode.llm.common import read

#: Known licence sentences, normalised, with their identifiers.
SENTENCES = {
    10: "released under the mit license",
    11: "licensed under the mit license",
    12: "mit license",
    13: "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    14: "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    15: "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement",
    16: "spdx license identifier mit",
    20: "licensed under the apache license version 2 0",
    21: "licensed under the apache license version 2 0 the license",
    22: "you may not use this file except in compliance with the license",
    23: "you may obtain a copy of the license at",
    24: "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    25: "spdx license identifier apache 2 0",
    26: "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license",
    30: "this work is licensed under the gnu general public license version 3",
    31: "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    32: "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    33: "spdx license identifier gpl 3 0 only",
    34: "spdx license identifier gpl 3 0 or later",
    40: "licensed under cc by nc 4 0",
    41: "this work is licensed under a creative commons attribution noncommercial 4 0 international license",
    42: "licensed under cc by 4 0",
    43: "this work is licensed under a creative commons attribution 4 0 international license",
    44: "licensed under cc by sa 4 0",
    45: "this work is licensed under a creative commons attribution sharealike 4 0 international license",
    50: "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    51: "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    52: "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
    53: "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    54: "spdx license identifier bsd 3 clause",
    55: "spdx license identifier bsd 2 clause",
}
#: Rules as (licence, identifiers in order).
RULES = [
    ("Apache-2.0", (20,)),
    ("Apache-2.0", (21, 22)),
    ("Apache-2.0", (25,)),
    ("Apache-2.0", (26,)),
    ("BSD-2-Clause", (50, 51, 52)),
    ("BSD-2-Clause", (55,)),
    ("BSD-3-Clause", (50, 51, 52, 53)),
    ("BSD-3-Clause", (54,)),
    ("CC-BY-4.0", (42,)),
    ("CC-BY-4.0", (43,)),
    ("CC-BY-NC-4.0", (40,)),
    ("CC-BY-NC-4.0", (41,)),
    ("CC-BY-SA-4.0", (44,)),
    ("CC-BY-SA-4.0", (45,)),
    ("GPL-3.0-only", (30,)),
    ("GPL-3.0-only", (33,)),
    ("GPL-3.0-or-later", (31, 32)),
    ("GPL-3.0-or-later", (34,)),
    ("MIT", (10,)),
    ("MIT", (11,)),
    ("MIT", (13, 14)),
    ("MIT", (16,)),
]
#: Stands for a break while wrapped lines are joined: the paragraph separator.
BREAK = "\u2029"
ANCHORS = "licen[cs]e|licensed|permission|permitted|copyright|warrant"
#: The same with the notice that reserves all rights, which is no licence: for op6_notices.
ALL_SENTENCES = SENTENCES | {60: "all rights reserved"}
ALL_RULES = [*RULES, ("Proprietary", (60,))]
ALL_ANCHORS = f"{ANCHORS}|rights[^a-z0-9]+reserved"


#: Sentences of the texts and notices of further licences, normalised: for op6_license_texts.
TEXT_SENTENCES = ALL_SENTENCES | {
    70: "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    71: "the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness",
    72: "spdx license identifier isc",
    73: "isc license",
    80: "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version",
    81: "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license version 2 as published by the free software foundation",
    82: "spdx license identifier gpl 2 0 only",
    83: "spdx license identifier gpl 2 0 or later",
    84: "you should have received a copy of the gnu general public license along with this program",
    85: "licensed under the gnu general public license version 2",
    90: "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2 1 of the license or at your option any later version",
    91: "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    92: "this library is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    93: "spdx license identifier lgpl 2 1 or later",
    94: "spdx license identifier lgpl 3 0 or later",
    100: "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    101: "spdx license identifier agpl 3 0 only",
    102: "spdx license identifier agpl 3 0 or later",
    110: "this source code form is subject to the terms of the mozilla public license v 2 0",
    111: "if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0",
    112: "if a copy of the mpl was not distributed with this file you can obtain one at https mozilla org mpl 2 0",
    113: "spdx license identifier mpl 2 0",
    120: "this is free and unencumbered software released into the public domain",
    121: "anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary for any purpose commercial or non commercial and by any means",
    122: "spdx license identifier unlicense",
    130: "distributed under the boost software license version 1 0",
    131: "boost software license version 1 0",
    132: "spdx license identifier bsl 1 0",
    140: "to the extent possible under law the person who associated cc0 with this work has waived all copyright and related or neighboring rights to this work",
    141: "this work is dedicated to the public domain under cc0 1 0",
    142: "spdx license identifier cc0 1 0",
    150: "this software is provided as is without any express or implied warranty",
    151: "in no event will the authors be held liable for any damages arising from the use of this software",
    152: "permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions",
    153: "spdx license identifier zlib",
    160: "this program and the accompanying materials are made available under the terms of the eclipse public license 2 0 which is available at https www eclipse org legal epl 2 0",
    161: "spdx license identifier epl 2 0",
    170: "subject to the terms and conditions of this license each contributor hereby grants to you a perpetual worldwide non exclusive no charge royalty free irrevocable copyright license to reproduce prepare derivative works of publicly display publicly perform sublicense and distribute the work and such derivative works in source or object form",
    171: "you must cause any modified files to carry prominent notices stating that you changed the files",
    172: "you must give any other recipients of the work or derivative works a copy of this license",
    173: "apache license version 2 0 january 2004",
    180: "everyone is permitted to copy and distribute verbatim copies of this license document but changing it is not allowed",
    181: "gnu general public license version 3 29 june 2007",
    182: "gnu general public license version 2 june 1991",
    183: "gnu affero general public license version 3 19 november 2007",
    184: "gnu lesser general public license version 3 29 june 2007",
    185: "gnu lesser general public license version 2 1 february 1999",
    186: "the gnu general public license is a free copyleft license for software and other kinds of works",
    190: "in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
    191: "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed",
}
#: Their rules. A rule of several sentences holds if no more than GAP other sentences stand between one and the next.
TEXT_RULES = [
    *ALL_RULES,
    ("AGPL-3.0-only", (101,)),
    ("AGPL-3.0-only", (183, 180)),
    ("AGPL-3.0-or-later", (100, 32)),
    ("AGPL-3.0-or-later", (102,)),
    ("Apache-2.0", (172, 171)),
    ("Apache-2.0", (173, 170)),
    ("BSL-1.0", (130,)),
    ("BSL-1.0", (131,)),
    ("BSL-1.0", (132,)),
    ("CC0-1.0", (140,)),
    ("CC0-1.0", (141,)),
    ("CC0-1.0", (142,)),
    ("EPL-2.0", (160,)),
    ("EPL-2.0", (161,)),
    ("GPL-2.0-only", (81, 32)),
    ("GPL-2.0-only", (82,)),
    ("GPL-2.0-only", (85,)),
    ("GPL-2.0-only", (182, 180)),
    ("GPL-2.0-or-later", (80, 32)),
    ("GPL-2.0-or-later", (83,)),
    ("GPL-3.0-only", (181, 180)),
    ("ISC", (70, 71)),
    ("ISC", (72,)),
    ("LGPL-2.1-only", (185, 180)),
    ("LGPL-2.1-or-later", (90, 92)),
    ("LGPL-2.1-or-later", (93,)),
    ("LGPL-3.0-only", (184, 180)),
    ("LGPL-3.0-or-later", (91, 92)),
    ("LGPL-3.0-or-later", (94,)),
    ("MPL-2.0", (110, 111)),
    ("MPL-2.0", (110, 112)),
    ("MPL-2.0", (113,)),
    ("Unlicense", (120, 121)),
    ("Unlicense", (122,)),
    ("Zlib", (150, 151, 152)),
    ("Zlib", (153,)),
]
TEXT_ANCHORS = f"{ALL_ANCHORS}|public[^a-z0-9]+domain|mozilla|in[^a-z0-9]+no[^a-z0-9]+event|anyone[^a-z0-9]+is[^a-z0-9]+free|notices"
GAP = 20


def rule_pattern(ids: tuple[int, ...], gap: int | None = None) -> str:
    """A sequence that holds the identifiers in order, others between them or not; with a gap no more than so many."""
    return "," + f",(?:[0-9]+,){'*' if gap is None else f'{{0,{gap}}}'}".join(map(str, ids)) + ","


def _sequence(text: Column, sentences: dict[int, str], places: bool = False) -> Column:
    """',id,id,' of the known sentences among the pieces between line feeds; with places also 0 for every other piece that holds a letter or digit."""
    known = F.create_map(*(F.lit(x) for i, s in sentences.items() for x in (s, str(i))))
    pieces = F.filter(F.split(text, "\n"), lambda s: F.length(s) >= 5)
    plain = F.transform(pieces, lambda s: F.btrim(F.regexp_replace(F.lower(s), "[^a-z0-9]+", " ")))
    if places:
        ids = F.transform(F.filter(plain, lambda s: s != ""), lambda s: F.coalesce(known[s], F.lit("0")))
        return F.when(F.size(F.filter(ids, lambda i: i != "0")) == 0, "").otherwise(F.concat(F.lit(","), F.array_join(ids, ","), F.lit(",")))
    ids = F.filter(F.transform(plain, lambda s: known[s]), lambda i: i.isNotNull())
    return F.when(F.size(ids) == 0, "").otherwise(F.concat(F.lit(","), F.array_join(ids, ","), F.lit(",")))


def scan(docs: DataFrame, known: dict[int, str] = SENTENCES, rules: list[tuple[str, tuple[int, ...]]] = RULES, anchors: str = ANCHORS, gap: int | None = None) -> DataFrame:
    """(doc_id, licenses, by_line, by_sentence): the licences in order of name, comma-joined, and the two sequences of identifiers. With a gap, rules bound the sentences of any kind between theirs."""
    text = F.coalesce(F.col("text"), F.lit(""))
    cut = F.regexp_replace(text, r"([.!?])[\x20\t]+", "$1\n")
    joined = F.regexp_replace(F.regexp_replace(cut, r"\n[\x20\t]*\n", BREAK), r"([.!?])[\x20\t\r]*\n", "$1" + BREAK)
    sentences = F.translate(F.translate(joined, "\n", " "), BREAK, "\n")
    hit = text.rlike(f"(?i)(?:{anchors})")
    out = docs.select(F.col("doc_id"), hit.alias("hit"), F.when(hit, cut).alias("lines"), F.when(hit, sentences).alias("sentences"))
    out = out.select("doc_id", *(F.when(F.col("hit"), _sequence(F.col(c), known, gap is not None)).otherwise("").alias(a) for c, a in (("lines", "by_line"), ("sentences", "by_sentence"))))
    names = sorted({n for n, _ in rules})

    def found(name: str) -> Column:
        patterns = "|".join(rule_pattern(ids, gap) for n, ids in rules if n == name)
        return F.when(F.col("by_line").rlike(patterns) | F.col("by_sentence").rlike(patterns), name)

    sequences = [c if gap is None else F.regexp_replace(c, "(?<=,)(?:0,)+", "").alias(c) for c in ("by_line", "by_sentence")]
    return out.select("doc_id", F.array_join(F.array_compact(F.array(*map(found, names))), ",").alias("licenses"), *sequences)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(read(spark, sf_dir, "documents"))


def notices_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(read(spark, sf_dir, "documents"), ALL_SENTENCES, ALL_RULES, ALL_ANCHORS)


def texts_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(read(spark, sf_dir, "documents"), TEXT_SENTENCES, TEXT_RULES, TEXT_ANCHORS, GAP)


def _oracle(sentences: dict[int, str] = SENTENCES, rules: list[tuple[str, tuple[int, ...]]] = RULES) -> str:
    known = ", ".join(f"('{s}', '{i}')" for i, s in sentences.items())
    names = sorted({n for n, _ in rules})
    found = ", ".join(f"CASE WHEN regexp_matches(by_line, '{p}') OR regexp_matches(by_sentence, '{p}') THEN '{n}' END" for n in names for p in ["|".join(rule_pattern(i) for m, i in rules if m == n)])
    return rf"""
WITH known(s, id) AS (VALUES {known}),
d AS (SELECT doc_id, coalesce(text, '') AS text, regexp_replace(coalesce(text, ''), '([.!?])[ \t]+', '\1' || chr(10), 'g') AS cut FROM documents),
u AS (SELECT doc_id, cut, replace(replace(regexp_replace(regexp_replace(cut, '\n[ \t]*\n', chr(8233), 'g'), '([.!?])[ \t\r]*\n', '\1' || chr(8233), 'g'), chr(10), ' '), chr(8233), chr(10)) AS sentences FROM d),
p AS (SELECT doc_id, kind, generate_subscripts(parts, 1) AS pos, unnest(parts) AS piece FROM (SELECT doc_id, 0 AS kind, string_split(cut, chr(10)) AS parts FROM u UNION ALL SELECT doc_id, 1, string_split(sentences, chr(10)) FROM u)),
m AS (SELECT doc_id, kind, ',' || string_agg(id, ',' ORDER BY pos) || ',' AS seq FROM p JOIN known ON trim(regexp_replace(lower(piece), '[^a-z0-9]+', ' ', 'g')) = known.s WHERE length(piece) >= 5 GROUP BY doc_id, kind),
x AS (SELECT d.doc_id, coalesce(a.seq, '') AS by_line, coalesce(b.seq, '') AS by_sentence FROM d LEFT JOIN m a ON a.doc_id = d.doc_id AND a.kind = 0 LEFT JOIN m b ON b.doc_id = d.doc_id AND b.kind = 1)
SELECT doc_id, array_to_string(list_filter([{found}], lambda y: y IS NOT NULL), ',') AS licenses, by_line, by_sentence FROM x
"""


ORACLE = _oracle()
NOTICES_ORACLE = _oracle(ALL_SENTENCES, ALL_RULES)


def _texts_oracle() -> str:
    known = ", ".join(f"('{s}', '{i}')" for i, s in TEXT_SENTENCES.items())
    names = sorted({n for n, _ in TEXT_RULES})
    found = ", ".join(f"CASE WHEN regexp_matches(lines, '{p}') OR regexp_matches(sentences, '{p}') THEN '{n}' END" for n in names for p in ["|".join(rule_pattern(i, GAP) for m, i in TEXT_RULES if m == n)])
    return rf"""
WITH known(s, id) AS (VALUES {known}),
d AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '([.!?])[ \t]+', '\1' || chr(10), 'g') AS cut FROM documents),
u AS (SELECT doc_id, cut, replace(replace(regexp_replace(regexp_replace(cut, '\n[ \t]*\n', chr(8233), 'g'), '([.!?])[ \t\r]*\n', '\1' || chr(8233), 'g'), chr(10), ' '), chr(8233), chr(10)) AS joined FROM d),
p AS (SELECT doc_id, kind, generate_subscripts(parts, 1) AS pos, unnest(parts) AS piece FROM (SELECT doc_id, 0 AS kind, string_split(cut, chr(10)) AS parts FROM u UNION ALL SELECT doc_id, 1, string_split(joined, chr(10)) FROM u)),
n AS (SELECT doc_id, kind, pos, trim(regexp_replace(lower(piece), '[^a-z0-9]+', ' ', 'g')) AS s FROM p WHERE length(piece) >= 5),
m AS (SELECT doc_id, kind, ',' || string_agg(coalesce(id, '0'), ',' ORDER BY pos) || ',' AS every, ',' || string_agg(id, ',' ORDER BY pos) || ',' AS seq FROM n LEFT JOIN known ON n.s = known.s WHERE n.s <> '' GROUP BY doc_id, kind HAVING count(id) > 0),
x AS (SELECT d.doc_id, coalesce(a.seq, '') AS by_line, coalesce(b.seq, '') AS by_sentence, coalesce(a.every, '') AS lines, coalesce(b.every, '') AS sentences FROM d LEFT JOIN m a ON a.doc_id = d.doc_id AND a.kind = 0 LEFT JOIN m b ON b.doc_id = d.doc_id AND b.kind = 1)
SELECT doc_id, array_to_string(list_filter([{found}], lambda y: y IS NOT NULL), ',') AS licenses, by_line, by_sentence FROM x
"""


TEXTS_ORACLE = _texts_oracle()
