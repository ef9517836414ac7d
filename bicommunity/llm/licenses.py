"""Licence scans: known sentences become identifiers, rules match their order.

DataFrame functions only; the tables below are the only data, of fixed size.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Sentences of public licences and the usual notices, normalised (lower
# case, runs of other characters than a-z and 0-9 as one space).
SENTENCES: dict[str, str] = {
    "mit_notice": "released under the mit license",
    "mit_notice_2": "licensed under the mit license",
    "mit_notice_3": "this project is licensed under the mit license",
    "mit_title": "the mit license mit",
    "mit_title_2": "mit license",
    "mit_grant": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    "mit_keep": "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    "mit_as_is": "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement",
    "mit_liability": "in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
    "apache_notice": "licensed under the apache license version 2 0",
    "apache_grant": "licensed under the apache license version 2 0 the license",
    "apache_comply": "you may not use this file except in compliance with the license",
    "apache_copy": "you may obtain a copy of the license at http www apache org licenses license 2 0 unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    "apache_copy_s": "you may obtain a copy of the license at https www apache org licenses license 2 0 unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    "apache_at": "you may obtain a copy of the license at",
    "apache_url": "http www apache org licenses license 2 0",
    "apache_url_s": "https www apache org licenses license 2 0",
    "apache_at_url": "you may obtain a copy of the license at http www apache org licenses license 2 0",
    "apache_at_url_s": "you may obtain a copy of the license at https www apache org licenses license 2 0",
    "apache_unless": "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    "apache_limits": "see the license for the specific language governing permissions and limitations under the license",
    "gpl3_notice": "this work is licensed under the gnu general public license version 3",
    "gpl2_notice": "this work is licensed under the gnu general public license version 2",
    "gpl_free": "this program is free software",
    "gpl3_later": "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "gpl2_later": "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version",
    "gpl_hope": "this program is distributed in the hope that it will be useful but without any warranty",
    "gpl_no_warranty": "without even the implied warranty of merchantability or fitness for a particular purpose",
    "gpl_details": "see the gnu general public license for more details",
    "bsd_grant": "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    "bsd_source": "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    "bsd_binary": "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
    "bsd_endorse": "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    "bsd_as_is": "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed",
    "cc_by_nc_4": "licensed under cc by nc 4 0",
    "cc_by_4": "licensed under cc by 4 0",
    "cc_by_sa_4": "licensed under cc by sa 4 0",
    "cc_by_4_long": "this work is licensed under a creative commons attribution 4 0 international license",
    "cc_by_nc_4_long": "this work is licensed under a creative commons attribution noncommercial 4 0 international license",
    "cc0": "this work is dedicated to the public domain under cc0 1 0",
    "unlicense": "this is free and unencumbered software released into the public domain",
    "rights_reserved": "all rights reserved",
}

# Rules as (licence, sentences in order); sentences that aren't known may
# stand between them, other known ones may not.
RULES: list[tuple[str, tuple[str, ...]]] = [
    ("MIT", ("mit_notice",)),
    ("MIT", ("mit_notice_2",)),
    ("MIT", ("mit_notice_3",)),
    ("MIT", ("mit_grant", "mit_keep", "mit_as_is", "mit_liability")),
    ("Apache-2.0", ("apache_notice",)),
    *(("Apache-2.0", ("apache_grant", "apache_comply", *where, "apache_limits")) for s in ("", "_s") for where in ((f"apache_copy{s}",), (f"apache_at_url{s}", "apache_unless"), ("apache_at", f"apache_url{s}", "apache_unless"))),
    ("GPL-3.0-only", ("gpl3_notice",)),
    ("GPL-2.0-only", ("gpl2_notice",)),
    ("GPL-3.0-or-later", ("gpl_free", "gpl3_later", "gpl_hope", "gpl_no_warranty", "gpl_details")),
    ("GPL-2.0-or-later", ("gpl_free", "gpl2_later", "gpl_hope", "gpl_no_warranty", "gpl_details")),
    ("BSD-2-Clause", ("bsd_grant", "bsd_source", "bsd_binary", "bsd_as_is")),
    ("BSD-3-Clause", ("bsd_grant", "bsd_source", "bsd_binary", "bsd_endorse")),
    ("CC-BY-NC-4.0", ("cc_by_nc_4",)),
    ("CC-BY-NC-4.0", ("cc_by_nc_4_long",)),
    ("CC-BY-4.0", ("cc_by_4",)),
    ("CC-BY-4.0", ("cc_by_4_long",)),
    ("CC-BY-SA-4.0", ("cc_by_sa_4",)),
    ("CC0-1.0", ("cc0",)),
    ("Unlicense", ("unlicense",)),
    ("all-rights-reserved", ("rights_reserved",)),
]

#: Words that start a line within the sentences usually set in capitals.
CAPITALS = sorted({w for i in ("mit_as_is", "mit_liability", "bsd_as_is", "apache_unless", "gpl_no_warranty") for w in SENTENCES[i].upper().split() if len(w) > 1} | {"GNU"})
#: Names that start a line within a sentence.
NAMES = (r"Version [23]\.0", r"License[,.]? (?:as|at|for|is|or) ", r"License\.", "Public License", "General Public", "Software (?:without|and|is) ", "(?:Free )?Software Foundation")
#: A line that starts in lower case, or as one of these, goes on with the sentence before (wrapped
#: notices); a blank line ends a sentence all the same.
WRAP = rf"\n[ \t#*/]*([a-z(\"']|(?:{'|'.join(CAPITALS)})\b|A [A-Z][A-Z]|{'|'.join(NAMES)})"
#: Ends of sentences; a line also ends one.
STOP = r"([.!?;:])[ \t\n]+"
MARK = "\x01"


def normalise(sentence: str) -> str:
    return re.sub(r"[^a-z0-9]+", " ", sentence.lower()).strip()


def identifiers(text: Column) -> Column:
    """Identifiers of the known sentences of a text, in order."""
    cut = F.regexp_replace(F.regexp_replace(text, F.lit(WRAP), F.lit(" $1")), F.lit(STOP), F.lit("$1" + MARK))
    known = F.map_from_entries(F.array(*[F.struct(F.lit(s), F.lit(i)) for i, s in SENTENCES.items()]))
    lower = F.translate(cut, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    plain = F.transform(F.split(lower, f"[{MARK}\n]"), lambda s: F.trim(F.regexp_replace(s, F.lit("[^a-z0-9]+"), F.lit(" "))))
    # a sentence that can't be known isn't looked up: the shortest and longest known ones bound its length
    low, high = min(map(len, SENTENCES.values())), max(map(len, SENTENCES.values()))
    return F.filter(F.transform(F.filter(plain, lambda s: F.length(s).between(low, high)), lambda s: F.element_at(known, s)), lambda i: i.isNotNull())


def scan(docs: DataFrame, text: str = "text") -> DataFrame:
    """``doc_id, licenses, rules, sentences``: licences of the matched rules (sorted,
    once each), how many rules matched, and the identifiers in order. A row per input row: null and
    blank texts have empty lists, as have texts without a known sentence.
    """
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(identifiers(F.col(text)), F.expr("cast(array() as array<string>)")).alias("sentences"))
    chain = found.withColumn("chain", F.concat(F.lit(" "), F.array_join("sentences", " "), F.lit(" ")))
    hits = F.array_compact(F.array(*[F.when(F.col("chain").contains(f" {' '.join(r)} "), F.lit(name)) for name, r in RULES]))
    return chain.select("doc_id", F.array_sort(F.array_distinct(hits)).alias("licenses"), F.size(hits).cast("long").alias("rules"), "sentences")


def scan_sql() -> str:
    """DuckDB SQL for the digest of ``scan`` over ``documents``."""
    pairs = ", ".join(f"('{i}', '{s}')" for i, s in SENTENCES.items())
    hits = ", ".join(f"CASE WHEN contains(chain, ' {' '.join(r)} ') THEN '{name}' END" for name, r in RULES)
    wrap, stop = WRAP.replace("'", "''"), STOP
    return f"""
    WITH known(id, sentence) AS (VALUES {pairs}),
    lookup AS (SELECT map(list(sentence), list(id)) AS m FROM known),
    cut AS (SELECT doc_id, string_split_regex(translate(regexp_replace(regexp_replace(coalesce(text, ''), '{wrap}', ' \\1', 'g'), '{stop}', '\\1' || chr(1), 'g'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x01\\n]') AS s FROM documents),
    ids AS (SELECT doc_id, list_filter(list_transform(s, lambda x: m[trim(regexp_replace(x, '[^a-z0-9]+', ' ', 'g'))]), lambda x: x IS NOT NULL) AS sentences FROM cut, lookup),
    chained AS (SELECT doc_id, sentences, ' ' || array_to_string(sentences, ' ') || ' ' AS chain FROM ids),
    hit AS (SELECT doc_id, sentences, list_filter([{hits}], lambda x: x IS NOT NULL) AS hits FROM chained)
    SELECT doc_id, array_to_string(list_sort(list_distinct(hits)), ',') AS licenses, CAST(len(hits) AS BIGINT) AS rules, array_to_string(sentences, ',') AS sentences FROM hit"""
