"""Licence scan by sentence rules.

A known licence sentence is found where it stands between line ends or closing
signs, whatever its case, blanks and the marks around it, and is mapped to its
identifier. It may be wrapped over lines, each with a comment leader, but not
over a blank line; an address may follow it. The SQL knows unwrapped sentences
only. A rule is an ordered list of identifiers; it holds where they occur in this order
in a document, other sentences between them or not.

Everything is column expressions over one scan: no shuffle and no Python. Null
and empty texts have no sentences and no licence; texts are scanned whole, however
long. Repeated rows are scanned each. Rules that hold at once are all told, in
their order. An empty table gives no rows. Other columns are never looked at,
whatever their names.
"""

from __future__ import annotations

import re
from itertools import chain

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Sentences of well-known public licences and notices, normalised.
SENTENCES = {
    "a1": "licensed under the apache license, version 2.0",
    "a2": "licensed under the apache license, version 2.0 (the \"license\")",
    "a3": "you may not use this file except in compliance with the license",
    "a4": "you may obtain a copy of the license at",
    "a5": "see the license for the specific language governing permissions and limitations under the license",
    "b1": "redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer",
    "b2": "redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution",
    "b3": "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    "c1": "licensed under cc by-nc 4.0",
    "c2": "licensed under cc by 4.0",
    "c3": "licensed under cc by-sa 4.0",
    "c4": "this work is licensed under a creative commons attribution 4.0 international license",
    "c5": "this work is licensed under a creative commons attribution-noncommercial 4.0 international license",
    "c6": "this work is dedicated to the public domain",
    "g1": "this work is licensed under the gnu general public license, version 3",
    "g2": "this program is free software: you can redistribute it and/or modify it under the terms of the gnu general public license as published by the free software foundation, either version 3 of the license, or (at your option) any later version",
    "g3": "you should have received a copy of the gnu general public license along with this program",
    "g4": "licensed under the gnu lesser general public license, version 3",
    "m1": "released under the mit license",
    "m2": "permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"software\"), to deal in the software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the software, and to permit persons to whom the software is furnished to do so, subject to the following conditions",
    "m3": "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    "m4": "licensed under the mit license",
    "r1": "all rights reserved",
}
# Rule, kind, identifiers in order.
RULES = [
    ("apache-2.0 notice", "permissive", ["a1"]),
    ("apache-2.0 header", "permissive", ["a2", "a3", "a4", "a5"]),
    ("bsd-2-clause text", "permissive", ["b1", "b2"]),
    ("bsd-3-clause text", "permissive", ["b1", "b2", "b3"]),
    ("cc-by-4.0 notice", "permissive", ["c2"]),
    ("cc-by-4.0 text", "permissive", ["c4"]),
    ("cc-by-nc-4.0 notice", "non-commercial", ["c1"]),
    ("cc-by-nc-4.0 text", "non-commercial", ["c5"]),
    ("cc-by-sa-4.0 notice", "share-alike", ["c3"]),
    ("gpl-3.0 notice", "copyleft", ["g1"]),
    ("gpl-3.0 header", "copyleft", ["g2", "g3"]),
    ("lgpl-3.0 notice", "copyleft", ["g4"]),
    ("mit notice", "permissive", ["m1"]),
    ("mit notice", "permissive", ["m4"]),
    ("mit text", "permissive", ["m2", "m3"]),
    ("public domain", "permissive", ["c6"]),
    ("rights reserved", "proprietary", ["r1"]),
]
MARKS = " .!?;:,\"'*#/-|<>()[]"


#: Where a wrapped sentence goes on, with the leader of a comment or without.
GAP = r" ?\n ?(?:(?:[/*#;%>|-]+|<!--|dnl|rem) )?"


def _quoted(sentence: str) -> str:
    return sentence.strip(MARKS)


def _pattern() -> str:
    """Known sentences in a text with single blanks; the longest comes first, as one
    may begin another."""
    marks = "[" + re.escape(MARKS) + "]"
    words = [f"(?: |{GAP})".join(re.escape(w) for w in _quoted(s).split(" ")) for s in sorted(SENTENCES.values(), key=len, reverse=True)]
    return rf"(?:(?:\A|\n) ?(?:(?:%+|dnl|rem) )?|(?<=[.!?;] )){marks}*+({'|'.join(words)})(?={marks}*(?:\n|\z|[.!?;] )| https?://)"


def sentences(text: Column) -> Column:
    """The known sentences of a text in order, normalised."""
    flat = F.regexp_replace(F.lower(text), r"[ \t\r\x0B\f]+", " ")
    return F.transform(F.regexp_extract_all(flat, F.lit(_pattern()), F.lit(1)), lambda s: F.regexp_replace(s, GAP, " "))


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_known (licence sentences), sentence_ids (in order), licences and
    kinds (of the rules that hold, each once, in the rules' order)."""
    known = F.create_map(*[F.lit(x) for x in chain.from_iterable((_quoted(s), i) for i, s in SENTENCES.items())])
    ids = F.filter(F.transform(sentences(F.coalesce("text", F.lit(""))), lambda s: F.try_element_at(known, s)), lambda i: i.isNotNull())
    found = docs.select("doc_id", ids.alias("ids")).select("doc_id", F.size("ids").cast("long").alias("n_known"), F.array_join("ids", " ").alias("sentence_ids"))

    def holding(value: int) -> Column:
        each = [F.when(F.col("sentence_ids").like("%" + "%".join(rule[2]) + "%"), F.lit(rule[value])) for rule in RULES]
        return F.array_join(F.array_distinct(F.array_compact(F.array(*each))), ", ")

    return found.select("doc_id", "n_known", "sentence_ids", holding(0).alias("licences"), holding(1).alias("kinds"))


def scan_sql(documents: str = "documents") -> str:
    """The same by DuckDB."""

    def q(s: str) -> str:
        return "'" + s.replace("'", "''") + "'"

    known = ", ".join(f"({q(_quoted(s))}, {q(i)})" for i, s in SENTENCES.items())

    def holding(value: int) -> str:
        seen: dict[str, list[str]] = {}
        for rule in RULES:
            seen.setdefault(rule[value], []).append(f"coalesce(sentence_ids LIKE {q('%' + '%'.join(rule[2]) + '%')}, false)")
        return "array_to_string(list_filter([" + ", ".join(f"CASE WHEN {' OR '.join(tests)} THEN {q(name)} END" for name, tests in seen.items()) + "], lambda x: x IS NOT NULL), ', ')"

    # kinds in the order of the first rule that holds
    def kinds() -> str:
        firsts = []
        for k in dict.fromkeys(r[1] for r in RULES):
            tests = [(n, f"sentence_ids LIKE {q('%' + '%'.join(r[2]) + '%')}") for n, r in enumerate(RULES) if r[1] == k]
            firsts.append("CASE " + " ".join(f"WHEN {t} THEN {{'pos': {n}, 'kind': {q(k)}}}" for n, t in tests) + " END")
        return "array_to_string(list_transform(list_sort(list_filter([" + ", ".join(firsts) + "], lambda x: x IS NOT NULL)), lambda x: x.kind), ', ')"

    return rf"""
WITH cut AS (
  SELECT row_number() OVER () AS r, doc_id,
         string_split(regexp_replace(regexp_replace(lower(coalesce(text, '')), '[ \t\r\x0B\f]+', ' ', 'g'), '([.!?;]) ', '\1' || chr(10), 'g'), chr(10)) AS parts FROM {documents}
), each AS (
  SELECT r, doc_id, unnest(parts) AS s, generate_subscripts(parts, 1) AS pos FROM cut
), known(sentence, id) AS (VALUES {known}
), hits AS (
  SELECT r, count(*) AS n_known, string_agg(id, ' ' ORDER BY pos) AS ids FROM each JOIN known ON trim(s, {q(MARKS)}) = sentence GROUP BY r
), found AS (
  SELECT doc_id, CAST(coalesce(n_known, 0) AS BIGINT) AS n_known, coalesce(ids, '') AS sentence_ids FROM cut LEFT JOIN hits USING (r)
)
SELECT doc_id, n_known, sentence_ids, {holding(0)} AS licences, {kinds()} AS kinds FROM found
"""
