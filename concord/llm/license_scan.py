"""Licence recognition by sentence rules, in JVM-side expressions only.

A text is cut into pieces at line ends and at sentence marks before white space. A piece is normalised (ASCII lower
case, everything but ASCII letters and digits to single spaces, which also removes comment marks). Known licence sentences are
looked up among the pieces and among joins of pieces on consecutive lines, since sentences may be wrapped: the leftmost, then
longest join counts, and none goes over a sentence mark or a blank line (one without letters and digits). The table of known
sentences gives the identifier. Rules are ordered sequences of identifiers. A rule matches
where its identifiers follow one another in the sequence of the recognised sentences of a text; other
sentences may stand between. Rules are tried in order of priority: a match is
reported only if none of its sentences lies in a match of an earlier rule.

The rule table is a parameter of bounded size (``MAX_SENTENCES``), kept as literals of the plan; documents never shuffle. Defined results: a
null text is an empty one and has no match; repeated sentences match once for each place; ids may be null or repeat.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from concord.llm.native import let

MAX_SENTENCES = 1_000
MARK, LINE = r"[.!?;]+\s+", r"\r\n|[\r\n]"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class Rule:
    licence: str
    sentences: tuple[str, ...]


#: Opening and notice sentences of common licences, most specific rules first.
RULES = (
    Rule("MIT", (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
        "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    )),
    Rule("BSD-3-Clause", (
        "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
        "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
        "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    )),
    Rule("BSD-2-Clause", (
        "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
        "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    )),
    Rule("Apache-2.0", (
        "Licensed under the Apache License, Version 2.0 (the \"License\");",
        "you may not use this file except in compliance with the License.",
    )),
    Rule("ISC", ("Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",)),
    Rule("MPL-2.0", (
        "This Source Code Form is subject to the terms of the Mozilla Public License, v.",
        "If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
    )),
    Rule("LGPL-2.1-or-later", (
        "This library is free software;",
        "you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation;",
        "either version 2.1 of the License, or (at your option) any later version.",
    )),
    Rule("GPL-2.0-or-later", (
        "This program is free software;",
        "you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation;",
        "either version 2 of the License, or (at your option) any later version.",
    )),
    Rule("GPL-3.0-or-later", (
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    )),
    Rule("Unlicense", ("This is free and unencumbered software released into the public domain.",)),
    Rule("MIT", ("Released under the MIT License.",)),
    Rule("MIT", ("Licensed under the MIT License.",)),
    Rule("Apache-2.0", ("Licensed under the Apache License, Version 2.0.",)),
    Rule("GPL-3.0", ("This work is licensed under the GNU General Public License, version 3.",)),
    Rule("GPL-2.0", ("This work is licensed under the GNU General Public License, version 2.",)),
    Rule("CC-BY-NC-4.0", ("Licensed under CC BY-NC 4.0.",)),
    Rule("CC-BY-4.0", ("Licensed under CC BY 4.0.",)),
    Rule("CC-BY-SA-4.0", ("Licensed under CC BY-SA 4.0.",)),
)


def normal(sentence: str) -> str:
    """The normal form, for the rule table."""
    kept = "".join(c if c in LOWER or c in "0123456789" else " " for c in sentence.translate(str.maketrans(UPPER, LOWER)))
    return " ".join(kept.split())


def _normalised(c: Column) -> Column:
    return F.trim(F.regexp_replace(F.translate(c, UPPER, LOWER), "[^a-z0-9]+", " "))


def identifiers(rules: tuple[Rule, ...]) -> dict[str, int]:
    """Known sentences with their identifiers, in order of first mention."""
    known: dict[str, int] = {}
    for rule in rules:
        for s in rule.sentences:
            if not normal(s):
                raise ValueError(f"empty sentence in a rule of {rule.licence}")
            known.setdefault(normal(s), len(known) + 1)
    if len(known) > MAX_SENTENCES:
        raise ValueError(f"{len(known)} sentences exceed {MAX_SENTENCES}")
    return known


HIT = "array<struct<rule:int,first:int,last:int>>"


def licences(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(doc_id, n_sentences, sentence_ids, hits, licenses).

    ``n_sentences`` counts the pieces. ``hits`` holds (rule, first, last) with rule the 0-based place in the table and first and last the
    0-based numbers of the first and the last piece, by first piece; ``licenses`` names the different licences in alphabetical order, comma-joined.
    """
    known = identifiers(rules)
    ids = F.create_map(*[F.lit(x) for pair in known.items() for x in pair])
    sequences = [[known[normal(s)] for s in r.sentences] for r in rules]
    text = F.coalesce(docs["text"].cast("string"), F.lit(""))

    wrapped = [k for k in known if " " in k]
    longest = max((len(k.split()) for k in wrapped), default=1)  # pieces of one word at least

    def begins(joined: Column) -> Column:  # a known sentence, which has more words
        return F.exists(F.array(*[F.lit(k) for k in wrapped]).cast("array<string>"), lambda k: F.startswith(k, F.concat(joined, F.lit(" "))))

    def join(pieces: Column, i: Column) -> Column:  # the longest known sentence from piece i: (id, at, to)
        start = F.struct(F.lit("").alias("joined"), i.alias("next"), F.lit(True).alias("open"), F.lit(None).cast("int").alias("id"), i.alias("to"))

        def step(acc: Column, p: Column) -> Column:
            def grown(j: Column) -> Column:
                return let(F.element_at(ids, j), lambda v: F.struct(
                    j.alias("joined"), (acc["next"] + 1).alias("next"), (~p["ends"] & begins(j)).alias("open"),
                    F.coalesce(v, acc["id"]).alias("id"), F.when(v.isNotNull(), acc["next"]).otherwise(acc["to"]).alias("to"),
                ))

            return F.when(acc["open"], let(F.ltrim(F.concat_ws(" ", acc["joined"], p["s"])), grown)).otherwise(acc)

        return F.aggregate(F.slice(pieces, i + 1, longest), start, step, lambda acc: F.struct(acc["id"].alias("id"), i.alias("at"), acc["to"].alias("to")))

    def recognised(pieces: Column) -> Column:  # of the sentences that are known: (id, first piece, last piece), in order
        placed = F.transform(pieces, lambda p, i: F.when(~p["ends"] & begins(p["s"]), join(pieces, i)).otherwise(F.struct(F.element_at(ids, p["s"]).alias("id"), i.alias("at"), i.alias("to"))))
        seen = F.filter(placed, lambda x: x["id"].isNotNull())

        def apart(v: Column) -> Column:
            return F.aggregate(v, F.slice(v, 1, 0), lambda acc, x: F.when((F.size(acc) > 0) & (F.get(acc, F.size(acc) - 1)["to"] >= x["at"]), acc).otherwise(F.array_append(acc, x)))

        return let(seen, lambda v: F.when(F.exists(v, lambda x: x["to"] > x["at"]), apart(v)).otherwise(v))

    table = F.array(*[F.struct(F.lit(k).alias("k"), F.array(*[F.lit(v) for v in sequence]).alias("want")) for k, sequence in enumerate(sequences)])

    def matched(seen: Column, rule: Column) -> Column:
        def here(x: Column, i: Column) -> Column:
            n = F.size(rule["want"])
            hit = F.struct(rule["k"].alias("rule"), x["at"].alias("first"), F.get(seen, i + n - 1)["to"].alias("last"))
            return F.when(F.transform(F.slice(seen, i + 1, n), lambda y: y["id"]) == rule["want"], hit)

        return F.filter(F.transform(seen, here), lambda h: h.isNotNull())

    def hits(seen: Column) -> Column:
        every = F.flatten(F.transform(table, lambda r: matched(seen, r))).cast(HIT)  # in order of priority
        over = lambda acc, h: F.exists(acc, lambda e: (e["rule"] < h["rule"]) & (e["first"] <= h["last"]) & (h["first"] <= e["last"]))
        kept = F.aggregate(every, F.array().cast(HIT), lambda acc, h: F.when(over(acc, h), acc).otherwise(F.array_append(acc, h)))
        return F.array_sort(kept, lambda x, y: F.when(x["first"] < y["first"], -1).when(x["first"] > y["first"], 1).otherwise(0))

    one = docs.select(docs["doc_id"].alias("doc_id"), text.alias("text"))
    # the lines of the stretches between sentence marks, each stretch closed by an empty line, which like a blank one ends a piece's joins
    lines = F.flatten(F.transform(F.split("text", MARK, -1), lambda part: F.array_append(F.transform(F.split(part, LINE, -1), _normalised), F.lit(""))))
    pieces = let(lines, lambda v: F.filter(F.transform(v, lambda s, i: F.struct(s.alias("s"), (F.get(v, i + 1) == "").alias("ends"))), lambda p: p["s"] != ""))
    made = let(pieces, lambda p: F.struct(F.size(p).cast("long").alias("n_sentences"), recognised(p).alias("seen")))
    made = let(made, lambda m: F.struct(m["n_sentences"].alias("n_sentences"), m["seen"].alias("seen"), F.when(F.size(m["seen"]) > 0, hits(m["seen"])).otherwise(F.array().cast(HIT)).alias("hits")))
    names = F.array(*[F.lit(r.licence) for r in rules])
    return one.select("doc_id", made.alias("m")).select(
        "doc_id", "m.n_sentences",
        F.transform("m.seen", lambda x: x["id"]).alias("sentence_ids"),
        "m.hits",
        F.array_join(F.array_sort(F.array_distinct(F.transform("m.hits", lambda h: F.get(names, h["rule"])))), ",").alias("licenses"),
    )


def license_report(docs: DataFrame) -> DataFrame:
    """Flat form for the query: sequences and spans as text."""
    listed = F.transform("hits", lambda h: F.concat_ws(":", h["rule"].cast("string"), h["first"].cast("string"), h["last"].cast("string")))
    return licences(docs).select(
        "doc_id", "n_sentences", F.size("hits").cast("long").alias("n_hits"), F.array_join(F.transform("sentence_ids", lambda i: i.cast("string")), ",").alias("sentence_ids"),
        F.array_join(listed, ",").alias("hits"), "licenses",
    )


def oracle(rules: tuple[Rule, ...] = RULES) -> str:
    """DuckDB SQL for ``license_report`` where, as in the standard table, no two rules can claim the same sentences in part."""
    known = identifiers(rules)
    values = ", ".join(f"('{s}', {i})" for s, i in known.items())
    rows = ", ".join(f"({k}, '{r.licence}', [{', '.join(str(known[normal(s)]) for s in r.sentences)}])" for k, r in enumerate(rules))
    return f"""
WITH known(s, id) AS (VALUES {values}), rules(rule, licence, seq) AS (VALUES {rows}),
d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
p AS (
  SELECT r, list_filter(list_transform(string_split_regex(text, '[.!?;]+\\s+|[\\r\\n]+'),
    lambda x: trim(regexp_replace(translate(x, '{UPPER}', '{LOWER}'), '[^a-z0-9]+', ' ', 'g'))), lambda x: x <> '') AS s FROM d),
u AS (SELECT r, unnest(s) AS s, generate_subscripts(s, 1) - 1 AS pos FROM p),
k AS (SELECT r, id, pos, row_number() OVER (PARTITION BY r ORDER BY pos) AS n FROM u JOIN known USING (s)),
seqs AS (SELECT r, list(id ORDER BY n) AS ids, list(pos ORDER BY n) AS ats FROM k GROUP BY r),
h AS (
  SELECT k.r, rule, licence, pos AS first, ats[n + len(seq) - 1] AS last
  FROM k JOIN seqs USING (r), rules WHERE ids[n:n + len(seq) - 1] = seq),
g AS (
  SELECT r, count(*) AS c, string_agg(rule || ':' || first || ':' || last, ',' ORDER BY first) AS hits,
    array_to_string(list_sort(list(DISTINCT licence)), ',') AS licenses FROM h GROUP BY r)
SELECT doc_id, CAST(len(s) AS BIGINT) AS n_sentences, CAST(coalesce(c, 0) AS BIGINT) AS n_hits,
  coalesce(array_to_string(ids, ','), '') AS sentence_ids, coalesce(hits, '') AS hits, coalesce(licenses, '') AS licenses
FROM d JOIN p USING (r) LEFT JOIN seqs USING (r) LEFT JOIN g USING (r)
"""
