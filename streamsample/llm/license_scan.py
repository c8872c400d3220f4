"""Licences recognised by ordered rules over known sentences; DataFrame functions only.

A text is cut into sentences, each sentence, or line of it, is normalised (runs of other than ASCII letters and digits become one blank) and looked
up in the table of known sentences, which is a fixed list and so may be broadcast. Only hits go on, as (position, identifier).
A document's hits in order form its identifier sequence, and a rule, itself a list of identifiers, matches as often
as its identifiers stand next to one another in that sequence, sentences that go with any licence aside. Rules are tried from the longest to the
shortest, and what one of them has matched is gone for the others.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import read

#: Identifier -> sentence of a public licence or notice.
SENTENCES = {
    "apache-notice": "Licensed under the Apache License, Version 2.0.",
    "apache-notice-long": 'Licensed under the Apache License, Version 2.0 (the "License");',
    "apache-use": "you may not use this file except in compliance with the License.",
    "apache-copy": "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
    "mit-notice": "Released under the MIT License.",
    "mit-title": "The MIT License (MIT)",
    "mit-condition": "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "mit-as-is": 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT.',
    "gpl3-notice": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "gpl-hope": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY;",
    "bsd-redistribution": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "bsd-source": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "bsd-binary": "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "bsd-endorse": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "cc-by-nc-notice": "Licensed under CC BY-NC 4.0.",
    "cc-by-notice": "Licensed under CC BY 4.0.",
    "cc-by-sa-notice": "Licensed under CC BY-SA 4.0.",
    "cc0-notice": "Released under CC0 1.0.",
    "mpl-notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v.",
    "reserved": "All rights reserved.",
    "apache-basis": 'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.',
    "mit-grant": 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:',
    "gpl-program": "This program is free software;",
    "lgpl-library": "This library is free software;",
    "gpl-terms": "you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation;",
    "lgpl-terms": "you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation;",
    "gpl-version-2": "either version 2 of the License, or (at your option) any later version.",
    "gpl-version-2.1": "either version 2.1 of the License, or (at your option) any later version.",
    "lgpl3-free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "agpl-free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "isc-grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "isc-as-is": 'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS.',
    "0bsd-grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.",
    "bsd-advertising": "All advertising materials mentioning features or use of this software must display the following acknowledgement:",
    "zlib-as-is": "This software is provided 'as-is', without any express or implied warranty.",
    "zlib-altered": "Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.",
    "boost-title": "Boost Software License - Version 1.0 - August 17th, 2003",
    "boost-notice": "Distributed under the Boost Software License, Version 1.0.",
    "epl-notice": "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0/",
    "unlicense-notice": "This is free and unencumbered software released into the public domain.",
    "artistic-title": "The Artistic License 2.0",
}

#: Fixed values: (licence, its identifiers in order).
RULES = [
    ("Apache-2.0", ["apache-notice"]),
    ("Apache-2.0", ["apache-notice-long", "apache-use"]),
    ("MIT", ["mit-notice"]),
    ("MIT", ["mit-condition", "mit-as-is"]),
    ("GPL-3.0", ["gpl3-notice"]),
    ("GPL-3.0-or-later", ["gpl-free", "gpl-hope"]),
    ("BSD-2-Clause", ["bsd-redistribution", "bsd-source", "bsd-binary"]),
    ("BSD-3-Clause", ["bsd-redistribution", "bsd-source", "bsd-binary", "bsd-endorse"]),
    ("CC-BY-NC-4.0", ["cc-by-nc-notice"]),
    ("CC-BY-4.0", ["cc-by-notice"]),
    ("CC-BY-SA-4.0", ["cc-by-sa-notice"]),
    ("CC0-1.0", ["cc0-notice"]),
    ("MPL-2.0", ["mpl-notice"]),
    ("All-Rights-Reserved", ["reserved"]),
    ("Apache-2.0", ["apache-notice-long", "apache-use", "apache-copy", "apache-basis"]),
    ("Apache-2.0", ["apache-notice-long", "apache-use", "apache-copy"]),
    ("Apache-2.0", ["apache-notice-long", "apache-use", "apache-basis"]),
    ("MIT", ["mit-title", "mit-grant", "mit-condition", "mit-as-is"]),
    ("MIT", ["mit-grant", "mit-condition", "mit-as-is"]),
    ("MIT", ["mit-title", "mit-condition", "mit-as-is"]),
    ("GPL-2.0-or-later", ["gpl-program", "gpl-terms", "gpl-version-2"]),
    ("LGPL-2.1-or-later", ["lgpl-library", "lgpl-terms", "gpl-version-2.1"]),
    ("LGPL-3.0-or-later", ["lgpl3-free"]),
    ("AGPL-3.0-or-later", ["agpl-free"]),
    ("ISC", ["isc-grant", "isc-as-is"]),
    ("0BSD", ["0bsd-grant", "isc-as-is"]),
    ("BSD-4-Clause", ["bsd-redistribution", "bsd-source", "bsd-binary", "bsd-advertising", "bsd-endorse"]),
    ("Zlib", ["zlib-as-is", "zlib-altered"]),
    ("BSL-1.0", ["boost-title"]),
    ("BSL-1.0", ["boost-notice"]),
    ("EPL-2.0", ["epl-notice"]),
    ("Unlicense", ["unlicense-notice"]),
    ("Artistic-2.0", ["artistic-title"]),
]
#: Identifiers that go with any licence; they don't part the others of a rule.
NEUTRAL = ("reserved",)

# a line that names a licence by its short identifier, for each licence of the rules
for _name in dict.fromkeys(n for n, _ in RULES):
    if _name != "All-Rights-Reserved":
        SENTENCES[f"spdx-{_name}"] = f"SPDX-License-Identifier: {_name}"
        RULES.append((_name, [f"spdx-{_name}"]))

CUT = r"([.;!?])[\x20\x09-\x0D]+"


def normal(sentence: str) -> str:
    return "".join(c if c.isascii() and c.isalnum() else " " for c in sentence).lower().strip()


def known_sentences(spark: SparkSession, sentences: dict[str, str] | None = None) -> DataFrame:
    rows = [(" ".join(normal(s).split()), k) for k, s in (sentences or SENTENCES).items()]
    parts = {}
    for text, k in rows:
        parts.setdefault(text, k)
    pairs = [F.struct(F.lit(s).alias("sentence"), F.lit(k).alias("sentence_id")) for s, k in sorted(parts.items())]
    return spark.range(1).select(F.inline(F.array(*pairs)))


#: Marks at a line's start that would look like the end of a sentence: comments that begin with ; or !.
MARK = r"\n[\x20\x09]*[;!]+[\x20\x09]+"


def found_sentences(text: Column, known: list[str]) -> Column:
    """The known sentences of a text in order, as an array of (at, line, sentence): at, line: number of the sentence and of the line in it.

    White space after . ; ! ? ends a sentence. Within one, a line is looked up by itself, and so are lines that follow one another, with
    what is no letter or digit between them, comment marks and empty lines too, as a blank. Of finds that begin at one line the longest counts.
    """
    begun = sorted({" ".join(w[:n]) for w in map(str.split, known) for n in range(1, len(w))})
    cut = F.split(F.regexp_replace(F.coalesce(text, F.lit("")), MARK, "\n"), r"(?<=[.;!?])[\x20\x09-\x0D]+", -1)
    lines = F.transform(cut, lambda s: F.transform(F.split(s, "\n", -1), lambda x: F.trim(F.lower(F.regexp_replace(x, "[^A-Za-z0-9]+", " ")))))
    numbered = F.transform(lines, lambda x, k: F.struct(k.alias("at"), x.alias("lines")))
    some = F.filter(numbered, lambda p: F.exists(p["lines"], lambda x: x.isin([*known, *begun])))
    kind = "array<struct<line: int, sentence: string>>"

    def step(acc: Column, x: Column) -> Column:
        """The finds so far and the starts of known sentences that end with the line before, each with its first line."""
        grown = F.concat(F.transform(acc["open"], lambda o: F.struct(o["line"].alias("line"), F.concat(o["sentence"], F.lit(" "), x["sentence"]).alias("sentence"))), F.array(x))
        return F.struct(F.filter(grown, lambda g: g["sentence"].isin(begun)).alias("open"), F.concat(acc["found"], F.filter(grown, lambda g: g["sentence"].isin(known))).alias("found"))

    def finds(p: Column) -> Column:
        full = F.filter(F.transform(p["lines"], lambda x, k: F.struct(k.alias("line"), x.alias("sentence"))), lambda x: x["sentence"] != "")
        nothing = F.array().cast(kind)
        found = F.aggregate(full, F.struct(nothing.alias("open"), nothing.alias("found")), step, lambda acc: acc["found"])
        # sorted, what begins at one line ends with the longest; the outer transform binds the array once
        last = lambda v: F.filter(v, lambda f, k: F.coalesce(F.get(v, k + 1)["line"] != f["line"], F.lit(True)))
        longest = F.transform(F.array(F.array_sort(found)), last)[0]
        return F.transform(longest, lambda f: F.struct(p["at"].alias("at"), f["line"].alias("line"), f["sentence"].alias("sentence")))

    return F.flatten(F.transform(some, finds))


def _longest_first(rules: list[tuple[str, list[str]]]) -> list[tuple[str, list[str]]]:
    return sorted(rules, key=lambda r: (-len(r[1]), r))


def rule_counts(ids: Column, rules: list[tuple[str, list[str]]]) -> Column:
    """Array of (licence, matches), licences without a match left out. One fold over the rules, each of which takes its matches out of the sequence."""
    ordered = _longest_first(rules)

    def said(x: Column) -> Column:
        return F.concat(F.lit("<"), F.array_join(x, "><"), F.lit(">"))

    neutral = F.array(*map(F.lit, NEUTRAL))
    single = [len(r) == 1 and r[0] in NEUTRAL for _, r in ordered]
    start = F.struct(said(F.filter(ids, lambda x: ~F.array_contains(neutral, x))).alias("rest"), F.array().cast("array<long>").alias("counts"))
    patterns = F.array(*[F.struct(F.lit("".join(f"<{i}>" for i in r)).alias("p"), F.lit(n).alias("neutral")) for (_, r), n in zip(ordered, single, strict=True)])

    def step(acc: Column, x: Column) -> Column:
        rest = F.when(x["neutral"], said(ids)).otherwise(acc["rest"])
        gone = F.replace(rest, x["p"], F.lit(""))
        found = ((F.char_length(rest) - F.char_length(gone)) / F.char_length(x["p"])).cast("long")
        return F.struct(F.when(x["neutral"], acc["rest"]).otherwise(F.replace(acc["rest"], x["p"], F.lit("|"))).alias("rest"), F.concat(acc["counts"], F.array(found)).alias("counts"))

    counts = F.aggregate(patterns, start, step, lambda acc: acc["counts"])
    places: dict[str, list[int]] = {}
    for k, (name, _) in enumerate(ordered):
        places.setdefault(name, []).append(k)
    # the outer transform binds the counts once
    total = [(name, lambda c, ks=tuple(ks): sum((F.get(c, k) for k in ks[1:]), F.get(c, ks[0]))) for name, ks in sorted(places.items())]
    pairs = F.flatten(F.transform(F.array(counts), lambda c: F.array(*[F.struct(F.lit(n).alias("licence"), f(c).alias("matches")) for n, f in total])))
    nothing = F.array().cast("array<struct<licence: string, matches: bigint>>")
    return F.when(F.size(ids) > 0, F.filter(pairs, lambda x: x["matches"] > 0)).otherwise(nothing)


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", sentences: dict[str, str] | None = None, rules: list[tuple[str, list[str]]] | None = None) -> DataFrame:
    """(doc_id, n_hits, sentence_ids, matches) for each row of ``docs``; matches: array of (licence, number).

    Null and empty texts have no hits. Rows that share an id (a null id too) are scanned together and each gets the joint
    outcome. Other columns are not read. An empty table gives an empty result.
    """
    spark = docs.sparkSession
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("raw"))
    known = sorted({" ".join(normal(s).split()) for s in (sentences or SENTENCES).values()})
    said = base.select("doc_id", F.inline(found_sentences(F.col("raw"), known))).select("doc_id", F.struct("at", "line").alias("pos"), "sentence")
    hits = said.join(F.broadcast(known_sentences(spark, sentences)), "sentence")
    seqs = hits.groupBy(F.col("doc_id").alias("hit_id")).agg(F.array_sort(F.collect_list(F.struct("pos", "sentence_id"))).alias("hits"))
    seqs = seqs.select("hit_id", F.col("hits.sentence_id").alias("sentence_ids"))
    ids = F.coalesce("sentence_ids", F.array().cast("array<string>"))
    all_docs = base.select("doc_id").join(seqs, F.col("doc_id").eqNullSafe(F.col("hit_id")), "left").select("doc_id", ids.alias("sentence_ids"))
    return all_docs.select("doc_id", F.size("sentence_ids").cast("long").alias("n_hits"), "sentence_ids", rule_counts(F.col("sentence_ids"), rules or RULES).alias("matches"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = scan(read(spark, sf_dir, "documents"))
    named = F.transform("matches", lambda m: F.concat_ws("=", m["licence"], m["matches"].cast("string")))
    return out.select("doc_id", "n_hits", F.array_join("sentence_ids", ",").alias("sentence_ids"), F.array_join(named, ",").alias("licences"))


def oracle() -> str:
    """The same over SQL text functions: rules with several identifiers take their matches out of the joined sequence one after the other."""
    known = ", ".join("('" + " ".join(normal(s).split()) + f"', '{k}')" for k, s in SENTENCES.items())
    neutral = ", ".join(f"'{n}'" for n in NEUTRAL)
    rules = [(n, "".join(f"<{i}>" for i in r), len(r), len(r) == 1 and r[0] in NEUTRAL) for n, r in _longest_first(RULES)]
    rest = "SELECT doc_id, every, rest FROM q"
    counts = []
    for k, (name, p, size, free) in enumerate(rules):
        found = f"(length({'every' if free else 'rest'}) - length(replace({'every' if free else 'rest'}, '{p}', ''))) // {len(p)}"
        if size > 1:
            rest = f"SELECT * REPLACE (replace(rest, '{p}', '|') AS rest), {found} AS c{k} FROM ({rest})"
            counts.append(f"SELECT doc_id, '{name}' AS licence, c{k} AS c FROM t")
        else:
            counts.append(f"SELECT doc_id, '{name}' AS licence, {found} AS c FROM t")
    return rf"""
WITH s AS (
  SELECT doc_id, string_split(regexp_replace(coalesce(text, ''), '{CUT}', '\1' || chr(10), 'g'), chr(10)) AS parts FROM documents),
p AS (SELECT doc_id, unnest(parts) AS part, generate_subscripts(parts, 1) AS pos FROM s),
k(sentence, sentence_id) AS (VALUES {known}),
h AS (
  SELECT doc_id, pos, sentence_id FROM p JOIN k
  ON trim(lower(regexp_replace(part, '[^A-Za-z0-9]+', ' ', 'g'))) = sentence),
q AS (SELECT doc_id, count(*) AS n_hits, string_agg(sentence_id, ',' ORDER BY pos) AS sentence_ids,
  string_agg('<' || sentence_id || '>', '' ORDER BY pos) AS every,
  coalesce(string_agg('<' || sentence_id || '>', '' ORDER BY pos) FILTER (WHERE sentence_id NOT IN ({neutral})), '') AS rest FROM h GROUP BY doc_id),
t AS ({rest}),
c AS (SELECT doc_id, licence, sum(c) AS c FROM ({" UNION ALL ".join(counts)}) GROUP BY doc_id, licence HAVING sum(c) > 0),
l AS (SELECT doc_id, string_agg(licence || '=' || c::bigint, ',' ORDER BY licence) AS licences FROM c GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_hits, 0) AS n_hits, coalesce(sentence_ids, '') AS sentence_ids, coalesce(licences, '') AS licences
FROM documents d LEFT JOIN q USING (doc_id) LEFT JOIN l USING (doc_id)
"""
