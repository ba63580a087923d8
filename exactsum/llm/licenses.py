"""Licence recognition by sentence rules, in DataFrame functions only.

A text is cut into pieces where a sentence ends (a closing mark before white space, or a blank line),
and a piece into its lines.  A sentence is a run of whole lines of one piece, so licence bodies match
whether they are wrapped or not, and notices without a closing mark match as lines of their own.
Sentences are normalised (lower case, letters and digits only, which also drops comment leaders and
bullets) and looked up among known licence sentences; a match inside a longer match doesn't count.

The identifiers found, in text order, are matched against ordered rules.  Each rule is a sequence of
identifiers that must follow each other, with nothing but unknown sentences between them.  Rules are
tried in their order, those that say more first, and a rule takes the identifiers it matches, so no
later rule can use them.  Rules of last resort count only where no other rule matched.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Identifier and sentence, as licence texts and customary notices state them.
SENTENCES = [
    ("mit-notice", "Released under the MIT License."),
    ("mit-notice", "Licensed under the MIT License."),
    ("mit-notice", "This project is licensed under the MIT License."),
    ("mit-notice", "Distributed under the MIT License."),
    ("mit-grant", 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:'),
    ("mit-keep", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("mit-keep", "The above copyright notice and this permission notice (including the next paragraph) shall be included in all copies or substantial portions of the Software."),
    ("as-is-software", 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT.'),
    ("as-is-author", 'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS.'),
    ("apache2-notice", "Licensed under the Apache License, Version 2.0."),
    ("apache2-notice", 'Licensed under the Apache License, Version 2.0 (the "License");'),
    ("apache2-notice", "This project is licensed under the Apache License, Version 2.0."),
    ("apache2-may", "you may not use this file except in compliance with the License."),
    ("gpl2-notice", "Licensed under the GNU General Public License, version 2."),
    ("gpl2-notice", "This work is licensed under the GNU General Public License, version 2."),
    ("gpl3-notice", "Licensed under the GNU General Public License, version 3."),
    ("gpl3-notice", "This work is licensed under the GNU General Public License, version 3."),
    ("gpl2-free", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("gpl2-only-free", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License version 2 as published by the Free Software Foundation."),
    ("gpl3-free", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("gpl3-free", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 3 of the License, or (at your option) any later version."),
    ("lgpl21-free", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version."),
    ("lgpl3-free", "This library is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("agpl3-free", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("gpl-hope", "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY;"),
    ("lgpl-hope", "This library is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY;"),
    ("mpl2-notice", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("mpl2-copy", "If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("mpl2-copy", "If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."),
    ("epl1-notice", "All rights reserved. This program and the accompanying materials are made available under the terms of the Eclipse Public License v1.0 which accompanies this distribution, and is available at http://www.eclipse.org/legal/epl-v10.html"),
    ("epl2-notice", "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0/"),
    ("bsd-grant", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("bsd-source", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."),
    ("bsd-binary", "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."),
    ("bsd-names", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    ("bsd-names", "Neither the name of the author nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    ("bsd-names", "The name of the author may not be used to endorse or promote products derived from this software without specific prior written permission."),
    ("bsd-advert", "All advertising materials mentioning features or use of this software must display the following acknowledgement:"),
    ("isc-grant", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("isc-grant", "Permission to use, copy, modify, and distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("zero-bsd-grant", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted."),
    ("boost-notice", "Distributed under the Boost Software License, Version 1.0."),
    ("cc-by-nc-4-notice", "Licensed under CC BY-NC 4.0."),
    ("cc-by-4-notice", "Licensed under CC BY 4.0."),
    ("cc-by-sa-4-notice", "Licensed under CC BY-SA 4.0."),
    ("cc-by-4-notice", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("cc-by-sa-4-notice", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("cc-by-nc-4-notice", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("cc0-notice", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
    ("unlicense", "This is free and unencumbered software released into the public domain."),
    ("all-rights", "All rights reserved."),
]

#: Identifiers of the common licence list that a tag line may name.
TAGS = "0BSD AGPL-3.0-only AGPL-3.0-or-later Apache-2.0 BSD-2-Clause BSD-3-Clause BSD-4-Clause BSL-1.0 CC-BY-4.0 CC-BY-NC-4.0 CC-BY-SA-4.0 CC0-1.0 EPL-1.0 EPL-2.0 GPL-2.0-only GPL-2.0-or-later GPL-3.0-only GPL-3.0-or-later ISC LGPL-2.1-only LGPL-2.1-or-later LGPL-3.0-only LGPL-3.0-or-later MIT MPL-2.0 Unlicense".split()

#: Licence and the identifiers that must follow each other, in the order in which rules are tried.
RULES = [
    ("BSD-4-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-advert", "bsd-names")),
    ("BSD-3-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-names")),
    ("BSD-2-Clause", ("bsd-grant", "bsd-source", "bsd-binary")),
    ("MIT", ("mit-grant", "mit-keep", "as-is-software")),
    ("MIT", ("mit-grant", "mit-keep")),
    ("GPL-2.0-or-later", ("gpl2-free", "gpl-hope")),
    ("GPL-2.0-only", ("gpl2-only-free", "gpl-hope")),
    ("GPL-3.0-or-later", ("gpl3-free", "gpl-hope")),
    ("AGPL-3.0-or-later", ("agpl3-free", "gpl-hope")),
    ("LGPL-2.1-or-later", ("lgpl21-free", "lgpl-hope")),
    ("LGPL-3.0-or-later", ("lgpl3-free", "lgpl-hope")),
    ("MPL-2.0", ("mpl2-notice", "mpl2-copy")),
    ("Apache-2.0", ("apache2-notice", "apache2-may")),
    ("ISC", ("isc-grant", "as-is-author")),
    ("0BSD", ("zero-bsd-grant", "as-is-author")),
    ("GPL-2.0-or-later", ("gpl2-free",)),
    ("GPL-2.0-only", ("gpl2-only-free",)),
    ("GPL-3.0-or-later", ("gpl3-free",)),
    ("AGPL-3.0-or-later", ("agpl3-free",)),
    ("LGPL-2.1-or-later", ("lgpl21-free",)),
    ("LGPL-3.0-or-later", ("lgpl3-free",)),
    ("MPL-2.0", ("mpl2-notice",)),
    ("EPL-1.0", ("epl1-notice",)),
    ("EPL-2.0", ("epl2-notice",)),
    ("Apache-2.0", ("apache2-notice",)),
    ("GPL-2.0-only", ("gpl2-notice",)),
    ("GPL-3.0-only", ("gpl3-notice",)),
    ("MIT", ("mit-notice",)),
    ("ISC", ("isc-grant",)),
    ("0BSD", ("zero-bsd-grant",)),
    ("BSL-1.0", ("boost-notice",)),
    ("CC-BY-NC-4.0", ("cc-by-nc-4-notice",)),
    ("CC-BY-SA-4.0", ("cc-by-sa-4-notice",)),
    ("CC-BY-4.0", ("cc-by-4-notice",)),
    ("CC0-1.0", ("cc0-notice",)),
    ("Unlicense", ("unlicense",)),
    *[(tag, (f"tag-{tag}",)) for tag in TAGS],
]
#: Tried last, and only where no other rule matched.
LAST_RESORT = [("Proprietary", ("all-rights",))]

#: Only in the DuckDB query: it passes over a piece without any of these (in lower case), also where a line end parts two words of one.
HINTS = "licen|copyright|warrant|redistribut|rights reserved|public domain|software|program|advertising materials|copy of the mpl|endorse or promote"
#: Where sentences end; line ends are unified before.
BREAK = r"([.!?;])[\x20\x09-\x0D]+|\n[\x20\x09-\x0D]*\n"
#: Only in the DuckDB query: lines of one sentence at most.
LINES = 16


def plain(sentence: str) -> str:
    return re.sub("[^a-z0-9]+", " ", sentence.lower()).strip()


def lookup() -> dict[str, str]:
    """Normalised sentence to identifier.  A known sentence with a break inside counts by its longest part."""
    known: dict[str, str] = {}
    parts_of = [(name, [plain(p) for p in re.sub(BREAK, lambda m: f"{m[1]}\0", sentence).split("\0")]) for name, sentence in [*SENTENCES, *[(f"tag-{t}", f"SPDX-License-Identifier: {t}") for t in TAGS]]]
    for name, parts in parts_of:
        if len(parts) == 1:
            known[parts[0]] = name
    for name, parts in parts_of:
        if len(parts) > 1:
            known.setdefault(max(parts, key=len), name)
    return known


def _let(value: Column, use) -> Column:
    return F.get(F.transform(F.array(value), use), 0)


def lines(text: Column) -> Column:
    """A text in lower case, each line between marks: a line end or, where a piece ends, \\1."""
    unified = F.regexp_replace(F.lower(text), "\r\n?", "\n")
    return F.concat(F.lit("\n"), F.regexp_replace(unified, BREAK, "$1\u0001"), F.lit("\n"))


def line_start() -> str:
    """Matches the mark before each of lines(); group 1 is the longest known sentence in whole lines from there on, if any.

    Normalising all of a text takes longer than to allow for what is dropped, between words and at a line's ends.
    """
    drop = "[^a-z0-9\n\u0001]"
    between = f"(?:{drop}++\n?|\n){drop}*+"  # never a line without a word
    longest_first = sorted(lookup(), key=len, reverse=True)
    known = "|".join(s.replace(" ", between) for s in longest_first)
    return f"[\n\u0001]{drop}*+(?:(?=({known}){drop}*+[\n\u0001])|)"


def identified(text: Column) -> Column:
    """Identifiers of the known sentences of a text, in its order.  Every line is looked up, with as many after it as a sentence takes."""
    known = F.create_map(*[F.lit(x) for pair in lookup().items() for x in pair])
    most = max(len(s.split()) for s in lookup())  # a line has a word at least, so no sentence takes more lines

    def maximal(found):
        """Without those that end inside one that starts before; found has one for a line at most, in order."""
        before = lambda k: F.slice(found, F.greatest(k + 2 - most, F.lit(1)), F.least(k, F.lit(most - 1)))
        return F.filter(found, lambda r, k: ~F.exists(before(k), lambda o: o["end"] >= r["end"]))

    starts = F.transform(F.regexp_extract_all(lines(text), F.lit(line_start()), F.lit(1)), lambda s, i: F.struct(i.alias("i"), s.alias("s")))
    found = F.transform(
        F.filter(starts, lambda r: r["s"] != ""),
        lambda r: F.struct((r["i"] + F.size(F.split(r["s"], "\n"))).alias("end"), known[F.regexp_replace(r["s"], "[^a-z0-9]+", " ")].alias("id")),
    )
    return F.transform(_let(found, maximal), lambda r: r["id"])


def marked(ids: tuple[str, ...]) -> str:
    return "".join(f"<{i}>" for i in ids)


def matched(ids: Column) -> Column:
    """Sorted names of the licences whose rules the identifiers match."""

    def tried(rules, line):
        given = F.array(*[F.struct(F.lit(name).alias("name"), F.lit(marked(r)).alias("line")) for name, r in rules])
        start = F.struct(line.alias("line"), F.array().cast("array<string>").alias("names"))
        step = lambda s, r: F.when(F.contains(s["line"], r["line"]), F.struct(F.replace(s["line"], r["line"], F.lit("|")).alias("line"), F.concat(s["names"], F.array(r["name"])).alias("names"))).otherwise(s)
        return F.aggregate(given, start, step)

    line = F.array_join(F.transform(ids, lambda i: F.concat(F.lit("<"), i, F.lit(">"))), "")
    last = lambda s: F.when(F.size(s["names"]) > 0, s["names"]).otherwise(tried(LAST_RESORT, s["line"])["names"])
    names = F.array_sort(F.array_distinct(_let(tried(RULES, line), last)))
    return F.when(F.size(ids) > 0, names).otherwise(F.array().cast("array<string>"))


def recognised(docs: DataFrame, text: str = "text", prefix: str = "") -> DataFrame:
    """Adds sentence_ids (array, in text order) and licenses (sorted array) to docs.

    Null and empty texts have neither; rows are judged alone, so ties and repeated rows need no care.
    All columns of docs are kept; where one has the name of a new one, give a `prefix` for the new
    ones, else it is an error.
    """
    ids, names = f"{prefix}sentence_ids", f"{prefix}licenses"
    if clash := {ids, names} & set(docs.columns):
        raise ValueError(f"docs already has {sorted(clash)}; give a prefix")
    d = docs.withColumn(ids, F.coalesce(identified(F.col(text)), F.array().cast("array<string>")))
    return d.withColumn(names, matched(F.col(ids)))


def oracle(table: str = "documents") -> str:
    """The digest query in DuckDB's SQL, from the same fixed values."""
    values = ", ".join(f"('{k}', '{v}')" for k, v in lookup().items())
    line, cases = "line", []
    for name, ids in RULES:
        cases.append(f"CASE WHEN contains({line}, '{marked(ids)}') THEN '{name}' END")
        line = f"replace({line}, '{marked(ids)}', '|')"
    names = f"list_sort(list_distinct([x FOR x IN [{', '.join(cases)}] IF x IS NOT NULL]))"
    last = f"CASE WHEN contains(line, '{marked(LAST_RESORT[0][1])}') THEN '{LAST_RESORT[0][0]}' ELSE '' END"
    return rf"""
WITH known(norm, id) AS (VALUES {values}),
cut AS (
  SELECT doc_id, string_split(regexp_replace(regexp_replace(text, '\r\n?', chr(10), 'g'), '{BREAK}', '\1' || chr(1), 'g'), chr(1)) AS parts FROM {table}
), piece AS (SELECT doc_id, unnest(parts) AS p, unnest(range(len(parts))) AS k FROM cut
), line AS (
  SELECT doc_id, k, list_transform(string_split(p, chr(10)), lambda s: trim(regexp_replace(lower(s), '[^a-z0-9]+', ' ', 'g'))) AS l
  FROM piece WHERE regexp_matches(lower(p), '{HINTS}')
), first AS (SELECT doc_id, k, l, unnest(range(1, len(l) + 1)) AS i FROM line
), run AS (SELECT doc_id, k, l, i, unnest(range(i, least(i + {LINES}, len(l) + 1))) AS j FROM first WHERE l[i] <> ''
), found AS (
  SELECT doc_id, k, i, j, id FROM (SELECT doc_id, k, i, j, array_to_string(l[i:j], ' ') AS norm FROM run WHERE l[j] <> '') JOIN known USING (norm)
), most AS (
  SELECT * FROM found f WHERE NOT EXISTS (SELECT 1 FROM found o WHERE o.doc_id = f.doc_id AND o.k = f.k AND o.i <= f.i AND o.j >= f.j AND o.j - o.i > f.j - f.i)
), seq AS (SELECT doc_id, string_agg('<' || id || '>', '' ORDER BY k, i, j) AS line, count(*) AS n FROM most GROUP BY doc_id
), judged AS (SELECT doc_id, line, n, {names} AS names, {last} AS last FROM seq
)
SELECT d.doc_id, coalesce(n, 0)::INTEGER AS n_sentences, coalesce(line, '') AS sentence_ids,
       coalesce(CASE WHEN len(names) > 0 THEN array_to_string(names, '|') ELSE last END, '') AS licenses
FROM {table} d LEFT JOIN judged USING (doc_id)
"""
