"""Licence scans by recognised sentences and ordered rules."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Normalised licence sentences and their identifiers.
SENTENCES = {
    "licensed under the apache license version 2 0": "apache2-under",
    "licensed under the apache license version 2 0 the license": "apache2-under",
    "you may not use this file except in compliance with the license": "apache-compliance",
    "spdx license identifier apache 2 0": "spdx-apache2",
    "released under the mit license": "mit-under",
    "licensed under the mit license": "mit-under",
    "this project is licensed under the mit license": "mit-under",
    "spdx license identifier mit": "spdx-mit",
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction": "mit-grant",
    "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software": "mit-notice",
    "the software is provided as is without warranty of any kind express or implied": "mit-warranty",
    "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met": "bsd-grant",
    "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer": "bsd-source",
    "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution": "bsd-binary",
    "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission": "bsd-endorse",
    "spdx license identifier bsd 3 clause": "spdx-bsd3",
    "this work is licensed under the gnu general public license version 3": "gpl3-under",
    "licensed under the gnu general public license version 3": "gpl3-under",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version": "gpl3-later",
    "spdx license identifier gpl 3 0 only": "spdx-gpl3",
    "licensed under cc by nc 4 0": "ccbync4-under",
    "licensed under cc by 4 0": "ccby4-under",
    "licensed under cc by sa 4 0": "ccbysa4-under",
    "this work is licensed under a creative commons attribution 4 0 international license": "ccby4-under",
    "this work is dedicated to the public domain": "public-domain",
    "all rights reserved": "reserved",
}
#: Rules in the order in which they are tried; a rule matches neighbouring identifiers and uses them up.
RULES = (
    ("MIT", ("mit-grant", "mit-notice", "mit-warranty")),
    ("MIT", ("mit-grant", "mit-notice")),
    ("BSD-3-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-endorse")),
    ("BSD-2-Clause", ("bsd-grant", "bsd-source", "bsd-binary")),
    ("Apache-2.0", ("apache2-under", "apache-compliance")),
    ("Apache-2.0", ("spdx-apache2",)),
    ("Apache-2.0", ("apache2-under",)),
    ("MIT", ("spdx-mit",)),
    ("MIT", ("mit-under",)),
    ("BSD-3-Clause", ("spdx-bsd3",)),
    ("GPL-3.0-or-later", ("gpl3-later",)),
    ("GPL-3.0-only", ("spdx-gpl3",)),
    ("GPL-3.0-only", ("gpl3-under",)),
    ("CC-BY-NC-4.0", ("ccbync4-under",)),
    ("CC-BY-SA-4.0", ("ccbysa4-under",)),
    ("CC-BY-4.0", ("ccby4-under",)),
    ("Public-Domain", ("public-domain",)),
    ("All-Rights-Reserved", ("reserved",)),
)
#: Further whole sentences of common licences; texts wrapped at any width are recognised by them.
FULL_SENTENCES = {
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions": "mit-grant",
    "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement": "mit-warranty",
    "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied": "apache-warranty",
    "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies": "isc-grant",
    "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed": "bsd-warranty",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version": "gpl2-later",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license version 2 as published by the free software foundation": "gpl2-only",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation version 3": "gpl3-under",
    "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2 1 of the license or at your option any later version": "lgpl21-later",
    "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version": "lgpl3-later",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version": "agpl3-later",
    "this source code form is subject to the terms of the mozilla public license v 2 0": "mpl2-under",
    "you may obtain a copy of the license at": "apache-copy",
    "http www apache org licenses license 2 0": "apache-url",
    "see the license for the specific language governing permissions and limitations under the license": "apache-see",
    "see the gnu general public license for more details": "gpl-see",
    "licensed under the gnu general public license version 3 or later": "gpl3-later",
    "licensed under the gnu general public license version 3 or any later version": "gpl3-later",
    "mit license": "mit-under",
    "the mit license": "mit-under",
    "isc license": "isc-under",
    "spdx license identifier isc": "isc-under",
    "spdx license identifier mpl 2 0": "mpl2-under",
    "spdx license identifier gpl 2 0 only": "gpl2-only",
    "spdx license identifier gpl 2 0 or later": "gpl2-later",
    "spdx license identifier gpl 3 0 or later": "gpl3-later",
    "spdx license identifier lgpl 2 1 or later": "lgpl21-later",
    "spdx license identifier lgpl 3 0 or later": "lgpl3-later",
    "spdx license identifier agpl 3 0 or later": "agpl3-later",
    "spdx license identifier bsd 2 clause": "spdx-bsd2",
}
#: Their rules, tried after those above.
FULL_RULES = (
    ("ISC", ("isc-grant",)),
    ("ISC", ("isc-under",)),
    ("BSD-2-Clause", ("spdx-bsd2",)),
    ("GPL-2.0-or-later", ("gpl2-later",)),
    ("GPL-2.0-only", ("gpl2-only",)),
    ("LGPL-2.1-or-later", ("lgpl21-later",)),
    ("LGPL-3.0-or-later", ("lgpl3-later",)),
    ("AGPL-3.0-or-later", ("agpl3-later",)),
    ("MPL-2.0", ("mpl2-under",)),
)
#: Words from which a known sentence may go on to the end of its line.
GOES_ON = 12
#: Fixed value: a sentence with one of these speaks of a licence, known or not.
CUE = r"licen[sc]e|all rights reserved|permission is hereby|redistribution|copyright|without warranty|public domain|contributors may be used|redistribute it"


def _normal(sentence: Column) -> Column:
    return F.btrim(F.regexp_replace(F.lower(sentence), "[^a-z0-9]+", " "))


def _marked(text: Column) -> Column:
    """The normalised sentences of a text in a row: "!" before those that speak of a licence, ">" after each.

    A line end that is not behind a stop is "~", as the sentence may go on in the next line. A blank line ends a sentence.
    """
    pieces = F.split(text, r"(?<=\n)|(?<!\b[vV])[.!?][ \t]+")
    end = lambda s: F.when(s.rlike(r"[^.!?\s][ \t\r]*\n\z"), "~").otherwise(">")
    one = lambda s: F.when(_normal(s) == "", ">").otherwise(F.concat(F.when(F.lower(s).rlike(CUE), "!").otherwise(""), _normal(s), end(s)))
    return F.array_join(F.transform(pieces, one), "")


def _identifiers(text: Column) -> Column:
    """Array with an entry for each sentence that is known or speaks of a licence: its identifier, or null.

    A known sentence starts and ends at a sentence's or line's start and end, over any number of lines in between; long
    ones may go on in their last line. The longest is taken first. Lines that are left count each.
    """
    every = sorted((SENTENCES | FULL_SENTENCES).items(), key=lambda x: (-len(x[0]), x[0]))
    rest = lambda k: "(?:[ ][^~>|]*)?" if len(k.split()) >= GOES_ON else ""
    known = F.array(*[F.struct(F.lit(k).alias("s"), F.lit("(?<![^~>])!?" + "(?: |~!?)".join(k.split()) + rest(k) + "(?=[~>])").alias("find"), F.lit(f"|{v}|").alias("id")) for k, v in every])
    flat = lambda m: F.translate(m, "~>!", "  ")
    found = lambda m: F.aggregate(F.filter(known, lambda k: F.contains(flat(m), k["s"])), m, lambda a, k: F.regexp_replace(a, k["find"], k["id"]))
    left = F.get(F.transform(F.array(_marked(text)), found), F.lit(0))
    spoken = F.filter(F.split(left, "[~>]"), lambda x: x.startswith("|") | x.startswith("!"))
    return F.transform(spoken, lambda x: F.when(x.startswith("|"), F.translate(x, "|", "")))


def scan(docs: DataFrame, *keep: str) -> DataFrame:
    """``keep`` columns of each row with ``licenses`` (array, in rule order), ``n_matched`` and ``n_unknown``.

    Sentences end at line ends and at full stops before a blank, but known ones are found over the lines of a paragraph,
    too; they are compared in lower case with all but letters and digits as one space. ``n_matched`` counts recognised sentences, ``n_unknown`` sentences that speak of a licence but
    aren't known. Null and empty texts give an empty array and zeros. Texts without any cue are decided by one pattern
    search. All in one pass, without a shuffle.
    """
    rules = F.array(*[F.struct(F.lit(name).alias("name"), F.lit("|" + "||".join(ids) + "|").alias("ids")) for name, ids in RULES + FULL_RULES])
    ids = _identifiers(F.col("text"))
    start = lambda x: F.struct(F.array_join(F.transform(F.filter(x, lambda i: i.isNotNull()), lambda i: F.concat(F.lit("|"), i, F.lit("|"))), "").alias("rest"), F.array().cast("array<string>").alias("found"))
    step = lambda a, r: F.when(F.instr(a["rest"], r["ids"]) > 0, F.struct(F.replace(a["rest"], r["ids"], F.lit("#")).alias("rest"), F.concat(a["found"], F.array(r["name"])).alias("found"))).otherwise(a)
    result = F.get(
        F.transform(F.array(ids), lambda x: F.struct(F.array_distinct(F.aggregate(rules, start(x), step, lambda a: a["found"])).alias("licenses"), F.size(F.filter(x, lambda i: i.isNotNull())).cast("long").alias("n_matched"), F.size(F.filter(x, lambda i: i.isNull())).cast("long").alias("n_unknown"))),
        F.lit(0),
    )
    none = F.struct(F.array().cast("array<string>").alias("licenses"), F.lit(0).cast("long").alias("n_matched"), F.lit(0).cast("long").alias("n_unknown"))
    # one case-insensitive search decides most texts
    return docs.select(*keep, F.when(F.col("text").rlike("(?i)" + CUE), result).otherwise(none).alias("r")).select(*keep, "r.*")


def _sql() -> str:
    """DuckDB twin of the query for texts with sentences of one line; the rules become nested steps."""
    known = ", ".join(f"('{s}', '{i}')" for s, i in SENTENCES.items())
    steps, last = "", "q"
    for k, (name, ids) in enumerate(RULES):
        pattern = "|" + "||".join(ids) + "|"
        steps += f", r{k} as (select doc_id, replace(rest, '{pattern}', '#') as rest, case when contains(rest, '{pattern}') and not list_contains(found, '{name}') then list_append(found, '{name}') else found end as found, m, u from {last})"
        last = f"r{k}"
    return rf"""
with n(s, id) as (values {known}),
s as (select doc_id, lower(unnest(regexp_split_to_array(text, '\n+|[.!?][ \t]+'))) as s, generate_subscripts(regexp_split_to_array(text, '\n+|[.!?][ \t]+'), 1) as pos from documents),
c as (select doc_id, pos, trim(regexp_replace(s, '[^a-z0-9]+', ' ', 'g')) as s from s where regexp_matches(s, '{CUE}')),
i as (select doc_id, pos, id from c left join n using (s)),
q as (select doc_id, coalesce(string_agg('|' || id || '|', '' order by pos), '') as rest, []::varchar[] as found, count(id) as m, count(*) - count(id) as u from i group by doc_id){steps}
select d.doc_id, coalesce(array_to_string(found, ','), '') as licenses, coalesce(m, 0)::bigint as n_matched, coalesce(u, 0)::bigint as n_unknown from documents d left join {last} using (doc_id)
"""


SQL = _sql()
