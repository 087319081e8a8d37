"""Licence recognition by sentence rules, in DataFrame operations only.

Each text is cut into pieces (at line ends and after . ; : ! ? before white space), which are lower-cased
and stripped to letters, digits and points. A dictionary maps known licence sentences to identifiers; one is found where it fills a
piece or several pieces in a row, so wrapped lines and ``Identifier: MIT`` or ``v. 2.0`` do no harm, but a blank line within it does. The identifiers
of a document, in text order, form a sequence in which ordered rules are looked for: a rule names the run of
identifiers that a licence needs, and a rule whose run is part of a longer one that matched gives way to it.

The dictionary and the rules are constants of this module, literals in the plan. The SQL knows the one-line sentences and the
first 22 rules only; both agree where texts have no others.

Edge cases: null and empty texts have no sentences and no licence; a licence stated twice counts twice in
``n_sentences`` and once in ``licenses``; unknown sentences between two known ones don't break a rule (they have
no identifier) but are counted in ``gaps``; an empty table gives no rows; repeated rows are answered each; very long
texts are scanned whole, in memory in proportion to their length; other columns play no part, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Normalised licence sentences by identifier.
SENTENCES = {
    101: "licensed under the apache license version 2.0",
    102: "you may not use this file except in compliance with the license",
    103: "you may obtain a copy of the license at",
    104: "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis",
    201: "released under the mit license",
    202: "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files",
    203: "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    204: "the software is provided as is without warranty of any kind",
    205: "licensed under the mit license",
    301: "this work is licensed under the gnu general public license version 3",
    302: "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation",
    303: "either version 3 of the license or at your option any later version",
    304: "either version 2 of the license or at your option any later version",
    305: "you should have received a copy of the gnu general public license along with this program",
    306: "this work is licensed under the gnu general public license version 2",
    401: "licensed under cc by nc 4.0",
    402: "licensed under cc by 4.0",
    403: "licensed under cc by sa 4.0",
    404: "this work is licensed under a creative commons attribution noncommercial 4.0 international license",
    405: "this work is licensed under a creative commons attribution 4.0 international license",
    501: "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    502: "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    601: "this source code form is subject to the terms of the mozilla public license v 2.0",
    901: "all rights reserved",
    902: "spdx license identifier apache 2.0",
    903: "spdx license identifier mit",
    904: "spdx license identifier gpl 3.0 only",
    905: "spdx license identifier bsd 3 clause",
}

# Fixed values: (rank, licence, identifiers in order). Longer rules come first where one begins another.
RULES = [
    (1, "Apache-2.0", (101, 102, 103, 104)),
    (2, "Apache-2.0", (101,)),
    (3, "Apache-2.0", (902,)),
    (4, "MIT", (202, 203, 204)),
    (5, "MIT", (201,)),
    (6, "MIT", (205,)),
    (7, "MIT", (903,)),
    (8, "GPL-3.0-or-later", (302, 303)),
    (9, "GPL-2.0-or-later", (302, 304)),
    (10, "GPL-3.0-only", (301,)),
    (11, "GPL-2.0-only", (306,)),
    (12, "GPL-3.0-only", (904,)),
    (13, "CC-BY-NC-4.0", (401,)),
    (14, "CC-BY-NC-4.0", (404,)),
    (15, "CC-BY-4.0", (402,)),
    (16, "CC-BY-4.0", (405,)),
    (17, "CC-BY-SA-4.0", (403,)),
    (18, "BSD-3-Clause", (501, 502)),
    (19, "BSD-2-Clause", (501,)),
    (20, "BSD-3-Clause", (905,)),
    (21, "MPL-2.0", (601,)),
    (22, "LicenseRef-all-rights-reserved", (901,)),
]

_MIT = "the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions"
_AS_IS = "express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and"
_GPL = "this program is free software you can redistribute it and or modify it under the terms of"
_NAMES = "may be used to endorse or promote products derived from this software without specific prior written permission"

#: How the published texts put the sentences above, and further ones: (words, identifiers). ``*`` stands for names.
FORMS = [
    (SENTENCES[101] + " the license", (101,)),
    (SENTENCES[104] + " without warranties or conditions of any kind either express or implied", (104,)),
    ("apache license version 2.0 january 2004", (105,)),
    (f"{SENTENCES[202]} {_MIT}", (202,)),
    (SENTENCES[203].replace("notice shall", "notice including the next paragraph shall"), (203,)),
    (f"{SENTENCES[204]} {_AS_IS} noninfringement", (204,)),
    (f"{SENTENCES[204]} {_AS_IS} non infringement", (204,)),
    *((f"this {what} is {how} under the mit license", (i,)) for what in ("project", "software", "work") for how, i in (("released", 201), ("licensed", 205))),
    (f"{SENTENCES[302]} {SENTENCES[303]}", (302, 303)),
    (f"{SENTENCES[302]} {SENTENCES[304]}", (302, 304)),
    *((f"{_GPL} the gnu general public license version {v} as published by the free software foundation", (i,)) for v, i in ((3, 301), (2, 306))),
    *((f"{SENTENCES[302]} version {v} of the license", (i,)) for v, i in ((3, 301), (2, 306))),
    ("gnu general public license version 3 29 june 2007", (307,)),
    ("gnu general public license version 2 june 1991", (308,)),
    ("this work is licensed under a creative commons attribution sharealike 4.0 international license", (403,)),
    (f"neither the name of * nor the names of its contributors {_NAMES}", (502,)),
    (f"neither the names of * nor the names of its contributors {_NAMES}", (502,)),
    (f"the name of the author {_NAMES.replace('may be', 'may not be')}", (502,)),
    ("all advertising materials mentioning features or use of this software must display the following acknowledgement", (503,)),
    ("mozilla public license version 2.0", (602,)),
]

#: Short names after ``SPDX-License-Identifier:``, as normalised.
SPDX = {
    "apache 2.0": 902, "mit": 903, "gpl 3.0 only": 904, "gpl 3.0": 904, "bsd 3 clause": 905, "bsd 2 clause": 906, "gpl 2.0 only": 907, "gpl 2.0": 907,
    "gpl 2.0 or later": 908, "gpl 3.0 or later": 909, "mpl 2.0": 910, "cc by 4.0": 911, "cc by sa 4.0": 912, "cc by nc 4.0": 913, "bsd 4 clause": 914,
}
FORMS += [(f"spdx license identifier {x}", (i,)) for x, i in SPDX.items()]
FORMS += [(f"spdx license identifier {x} {op} {y}", (i, k)) for x, i in SPDX.items() for y, k in SPDX.items() for op in ("or", "and") if i != k]

#: Rules of the further identifiers. A whole GPL text ends with the header that it recommends, which is not the text's own.
MORE_RULES = [
    (23, "Apache-2.0", (105,)),
    (24, "GPL-3.0-only", (307, 302, 303)),
    (25, "GPL-3.0-only", (307,)),
    (26, "GPL-2.0-only", (308, 302, 304)),
    (27, "GPL-2.0-only", (308,)),
    (28, "BSD-4-Clause", (501, 503, 502)),
    (29, "MPL-2.0", (602,)),
    (30, "BSD-2-Clause", (906,)),
    (31, "GPL-2.0-only", (907,)),
    (32, "GPL-2.0-or-later", (908,)),
    (33, "GPL-3.0-or-later", (909,)),
    (34, "MPL-2.0", (910,)),
    (35, "CC-BY-4.0", (911,)),
    (36, "CC-BY-SA-4.0", (912,)),
    (37, "CC-BY-NC-4.0", (913,)),
    (38, "BSD-4-Clause", (914,)),
]

#: Identifiers by words; a form that is already a sentence above keeps that identifier.
KNOWN = dict(FORMS) | {v: (k,) for k, v in SENTENCES.items()}

#: Headings, which may have a blank line within.
TITLES = {(105,), (307,), (308,), (602,)}

#: Every known sentence has a word that begins with one of these, or is of use only beside one that has.
ANCHOR = r"(?i)licen[sc]|permi|rights|compliance|law|warrant|version [23]|redistribution|endorse"
_STAR = r"^(neither the names? of) .+ (nor the names)"


def _pattern() -> str:
    """A known sentence that fills one line of the stream or several ones, after a number of a list or none; alternatives are grouped by
    their first word and the longest comes first."""
    groups: dict[str, list[str]] = {}
    for words in sorted(KNOWN, key=lambda w: (-len(w), w)):
        first, rest = words.split(" ", 1)
        gap = r"[ \n]\n?" if KNOWN[words] in TITLES else r"[ \n]"
        rest = rest.replace(".", r"\.").replace(" ", gap).replace("*", r"(?:[a-z0-9.]+[ \n]){0,19}?[a-z0-9.]+")
        groups.setdefault(first, []).append(rest)
    return r"(?<![^\n])(?:\d{1,2} )?((?:" + "|".join(rf"{first}[ \n](?:{'|'.join(rest)})" for first, rest in groups.items()) + r"))(?![^\n])"


def stream(text: Column) -> Column:
    """The normalised pieces of a text, a line each: cut at line ends and after . ; : ! ? before white space, in lower case, anything but
    letters, digits and inner points as one blank."""
    cut = F.lower(F.regexp_replace(F.coalesce(text, F.lit("")), r"([.;:!?])[\x20\x09-\x0D]+", "$1\n"))
    plain = F.regexp_replace(F.regexp_replace(cut, r"gpl-([23]\.0)\+", "gpl-$1-or-later"), r"[^a-z0-9.\n]+", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(plain, r"\.+(?=[ \n]|\z)", ""), r" *\n *", "\n"))


def _sequence(ids) -> str:
    return "," + ",".join(map(str, ids)) + ","


def scan(docs: DataFrame) -> DataFrame:
    """One row per document: ``doc_id, n_sentences, sids, licenses, primary_license, rule_ids, gaps``.

    ``sids`` is the sequence of identifiers as text (``101,102``). A rule counts if its sequence occurs in it
    and isn't part of a longer rule that matched; ``primary_license`` is that of the first such rule. ``gaps`` are
    the unknown sentences between the first and the last known one. No row leaves its task: there is no shuffle."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", F.when(text.rlike(ANCHOR), stream(text)).otherwise("").alias("stream"))
    known = F.create_map(*(x for k, v in KNOWN.items() for x in (F.lit(k), F.array(*map(F.lit, v)))))
    pattern = F.lit(_pattern())
    rows = rows.withColumn("said", F.regexp_extract_all("stream", pattern, F.lit(1)))
    rows = rows.withColumn("ids", F.flatten(F.transform("said", lambda x: F.element_at(known, F.regexp_replace(F.regexp_replace(x, "[ \n]+", " "), _STAR, "$1 * $2")))).cast("array<string>"))
    rows = rows.withColumn("n", F.size("ids"))
    # lines between the first known sentence and the last that are part of none
    rows = rows.withColumn("between", F.when(F.col("n") > 0, F.regexp_extract(F.regexp_replace("stream", pattern, F.lit("{}")), r"(?s)\{.*\}", 0)).otherwise(""))
    rows = rows.withColumn("seq", F.concat(F.lit(","), F.array_join("ids", ","), F.lit(",")))
    rules = F.array(*(F.struct(F.lit(r).alias("rule"), F.lit(name).alias("license"), F.lit(_sequence(ids)).alias("seq")) for r, name, ids in RULES + MORE_RULES))
    rows = rows.withColumn("hit", F.when(F.col("n") == 0, F.slice(rules, 1, 0)).otherwise(F.filter(rules, lambda r: F.contains(F.col("seq"), r["seq"]))))
    rows = rows.withColumn("hit", F.filter("hit", lambda r: ~F.exists("hit", lambda o: (F.length(o["seq"]) > F.length(r["seq"])) & F.contains(o["seq"], r["seq"]))))
    names = F.transform("hit", lambda r: r["license"])
    gaps = F.when(F.col("n") > 0, F.length("between") - F.length(F.translate("between", "\n", "")) + 1 - F.size("said")).otherwise(0)
    return rows.select(
        "doc_id",
        F.col("n").cast("long").alias("n_sentences"),
        F.array_join("ids", ",").alias("sids"),
        F.array_join(F.array_sort(F.array_distinct(names)), ",").alias("licenses"),
        F.element_at(F.concat(names, F.array(F.lit(""))), 1).alias("primary_license"),
        F.array_join(F.transform("hit", lambda r: r["rule"].cast("string")), ",").alias("rule_ids"),
        gaps.cast("long").alias("gaps"),
    )


def oracle() -> str:
    """DuckDB's SQL for texts whose licences are one-line sentences of ``SENTENCES``."""
    known = ", ".join(f"({k}, '{v}')" for k, v in SENTENCES.items())
    rules = ", ".join(f"({r}, '{n}', '{_sequence(ids)}')" for r, n, ids in RULES)
    return f"""
with known(sid, norm) as (values {known}), rules(rule, license, seq) as (values {rules}),
docs as (select doc_id, coalesce(text, '') as text, row_number() over () as rid from documents),
cut as (select rid, string_split(regexp_replace(text, '([.;:!?])[\\x20\\x09-\\x0D]+', '\\1' || chr(10), 'g'), chr(10)) as p from docs),
parts as (select rid, unnest(p) as s, generate_subscripts(p, 1) as pos from cut),
hits as (select rid, pos, sid from (select *, trim(regexp_replace(regexp_replace(lower(s), '[^a-z0-9.]+', ' ', 'g'), '\\.+( |$)', '\\1', 'g')) as norm from parts where regexp_matches(s, '{ANCHOR}')) join known using (norm)),
seqs as (select rid, count(*) as n, string_agg(sid, ',' order by pos) as sids, max(pos) - min(pos) + 1 - count(*) as gaps from hits group by rid),
met as (select rid, rule, license, seq from seqs join rules on contains(',' || sids || ',', seq)),
best as (select * from met m where not exists (select 1 from met o where o.rid = m.rid and length(o.seq) > length(m.seq) and contains(o.seq, m.seq))),
said as (select rid, string_agg(rule, ',' order by rule) as rule_ids, arg_min(license, rule) as primary_license from best group by rid),
names as (select rid, string_agg(license, ',' order by license) as licenses from (select distinct rid, license from best) group by rid)
select doc_id, coalesce(n, 0)::bigint as n_sentences, coalesce(sids, '') as sids, coalesce(licenses, '') as licenses,
 coalesce(primary_license, '') as primary_license, coalesce(rule_ids, '') as rule_ids, coalesce(gaps, 0)::bigint as gaps
from docs left join seqs using (rid) left join said using (rid) left join names using (rid)"""
