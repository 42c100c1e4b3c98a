"""Licence scans by sentence rules, in Spark's own functions only.

Texts are normalised and marked where a sentence may begin or end: after [.!?;:] before a space
and at line ends. Known licence sentences are found between two marks; marks inside one are passed
over, so hard wraps, comment signs, colons and abbreviations do not hide it, and of several that
begin at a mark the longest counts. The sequence of identifiers is matched against ordered rules: a
rule names a licence if its identifiers follow one another. A rule that lies wholly inside a longer
rule's match is reported with it only if it also stands alone as a rule of its own.

The SQL of op7_license_scan knows SENTENCES only, each between neighbouring marks; the operator
finds all of these and more, and the two agree where a table holds no other form.

Cases: SPDX expressions of several licences are not taken apart; null and empty texts have no sentences; repeated rows are scanned each; other columns are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Identifiers and normalised licence sentences (lower case, words joined by one space).
SENTENCES = {
    "apache2_under": "licensed under the apache license version 2 0",
    "apache2_grant": "licensed under the apache license version 2 0 the license",
    "apache2_limit": "you may not use this file except in compliance with the license",
    "apache2_copy": "you may obtain a copy of the license at",
    "apache2_spdx": "spdx license identifier apache 2 0",
    "mit_released": "released under the mit license",
    "mit_under": "licensed under the mit license",
    "mit_grant": "permission is hereby granted free of charge to any person obtaining a copy of this software",
    "mit_notice": "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    "mit_spdx": "spdx license identifier mit",
    "as_is": "the software is provided as is without warranty of any kind express or implied",
    "gpl3_work": "this work is licensed under the gnu general public license version 3",
    "gpl3_under": "licensed under the gnu general public license version 3",
    "gpl_free": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license",
    "gpl3_spdx": "spdx license identifier gpl 3 0 only",
    "gpl2_work": "this work is licensed under the gnu general public license version 2",
    "lgpl_under": "licensed under the gnu lesser general public license",
    "ccbync4_under": "licensed under cc by nc 4 0",
    "ccby4_under": "licensed under cc by 4 0",
    "ccbysa4_under": "licensed under cc by sa 4 0",
    "cc0_mark": "to the extent possible under law the author has waived all copyright",
    "bsd_redist": "redistribution and use in source and binary forms with or without modification are permitted",
    "bsd_spdx": "spdx license identifier bsd 3 clause",
    "mpl2_form": "this source code form is subject to the terms of the mozilla public license v 2 0",
    "rights": "all rights reserved",
}

def _gnu(name: str, version: str, subject: str) -> list[str]:
    """The usual headers of the GNU licences."""
    start = f"this {subject} is free software you can redistribute it and or modify it under the terms of the gnu {name}general public license"
    fsf = "as published by the free software foundation"
    ends = (
        f"{fsf} either version {version} of the license or at your option any later version", f"{fsf} version {version} of the license",
        f"{fsf} version {version}", f"version {version} as published by the free software foundation", f"version {version}",
    )
    return [f"{start} {end}" for end in ends]


def _spdx(*names: str) -> list[str]:
    return [f"spdx license identifier {name}" for name in names]


def _gnu_spdx(name: str, *versions: str) -> list[str]:
    return _spdx(*[f"{name} {v}{end}" for v in versions for end in ("", " only", " or later")])


# Whole standard sentences that stand for the same identifiers.
WHOLE = {
    "mit_grant": [
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"
        " the software to deal in the software without restriction including without limitation the rights to use copy modify merge"
        " publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to"
        " do so subject to the following conditions"
    ],
    "mit_notice": [
        "the above copyright notice and this permission notice including the next paragraph shall be included in all copies or"
        " substantial portions of the software"
    ],
    "as_is": [
        "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of"
        " merchantability fitness for a particular purpose and noninfringement"
    ],
    "bsd_redist": [
        "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"
    ],
    "bsd_spdx": _spdx("bsd 2 clause"),
    "mpl2_form": _spdx("mpl 2 0"),
    "gpl3_work": [x for subject in ("program", "file", "software") for x in _gnu("", "3", subject)],
    "gpl2_work": [x for subject in ("program", "file", "software") for x in _gnu("", "2", subject)] + _gnu_spdx("gpl", "2 0"),
    "gpl3_spdx": _spdx("gpl 3 0", "gpl 3 0 or later"),
    "lgpl_under": [x for subject in ("library", "program") for v in ("2", "2 1", "3") for x in _gnu("lesser ", v, subject)]
    + _gnu_spdx("lgpl", "2 0", "2 1", "3 0"),
    "ccbync4_under": ["this work is licensed under a creative commons attribution noncommercial 4 0 international license", *_spdx("cc by nc 4 0")],
    "ccby4_under": ["this work is licensed under a creative commons attribution 4 0 international license", *_spdx("cc by 4 0")],
    "ccbysa4_under": ["this work is licensed under a creative commons attribution sharealike 4 0 international license", *_spdx("cc by sa 4 0")],
    "cc0_mark": [
        "the person who associated cc0 with this work has waived all copyright and related or neighboring rights to this work",
        "to the extent possible under law the author has waived all copyright and related or neighboring rights to this work",
        *_spdx("cc0 1 0"),
    ],
}
# Ordered rules, longest first; a licence and the identifiers that must follow one another.
RULES = (
    ("Apache-2.0", ("apache2_grant", "apache2_limit", "apache2_copy")),
    ("MIT", ("mit_grant", "mit_notice", "as_is")),
    ("Apache-2.0", ("apache2_grant", "apache2_limit")),
    ("MIT", ("mit_grant", "mit_notice")),
    ("Apache-2.0", ("apache2_under",)),
    ("Apache-2.0", ("apache2_grant",)),
    ("Apache-2.0", ("apache2_spdx",)),
    ("MIT", ("mit_released",)),
    ("MIT", ("mit_under",)),
    ("MIT", ("mit_spdx",)),
    ("GPL-3.0", ("gpl3_work",)),
    ("GPL-3.0", ("gpl3_under",)),
    ("GPL-3.0", ("gpl3_spdx",)),
    ("GPL-2.0", ("gpl2_work",)),
    ("GPL", ("gpl_free",)),
    ("LGPL", ("lgpl_under",)),
    ("CC-BY-NC-4.0", ("ccbync4_under",)),
    ("CC-BY-4.0", ("ccby4_under",)),
    ("CC-BY-SA-4.0", ("ccbysa4_under",)),
    ("CC0", ("cc0_mark",)),
    ("BSD", ("bsd_redist",)),
    ("BSD", ("bsd_spdx",)),
    ("MPL-2.0", ("mpl2_form",)),
    ("proprietary", ("rights",)),
)
#: Every known sentence holds one of these, so a text without any has none.
HINTS = ("licen", "rights", "permission", "warrant", "redistrib", "copyright", "apache", "software", "public license")


def _marked(text: Column) -> Column:
    """Words joined by one space, with a bar wherever a sentence may begin or end."""
    cut = F.regexp_replace(F.concat(F.lit("\n"), text, F.lit("\n")), r"[.!?;:][\x20\x09\x0D]+", "\n")
    return F.regexp_replace(F.regexp_replace(F.lower(cut), r"[^a-z0-9\n]+", " "), r" ?\n[ \n]*", "|")


def _known(text: Column, names: dict[str, str]) -> Column:
    """Identifiers of the known sentences, in order."""
    longest = sorted(names, key=lambda body: (-len(body.split()), body))
    pattern = r"(?<=\|)(?:" + "|".join("[ |]".join(body.split()) for body in longest) + r")(?=\|)"
    table = F.create_map(*[F.lit(x) for pair in names.items() for x in pair])
    found = F.regexp_extract_all(_marked(text), F.lit(pattern), F.lit(0))
    return F.transform(found, lambda s: F.element_at(table, F.translate(s, "|", " ")))


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", sentences=None, rules=RULES) -> DataFrame:
    """(doc_id, n_known, sentence_ids, licenses): identifiers in order, licences by rule order."""
    names = {text: name for name, text in (sentences or SENTENCES).items()}
    if not sentences:
        names |= {text: name for name, bodies in WHOLE.items() for text in bodies}
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    ids = _known(text, names)
    hinted = F.lit(True) if sentences else F.lower(text).rlike("|".join(HINTS))
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"), F.when(hinted, ids).otherwise(F.array().cast("array<string>")).alias("sentence_ids")
    )
    line = F.concat(F.lit(","), F.array_join("sentence_ids", ","), F.lit(","))
    matched = F.array_distinct(
        F.filter(
            F.array(*[F.when(line.contains("," + ",".join(ids) + ","), F.lit(name)) for name, ids in rules]),
            lambda x: x.isNotNull(),
        )
    )
    none = F.array().cast("array<string>")
    return rows.select(
        "doc_id",
        F.size("sentence_ids").cast("long").alias("n_known"),
        "sentence_ids",
        F.when(F.size("sentence_ids") > 0, matched).otherwise(none).alias("licenses"),
    )


def report(docs: DataFrame) -> DataFrame:
    """(doc_id, n_known, sentence_ids, licenses) with lists joined by commas."""
    return scan(docs).select(
        "doc_id", "n_known", F.array_join("sentence_ids", ",").alias("sentence_ids"), F.array_join("licenses", ",").alias("licenses")
    )


def _values(rows) -> str:
    return ", ".join("(" + ", ".join(f"'{x}'" if isinstance(x, str) else str(x) for x in r) + ")" for r in rows)


ORACLE = rf"""
WITH known(id, body) AS (VALUES {_values(SENTENCES.items())}),
rules(ord, lic, seq) AS (VALUES {_values((i, name, "," + ",".join(ids) + ",") for i, (name, ids) in enumerate(RULES))}),
s AS (SELECT doc_id, unnest(x) AS body, generate_subscripts(x, 1) AS pos FROM (
  SELECT doc_id, list_transform(string_split(regexp_replace(coalesce(text, ''), '([.!?;:])[\x20\x09\x0D]+', '\1' || chr(10), 'g'), chr(10)),
    lambda y: trim(regexp_replace(lower(y), '[^a-z0-9]+', ' ', 'g'))) AS x FROM documents)),
i AS (SELECT doc_id, count(*) AS n, string_agg(id, ',' ORDER BY pos) AS ids FROM s JOIN known USING (body) GROUP BY doc_id),
f AS (SELECT doc_id, lic, min(ord) AS o FROM i JOIN rules ON contains(',' || ids || ',', seq) GROUP BY doc_id, lic),
g AS (SELECT doc_id, string_agg(lic, ',' ORDER BY o) AS licenses FROM f GROUP BY doc_id)
SELECT d.doc_id, coalesce(i.n, 0) AS n_known, coalesce(i.ids, '') AS sentence_ids, coalesce(g.licenses, '') AS licenses
FROM documents d LEFT JOIN i ON d.doc_id = i.doc_id LEFT JOIN g ON d.doc_id = g.doc_id
"""
