"""License scans by sentence rules.

A text is cut into sentences, each sentence normalised (lower case, runs of anything but letters and digits as
one space), and mapped to the identifier of a known licence sentence. The identifiers, in the order of the
text, are matched against ordered rules: a rule is a run of identifiers; the first rules are the most specific,
and what a rule has matched later rules do not see. Only native functions; one narrow pass.

By default a line feed ends a sentence. With wrapped=True only sentence ends and blank lines do: a sentence that runs
over several lines (comment marks between them are no letters and fall away) is looked up whole, and line by line
where it is not known so.

Defined cases: a null or empty text has no sentence; repeated sentences count each time; sentences that are not
known are skipped, so other prose may stand between licence sentences; repeated rows are rows; other columns
are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Known licence sentences, normalised, by identifier.
SENTENCES = {
    "mit-notice": ["released under the mit license", "licensed under the mit license", "this project is licensed under the mit license"],
    "mit-grant": [
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software "
        "to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense "
        "and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions"
    ],
    "mit-condition": ["the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software"],
    "apache2-notice": ["licensed under the apache license version 2 0", "licensed under the apache license version 2 0 the license", "released under the apache license version 2 0"],
    "apache2-use": ["you may not use this file except in compliance with the license"],
    "apache2-obtain": ["you may obtain a copy of the license at http www apache org licenses license 2 0"],
    "gpl3-notice": [
        "this work is licensed under the gnu general public license version 3",
        "licensed under the gnu general public license version 3",
        "released under the gnu general public license version 3",
    ],
    "gpl-redistribute": ["this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation"],
    "gpl2-notice": ["licensed under the gnu general public license version 2", "this work is licensed under the gnu general public license version 2"],
    "ccbync4-notice": ["licensed under cc by nc 4 0", "this work is licensed under cc by nc 4 0", "licensed under a creative commons attribution noncommercial 4 0 international license"],
    "ccby4-notice": ["licensed under cc by 4 0", "this work is licensed under cc by 4 0", "licensed under a creative commons attribution 4 0 international license"],
    "ccbysa4-notice": ["licensed under cc by sa 4 0", "this work is licensed under cc by sa 4 0"],
    "cc0-notice": ["released under cc0 1 0", "this work is dedicated to the public domain"],
    "bsd3-notice": ["licensed under the bsd 3 clause license", "released under the bsd 3 clause license"],
    "bsd-redistribution": ["redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"],
    "reserved": ["all rights reserved"],
}

# Rules in the order in which they are tried.
RULES = [
    ("MIT", ["mit-notice", "mit-grant", "mit-condition"]),
    ("MIT", ["mit-grant", "mit-condition"]),
    ("Apache-2.0", ["apache2-notice", "apache2-use", "apache2-obtain"]),
    ("Apache-2.0", ["apache2-notice", "apache2-use"]),
    ("GPL-3.0", ["gpl-redistribute", "gpl3-notice"]),
    ("BSD-3-Clause", ["bsd3-notice", "bsd-redistribution"]),
    ("MIT", ["mit-notice"]),
    ("Apache-2.0", ["apache2-notice"]),
    ("GPL-3.0", ["gpl3-notice"]),
    ("GPL-2.0", ["gpl2-notice"]),
    ("GPL", ["gpl-redistribute"]),
    ("CC-BY-NC-4.0", ["ccbync4-notice"]),
    ("CC-BY-4.0", ["ccby4-notice"]),
    ("CC-BY-SA-4.0", ["ccbysa4-notice"]),
    ("CC0-1.0", ["cc0-notice"]),
    ("BSD-3-Clause", ["bsd3-notice"]),
    ("BSD", ["bsd-redistribution"]),
    ("Proprietary", ["reserved"]),
]

_BREAK = r"[.!?][\x20\x09-\x0D]+|\n"
#: Where line feeds do not end a sentence, blank lines do; a line of comment marks alone counts as blank.
_WRAPPED_BREAK = r"[.!?][\x20\x09-\x0D]+|\n[\x20\x09\x0D#*/;-]*(?=\n)"


def known_sentences(sentences: dict[str, list[str]] = SENTENCES) -> dict[str, str]:
    return {s: name for name, group in sentences.items() for s in group}


def _normal(s: Column) -> Column:
    return F.btrim(F.regexp_replace(s, "[^a-z0-9]+", " "))


def identifiers(text: Column, known: dict[str, str], wrapped: bool = False) -> Column:
    """Identifiers of the known sentences of a text, in its order."""
    plain = F.lower(F.coalesce(text, F.lit("")))
    if wrapped:
        lines = lambda s: F.transform(F.split(s, "\n"), _normal)
        normal = F.flatten(F.transform(F.split(plain, _WRAPPED_BREAK), lambda s: F.when(_normal(s).isin(list(known)), F.array(_normal(s))).otherwise(lines(s))))
    else:
        normal = F.transform(F.split(plain, _BREAK), _normal)
    hits = F.filter(normal, lambda s: s.isin(list(known)))
    named = F.create_map(*[F.lit(x) for pair in known.items() for x in pair])
    return F.transform(hits, lambda s: F.element_at(named, s))


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", sentences: dict[str, list[str]] = SENTENCES, rules=RULES, wrapped: bool = False) -> DataFrame:
    """Documents with a known sentence: key, n_sentences, sentence_ids, licenses (joined by |, in the order of the rules)."""
    found = docs.select(F.col(key), identifiers(F.col(text), known_sentences(sentences), wrapped).alias("ids")).filter(F.size("ids") > 0)
    found = found.withColumn("rest", F.concat(F.lit("|"), F.array_join("ids", "||"), F.lit("|"))).withColumn("licenses", F.array().cast("array<string>"))
    for name, run in rules:
        piece = F.lit("".join(f"|{x}|" for x in run))
        hit = F.when(F.contains("rest", piece), F.array(F.lit(name))).otherwise(F.array().cast("array<string>"))
        found = found.select(key, "ids", F.concat("licenses", hit).alias("licenses"), F.replace("rest", piece, F.lit("||.||")).alias("rest"))
    return found.select(
        key, F.size("ids").cast("long").alias("n_sentences"), F.array_join("ids", "|").alias("sentence_ids"), F.array_join(F.array_distinct("licenses"), "|").alias("licenses")
    )
