"""Licence scans with ordered signature rules, in Spark expressions only.

Texts are reduced to lower-case words with one space between them. A keyword prefilter decides
which texts go on, and which rules each of them meets; a rule is a regular expression with a
keyword, a label and a priority. Every match is an interval; a match that lies inside another one
of higher priority (or of equal priority and greater length) is suppressed. The labels are those
of the four base phrases and of the matches left.

Rules are the hand-written PASSAGES and, for each name of FAMILIES, the FORMS that it is used in,
its bare name included; hundreds in all.

Defined results: null, empty or wordless text: 0 words, no labels, score 0; repeated rows give
repeated results; null ids are kept; no rows: no rows. Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Base phrases and their labels.
BASE = (
    ("gnu general public license", "gpl"),
    ("apache license", "apache"),
    ("cc by", "cc-by"),
    ("mit license", "mit"),
)

# Label, keyword of the prefilter, names (as normalised words), versions in use.
FAMILIES = (
    ("gpl", "general public", "gnu general public licen[cs]e|general public licen[cs]e", "1 2 3"),
    ("gpl", "gpl", "gnu gpl|gpl", "1 2 3"),
    ("lgpl", "lesser general", "gnu lesser general public licen[cs]e|lesser general public licen[cs]e", "2 3"),
    ("lgpl", "library general", "gnu library general public licen[cs]e", "2"),
    ("lgpl", "lgpl", "gnu lgpl|lgpl", "2 3"),
    ("agpl", "affero", "gnu affero general public licen[cs]e|affero general public licen[cs]e", "1 3"),
    ("agpl", "agpl", "gnu agpl|agpl", "1 3"),
    ("gfdl", "free documentation", "gnu free documentation licen[cs]e", "1"),
    ("apache", "apache", "apache software licen[cs]e|apache licen[cs]e|apache", "1 2"),
    ("mit", "mit", "mit x11 licen[cs]e|mit expat licen[cs]e|mit licen[cs]e", ""),
    ("bsd", "bsd", "bsd licen[cs]e|bsd style licen[cs]e|bsd", "2 3 4"),
    ("isc", "isc", "isc licen[cs]e", ""),
    ("mpl", "mozilla", "mozilla public licen[cs]e", "1 2"),
    ("mpl", "mpl", "mpl", "1 2"),
    ("epl", "eclipse", "eclipse public licen[cs]e", "1 2"),
    ("cddl", "cddl", "cddl", "1"),
    ("cddl", "common development", "common development and distribution licen[cs]e", "1"),
    ("eupl", "european union public", "european union public licen[cs]e", "1"),
    ("artistic", "artistic", "perl artistic licen[cs]e|artistic licen[cs]e", "1 2"),
    ("zlib", "zlib", "zlib libpng licen[cs]e|zlib licen[cs]e", ""),
    ("boost", "boost", "boost software licen[cs]e", "1"),
    ("unlicense", "unlicense", "the unlicense|unlicense", ""),
    ("wtfpl", "wtfpl", "wtfpl", "1 2"),
    ("psf", "python software", "python software foundation licen[cs]e", "2"),
    ("ofl", "open font", "sil open font licen[cs]e|open font licen[cs]e", "1"),
    ("odbl", "open database", "open database licen[cs]e", "1"),
    ("cc0", "cc0", "cc0", "1"),
    ("cc-by", "creative commons attribution", "creative commons attribution", "1 2 3 4"),
    ("cc-by", "cc by", "cc by", "1 2 3 4"),
    ("cc-by-sa", "cc by sa", "cc by sa", "1 2 3 4"),
    ("cc-by-nc", "cc by nc", "cc by nc", "1 2 3 4"),
    ("cc-by-nd", "cc by nd", "cc by nd", "1 2 3 4"),
    ("cc-by-sa", "attribution sharealike", "creative commons attribution sharealike", "1 2 3 4"),
    ("cc-by-nc", "attribution noncommercial", "creative commons attribution noncommercial", "1 2 3 4"),
)

# Priority, pattern around a name {n} and a version {v}; a form without {v} is used once.
FORMS = (
    (90, "spdx licen[cs]e identifier {n} {v}( 0)?( only| or later)?"),
    (85, "spdx licen[cs]e identifier {n}"),
    (70, "(licen[cs]ed|released|distributed|available|provided) under( the)?( terms of the)? {n} v(ersion)? ?{v}( 0)?"),
    (60, "(licen[cs]ed|released|distributed|available|provided) under( the)?( terms of the)? {n}"),
    (50, "{n} v(ersion)? ?{v}( 0)?( or( any)? later( version)?)?"),
    (45, "{n} {v}( 0)?"),
    (30, "{n} as published by the free software foundation"),
    (25, "{n}"),
)
# Names that are common words too and say no licence alone.
NOT_ALONE = ("apache",)

# Passages that say a licence without its name: priority, label, keyword, pattern.
PASSAGES = (
    (80, "mit", "permission is hereby granted", "permission is hereby granted free of charge to any person obtaining a copy"),
    (80, "isc", "permission to use copy", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    (80, "bsd", "redistribution and use", "redistribution and use in source and binary forms with or without modification are permitted"),
    (40, "public-domain", "public domain", "(placed|released|dedicated) (in|into|to) the public domain"),
    (20, "proprietary", "all rights reserved", "all rights reserved"),
    (80, "gpl", "is free software", "(this program|this file|this library|it) is free software you can redistribute it and or modify it under the terms of the gnu general public license"),
    (80, "lgpl", "is free software", "(this program|this file|this library|it) is free software you can redistribute it and or modify it under the terms of the gnu (lesser|library) general public license"),
    (80, "agpl", "is free software", "(this program|this file|this library|it) is free software you can redistribute it and or modify it under the terms of the gnu affero general public license"),
    (75, "gpl", "received a copy of the gnu general public", "you should have received a copy of the gnu general public license along with this (program|file|software|library)"),
    (75, "lgpl", "received a copy of the gnu lesser general public", "you should have received a copy of the gnu lesser general public license along with this (program|file|software|library)"),
    (75, "agpl", "received a copy of the gnu affero general public", "you should have received a copy of the gnu affero general public license along with this (program|file|software|library)"),
    (75, "gfdl", "permission is granted to copy distribute", "permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation license"),
    (80, "apache", "you may not use this file except", "you may not use this file except in compliance with the license"),
    (65, "apache", "distributed on an as is basis", "distributed on an as is basis without warranties or conditions of any kind"),
    (75, "mit", "the above copyright notice and this permission notice", "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software"),
    (75, "bsd", "neither the name", "neither the name of .{1,80} nor the names of its contributors may be used to endorse or promote products"),
    (70, "bsd", "redistributions of source code", "redistributions of source code must retain the above copyright notice"),
    (70, "bsd", "redistributions in binary form", "redistributions in binary form must reproduce the above copyright notice"),
    (80, "mpl", "source code form is subject", "this source code form is subject to the terms of the mozilla public license"),
    (75, "epl", "accompanying materials are made available", "accompanying materials are made available under the terms of the eclipse public license"),
    (80, "zlib", "as is without any express or implied", "this software is provided as is without any express or implied warranty in no event will the authors be held liable"),
    (75, "zlib", "must not be misrepresented", "the origin of this software must not be misrepresented"),
    (80, "boost", "permission is hereby granted free of charge", "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation"),
    (80, "unlicense", "unencumbered software", "this is free and unencumbered software released into the public domain"),
    (80, "wtfpl", "you just do what", "you just do what the fuck you want to"),
    (70, "cc0", "waived all copyright", "waived all copyright and related or neighboring rights"),
    (60, "cc-by", "creativecommons org licenses by", "creativecommons org licenses by [1-4]( 0)?"),
    (60, "cc-by-sa", "creativecommons org licenses by sa", "creativecommons org licenses by sa [1-4]( 0)?"),
    (60, "cc-by-nc", "creativecommons org licenses by nc", "creativecommons org licenses by nc [1-4]( 0)?"),
    (60, "cc-by-nd", "creativecommons org licenses by nd", "creativecommons org licenses by nd [1-4]( 0)?"),
    (60, "cc0", "creativecommons org publicdomain zero", "creativecommons org publicdomain zero 1( 0)?"),
    (55, "apache", "apache org licenses", "(www )?apache org licenses (license 2 0|license 2|1 1)"),
    (55, "gpl", "gnu org licenses", "(www )?gnu org licenses (old licenses )?gpl( [23] 0)?"),
    (55, "lgpl", "gnu org licenses", "(www )?gnu org licenses (old licenses )?lgpl( [23] [01])?"),
    (55, "agpl", "gnu org licenses", "(www )?gnu org licenses agpl( 3 0)?"),
    (55, "mit", "opensource org licenses mit", "opensource org licenses mit( license)?"),
    (35, "proprietary", "confidential and proprietary", "(is|are|contains) confidential and proprietary( information)?"),
    (35, "proprietary", "unauthorized copying", "unauthorized copying of this (file|software|document)( via any medium)? is strictly prohibited"),
    (35, "public-domain", "no copyright", "(there is )?no copyright (is claimed|applies)"),
)
SCORED = 90.0
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def rules() -> list[tuple[int, str, str, str]]:
    """(priority, label, keyword, pattern), highest priority first."""
    out = list(PASSAGES)
    for label, keyword, names, versions in FAMILIES:
        for priority, form in FORMS:
            used = names if form != "{n}" else "|".join(n for n in names.split("|") if n not in NOT_ALONE)
            for v in versions.split() if "{v}" in form else [""]:
                out.append((priority, label, keyword, form.replace("{n}", f"({used})").replace("{v}", v)))
    return sorted(out, key=lambda r: (-r[0], r[1], r[3]))


def ascii_lower(text: Column) -> Column:
    """A-Z lowered; other characters stay or change into others outside ASCII."""
    upper, low = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    odd = text.contains("K") | text.contains("İ")  # the two that lower() would turn into ASCII
    return F.when(odd, F.translate(text, upper, low)).otherwise(F.lower(text))


def _places(words: Column, phrase: str) -> Column:
    want = phrase.split(" ")
    last = F.size(words) - len(want)
    here = lambda i: F.array([F.get(words, i + k) == F.lit(w) for k, w in enumerate(want)])
    return F.when(last >= 0, F.filter(F.sequence(F.lit(0), last), lambda i: F.forall(here(i), lambda x: x))).otherwise(F.array().cast("array<int>"))


def _spans(text: Column, rule: Column) -> Column:
    """The intervals of a rule's matches, in order: each match is the next place where its words stand by themselves."""
    found = F.regexp_extract_all(text, F.concat(F.lit("(?<= )("), rule["pattern"], F.lit(")(?= )")), F.lit(0))
    empty = F.expr("cast(array() as array<struct<s:int,e:int>>)")
    start = F.struct(F.lit(1).alias("at"), empty.alias("spans"))

    def step(acc, m):
        s = F.call_function("locate", F.concat(F.lit(" "), m, F.lit(" ")), text, acc["at"]) + 1
        return F.struct((s + F.length(m)).alias("at"), F.concat(acc["spans"], F.array(F.struct(s.alias("s"), (s + F.length(m)).alias("e")))).alias("spans"))

    return F.aggregate(found, start, step, lambda acc: acc["spans"])


def scan_licenses(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score for each row of (doc_id, text)."""
    table = rules()
    keywords = sorted({f" {r[2]} " for r in table} | {f" {p} " for p, _ in BASE})
    lit_rules = F.array(*[F.struct(F.lit(p).alias("priority"), F.lit(lab).alias("label"), F.lit(f" {k} ").alias("keyword"), F.lit(x).alias("pattern")) for p, lab, k, x in table])
    norm = F.trim(F.regexp_replace(ascii_lower(F.coalesce("text", F.lit(""))), SEPARATORS, " "))
    d = docs.select("doc_id", F.concat(F.lit(" "), norm, F.lit(" ")).alias("_t"))
    gate = F.lit(False)
    for k in keywords:
        gate = gate | F.col("_t").contains(k)
    d = d.withColumn("_gate", gate)
    some = F.col("_gate")
    d = d.withColumn("_words", F.when(some, F.split(F.trim("_t"), " ")))
    places = [F.when(F.col("_t").contains(f" {p} "), _places(F.col("_words"), p)).otherwise(F.array().cast("array<int>")) for p, _ in BASE]
    d = d.withColumn("_base", F.when(some, F.array(*places)))
    d = d.withColumn("_at", F.flatten("_base"))
    d = d.withColumn("_keys", F.when(some, F.filter(F.array(*map(F.lit, keywords)), lambda k: F.col("_t").contains(k))))
    met = F.filter(lit_rules, lambda r: F.array_contains(F.col("_keys"), r["keyword"]))
    every = F.flatten(F.transform(met, lambda r: F.transform(_spans(F.col("_t"), r), lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), r["priority"].alias("priority"), r["label"].alias("label")))))
    d = d.withColumn("_spans", F.when(some & (F.size("_keys") > 0), every))

    def suppressed(x):
        return F.exists(F.col("_spans"), lambda o: (o["s"] <= x["s"]) & (o["e"] >= x["e"]) & ((o["priority"] > x["priority"]) | ((o["priority"] == x["priority"]) & (o["e"] - o["s"] > x["e"] - x["s"]))))

    d = d.withColumn("_left", F.filter("_spans", lambda x: ~suppressed(x)))
    base_labels = F.array_sort(F.filter(F.array(*[F.when(F.size(F.get("_base", F.lit(i))) > 0, F.lit(lab)) for i, (_, lab) in enumerate(BASE)]), lambda x: x.isNotNull()))
    none = F.array().cast("array<string>")
    d = d.withColumn("_names", F.when(some, base_labels).otherwise(none))
    labels = F.array_sort(F.array_distinct(F.concat("_names", F.coalesce(F.transform("_left", lambda x: x["label"]), none))))
    best = F.array_max(F.transform("_left", lambda x: x["priority"])) / SCORED
    at = F.coalesce("_at", F.array().cast("array<int>"))
    return d.select(
        "doc_id",
        F.when(F.length("_t") > 2, F.length("_t") - F.length(F.replace("_t", F.lit(" "), F.lit(""))) - 1).otherwise(0).cast("long").alias("n_words"),
        F.size(at).cast("long").alias("n_base"),
        F.array_min(at).cast("long").alias("first_word"),
        F.array_max(at).cast("long").alias("last_word"),
        F.array_join("_names", ",").alias("base_labels"),
        F.array_join(labels, ",").alias("labels"),
        F.greatest(F.coalesce(best, F.lit(0.0)), F.when(F.size(at) > 0, F.lit(0.5)).otherwise(F.lit(0.0))).cast("double").alias("score"),
    )
