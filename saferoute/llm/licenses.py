"""License scan: ordered signature rules over the words of a text, in DataFrame functions only.

A rule has a gate (its first word), a regex that must match from the gate on, a label, a priority
and a weight. Texts without any keyword are passed over; in the others only words that are gates are
looked at, and only against the rules of their gate. Detections that lie within another one of the same or
a higher priority are suppressed, earlier rules first; what remains gives the method's labels and
the score. Base phrases are rules like others, but all their places count and their labels stay.

All work is done within a row, so there is no shuffle and no group that could be skewed. Regexes reach
at most ``REACH`` words, so a place is held only against those ``REACH`` words before it.
Nulls are empty texts: no words, no labels, score 0. Repeated rows give equal rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Words a rule may span.
REACH = 24
NOT_WORD = r"\x00-\x2F\x3A-\x60\x7B-\x7F"
LICENSE_WORD = f"[^{NOT_WORD}]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: Phrases of the base rules and their labels.
BASE = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}

#: Label; versions; names, as regexes over words in lower case.
FAMILIES = """
gpl; 1.0 2.0 3.0; gnu general public licen[cs]e|gnu gpl|gpl|general public licen[cs]e
lgpl; 2.0 2.1 3.0; gnu (?:lesser|library) general public licen[cs]e|gnu lgpl|lgpl|lesser general public licen[cs]e
agpl; 1.0 3.0; gnu affero general public licen[cs]e|gnu agpl|agpl|affero general public licen[cs]e
gfdl; 1.1 1.2 1.3; gnu free documentation licen[cs]e|gfdl
apache; 1.0 1.1 2.0; apache(?: software)? licen[cs]e|apache
mit; ; mit licen[cs]e|expat licen[cs]e|x11 licen[cs]e
bsd; 2 3 4; bsd licen[cs]e|new bsd licen[cs]e|simplified bsd licen[cs]e|modified bsd licen[cs]e
mpl; 1.0 1.1 2.0; mozilla public licen[cs]e|mpl
epl; 1.0 2.0; eclipse public licen[cs]e|epl
cddl; 1.0 1.1; common development and distribution licen[cs]e|cddl
cpl; 1.0; common public licen[cs]e
eupl; 1.0 1.1 1.2; european union public licen[cs]e|eupl
osl; 1.0 2.0 2.1 3.0; open software licen[cs]e
afl; 1.1 2.0 2.1 3.0; academic free licen[cs]e
artistic; 1.0 2.0; artistic licen[cs]e|perl artistic licen[cs]e
bsl; 1.0; boost software licen[cs]e
busl; 1.1; business source licen[cs]e
isc; ; isc licen[cs]e
zlib; ; zlib licen[cs]e|zlib libpng licen[cs]e
wtfpl; 2; wtfpl|do what the fuck you want to public licen[cs]e
unlicense; ; unlicense|the unlicense
psf; 2; python software foundation licen[cs]e
php; 3.0 3.01; php licen[cs]e
ruby; ; ruby licen[cs]e
zpl; 1.1 2.0 2.1; zope public licen[cs]e
w3c; ; w3c software notice
ofl; 1.0 1.1; sil open font licen[cs]e|open font licen[cs]e
odbl; 1.0; open database licen[cs]e|odbl
odc-by; 1.0; open data commons attribution licen[cs]e
pddl; 1.0; public domain dedication and licen[cs]e|pddl
ms-pl; ; microsoft public licen[cs]e|ms pl
ms-rl; ; microsoft reciprocal licen[cs]e|ms rl
ncsa; ; university of illinois ncsa open source licen[cs]e|ncsa licen[cs]e
postgresql; ; postgresql licen[cs]e
openssl; ; openssl licen[cs]e
sspl; 1.0; server side public licen[cs]e|sspl
elastic; 2.0; elastic licen[cs]e
mulan; 1.0 2.0; mulan permissive software licen[cs]e
cecill; 1.0 2.0 2.1; cecill
upl; 1.0; universal permissive licen[cs]e
vim; ; vim licen[cs]e
tex; ; latex project public licen[cs]e|lppl
openrail; ; openrail(?: m)?|open rail m
llama; 2 3 3.1; llama community licen[cs]e
cc0; 1.0; cc0|creative commons zero
cc-by; 1.0 2.0 2.5 3.0 4.0; cc by|creative commons attribution
cc-by-sa; 1.0 2.0 2.5 3.0 4.0; cc by sa|creative commons attribution share ?alike
cc-by-nd; 1.0 2.0 2.5 3.0 4.0; cc by nd|creative commons attribution no ?deriv(?:ative)?s
cc-by-nc; 1.0 2.0 2.5 3.0 4.0; cc by nc|creative commons attribution non ?commercial
cc-by-nc-sa; 1.0 2.0 2.5 3.0 4.0; cc by nc sa|creative commons attribution non ?commercial share ?alike
cc-by-nc-nd; 1.0 2.0 2.5 3.0 4.0; cc by nc nd|creative commons attribution non ?commercial no ?deriv(?:ative)?s
"""

#: Label; sentence of a licence or notice.
NOTICES = """
mit; permission is hereby granted free of charge to any person obtaining a copy
isc; permission to use copy modify and or distribute this software for any purpose
bsd; redistribution and use in source and binary forms with or without modification
gpl; you can redistribute it and or modify it under the terms of the gnu general public licen[cs]e
lgpl; you can redistribute it and or modify it under the terms of the gnu lesser general public licen[cs]e
apache-2.0; licensed under the apache licen[cs]e version 2 0
unlicense; this is free and unencumbered software released into the public domain
public-domain; released into the public domain
public-domain; dedicated to the public domain
proprietary; all rights reserved
mit; the above copyright notice and this permission notice shall be included in all copies
mit; the software is provided as is without warranty of any kind
mit; dual licensed under the mit and gpl licen[cs]es?
bsl; permission is hereby granted free of charge to any person or organization obtaining a copy
hpnd; permission to use copy modify and distribute this software and its documentation for any purpose
bsd; redistributions of source code must retain the above copyright notice
bsd; redistributions in binary form must reproduce the above copyright notice
bsd-3; neither the name of (?:[^ ]+ ){1,8}nor the names of its contributors may be used
bsd; this software is provided by the (?:copyright holders|regents|author)(?: and contributors)? as is
zlib; this software is provided as is without any express or implied warranty
zlib; altered source versions must be plainly marked as such
gpl; this program is free software(?: you can redistribute it)?
lgpl; this library is free software(?: you can redistribute it)?
gpl; you should have received a copy of the gnu general public licen[cs]e
lgpl; you should have received a copy of the gnu (?:lesser|library) general public licen[cs]e
agpl; you should have received a copy of the gnu affero general public licen[cs]e
lgpl; you can redistribute it and or modify it under the terms of the gnu library general public licen[cs]e
agpl; you can redistribute it and or modify it under the terms of the gnu affero general public licen[cs]e
gfdl; permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation licen[cs]e
apache-2.0; you may not use this file except in compliance with the licen[cs]e
apache-2.0; you may obtain a copy of the licen[cs]e at(?: https?)? www apache org
apache-2.0; unless required by applicable law or agreed to in writing software distributed under the licen[cs]e
apache-2.0; either the apache licen[cs]e version 2 0 or the mit licen[cs]e
mpl-2.0; this source code form is subject to the terms of the mozilla public licen[cs]e
mpl-1.1; the contents of this file are subject to the mozilla public licen[cs]e
cddl; the contents of this file are subject to the terms of the common development and distribution licen[cs]e
epl; this program and the accompanying materials are made available under the terms of the eclipse public licen[cs]e
ofl; this font software is licensed under the sil open font licen[cs]e
wtfpl; you just do what the fuck you want to
artistic; same terms as perl itself
cc0; waived all copyright and related or neighbou?ring rights
cc-by; licensed under a creative commons attribution(?: [0-9] [0-9])?(?: international| unported)? licen[cs]e
cc-by-sa; licensed under a creative commons attribution share ?alike
cc-by-nc; licensed under a creative commons attribution non ?commercial
cc-by-nd; licensed under a creative commons attribution no ?deriv(?:ative)?s
creative-commons; some rights reserved
odbl; any rights in individual contents of the database are licensed under
public-domain; this work is in the public domain
public-domain; placed in(?:to)? the public domain
proprietary; unauthorized copying of this file via any medium is strictly prohibited
proprietary; unauthorised copying of this file via any medium is strictly prohibited
proprietary; confidential and proprietary
proprietary; no part of this (?:publication|book|document|work) may be reproduced
proprietary; may not be (?:copied|reproduced|redistributed|republished) without (?:the )?(?:express )?(?:prior )?(?:written )?(?:permission|consent)
"""


def rules() -> list[dict]:
    """Every rule in order of precedence: bare names, versioned names, identifiers, notices, base phrases."""
    out = []

    def add(name: str, label: str, priority: int, weight: float, base: bool = False) -> None:
        gate = name.split(" ")[0].split("(")[0]
        out.append({"gate": gate, "regex": f"^{name}(?= |$)", "label": label, "priority": priority, "weight": weight, "base": base})

    for line in FAMILIES.strip().splitlines():
        label, versions, names = (x.strip() for x in line.split(";"))
        for name in names.split("|") if "(?:" not in names else _alternatives(names):
            add(name, label, 1, 0.6)
            for v in versions.split():
                number = " ".join(v.split("."))
                tail = number[:-2] + "(?: 0)?" if number.endswith(" 0") else number
                add(f"{name}(?: (?:only|international|unported))?(?: version| v)? v?{tail}", f"{label}-{v}", 2, 0.9)
        words = label.replace("-", " ")
        add(f"spdx licen[cs]e identifier {words}(?: only| or later)?", label, 3, 1.0)
        for v in versions.split():
            add(f"spdx licen[cs]e identifier {words} {' '.join(v.split('.'))}(?: only| or later)?", f"{label}-{v}", 4, 1.0)
    for line in NOTICES.strip().splitlines():
        label, sentence = (x.strip() for x in line.split(";"))
        add(sentence, label, 3, 0.8)
    for phrase, label in BASE.items():
        add(phrase, label, 1, 0.7, True)
    return out


def _alternatives(names: str) -> list[str]:
    """Splits at the bars outside parentheses."""
    parts, depth = [""], 0
    for c in names:
        depth += (c == "(") - (c == ")")
        if c == "|" and not depth:
            parts.append("")
        else:
            parts[-1] += c
    return parts


#: Substrings one of which every rule's text has, in lower case; and those that need a second look.
KEYWORDS = ("licen", "gnu", "gpl", "apache", "mpl", "epl", "cddl", "eupl", "wtfpl", "odbl", "pddl", "sspl", "cecill", "lppl", "gfdl", "cc0", "openrail", "rail", "creative", "domain", "granted", "redistribut", "reserved", "w3c", "permission", "warrant", "copyright", "contributors", "confidential", "copying", "reproduced", "republished", "altered source", "free software", "perl itself", "waived", "want to")
PAIRS = (r"cc[\x00-\x2F\x3A-\x60\x7B-\x7F]+by", r"ms[\x00-\x2F\x3A-\x60\x7B-\x7F]+[pr]l")
#: Gates that are common words too count only before one of these words.
NEXT = {"mit": ("license", "licence"), "do": ("what",), "you": ("can", "should", "may", "just"), "this": ("is", "software", "program", "library", "source", "work", "font"), "the": ("unlicense", "above", "software", "contents"),
    "no": ("part",), "any": ("rights",), "some": ("rights",), "same": ("terms",), "neither": ("the",), "may": ("not",), "either": ("the",), "unless": ("required",), "placed": ("in", "into"),
    "all": ("rights",), "new": ("bsd",), "cc": ("by",), "ms": ("pl", "rl"), "open": ("source", "software", "font", "database", "data", "rail")}


def scan(docs: DataFrame, table: list[dict] | None = None) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score and detections.

    detections: array of (start, length in words, label, priority) that survive, by start."""
    table = rules() if table is None else table
    by_gate: dict[str, list[dict]] = {}
    for k, r in enumerate(table):
        by_gate.setdefault(r["gate"], []).append({"k": k, **{x: r[x] for x in ("regex", "label", "priority", "weight", "base")}})
    plain = [g for g in by_gate if g not in NEXT]
    text = F.coalesce("text", F.lit(""))
    low = F.lower(text)
    keyed = F.lit(False)
    for word in KEYWORDS:
        keyed = keyed | low.contains(word)
    for pair in PAIRS:
        keyed = keyed | low.contains(pair[:2]) & low.rlike(pair)

    def gated(w: Column, i: Column) -> Column:
        hit = w.isin(*plain)
        for gate, after in NEXT.items():
            if gate in by_gate:
                hit = hit | (w == gate) & F.get(F.col("words"), i + 1).isin(*after)
        return F.when(hit, F.struct(i.alias("start"), w.alias("gate")))

    kind = "struct<start:int,length:int,label:string,priority:int,weight:double,base:boolean,k:int,hit:boolean>"

    def detect(h: Column) -> Column:
        """The rules of a gate, each with its own pattern, which is compiled once."""

        def one(r: dict, window: Column) -> Column:
            found = F.regexp_extract(window, r["regex"], 0)
            length = F.length(F.regexp_replace(found, "[^ ]+", "")) + 1
            values = (h["start"], length, *(F.lit(r[x]) for x in ("label", "priority", "weight", "base", "k")), found != "")
            return F.struct(*values).cast(kind)

        def by_rules(window: Column) -> Column:
            out = None
            for gate, own in by_gate.items():
                tried = F.array(*[one(r, window) for r in own])
                out = F.when(h["gate"] == gate, tried) if out is None else out.when(h["gate"] == gate, tried)
            return F.filter(out, lambda d: d["hit"])

        return F.get(F.transform(F.array(F.array_join(F.slice("words", h["start"] + 1, REACH), " ")), by_rules), 0)

    words = docs.select("doc_id", F.regexp_count(text, F.lit(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")).cast("long").alias("n_words"), F.when(keyed, F.regexp_extract_all(F.translate(text, _UPPER, _LOWER), F.lit(LICENSE_WORD), 0)).alias("words"))
    hits = words.withColumn("hits", F.filter(F.transform("words", gated), lambda h: h.isNotNull()))
    places = hits.withColumn("places", F.transform("hits", detect)).drop("hits", "words")
    base = F.filter(F.flatten("places"), lambda d: d["base"])
    method = F.transform("places", lambda p: F.filter(p, lambda d: ~d["base"]))
    found = places.withColumn("base", base).withColumn("method", method).drop("places")

    def within(d: Column, e: Column) -> Column:
        inside = (e["start"] <= d["start"]) & (e["start"] + e["length"] >= d["start"] + d["length"])
        larger = (e["length"] > d["length"]) | (e["priority"] > d["priority"]) | (e["k"] < d["k"])
        return inside & larger & (e["priority"] >= d["priority"])

    def standing(p: Column, i: Column) -> Column:
        near = F.flatten(F.slice("method", F.greatest(i + 2 - REACH, F.lit(1)), F.least(i + 1, F.lit(REACH))))
        return F.filter(p, lambda d: ~F.exists(near, lambda e: within(d, e)))

    found = found.withColumn("kept", F.flatten(F.transform("method", standing)))
    join = lambda labels: F.coalesce(F.array_join(F.array_sort(F.array_distinct(labels)), ","), F.lit(""))
    base_labels = F.transform("base", lambda d: d["label"])
    return found.select(
        "doc_id",
        "n_words",
        F.greatest(F.coalesce(F.size("base"), F.lit(0)), F.lit(0)).cast("long").alias("n_base"),
        F.array_min(F.transform("base", lambda d: d["start"])).cast("long").alias("first_word"),
        F.array_max(F.transform("base", lambda d: d["start"])).cast("long").alias("last_word"),
        join(base_labels).alias("base_labels"),
        join(F.concat(base_labels, F.transform("kept", lambda d: d["label"]))).alias("labels"),
        F.coalesce(F.greatest(F.array_max(F.transform("kept", lambda d: d["weight"])), F.array_max(F.transform("base", lambda d: d["weight"]))), F.lit(0.0)).alias("score"),
        F.transform("kept", lambda d: F.struct(d["start"], d["length"], d["label"], d["priority"])).alias("detections"),
    )


def op1_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(common.table(spark, sf_dir, "documents")).drop("detections")
