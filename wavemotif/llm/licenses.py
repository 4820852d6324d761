"""License scans by ordered signature rules.

Texts become words (A-Z lower-cased; a word is a run of letters, digits and non-ASCII characters) joined by single spaces.
Rules are regular expressions over that form, each with a keyword, a literal that every match of it contains (so that the
expression is tried only where the keyword occurs), a priority, a confidence and a label; most are made from templates over a table of licenses and versions. All occurrences
of all rules are intervals; one that lies inside an interval of a rule with a higher priority (of the same priority: a longer
one, or the same one of a smaller label) is suppressed, so "gnu lesser general public license version 3" is one detection and not
three. Base phrases are counted by position and their labels always stay.

A long text is searched in overlapping parts of PART characters, so the work grows with its length and not with the square of its detections.
DataFrame functions only; each keyword is looked for once, and texts without any keyword of the rules never reach them. Defined cases: null text is empty and has no
words, labels "" and score 0; repeated rows give repeated rows; whole texts are scanned.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wavemotif.llm.common import documents

# fixed values: base phrases and labels
PHRASES = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))
#: Characters of a text that are searched together; what is compared grows with its square and the text's length.
PART = 1024
NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"

#: Label, keyword, name as a pattern, versions.
NAMED = (
    ("apache", "apache", r"apache(?: software)?(?: licen[cs]e)?", ("1.0", "1.1", "2.0")),
    ("gpl", "general public", r"(?:gnu )?general public licen[cs]e", ("1", "2", "3")),
    ("gpl", "gpl", r"(?:gnu )?gpl", ("1", "2", "3")),
    ("lgpl", "general public", r"(?:gnu )?(?:lesser|library) general public licen[cs]e", ("2", "2.1", "3")),
    ("lgpl", "lgpl", r"(?:gnu )?lgpl", ("2", "2.1", "3")),
    ("agpl", "affero", r"(?:gnu )?affero general public licen[cs]e", ("1", "3")),
    ("agpl", "agpl", r"(?:gnu )?agpl", ("1", "3")),
    ("gfdl", "documentation licen", r"(?:gnu )?free documentation licen[cs]e", ("1.1", "1.2", "1.3")),
    ("mpl", "mozilla public", r"mozilla public licen[cs]e", ("1.0", "1.1", "2.0")),
    ("epl", "eclipse public", r"eclipse public licen[cs]e", ("1.0", "2.0")),
    ("cddl", "distribution licen", r"common development and distribution licen[cs]e", ("1.0", "1.1")),
    ("cpl", "common public", r"common public licen[cs]e", ("1.0",)),
    ("eupl", "european union public", r"european union public licen[cs]e", ("1.0", "1.1", "1.2")),
    ("bsl", "boost software", r"boost software licen[cs]e", ("1.0",)),
    ("artistic", "artistic licen", r"artistic licen[cs]e", ("1.0", "2.0")),
    ("ofl", "open font", r"(?:sil )?open font licen[cs]e", ("1.0", "1.1")),
    ("afl", "academic free", r"academic free licen[cs]e", ("1.1", "2.0", "2.1", "3.0")),
    ("osl", "open software", r"open software licen[cs]e", ("1.0", "2.0", "2.1", "3.0")),
    ("cecill", "cecill", r"cecill(?: free software)?(?: licen[cs]e)?", ("1.0", "2.0", "2.1")),
    ("odbl", "database licen", r"open (?:data commons )?(?:open )?database licen[cs]e", ("1.0",)),
    ("zpl", "zope public", r"zope public licen[cs]e", ("1.1", "2.0", "2.1")),
    ("lppl", "latex project", r"latex project public licen[cs]e", ("1.0", "1.2", "1.3")),
    ("psf", "python software", r"python software foundation licen[cs]e", ("2",)),
    ("ms-pl", "microsoft public", r"microsoft public licen[cs]e", ()),
    ("mit", "mit licen", r"mit licen[cs]e", ()),
    ("isc", "isc licen", r"isc licen[cs]e", ()),
    ("zlib", "zlib", r"zlib(?: libpng)? licen[cs]e", ()),
    ("unlicense", "unlicense", r"(?:the )?unlicense", ()),
    ("wtfpl", "wtfpl", r"wtfpl", ()),
    ("ncsa", "ncsa", r"(?:university of illinois )?ncsa(?: open source)? licen[cs]e", ()),
    ("postgresql", "postgresql licen", r"postgresql licen[cs]e", ()),
    ("openssl", "openssl licen", r"openssl licen[cs]e", ()),
    ("w3c", "w3c", r"w3c(?: software)?(?: notice and)? licen[cs]e", ()),
    ("upl", "universal permissive", r"universal permissive licen[cs]e", ()),
    ("bsd", "bsd", r"bsd(?: style)?(?: licen[cs]e)?", ("2 clause", "3 clause", "4 clause")),
)
CC = (("cc-by", "", ""), ("cc-by-sa", "sa", "share ?alike"), ("cc-by-nd", "nd", "no ?deriv(?:ative)?s?"), ("cc-by-nc", "nc", "non ?commercial"), ("cc-by-nc-sa", "nc sa", "non ?commercial share ?alike"), ("cc-by-nc-nd", "nc nd", "non ?commercial no ?deriv(?:ative)?s?"))
CC_VERSIONS = ("1.0", "2.0", "2.5", "3.0", "4.0")
#: Label, keyword, pattern, priority, confidence.
NOTICES = (
    ("mit", "permission", r"permission is hereby granted free of charge to any person obtaining a copy of this software", 7, 0.95),
    ("isc", "permission", r"permission to use copy modify and or distribute this software for any purpose with or without fee", 7, 0.95),
    ("bsd", "redistribut", r"redistribution and use in source and binary forms with or without modification are permitted", 7, 0.95),
    ("bsd-3-clause", "endorse", r"may (?:not )?be used to endorse or promote products derived from this software", 7, 0.9),
    ("gpl", "free software", r"this program is free software you can redistribute it", 7, 0.9),
    ("apache-2.0", "apache", r"apache org licenses license 2 0", 7, 0.95),
    ("apache-2.0", "applicable law", r"unless required by applicable law or agreed to in writing software distributed under the license", 6, 0.9),
    ("boost", "permission", r"permission is hereby granted free of charge to any person or organization obtaining a copy", 7, 0.95),
    ("zlib", "warrant", r"this software is provided as is without any express or implied warranty in no event will the authors", 6, 0.8),
    ("public-domain", "public domain", r"(?:released|dedicated|placed) (?:in)?to the public domain", 5, 0.9),
    ("public-domain", "public domain", r"in the public domain", 3, 0.6),
    ("cc0", "cc0", r"cc0(?: 1 0)?(?: universal)?", 6, 0.9),
    ("cc0", "creative commons zero", r"creative commons zero(?: 1 0)?(?: universal)?", 6, 0.9),
    ("proprietary", "confidential", r"proprietary and confidential", 5, 0.8),
    ("proprietary", "prohibited", r"unauthori[sz]ed (?:copying|use|distribution)[a-z ]{0,60} prohibited", 5, 0.8),
    ("no-warranty", "warrant", r"without warranty of any kind", 1, 0.3),
    ("copyright", "copyright", r"copyright(?: c)? [12][0-9]{3}", 1, 0.4),
    ("license-file", "licen", r"see (?:the )?licen[cs]e file", 2, 0.4),
)

Rule = tuple[str, str, str, int, float]


def rules() -> list[Rule]:
    """(label, keyword, pattern, priority, confidence), in order. Patterns stand between spaces."""
    out: list[Rule] = []
    for label, word, name, versions in NAMED:
        out += [(label, word, rf"(?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?{name}", 5, 0.85), (label, word, name, 2, 0.5)]
        out.append((label, "spdx", rf"spdx license identifier {label.replace('-', ' ')}", 7, 0.95))
        for v in versions:
            number, tag = v.replace(".", " "), f"{label}-{v.replace(' ', '-')}"
            exact = number + (r"(?: 0)?" if "." not in v and "clause" not in v else "")
            out.append((tag, "spdx", rf"spdx license identifier {label} {exact}(?: only| or later)?", 9, 1.0))
            out.append((tag, word, rf"(?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?{name} (?:version |v )?v?{exact}", 8, 0.95))
            out.append((tag, word, rf"{name} (?:version |v )?v?{exact}(?: or (?:any )?later(?: version)?)?", 6, 0.9))
            if v.endswith(".0"):
                out.append((tag, word, rf"{name} (?:version |v )v?{number.split()[0]}", 4, 0.7))
    for label, short, long in CC:
        code = f"cc by {short}".strip()
        words = f"creative commons attribution {long}".strip()
        out += [(label, " cc ", code, 3, 0.7), (label, "creative commons", rf"{words}(?: licen[cs]e)?", 4, 0.8), (label, "creativecommons", rf"creativecommons org licenses {code[3:]}", 5, 0.9)]
        for v in CC_VERSIONS:
            number = v.replace(".", " ")
            out += [(f"{label}-{v}", " cc ", f"{code} {number}", 6, 0.95), (f"{label}-{v}", "creative commons", rf"{words}(?: licen[cs]e)? (?:version |v )?{number}", 7, 0.95), (f"{label}-{v}", "creativecommons", rf"creativecommons org licenses {code[3:]} {number}", 8, 1.0)]
    return out + [(a, b, c, d, e) for a, b, c, d, e in NOTICES]


def _array(given: list[Rule]) -> Column:
    """Keywords, each with its rules."""
    by: dict[str, list[Rule]] = {}
    for rule in given:
        by.setdefault(rule[1], []).append(rule)
    one = lambda a, p, p_, c: F.struct(F.lit(a).alias("label"), F.lit(f"(?<= ){p}(?= )").alias("pattern"), F.lit(p_).alias("priority"), F.lit(c).alias("confidence"))
    return F.array(*[F.struct(F.lit(k).alias("word"), F.array(*[one(a, p, p_, c) for a, _, p, p_, c in rs]).alias("rules")) for k, rs in by.items()])


def _occurrences(text: Column, offset: Column, rule: Column) -> Column:
    """Intervals of all matches of a rule in a part of a text that starts at offset, from the pieces between them."""
    found = F.regexp_extract_all(text, rule["pattern"], F.lit(0))
    pieces = F.split(text, rule["pattern"], -1)
    empty = F.array().cast("array<struct<start:int,end:int>>")

    def step(acc: Column, pair: Column) -> Column:
        start = acc["at"] + F.length(pair["piece"])
        end = start + F.length(pair["match"])
        return F.struct(F.concat(acc["spans"], F.array(F.struct(start.alias("start"), end.alias("end")))).alias("spans"), end.alias("at"))

    pairs = F.zip_with(F.slice(pieces, 1, F.size(found)), found, lambda p, m: F.struct(p.alias("piece"), m.alias("match")))
    spans = F.aggregate(pairs, F.struct(empty.alias("spans"), offset.cast("int").alias("at")), step, lambda acc: acc["spans"])
    return F.transform(spans, lambda s: F.struct(rule["priority"].alias("priority"), s["start"].alias("start"), s["end"].alias("end"), rule["label"].alias("label"), rule["confidence"].alias("confidence")))


def _inside(a: Column, b: Column) -> Column:
    """Whether detection a gives way to b."""
    la, lb = a["end"] - a["start"], b["end"] - b["start"]
    higher = (b["priority"] > a["priority"]) | ((b["priority"] == a["priority"]) & ((lb > la) | ((lb == la) & (b["label"] < a["label"]))))
    return (b["start"] <= a["start"]) & (b["end"] >= a["end"]) & higher


def _bind(value: Column, then) -> Column:
    """then(value), with value worked out once."""
    return F.element_at(F.transform(F.array(value), then), 1)


def _places(words: Column, phrase: str) -> Column:
    """Word numbers at which a phrase starts, from an array of words that is worked out once."""
    want = phrase.split(" ")

    def starts(ws: Column) -> Column:
        def here(w: Column, i: Column) -> Column:
            hit = w == want[0]
            for j in range(1, len(want)):
                hit = hit & (F.coalesce(F.get(ws, i + j), F.lit("")) == want[j])
            return F.when(hit, i)

        return F.array_compact(F.transform(ws, here))

    return _bind(words, starts)


def longest(given: list[Rule]) -> int:
    """No match is longer: a pattern's own length bounds what it matches, but for a repeat in braces, which adds its limit."""
    return max(len(p) + sum(int(n) for n in re.findall(r",(\d+)\}", p)) for _, _, p, _, _ in given)


def licenses(docs: DataFrame, given: list[Rule] | None = None) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score a row of docs."""
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    rows = documents(docs).withColumn("text", F.trim(F.regexp_replace(F.translate(F.coalesce("text", F.lit("")), upper, lower), NOT_WORD, " ")))
    rows = rows.select("doc_id", "text", F.concat(F.lit(" "), "text", F.lit(" ")).alias("padded"))
    n_words = F.when(F.col("text") == "", 0).otherwise(F.length("text") - F.length(F.replace(F.col("text"), F.lit(" "), F.lit(""))) + 1)

    def places(phrase: str) -> Column:
        return F.when(F.col("padded").contains(f" {phrase} "), _places(F.split("text", " "), phrase)).otherwise(F.array().cast("array<int>"))

    given = given or rules()
    gate = F.lit(False)
    for word in dict.fromkeys(rule[1] for rule in given):
        gate = gate | F.col("padded").contains(word)
    # parts overlap by a match's greatest length to both sides; a part keeps the detections that start in its own stretch
    margin = longest(given) + 2
    table = _array(given)

    def standing(part: Column, at: Column) -> Column:
        tried = F.flatten(F.transform(F.filter(table, lambda r: F.contains(part, r["word"])), lambda r: r["rules"]))
        from_ = F.greatest(at - margin, F.lit(0))
        kept = lambda found: F.filter(found, lambda a: (a["start"] >= at) & (a["start"] < at + PART) & ~F.exists(found, lambda b: _inside(a, b)))
        return _bind(F.flatten(F.transform(tried, lambda r: _occurrences(part, from_, r))), kept)

    def stretch(at: Column) -> Column:
        from_ = F.greatest(at - margin, F.lit(0))
        return _bind(F.substring(F.col("padded"), from_ + 1, at + (PART + margin) - from_), lambda part: standing(part, at))

    starts = F.sequence(F.lit(0), F.greatest(F.length("padded") - 1, F.lit(0)), F.lit(PART))
    none = F.array().cast("array<struct<priority:int,start:int,end:int,label:string,confidence:double>>")
    rows = rows.select("doc_id", n_words.cast("long").alias("n_words"), *[places(p).alias(f"at{i}") for i, (p, _) in enumerate(PHRASES)], F.when(gate, F.flatten(F.transform(starts, stretch))).otherwise(none).alias("standing"))
    every = F.concat(*[F.col(f"at{i}") for i in range(len(PHRASES))])
    base = F.array_sort(F.array_compact(F.array(*[F.when(F.size(f"at{i}") > 0, F.lit(label)) for i, (_, label) in enumerate(PHRASES)])))
    rows = rows.select("doc_id", "n_words", every.alias("every"), base.alias("base"), "standing")
    labels = F.array_sort(F.array_distinct(F.concat("base", F.transform("standing", lambda d: d["label"]))))
    score = F.greatest(F.coalesce(F.array_max(F.transform("standing", lambda d: d["confidence"])), F.lit(0.0)), F.when(F.size("base") > 0, 0.9).otherwise(0.0))
    return rows.select("doc_id", "n_words", F.size("every").cast("long").alias("n_base"), F.array_min("every").cast("long").alias("first_word"), F.array_max("every").cast("long").alias("last_word"), F.concat_ws(",", "base").alias("base_labels"), F.concat_ws(",", labels).alias("labels"), score.alias("score"))
