"""License scan by ordered signature rules, in DataFrame functions only.

Every rule is a regular expression with a label, a priority and a keyword without blanks that each of its matches
holds. The gate is derived from the rules: a text without anything a rule needs is passed over; of the others a rule
runs only where its keyword occurs. A detection that lies inside another one of a
better priority, or inside a longer one of the same priority, is suppressed. The four base phrases are matched word by
word on their own and stay whatever the rules say.

Nulls and edge cases: a null text is an empty one: no words, no labels, score 0; repeated rows give a row each; texts
of any length are read whole; extra columns pass through, and one named like a result column is replaced by it.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import free_names, lower_ascii

WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

#: Base phrases and their labels.
BASE = (("gnu general public license", "gpl"), ("apache license", "apache"), ("cc by", "cc-by"), ("mit license", "mit"))

_VERSION = r"(?:,?\s*(?:version|v\.?)?\s*{v})"
_UNDER = r"(?:licensed|released|distributed|available)\s+under"
_TAIL = r"(?:\s+(?:only|or\s+(?:any\s+)?later(?:\s+version)?))?"

#: label, keyword (in every match of every name), names (regular expressions), versions
FAMILIES = (
    ("gpl", "gnu", (r"gnu\s+general\s+public\s+licen[cs]e",), ("1", "2", "3")),
    ("lgpl", "gnu", (r"gnu\s+(?:lesser|library)\s+general\s+public\s+licen[cs]e",), ("2", "2\\.1", "3")),
    ("agpl", "affero", (r"gnu\s+affero\s+general\s+public\s+licen[cs]e", r"affero\s+general\s+public\s+licen[cs]e"), ("1", "3")),
    ("gfdl", "documentation", (r"gnu\s+free\s+documentation\s+licen[cs]e",), ("1\\.1", "1\\.2", "1\\.3")),
    ("apache", "apache", (r"apache\s+(?:software\s+)?licen[cs]e",), ("1\\.0", "1\\.1", "2\\.0")),
    ("mpl", "mozilla", (r"mozilla\s+public\s+licen[cs]e",), ("1\\.0", "1\\.1", "2\\.0")),
    ("epl", "eclipse", (r"eclipse\s+public\s+licen[cs]e",), ("1\\.0", "2\\.0")),
    ("cddl", "development", (r"common\s+development\s+and\s+distribution\s+licen[cs]e",), ("1\\.0", "1\\.1")),
    ("cpl", "common", (r"common\s+public\s+licen[cs]e",), ("1\\.0",)),
    ("eupl", "european", (r"european\s+union\s+public\s+licen[cs]e",), ("1\\.0", "1\\.1", "1\\.2")),
    ("bsl", "boost", (r"boost\s+software\s+licen[cs]e",), ("1\\.0",)),
    ("artistic", "artistic", (r"artistic\s+licen[cs]e",), ("1\\.0", "2\\.0")),
    ("osl", "software", (r"open\s+software\s+licen[cs]e",), ("1\\.0", "2\\.1", "3\\.0")),
    ("afl", "academic", (r"academic\s+free\s+licen[cs]e",), ("2\\.1", "3\\.0")),
    ("ofl", "font", (r"(?:sil\s+)?open\s+font\s+licen[cs]e",), ("1\\.0", "1\\.1")),
    ("odbl", "database", (r"open\s+database\s+licen[cs]e",), ("1\\.0",)),
    ("python", "python", (r"python\s+software\s+foundation\s+licen[cs]e",), ("2",)),
    ("php", "php", (r"php\s+licen[cs]e",), ("3\\.0", "3\\.01")),
    ("zope", "zope", (r"zope\s+public\s+licen[cs]e",), ("2\\.0", "2\\.1")),
    ("mit", "mit", (r"(?:the\s+)?mit\s+licen[cs]e", r"mit/x11\s+licen[cs]e"), ()),
    ("mit", "expat", (r"expat\s+licen[cs]e",), ()),
    ("bsd-2-clause", "bsd", (r"(?:2|two)[\s\-]clause\s+bsd\s+licen[cs]e", r"simplified\s+bsd\s+licen[cs]e", r"bsd[\s\-]2[\s\-]clause"), ()),
    ("bsd-3-clause", "bsd", (r"(?:3|three)[\s\-]clause\s+bsd\s+licen[cs]e", r"(?:new|modified|revised)\s+bsd\s+licen[cs]e", r"bsd[\s\-]3[\s\-]clause"), ()),
    ("bsd-4-clause", "bsd", (r"(?:4|four)[\s\-]clause\s+bsd\s+licen[cs]e", r"original\s+bsd\s+licen[cs]e"), ()),
    ("bsd", "bsd", (r"bsd[\s\-](?:style\s+)?licen[cs]e",), ()),
    ("isc", "isc", (r"\bisc\s+licen[cs]e",), ()),
    ("zlib", "zlib", (r"zlib(?:/libpng)?\s+licen[cs]e",), ()),
    ("unlicense", "unlicense", (r"\bunlicense\b",), ()),
    ("wtfpl", "wtfpl", (r"\bwtfpl\b",), ()),
    ("public-domain", "domain", (r"(?:released|dedicated|placed)\s+(?:in|into|to)\s+the\s+public\s+domain",), ()),
    ("proprietary", "reserved", (r"all\s+rights\s+reserved",), ()),
    ("proprietary", "proprietary", (r"proprietary\s+and\s+confidential", r"proprietary\s+licen[cs]e"), ()),
    ("ms-pl", "microsoft", (r"microsoft\s+public\s+licen[cs]e",), ()),
    ("ms-rl", "microsoft", (r"microsoft\s+reciprocal\s+licen[cs]e",), ()),
    ("cc0", "cc0", (r"\bcc0\b(?:\s*1\.0)?", ), ()),
    ("cc0", "commons", (r"creative\s+commons\s+zero",), ()),
    ("beerware", "beer", (r"beer[\s\-]?ware\s+licen[cs]e",), ()),
    ("postgresql", "postgresql", (r"postgresql\s+licen[cs]e",), ()),
    ("openssl", "openssl", (r"openssl\s+licen[cs]e",), ()),
    ("vim", "vim", (r"vim\s+licen[cs]e",), ()),
    ("w3c", "w3c", (r"w3c\s+(?:software\s+)?(?:notice\s+and\s+)?licen[cs]e",), ()),
)

#: Creative Commons: suffix of the short name, words of the long one.
COMMONS = (
    ("by", r"attribution"),
    ("by-sa", r"attribution[\s\-]+share[\s\-]?alike"),
    ("by-nd", r"attribution[\s\-]+no[\s\-]?deriv(?:s|atives)"),
    ("by-nc", r"attribution[\s\-]+non[\s\-]?commercial"),
    ("by-nc-sa", r"attribution[\s\-]+non[\s\-]?commercial[\s\-]+share[\s\-]?alike"),
    ("by-nc-nd", r"attribution[\s\-]+non[\s\-]?commercial[\s\-]+no[\s\-]?deriv(?:s|atives)"),
)
COMMONS_VERSIONS = ("1\\.0", "2\\.0", "2\\.5", "3\\.0", "4\\.0")


#: Signatures of notices and licence bodies, written by hand: label, keyword (in every match), the words in their order.
#: Between words there may be blanks, line ends and the marks of comments.
SIGNATURES = (
    ("mit", "granted", "permission is hereby granted, free of charge, to any person obtaining a copy"),
    ("mit", "opensource.org", "opensource.org/licenses/mit"),
    ("mit-0", "attribution", "mit no attribution"),
    ("x11", "contained", "except as contained in this notice, the name"),
    ("bsd", "redistribution", "redistribution and use in source and binary forms, with or without modification"),
    ("bsd", "opensource.org", "opensource.org/licenses/bsd-license"),
    ("bsd-3-clause", "endorse", "may be used to endorse or promote products derived from this software"),
    ("bsd-3-clause", "opensource.org", "opensource.org/licenses/bsd-3-clause"),
    ("bsd-2-clause", "opensource.org", "opensource.org/licenses/bsd-2-clause"),
    ("bsd-4-clause", "advertising", "all advertising materials mentioning features or use of this software"),
    ("isc", "distribute", "permission to use, copy, modify, and/or distribute this software for any purpose"),
    ("postgresql", "documentation", "permission to use, copy, modify, and distribute this software and its documentation for any purpose, without fee"),
    ("hpnd", "permission", "provided that the above copyright notice appears in all copies and that both that copyright notice and this permission notice appear"),
    ("zlib", "misrepresented", "the origin of this software must not be misrepresented"),
    ("libpng", "misrepresented", "the origin of this source code must not be misrepresented"),
    ("apache-2", "compliance", "you may not use this file except in compliance with the license"),
    ("apache-2", "apache.org", "apache.org/licenses/license-2.0"),
    ("apache-1.1", "apache", "this product includes software developed by the apache software foundation"),
    ("gpl", "redistribute", "this program is free software: you can redistribute it and/or modify"),
    ("gpl", "redistribute", "this program is free software; you can redistribute it and/or modify"),
    ("gpl", "gnu.org", "gnu.org/licenses/gpl"),
    ("gpl", "copyleft", "gnu.org/copyleft/gpl"),
    ("gpl", "convey", "you may convey verbatim copies of the program's source code as you receive it"),
    ("lgpl", "library", "this library is free software; you can redistribute it and/or modify"),
    ("lgpl", "library", "this library is free software: you can redistribute it and/or modify"),
    ("lgpl", "gnu.org", "gnu.org/licenses/lgpl"),
    ("agpl", "gnu.org", "gnu.org/licenses/agpl"),
    ("agpl", "interacting", "all users interacting with it remotely through a computer network"),
    ("gfdl", "gnu.org", "gnu.org/licenses/fdl"),
    ("gfdl", "invariant", "with no invariant sections, no front-cover texts, and no back-cover texts"),
    ("mpl-2", "subject", "this source code form is subject to the terms of the mozilla public license"),
    ("mpl-2", "mozilla.org", "mozilla.org/mpl/2.0"),
    ("mpl-1.1", "mozilla.org", "mozilla.org/mpl/mpl-1.1"),
    ("epl-2", "accompanying", "this program and the accompanying materials are made available under the terms of the eclipse public license 2.0"),
    ("epl-2", "eclipse.org", "eclipse.org/legal/epl-2.0"),
    ("epl-1", "eclipse.org", "eclipse.org/legal/epl-v10"),
    ("cddl", "cddl", "subject to the terms of the cddl"),
    ("bsl-1", "boost.org", "boost.org/license_1_0.txt"),
    ("bsl-1", "organization", "permission is hereby granted, free of charge, to any person or organization obtaining a copy"),
    ("unlicense", "unencumbered", "this is free and unencumbered software released into the public domain"),
    ("unlicense", "unlicense.org", "unlicense.org"),
    ("public-domain", "dedicate", "we dedicate this work to the public domain"),
    ("cc0", "creativecommons.org", "creativecommons.org/publicdomain/zero"),
    ("cc0", "waived", "has waived all copyright and related or neighboring rights"),
    ("cc-by", "creativecommons.org", "creativecommons.org/licenses/by/"),
    ("cc-by-sa", "creativecommons.org", "creativecommons.org/licenses/by-sa/"),
    ("cc-by-nc", "creativecommons.org", "creativecommons.org/licenses/by-nc/"),
    ("cc-by-nd", "creativecommons.org", "creativecommons.org/licenses/by-nd/"),
    ("cc-by-nc-sa", "creativecommons.org", "creativecommons.org/licenses/by-nc-sa/"),
    ("cc-by-nc-nd", "creativecommons.org", "creativecommons.org/licenses/by-nc-nd/"),
    ("openssl", "toolkit", "for use in the openssl toolkit"),
    ("beerware", "retain", "as long as you retain this notice you can do whatever you want with this stuff"),
    ("json", "evil", "the software shall be used for good, not evil"),
    ("ofl", "font", "reserved font name"),
    ("ofl", "scripts.sil.org", "scripts.sil.org/ofl"),
    ("python", "psf", "psf is making python available to licensee on an \"as is\" basis"),
    ("artistic", "artistic", "under the terms of the artistic license"),
    ("artistic-2", "opensource.org", "opensource.org/licenses/artistic-license-2.0"),
    ("ncsa", "illinois", "university of illinois/ncsa open source license"),
    ("upl", "universal", "universal permissive license"),
    ("blueoak", "oak", "blue oak model license"),
    ("sspl", "server", "server side public license"),
    ("busl", "business", "business source license"),
    ("commons-clause", "commons", "commons clause license condition"),
    ("elastic", "elastic", "elastic license 2.0"),
    ("polyform", "polyform", "polyform noncommercial license"),
    ("openrail", "openrail", "openrail-m"),
    ("odc-by", "attribution", "open data commons attribution license"),
    ("pddl", "dedication", "public domain dedication and license"),
    ("odbl", "opendatacommons.org", "opendatacommons.org/licenses/odbl"),
    ("ogl", "government", "open government licence"),
    ("etalab", "ouverte", "licence ouverte"),
    ("cern-ohl", "cern", "cern open hardware licence"),
    ("mulan", "mulan", "mulan permissive software license"),
    ("eupl", "eupl", "licensed under the eupl"),
    ("cecill", "cecill", "governed by the cecill license"),
    ("wtfpl", "wtfpl", "wtfpl.net"),
    ("proprietary", "prohibited", "unauthorized copying of this file, via any medium is strictly prohibited"),
    ("proprietary", "confidential", "this file contains confidential and proprietary information"),
    ("proprietary", "reproduced", "no part of this publication may be reproduced"),
)


def _signature(words: str) -> str:
    parts = [re.escape(w).replace("/", r"\/").replace(r"\ ", " ") for w in words.split(" ")]
    return r"[\s*#/;]+".join(parts)


def rules() -> list[tuple[int, str, str, str]]:
    """(priority, label, keyword, regular expression), best priority (smallest number) first.

    Order of the forms: licence identifiers, names with a version, written signatures of notices and bodies, Creative
    Commons long and short names, bare names.
    """
    out: list[tuple[int, str, str, str]] = []
    spdx = {label for label, _, _, _ in FAMILIES if label not in ("proprietary", "public-domain")}
    for label in sorted(spdx):
        out.append((1, label, "spdx", rf"spdx-license-identifier:\s*{label}(?:-[0-9.]+)?(?:-only|-or-later|\+)?\b"))
    for suffix, _ in COMMONS:
        out.append((1, f"cc-{suffix}", "spdx", rf"spdx-license-identifier:\s*cc-{suffix}(?:-[0-9.]+)?(?![\-a-z])"))
    for label, keyword, names, versions in FAMILIES:
        for name in names:
            for v in versions:
                out.append((2, f"{label}-{v.replace(chr(92), '').removesuffix('.0')}", keyword, name + _VERSION.format(v=v) + r"(?![\d])" + _TAIL))
    for suffix, words in COMMONS:
        short = suffix.replace("-", r"[\s\-]")
        for v in COMMONS_VERSIONS:
            plain = v.replace("\\", "").removesuffix(".0")
            out.append((2, f"cc-{suffix}-{plain}", "cc", rf"\bcc[\s\-]{short}(?![\s\-](?:sa|nd|nc)\b)\s*{v}\b"))
            out.append((2, f"cc-{suffix}-{plain}", "commons", rf"creative\s+commons\s+{words}(?:\s+\w+)?{_VERSION.format(v=v)}"))
            out.append((2, f"cc-{suffix}-{plain}", "creativecommons.org", rf"creativecommons\.org/licenses/{suffix}/{v}"))
        out.append((3, f"cc-{suffix}", "cc", rf"\bcc[\s\-]{short}(?![\s\-](?:sa|nd|nc)\b)"))
        out.append((3, f"cc-{suffix}", "commons", rf"creative\s+commons\s+{words}"))
    for label, keyword, words in SIGNATURES:
        out.append((2, label, keyword, _signature(words)))
    formed: set[str] = set()
    for label, keyword, names, _ in FAMILIES:
        for name in names:
            out.append((4, label, keyword, name))
        if label in formed:
            continue
        formed.add(label)
        for form in (_UNDER + r"\s+(?:the\s+)?(?:terms\s+of\s+)?(?:the\s+)?{n}", r"\blicen[cs]e\s*[:=]\s*{n}"):
            short = label.replace("-", r"[\s\-]")
            out.append((5, label, label.split("-")[0], form.format(n=short + r"\b")))
    return out


#: Pieces that many rules share: the text gate looks for these first, and for a rule's own keyword where none is in it.
SHARED = ("licen", "permission", "software", "copyright", "creativecommons.org", "gnu.org")


def _needs(keyword: str, rule: str) -> str:
    """What a text must hold for the rule to match: a piece that many rules share, the keyword, or a form of the rule."""
    if rule.startswith(_UNDER):
        return _UNDER
    if "licen[cs]e" in rule:
        return "licen"
    if rule.startswith(r"\bcc[\s\-]by"):
        return r"cc[\s\-]by"
    # only a rule without alternatives holds a piece for certain where it is spelled out
    plain = rule.replace("\\.", ".").replace("\\-", "-")
    spelled = [x for x in SHARED if x in plain] if "|" not in rule and "?" not in rule else []
    return spelled[0] if spelled else keyword


_NEEDS = sorted({_needs(keyword, rule) for _, _, keyword, rule in rules()})
_FORMS = [x for x in _NEEDS if re.escape(x).replace("\\", "") != x]
_PIECES = [x for x in _NEEDS if x not in _FORMS]
#: The same test as one expression, for a look at single texts.
_GATE = "|".join([*_FORMS, *map(re.escape, _PIECES)])


def gate(text):
    """Whether any rule can match: plain searches, which cost far less than one expression of many branches."""
    found = F.contains(text, F.lit(_PIECES[0]))
    for piece in _PIECES[1:]:
        found = found | F.contains(text, F.lit(piece))
    return found | text.rlike("|".join(_FORMS))


def base_places(words):
    """Start positions of the base phrases, in the array of words."""
    def at(phrase):
        parts = phrase.split(" ")
        def test(i):
            found = F.get(words, i) == parts[0]
            for k, part in enumerate(parts[1:], 1):
                found = found & (F.get(words, i + k) == part)
            return F.coalesce(found, F.lit(False))
        return F.filter(F.sequence(F.lit(0), F.size(words) - 1), test)

    return at


def _detections(text):
    """array<struct(priority, label, start, stop)> of all rules over a lower-case text."""
    table = F.array(*[F.struct(F.lit(p).alias("p"), F.lit(label).alias("label"), F.lit(k).alias("k"), F.lit(r).alias("r")) for p, label, k, r in rules()])
    live = F.filter(table, lambda rule: F.contains(text, rule["k"]))

    def places(rule):
        # the pieces between the matches give the places of all matches
        matches = F.regexp_extract_all(text, rule["r"], F.lit(0))
        pieces = F.split(text, rule["r"], -1)
        state = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<priority:int,label:string,start:int,stop:int>>").alias("seen"))

        def step(acc, i):
            start = acc["at"] + F.length(F.get(pieces, i))
            stop = start + F.length(F.get(matches, i))
            return F.struct(stop.alias("at"), F.concat(acc["seen"], F.array(F.struct(rule["p"].alias("priority"), rule["label"].alias("label"), start.alias("start"), stop.alias("stop")))).alias("seen"))

        none = F.array().cast("array<struct<priority:int,label:string,start:int,stop:int>>")
        return F.when(F.size(matches) > 0, F.aggregate(F.sequence(F.lit(0), F.size(matches) - 1), state, step, lambda s: s["seen"])).otherwise(none)

    return F.flatten(F.transform(live, places))


def _standing(found):
    """Detections that no better one contains."""

    def beaten(d):
        def wins(o):
            inside = (o["start"] <= d["start"]) & (o["stop"] >= d["stop"])
            longer = (o["stop"] - o["start"]) > (d["stop"] - d["start"])
            return inside & ((o["priority"] < d["priority"]) | ((o["priority"] == d["priority"]) & longer))

        return F.exists(found, wins)

    return F.filter(found, lambda d: ~beaten(d))


def scan_licenses(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with n_words, base (array of (label, start word)) and detections (array of (priority, label, start, stop))."""
    docs = docs.drop("n_words", "base", "detections")
    lowered, split = free_names(docs, "lowered", "split")
    lower = lower_ascii(F.coalesce(F.col(text), F.lit("")))
    with_text = docs.withColumn(lowered, lower)
    phrase = r"(?:^|[\x00-\x2F\x3A-\x60\x7B-\x7F])(?:gnu|apache|cc|mit)[\x00-\x2F\x3A-\x60\x7B-\x7F]+(?:general|license|by)"
    no_base = F.array().cast("array<struct<label:string,start:int>>")
    no_detection = F.array().cast("array<struct<priority:int,label:string,start:int,stop:int>>")
    words = F.regexp_extract_all(lowered, F.lit(WORD), F.lit(0))
    at = base_places(F.col(split))

    def named(label):
        return lambda i: F.struct(F.lit(label).alias("label"), i.alias("start"))

    base = F.concat(*[F.transform(at(p), named(label)) for p, label in BASE])
    return (
        with_text.withColumn("n_words", F.regexp_count(lowered, F.lit(WORD)).cast("bigint"))
        .withColumn(split, F.when(F.col(lowered).rlike(phrase), words))
        .withColumn("base", F.when(F.size(split) > 0, base).otherwise(no_base))
        .withColumn("detections", F.when(gate(F.col(lowered)), _standing(_detections(F.col(lowered)))).otherwise(no_detection))
        .drop(split, lowered)
    )


def op9_signature_rule_licenses(spark, sf_dir: str) -> DataFrame:
    found = scan_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    start = F.transform("base", lambda b: b["start"].cast("bigint"))
    base_labels = F.array_sort(F.array_distinct(F.transform("base", lambda b: b["label"])))
    own = F.transform("detections", lambda d: d["label"])
    best = F.array_min(F.transform("detections", lambda d: d["priority"]))
    return found.select(
        "doc_id",
        "n_words",
        F.size("base").cast("bigint").alias("n_base"),
        F.array_min(start).alias("first_word"),
        F.array_max(start).alias("last_word"),
        F.array_join(base_labels, ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_distinct(F.concat(base_labels, own))), ",").alias("labels"),
        F.when(F.size("detections") > 0, F.round(1.0 - 0.1 * (best - 1), 6)).when(F.size("base") > 0, F.lit(0.5)).otherwise(F.lit(0.0)).cast("double").alias("score"),
    )
