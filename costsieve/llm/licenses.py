"""License scans: ordered signature rules over normalised words, in DataFrame expressions only.

A text is read as words of letters, digits and anything beyond ASCII. Rules are regular expressions over those words. Each has a keyword, a word that stands in all its matches, and a priority, its place in the list. The
keywords that a text holds are found in one pass over its words; a text without any skips all rules, others try only the rules of the keywords they hold.
Of overlapping detections, one that lies inside another is suppressed; of equal ones, and of two that overlap in part, the one with the higher priority stays. Base phrases
are counted apart and are never suppressed.

Defined results: a null or empty text has no words, places or labels, null first and last words and the score 0; a null doc_id and repeated rows are
carried through; an empty table gives an empty result; other columns are ignored. Work is per row: nothing is shuffled.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import columns

BETWEEN_WORDS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"

# The base phrases and their labels.
BASE = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))


@dataclass(frozen=True)
class Rule:
    label: str
    pattern: str  # over words joined by single spaces; it neither begins nor ends with a space
    keyword: str  # one word that every match holds
    priority: int  # smaller wins
    weight: float  # how much a detection says about the license, 0 to 1


#: Licenses with a name, by label: the name's words, a keyword among them, and the versions that were published. Each gives rules for the name with a version, the short form with a version, and the name alone.
NAMED = (
    ("agpl", "(?:gnu )?affero general public", "affero", "3.0 1.0"),
    ("lgpl", "(?:gnu )?(?:lesser|library) general public", "general", "3.0 2.1 2.0"),
    ("gpl", "(?:gnu )?general public", "general", "3.0 2.0 1.0"),
    ("gfdl", "(?:gnu )?free documentation", "documentation", "1.3 1.2 1.1"),
    ("apache", "apache(?: software)?", "apache", "2.0 1.1 1.0"),
    ("mpl", "mozilla public", "mozilla", "2.0 1.1 1.0"),
    ("epl", "eclipse public", "eclipse", "2.0 1.0"),
    ("eupl", "european union public", "european", "1.2 1.1 1.0"),
    ("bsl", "boost software", "boost", "1.0"),
    ("afl", "academic free", "academic", "3.0 2.1 2.0 1.2 1.1"),
    ("osl", "open software", "open", "3.0 2.1 2.0 1.1 1.0"),
    ("cddl", "common development and distribution", "distribution", "1.1 1.0"),
    ("cpl", "common public", "common", "1.0"),
    ("ipl", "ibm public", "ibm", "1.0"),
    ("apsl", "apple public source", "apple", "2.0 1.2 1.1 1.0"),
    ("npl", "netscape public", "netscape", "1.1 1.0"),
    ("spl", "sun public", "sun", "1.0"),
    ("qpl", "q public", "q", "1.0"),
    ("psf", "python software foundation", "python", "2.0"),
    ("artistic", "artistic", "artistic", "2.0 1.0"),
    ("ofl", "(?:sil )?open font", "font", "1.1 1.0"),
    ("odbl", "(?:open data commons )?open database", "database", "1.0"),
    ("odc-by", "open data commons attribution", "commons", "1.0"),
    ("pddl", "(?:open data commons )?public domain dedication(?: and)?", "dedication", "1.0"),
    ("lpl", "lucent public", "lucent", "1.02 1.0"),
    ("lppl", "latex project public", "latex", "1.3c 1.3a 1.2 1.1 1.0"),
    ("ms-pl", "microsoft public", "microsoft", ""),
    ("ms-rl", "microsoft reciprocal", "microsoft", ""),
    ("sspl", "server side public", "server", "1.0"),
    ("busl", "business source", "business", "1.1"),
    ("elastic", "elastic", "elastic", "2.0"),
    ("zpl", "zope public", "zope", "2.1 2.0 1.1"),
    ("php", "php", "php", "3.01 3.0"),
    ("cecill", "cecill(?: free software)?", "cecill", "2.1 2.0 1.1 1.0"),
    ("ecl", "educational community", "educational", "2.0 1.0"),
    ("rpl", "reciprocal public", "reciprocal", "1.5 1.1"),
    ("nasa", "nasa open source", "nasa", "1.3"),
    ("mulan", "mulan permissive software", "mulan", "2.0 1.0"),
    ("llama", "llama(?: [23])?(?: community)?", "llama", ""),
    ("openrail", "openrail(?: m)?", "openrail", ""),
    ("ncsa", "(?:university of illinois )?ncsa(?: open source)?", "ncsa", ""),
    ("openssl", "openssl", "openssl", ""),
    ("postgresql", "postgresql", "postgresql", ""),
    ("vim", "vim", "vim", ""),
    ("ruby", "ruby", "ruby", ""),
    ("zlib", "zlib(?: libpng)?", "zlib", ""),
    ("isc", "isc", "isc", ""),
    ("mit", "mit", "mit", ""),
    ("mit", "expat", "expat", ""),
    ("x11", "x11", "x11", ""),
    ("0bsd", "(?:zero clause bsd|bsd zero clause|0bsd)", "0bsd|zero", ""),
    ("beerware", "beer ?ware", "beerware|beer", ""),
    ("unlicense", "unlicense", "unlicense", ""),
)

#: Creative Commons licenses: the short form, the long one, and the versions that were published under it.
CREATIVE = (
    ("by nc nd", "attribution non ?commercial no ?deriv(?:s|atives|ative works)", "4.0 3.0 2.5 2.0"),
    ("by nc sa", "attribution non ?commercial share ?alike", "4.0 3.0 2.5 2.0 1.0"),
    ("by nc", "attribution non ?commercial", "4.0 3.0 2.5 2.0 1.0"),
    ("by nd", "attribution no ?deriv(?:s|atives|ative works)", "4.0 3.0 2.5 2.0 1.0"),
    ("by sa", "attribution share ?alike", "4.0 3.0 2.5 2.0 1.0"),
    ("by", "attribution", "4.0 3.0 2.5 2.0 1.0"),
)

#: Notices by their wording: label, keyword, weight, pattern. They come first: whole sentences say more than names.
NOTICES = (
    ("mit", "hereby", 1.0, r"permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    ("mit", "hereby", 0.9, r"permission is hereby granted free of charge to any person obtaining a copy"),
    ("mit-0", "mit", 0.9, r"mit no attribution"),
    ("isc", "permission", 0.95, r"permission to use copy modify and(?: or)? distribute this software for any purpose with or without fee is hereby granted"),
    ("hpnd", "permission", 0.9, r"permission to use copy modify and distribute this software and its documentation for any purpose"),
    ("bsd-4-clause", "advertising", 0.95, r"all advertising materials mentioning features or use of this software must display the following acknowledg(?:e)?ment"),
    ("bsd-3-clause", "endorse", 0.95, r"neither the name of (?:[^ ]+ ){1,12}nor the names of its contributors may be used to endorse or promote products"),
    ("bsd", "redistribution", 0.9, r"redistribution and use in source and binary forms with or without modification are permitted(?: provided that the following conditions are met)?"),
    ("apache-2.0", "apache", 1.0, r"licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license"),
    ("apache-2.0", "apache", 1.0, r"licensed under the apache license version 2 0"),
    ("apache-2.0", "licenses", 1.0, r"apache org licenses license 2 0"),
    ("gpl-2.0-or-later", "redistribute", 1.0, r"redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version"),
    ("gpl-3.0-or-later", "redistribute", 1.0, r"redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version"),
    ("lgpl-2.1-or-later", "redistribute", 1.0, r"redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2 1 of the license or at your option any later version"),
    ("gpl-classpath-exception", "classpath", 0.9, r"classpath exception"),
    ("gpl-font-exception", "font", 0.9, r"font exception"),
    ("gcc-exception", "gcc", 0.9, r"gcc runtime library exception"),
    ("llvm-exception", "llvm", 0.9, r"(?:with )?llvm exceptions?"),
    ("gpl", "gnu", 0.7, r"gnu org licenses(?: gpl)?"),
    ("mpl-2.0", "mozilla", 1.0, r"this source code form is subject to the terms of the mozilla public license v ?2 0"),
    ("mpl-1.1", "mozilla", 0.95, r"the contents of this file are subject to the mozilla public license version 1 1"),
    ("epl-1.0", "eclipse", 0.95, r"made available under the terms of the eclipse public license v1 0"),
    ("epl-2.0", "eclipse", 0.95, r"made available under the terms of the eclipse public license (?:v|version )?2 0"),
    ("bsl-1.0", "boost", 1.0, r"distributed under the boost software license version 1 0"),
    ("cddl", "cddl", 0.8, r"(?:subject to the terms of|under) (?:the )?cddl"),
    ("zlib", "warranty", 0.9, r"this software is provided as is without any express or implied warranty in no event will the authors be held liable"),
    ("unlicense", "unencumbered", 1.0, r"this is free and unencumbered software released into the public domain"),
    ("wtfpl", "fuck", 1.0, r"do what the fuck you want to(?: public license)?"),
    ("json", "evil", 0.95, r"shall be used for good not evil"),
    ("beerware", "beer", 0.95, r"you can buy me a beer in return"),
    ("curl", "curl", 0.6, r"curl license"),
    ("w3c", "w3c", 0.85, r"w3c software (?:notice and (?:document )?license|license)"),
    ("unicode", "unicode", 0.85, r"unicode (?:inc )?license agreement"),
    ("cc0-1.0", "cc0", 1.0, r"cc0 1 0(?: universal)?"),
    ("cc0-1.0", "publicdomain", 1.0, r"creativecommons org publicdomain zero 1 0"),
    ("cc-pdm-1.0", "publicdomain", 0.95, r"creativecommons org publicdomain mark 1 0"),
    ("cc-pdm-1.0", "domain", 0.9, r"public domain mark 1 0"),
    ("cc0", "cc0", 0.8, r"cc0"),
    ("public-domain", "domain", 0.9, r"(?:released|dedicated|placed|put) (?:in|in ?to|to) the public domain"),
    ("public-domain", "domain", 0.6, r"(?:is|are) in the public domain"),
    ("public-domain", "domain", 0.4, r"public domain"),
    ("ogl-uk", "government", 0.9, r"(?:uk )?open government licen[cs]e(?: v(?:ersion )?[123](?: 0)?)?"),
    ("etalab", "etalab", 0.8, r"etalab(?: open)? licen[cs]e"),
    ("spdx", "spdx", 0.9, r"spdx license identifier [0-9a-z]+(?: [0-9]+)*"),
    ("proprietary", "proprietary", 0.9, r"proprietary and confidential"),
    ("proprietary", "confidential", 0.8, r"confidential and proprietary"),
    ("proprietary", "unauthorized", 0.9, r"unauthorized (?:copying|reproduction|use|distribution)(?: [^ ]+){0,10} (?:is )?(?:strictly )?prohibited"),
    ("proprietary", "without", 0.9, r"may not be (?:copied|reproduced|distributed|reprinted|republished)(?: or (?:copied|reproduced|distributed|transmitted))?(?: [^ ]+){0,8} without (?:the )?(?:prior |express )*(?:written )?(?:permission|consent)"),
    ("proprietary", "reproduction", 0.8, r"reproduction(?: [^ ]+){0,6} without (?:prior |written |express )*permission is prohibited"),
    ("non-commercial", "commercial", 0.7, r"(?:for )?non commercial use only"),
    ("non-commercial", "noncommercial", 0.7, r"(?:for )?noncommercial use only"),
    ("personal-use", "personal", 0.6, r"for personal use only"),
    ("reserved", "rights", 0.7, r"all rights(?: are)? reserved"),
    ("some-rights", "rights", 0.5, r"some rights reserved"),
    ("no-rights", "rights", 0.6, r"no rights reserved"),
    ("copyright", "copyright", 0.5, r"copyright (?:c )?(?:19|20)[0-9]{2}(?: (?:19|20)[0-9]{2})?"),
    ("copyright", "copyright", 0.3, r"copyright"),
    ("copyleft", "copyleft", 0.3, r"copyleft"),
)


def _number(version: str) -> str:
    """A version's words: 2.0 may be written 2."""
    major, _, minor = version.partition(".")
    return f"{major}(?: 0)?" if minor == "0" else f"{major} {minor}"


def _rules() -> tuple[Rule, ...]:
    made: list[tuple[str, str, str, float]] = [(label, pattern, keyword, weight) for label, keyword, weight, pattern in NOTICES]
    v, under = r"(?:version |v ?)?", r"(?:licensed|released|distributed|available|published) under (?:the )?(?:terms of (?:the )?)?"

    def add(label: str, pattern: str, keywords: str, weight: float) -> None:
        made.extend((label, pattern, keyword, weight) for keyword in keywords.split("|"))

    for label, name, keyword, versions in NAMED:
        tag = label.replace("-", " ")
        for version in versions.split():
            number = _number(version)
            if label in ("agpl", "lgpl", "gpl"):
                add(f"{label}-{version}-or-later", rf"{name} license (?:as published by the free software foundation )?(?:either )?{v}{number} (?:of the license )?or (?:at your option )?(?:any )?later(?: version)?", keyword, 1.0)
                add(f"{label}-{version}-only", rf"{name} license {v}{number} only", keyword, 1.0)
                add(f"{label}-{version}-or-later", rf"(?:gnu )?{tag} {v}{number} (?:or later|plus)", tag, 0.9)
            add(f"{label}-{version}", rf"{under}{name} license {v}{number}", keyword, 1.0)
            add(f"{label}-{version}", rf"{name} license {v}{number}", keyword, 1.0)
            add(f"{label}-{version}", rf"{tag} {v}{number}", tag.split()[0], 0.8)
            if version.endswith(".0") and " " not in tag:
                for joined in (f"{tag}v{version[0]}", f"{tag}{version[0]}"):
                    add(f"{label}-{version}", rf"{joined}(?: 0)?", joined, 0.8)
        add(label, rf"{under}{name} license", keyword, 0.9)
        add(label, rf"{name} license", keyword, 0.85)
    for short, long, versions in CREATIVE:
        tag = f"cc-{short.replace(' ', '-')}"
        for version in versions.split():
            number = _number(version)
            add(f"{tag}-{version}", rf"creative commons {long} {v}{number}(?: (?:international|unported|generic))?", "creative", 1.0)
            add(f"{tag}-{version}", rf"cc {short} {number}", "cc", 0.95)
            add(f"{tag}-{version}", rf"creativecommons org licenses {short} {number}", "creativecommons", 1.0)
        add(tag, rf"creative commons {long}(?: license)?", "creative", 0.9)
        add(tag, rf"cc {short}", "cc", 0.8)
    add("cc", r"creative commons(?: license)?", "creative", 0.4)
    for label, clauses in (("bsd-2-clause", "2|two|simplified"), ("bsd-3-clause", "3|three|new|revised|modified"), ("bsd-4-clause", "4|four|original"), ("bsd-1-clause", "1|one")):
        add(label, rf"bsd (?:{clauses}) clause(?: license)?", "bsd", 0.95)
        add(label, rf"(?:{clauses})(?: clause)? bsd(?: license)?", "bsd", 0.95)
    add("bsd", r"bsd(?: style| type)? license", "bsd", 0.8)
    add("gpl", r"general public license", "general", 0.6)
    return tuple(Rule(label, pattern, keyword, i, weight) for i, (label, pattern, keyword, weight) in enumerate(made))


RULES = _rules()


def words(text: Column) -> Column:
    """The words of a text, each between single spaces, in one string that begins and ends with a space; the empty text has none."""
    return F.concat(F.lit(" "), F.trim(F.regexp_replace(columns.lower_ascii(text), BETWEEN_WORDS, " ")), F.lit(" "))


def _spaces(line: Column) -> Column:
    return F.length(line) - F.length(F.replace(line, F.lit(" "), F.lit("")))


def base_places(line: Column) -> list[Column]:
    """For each base phrase the struct (label, n, first, last): number of places and their extreme word numbers."""
    found = []
    for phrase, label in BASE:
        # places cannot overlap: no phrase ends as it begins
        rest = F.split(line, f" {phrase}(?= )", -1)
        n = F.size(rest) - 1
        before = _spaces(F.element_at(rest, 1))
        after = _spaces(F.element_at(rest, -1)) - 1
        size = len(phrase.split())
        hit = F.struct(
            F.lit(label).alias("label"),
            n.cast("bigint").alias("n"),
            before.cast("bigint").alias("first"),
            (_spaces(line) - 1 - after - size).cast("bigint").alias("last"),
        )
        miss = F.struct(F.lit(label).alias("label"), F.lit(0).cast("bigint").alias("n"), F.lit(None).cast("bigint").alias("first"), F.lit(None).cast("bigint").alias("last"))
        found.append(F.when(F.contains(line, F.lit(f" {phrase} ")), hit).otherwise(miss))
    return found


SPAN = "array<struct<begin:int,low:int,priority:int,end:int,label:string,weight:double>>"


def detections(line: Column, held: Column, rules: tuple[Rule, ...]) -> Column:
    """All rules' detections as spans of word numbers, before suppression. ``held`` are the keywords that the text has."""
    none = F.expr(f"cast(array() as {SPAN})")
    by_word: dict[str, list[Rule]] = {}
    for r in rules:
        by_word.setdefault(r.keyword, []).append(r)
    written = [f"named_struct('word', {_quoted(word)}, 'rules', array({', '.join(map(_literal, own))}))" for word, own in by_word.items()]
    asked = F.filter(F.expr(f"array({', '.join(written)})"), lambda k: F.array_contains(held, k["word"]))  # one literal, and one expression for all rules
    hits = F.flatten(F.transform(F.flatten(F.transform(asked, lambda k: k["rules"])), lambda r: _found(line, r)))
    return F.when(F.size(held) > 0, hits).otherwise(none)


def _quoted(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _literal(rule: Rule) -> str:
    pattern = _quoted(f" (?:{rule.pattern})(?= )")
    return f"named_struct('pattern', {pattern}, 'priority', {rule.priority}, 'label', {_quoted(rule.label)}, 'weight', cast({rule.weight} as double))"


def _found(line: Column, rule: Column) -> Column:
    """The rule's spans; ``low`` is the end's negative, so that longer spans sort first."""
    return F.transform(
        columns.located(line, rule["pattern"], _spaces),
        lambda m: F.struct(
            m["begin"].alias("begin"),
            (-(m["begin"] + m["size"])).alias("low"),
            rule["priority"].alias("priority"),
            (m["begin"] + m["size"]).alias("end"),
            rule["label"].alias("label"),
            rule["weight"].alias("weight"),
        ),
    )


def suppressed(spans: Column) -> Column:
    """Sorted by begin, then the longest, then priority: a span stays if it ends beyond all before it, and of two that overlap in part the one with priority stays."""
    start = F.struct(F.lit(-1).alias("reach"), F.expr(f"cast(array() as {SPAN})").alias("out"))

    def step(state: Column, s: Column) -> Column:
        last = F.get(state["out"], F.size(state["out"]) - 1)
        inside = s["end"] <= state["reach"]
        crosses = s["begin"] < state["reach"]
        instead = F.concat(F.slice(state["out"], 1, F.greatest(F.size(state["out"]) - 1, F.lit(0))), F.array(s))
        weaker = crosses & (last["priority"] < s["priority"])
        out = F.when(inside | F.coalesce(weaker, F.lit(False)), state["out"]).when(crosses, instead).otherwise(F.concat(state["out"], F.array(s)))
        reach = F.when(inside | F.coalesce(weaker, F.lit(False)), state["reach"]).otherwise(s["end"])
        return F.struct(reach.alias("reach"), out.alias("out"))

    return F.aggregate(F.array_sort(spans), start, step, lambda s: s["out"])


def scan(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(doc_id, n_words, base, detections): base places per phrase, and the rules' spans after suppression."""
    texts = columns.documents(docs).select("doc_id", words(F.col("text")).alias("line"))
    line = F.col("line")
    keywords = F.array(*[F.lit(w) for w in sorted({r.keyword for r in rules})])
    texts = texts.withColumn("held", F.array_intersect(F.split("line", " "), keywords))
    n_words = F.when(line == "  ", F.lit(0)).otherwise(_spaces(line) - 1).cast("bigint")
    return texts.select("doc_id", n_words.alias("n_words"), F.array(*base_places(line)).alias("base"), detections(line, F.col("held"), rules).alias("all")).select(
        "doc_id", "n_words", "base", F.when(F.size("all") > 0, suppressed(F.col("all"))).otherwise(F.col("all")).alias("detections")
    )


def summary(scanned: DataFrame) -> DataFrame:
    """One row per document: counts, extreme places, labels, and as score the weight of the strongest detection."""
    held = F.filter("base", lambda b: b["n"] > 0)
    base_labels = F.transform(held, lambda b: b["label"])
    labels = F.concat(base_labels, F.transform("detections", lambda s: s["label"]))
    weights = F.concat(F.transform(held, lambda b: F.lit(0.6)), F.transform("detections", lambda s: s["weight"]), F.array(F.lit(0.0)))
    return scanned.select(
        "doc_id",
        "n_words",
        F.aggregate("base", F.lit(0).cast("bigint"), lambda a, b: a + b["n"]).alias("n_base"),
        F.array_min(F.transform(held, lambda b: b["first"])).alias("first_word"),
        F.array_max(F.transform(held, lambda b: b["last"])).alias("last_word"),
        F.array_join(F.array_sort(F.array_distinct(base_labels)), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_distinct(labels)), ",").alias("labels"),
        F.array_max(weights).alias("score"),
    )
