"""License scans by ordered signature rules, with column functions only.

Rules are regular expressions over the words of a text joined by single spaces, in order under the label that they stand for. A label's
rules are tried if one of its keywords occurs in those joined words (spaces where a word's edge is meant), each has a priority, and a
detection inside another one of higher priority, or of the same priority and longer, is suppressed. Fixed base phrases are
reported besides and never suppressed. Work is linear in the text and in the number of detections, sorting aside.

Defined results: a null or empty text has no words, no places and score 0; positions count words from 0; repeated rows get
repeated results; other columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .scans import scan

#: Phrases and their labels.
BASE = (("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc"))

_SEPARATORS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


@dataclass(frozen=True)
class Signature:
    """What names one license: keywords, of which one must occur for the rules to be tried, and (priority, pattern) in order."""

    label: str
    keywords: tuple[str, ...]
    rules: tuple[tuple[int, str], ...]


# Patterns are over lower-cased words joined by single spaces. Priorities: 60 the text of a license, 50 an identifier line,
# 40 a statement that names the license, 30 a shorter statement, 20 a name with "license", 10 a bare name.
SIGNATURES = (
    Signature("mit", (" mit ", "expat", "free of charge"), (
        (60, "permission is hereby granted free of charge to any person obtaining a copy of this software"),
        (60, "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability"),
        (50, "spdx license identifier (?:mit|expat)(?! 0)"),
        (40, "licen[sc]ed under (?:the )?(?:terms of the )?(?:mit|expat)(?: licen[sc]e)?"),
        (40, "(?:released|distributed|available|published|provided) under (?:the )?(?:terms of the )?(?:mit|expat)(?: licen[sc]e)?"),
        (30, "under (?:the )?(?:mit|expat) licen[sc]e"),
        (30, "licen[sc]e (?:is )?mit"),
        (20, "(?:mit|expat)(?: x11| style)? licen[sc]e"),
    )),
    Signature("mit-0", ("mit 0", "mit no attribution"), ((50, "spdx license identifier mit 0"), (30, "licen[sc]ed under (?:the )?mit (?:0|no attribution)"), (20, "mit (?:0|no attribution) licen[sc]e"), (10, "mit no attribution"))),
    Signature("x11", (" x11 ", "x consortium"), ((50, "spdx license identifier x11"), (40, "except as contained in this notice the name of the x consortium shall not be used"), (20, "x11 licen[sc]e"))),
    Signature("apache-2", ("apache", " asl "), (
        (60, "you may not use this file except in compliance with the (?:apache )?license"),
        (60, "terms and conditions for use reproduction and distribution"),
        (50, "spdx license identifier apache 2 0"),
        (40, "licen[sc]ed under (?:the )?(?:terms of the )?apache (?:software )?licen[sc]e (?:version |v ?)?2(?: 0)?"),
        (40, "(?:released|distributed|available|published|provided) under (?:the )?(?:terms of the )?apache (?:software )?licen[sc]e (?:version |v ?)?2(?: 0)?"),
        (40, "licen[sc]ed under (?:the )?(?:apache|asl) (?:version |v ?)?2(?: 0)?"),
        (30, "under (?:the )?apache (?:software )?licen[sc]e"),
        (30, "licen[sc]e (?:is )?apache (?:version |v ?)?2(?: 0)?"),
        (20, "apache (?:software )?licen[sc]e (?:version |v ?)?2(?: 0)?"),
        (20, "apache (?:version |v ?)?2(?: 0)? licen[sc]e"),
        (20, "asl (?:version |v ?)?2(?: 0)? licen[sc]e"),
        (10, "http www apache org licenses license 2 0"),
    )),
    Signature("apache-1.1", ("apache",), ((50, "spdx license identifier apache 1 1"), (40, "licen[sc]ed under (?:the )?apache (?:software )?licen[sc]e (?:version |v ?)?1 1"), (20, "apache (?:software )?licen[sc]e (?:version |v ?)?1 1"), (10, "this product includes software developed by the apache software foundation"))),
    Signature("bsd-2-clause", ("bsd", "redistribution"), ((60, "redistribution and use in source and binary forms with or without modification are permitted"), (50, "spdx license identifier bsd 2 clause"), (40, "licen[sc]ed under (?:the )?(?:terms of the )?(?:2 clause|two clause|simplified|freebsd) ?(?:bsd)?(?: licen[sc]e)?"), (30, "under (?:the )?bsd 2 clause(?: licen[sc]e)?"), (20, "bsd 2 clause licen[sc]e"), (20, "(?:2 clause|two clause|simplified) bsd licen[sc]e"))),
    Signature("bsd-3-clause", ("bsd", "endorse"), ((60, "neither the name of .{0,80}? nor the names of its contributors may be used to endorse"), (50, "spdx license identifier bsd 3 clause"), (40, "licen[sc]ed under (?:the )?(?:terms of the )?(?:3 clause|three clause|new|modified|revised) bsd(?: licen[sc]e)?"), (30, "under (?:the )?bsd 3 clause(?: licen[sc]e)?"), (20, "bsd 3 clause licen[sc]e"), (20, "(?:3 clause|three clause|new|modified|revised) bsd licen[sc]e"))),
    Signature("bsd-4-clause", ("bsd", "advertising materials"), ((60, "all advertising materials mentioning features or use of this software must display"), (50, "spdx license identifier bsd 4 clause"), (40, "licen[sc]ed under (?:the )?(?:4 clause|four clause|original) bsd(?: licen[sc]e)?"), (20, "bsd 4 clause licen[sc]e"), (20, "(?:4 clause|four clause|original) bsd licen[sc]e"))),
    Signature("bsd", (" bsd ",), ((40, "(?:licen[sc]ed|released|distributed|available) under (?:the )?(?:terms of the )?bsd licen[sc]e"), (30, "under a bsd style licen[sc]e"), (20, "bsd(?: style| type)? licen[sc]e"))),
    Signature("0bsd", ("0bsd", "zero clause"), ((50, "spdx license identifier 0bsd"), (30, "licen[sc]ed under (?:the )?(?:0bsd|zero clause bsd)"), (20, "(?:0bsd|zero clause bsd) licen[sc]e"))),
    Signature("isc", (" isc ", "with or without fee"), ((60, "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"), (50, "spdx license identifier isc"), (40, "(?:licen[sc]ed|released|distributed|available) under (?:the )?(?:terms of the )?isc(?: licen[sc]e)?"), (20, "isc licen[sc]e"))),
    Signature("zlib", ("zlib", "altered source"), ((60, "altered source versions must be plainly marked as such"), (50, "spdx license identifier zlib"), (40, "(?:licen[sc]ed|released|distributed|available) under (?:the )?zlib(?: libpng)?(?: licen[sc]e)?"), (20, "zlib(?: libpng)? licen[sc]e"))),
    Signature("boost-1", ("boost", " bsl "), ((50, "spdx license identifier bsl 1 0"), (40, "(?:licen[sc]ed|distributed|released) under the boost software licen[sc]e(?: (?:version |v ?)?1 0)?"), (20, "boost software licen[sc]e(?: (?:version |v ?)?1 0)?"), (10, "see accompanying file license 1 0 txt"))),
    Signature("unlicense", ("unlicense", "unencumbered"), ((60, "this is free and unencumbered software released into the public domain"), (50, "spdx license identifier unlicense"), (30, "under (?:the )?unlicense"), (10, "the unlicense"))),
    Signature("wtfpl", ("wtfpl", "what the fuck"), ((60, "you just do what the fuck you want to"), (50, "spdx license identifier wtfpl"), (30, "under (?:the )?wtfpl"), (20, "do what the fuck you want to public licen[sc]e"), (10, "wtfpl"))),
    Signature("gpl-2", ("gpl", "general public"), (
        (50, "spdx license identifier gpl 2 0(?: only| or later)?"),
        (40, "(?:licen[sc]ed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:gpl|general public licen[sc]e) ?(?:version |v ?)?2(?: 0)?"),
        (40, "terms of the gnu general public licen[sc]e as published by the free software foundation (?:either )?version 2"),
        (30, "under (?:the )?gplv2"), (20, "gnu general public licen[sc]e (?:version |v ?)?2(?: 0)?"), (20, "gnu gpl (?:version |v ?)?2(?: 0)?"), (10, "gpl ?(?:version |v ?)2(?: 0)?"), (10, "gpl 2 0"),
    )),
    Signature("gpl-3", ("gpl", "general public"), (
        (50, "spdx license identifier gpl 3 0(?: only| or later)?"),
        (40, "(?:licen[sc]ed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:gpl|general public licen[sc]e) ?(?:version |v ?)?3(?: 0)?"),
        (40, "terms of the gnu general public licen[sc]e as published by the free software foundation (?:either )?version 3"),
        (30, "under (?:the )?gplv3"), (20, "gnu general public licen[sc]e (?:version |v ?)?3(?: 0)?"), (20, "gnu gpl (?:version |v ?)?3(?: 0)?"), (10, "gpl ?(?:version |v ?)3(?: 0)?"), (10, "gpl 3 0"),
    )),
    Signature("gpl", ("gpl", "general public"), ((60, "you can redistribute it and or modify it under the terms of the gnu general public licen[sc]e"), (30, "under (?:the )?(?:terms of the )?(?:gnu )?gpl"), (20, "gnu general public licen[sc]e"), (20, "gnu gpl"), (20, "gpl licen[sc]e"))),
    Signature("lgpl-2.1", ("lgpl", "lesser general"), ((50, "spdx license identifier lgpl 2 1(?: only| or later)?"), (40, "(?:licen[sc]ed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:lgpl|lesser general public licen[sc]e) ?(?:version |v ?)?2 1"), (20, "gnu lesser general public licen[sc]e (?:version |v ?)?2 1"), (10, "lgpl ?(?:version |v ?)?2 1"))),
    Signature("lgpl-3", ("lgpl", "lesser general"), ((50, "spdx license identifier lgpl 3 0(?: only| or later)?"), (40, "(?:licen[sc]ed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:lgpl|lesser general public licen[sc]e) ?(?:version |v ?)?3(?: 0)?"), (20, "gnu lesser general public licen[sc]e (?:version |v ?)?3(?: 0)?"), (10, "lgpl ?(?:version |v ?)3(?: 0)?"))),
    Signature("lgpl", ("lgpl", "lesser general", "library general"), ((60, "under the terms of the gnu (?:lesser|library) general public licen[sc]e"), (30, "under (?:the )?(?:gnu )?lgpl"), (20, "gnu (?:lesser|library) general public licen[sc]e"), (20, "lgpl licen[sc]e"))),
    Signature("agpl-3", ("agpl", "affero"), ((60, "under the terms of the gnu affero general public licen[sc]e"), (50, "spdx license identifier agpl 3 0(?: only| or later)?"), (40, "(?:licen[sc]ed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:agpl|affero general public licen[sc]e)(?: ?(?:version |v ?)?3(?: 0)?)?"), (20, "gnu affero general public licen[sc]e(?: (?:version |v ?)?3(?: 0)?)?"), (10, "agpl ?(?:version |v ?)3(?: 0)?"))),
    Signature("mpl-1.1", (" mpl ", "mozilla"), ((50, "spdx license identifier mpl 1 1"), (40, "subject to the mozilla public licen[sc]e version 1 1"), (20, "mozilla public licen[sc]e (?:version |v ?)?1 1"), (10, "mpl (?:version |v ?)?1 1"))),
    Signature("mpl-2", (" mpl ", "mozilla"), ((60, "this source code form is subject to the terms of the mozilla public licen[sc]e(?: v 2 0)?"), (50, "spdx license identifier mpl 2 0"), (40, "(?:licen[sc]ed|released|distributed|available) under (?:the )?(?:terms of the )?(?:mpl|mozilla public licen[sc]e) ?(?:version |v ?)?2(?: 0)?"), (20, "mozilla public licen[sc]e(?: (?:version |v ?)?2(?: 0)?)?"), (10, "mpl (?:version |v ?)?2(?: 0)?"))),
    Signature("epl-1", (" epl ", "eclipse public"), ((50, "spdx license identifier epl 1 0"), (40, "under the terms of the eclipse public licen[sc]e (?:version |v ?)?1 0"), (20, "eclipse public licen[sc]e (?:version |v ?)?1(?: 0)?"), (10, "epl (?:version |v ?)?1 0"))),
    Signature("epl-2", (" epl ", "eclipse public"), ((50, "spdx license identifier epl 2 0"), (40, "under the terms of the eclipse public licen[sc]e (?:version |v ?)?2 0"), (20, "eclipse public licen[sc]e (?:version |v ?)?2(?: 0)?"), (10, "epl (?:version |v ?)?2 0"))),
    Signature("cddl-1", ("cddl", "common development and distribution"), ((50, "spdx license identifier cddl 1 0"), (40, "subject to the terms of the common development and distribution licen[sc]e"), (20, "common development and distribution licen[sc]e(?: (?:version |v ?)?1 0)?"), (10, "cddl (?:version |v ?)?1 0"))),
    Signature("eupl-1.2", ("eupl", "european union public"), ((50, "spdx license identifier eupl 1 2"), (40, "licen[sc]ed under the eupl"), (20, "european union public licen[sc]e(?: (?:version |v ?)?1 2)?"), (10, "eupl (?:version |v ?)?1 2"))),
    Signature("artistic-2", ("artistic",), ((50, "spdx license identifier artistic 2 0"), (40, "under (?:the )?(?:terms of the )?artistic licen[sc]e"), (20, "artistic licen[sc]e(?: (?:version |v ?)?2(?: 0)?)?"), (10, "same terms as perl itself"))),
    Signature("python-2", (" psf ", "python software foundation"), ((50, "spdx license identifier (?:python 2 0|psf 2 0)"), (30, "under the python software foundation licen[sc]e"), (20, "python software foundation licen[sc]e"), (20, "psf licen[sc]e(?: (?:version |v ?)?2)?"))),
    Signature("ofl-1.1", (" ofl ", "open font"), ((50, "spdx license identifier ofl 1 1"), (40, "this font software is licen[sc]ed under the sil open font licen[sc]e"), (20, "sil open font licen[sc]e(?: (?:version |v ?)?1 1)?"), (10, "ofl (?:version |v ?)?1 1"))),
    Signature("odbl-1", ("odbl", "open database"), ((50, "spdx license identifier odbl 1 0"), (40, "made available under the open database licen[sc]e"), (20, "open database licen[sc]e"), (10, "odbl (?:version |v ?)?1 0"))),
    Signature("odc-by-1", ("odc by", "open data commons attribution"), ((50, "spdx license identifier odc by 1 0"), (40, "made available under the open data commons attribution licen[sc]e"), (20, "open data commons attribution licen[sc]e"), (10, "odc by(?: 1 0)?"))),
    Signature("cc0-1", ("cc0", "cc zero", "creative commons zero", "waived all copyright"), ((60, "to the extent possible under law .{0,80}? waived all copyright"), (50, "spdx license identifier cc0 1 0"), (40, "(?:licen[sc]ed|released|dedicated|available) under (?:the )?(?:creative commons )?cc0"), (20, "creative commons zero(?: licen[sc]e)?"), (10, "cc0(?: 1 0)?"), (10, "cc zero"))),
    Signature("cc-by", (" cc by", "creative commons attribution"), (
        (50, r"spdx license identifier cc by \d 0"),
        (40, r"(?:licen[sc]ed|released|available|distributed) under (?:a |the )?cc by(?! (?:sa|nd|nc))(?: \d 0)?(?: licen[sc]e)?"),
        (40, r"(?:licen[sc]ed|released|available|distributed) under (?:a |the )?creative commons attribution(?! (?:share|no|non))(?: \d 0)?(?: international)?(?: licen[sc]e)?"),
        (20, r"creative commons attribution(?! (?:share|no|non))(?: \d 0)?(?: international)? licen[sc]e"),
        (10, r"cc by(?! (?:sa|nd|nc))(?: \d 0)?"),
        (10, "creative commons attribution(?! (?:share|no|non))"),
    )),
    Signature("cc-by-sa", (" cc by sa", "creative commons attribution"), (
        (50, r"spdx license identifier cc by sa \d 0"),
        (40, r"(?:licen[sc]ed|released|available|distributed) under (?:a |the )?cc by sa(?: \d 0)?(?: licen[sc]e)?"),
        (40, r"(?:licen[sc]ed|released|available|distributed) under (?:a |the )?creative commons attribution share ?alike(?: \d 0)?(?: licen[sc]e)?"),
        (10, r"cc by sa(?: \d 0)?"),
        (10, "creative commons attribution share ?alike"),
    )),
    Signature("cc-by-nd", (" cc by nd", "creative commons attribution"), ((50, r"spdx license identifier cc by nd \d 0"), (40, r"(?:licen[sc]ed|released|available) under (?:a |the )?cc by nd(?: \d 0)?"), (10, r"cc by nd(?: \d 0)?"), (10, "creative commons attribution no ?deriv(?:ative)?s(?: works)?"))),
    Signature("cc-by-nc", (" cc by nc", "creative commons attribution"), (
        (50, r"spdx license identifier cc by nc \d 0"),
        (40, r"(?:licen[sc]ed|released|available|distributed) under (?:a |the )?cc by nc(?! (?:sa|nd))(?: \d 0)?(?: licen[sc]e)?"),
        (40, r"(?:licen[sc]ed|released|available|distributed) under (?:a |the )?creative commons attribution non ?commercial(?! (?:share|no))(?: \d 0)?(?: licen[sc]e)?"),
        (10, r"cc by nc(?! (?:sa|nd))(?: \d 0)?"),
        (10, "creative commons attribution non ?commercial(?! (?:share|no))"),
    )),
    Signature("cc-by-nc-sa", (" cc by nc sa", "creative commons attribution"), ((50, r"spdx license identifier cc by nc sa \d 0"), (40, r"(?:licen[sc]ed|released|available) under (?:a |the )?cc by nc sa(?: \d 0)?"), (10, r"cc by nc sa(?: \d 0)?"), (10, "creative commons attribution non ?commercial share ?alike"))),
    Signature("cc-by-nc-nd", (" cc by nc nd", "creative commons attribution"), ((50, r"spdx license identifier cc by nc nd \d 0"), (40, r"(?:licen[sc]ed|released|available) under (?:a |the )?cc by nc nd(?: \d 0)?"), (10, r"cc by nc nd(?: \d 0)?"), (10, "creative commons attribution non ?commercial no ?deriv(?:ative)?s"))),
    Signature("public-domain", ("public domain",), ((60, "(?:released|placed|dedicated) (?:in)?to the public domain"), (30, "(?:is|are) in the public domain"), (30, "public domain dedication"), (20, "no copyright public domain"))),
    Signature("proprietary", ("all rights reserved", "proprietary", "commercial licen", "confidential", "may not be reproduced"), (
        (60, "proprietary and confidential"),
        (60, r"copyright .{0,60}? all rights reserved"),
        (40, "no part of this (?:publication|document|work) may be reproduced"),
        (40, "may not be reproduced (?:or distributed )?without (?:the )?(?:prior )?(?:written )?permission"),
        (40, "licen[sc]ed under (?:a |the )?(?:commercial|proprietary)(?: licen[sc]e)?"),
        (30, "under (?:a |the )?(?:commercial|proprietary) licen[sc]e"),
        (30, "licen[sc]e (?:is )?(?:commercial|proprietary)"),
        (20, "proprietary licen[sc]e"),
        (10, "unauthori[sz]ed copying of this file .{0,40}? is strictly prohibited"),
    )),
)
PRIORITIES = sorted({p for s in SIGNATURES for p, _ in s.rules}, reverse=True)


def any_of(patterns: list[str]) -> str:
    return "(?:" + "|".join(patterns) + ")"


def words_of(text: Column) -> Column:
    """Words joined and enclosed by single spaces; a text without words gives one space."""
    return F.regexp_replace(F.concat(F.lit(" "), text, F.lit(" ")), _SEPARATORS, " ")


def count_words(words: Column) -> Column:
    """Words in a string as words_of() makes it: one less than its spaces."""
    return (_spaces(words) - 1).cast("long")


def _spaces(text: Column) -> Column:
    return F.length(text) - F.length(F.replace(text, F.lit(" ")))


_PLACE = "struct<start: bigint, end: bigint, value: string>"


def places(words: Column, pattern: str) -> Column:
    """(start, end, value): in words, leftmost matches of a pattern that begin and end at word edges, found in one pass."""
    bounded = f"(?i)(?<= ){any_of([pattern])}(?= )"
    both = F.zip_with(F.split(words, bounded, -1), F.regexp_extract_all(words, F.lit(bounded), F.lit(0)), lambda gap, m: F.struct(_spaces(gap).cast("long").alias("gap"), F.coalesce(_spaces(m), F.lit(0)).cast("long").alias("inner"), m.alias("m")))
    step = lambda at, x: at + x["gap"] + x["inner"]
    # the spaces ahead of a word are one more than the words
    emit = lambda at, x: F.struct((at + x["gap"] - 1).alias("start"), (at + x["gap"] + x["inner"]).alias("end"), x["m"].alias("value"))
    return F.filter(scan(both, F.lit(0).cast("long"), step, emit, _PLACE), lambda p: p["value"].isNotNull())


_HIT = "struct<start: bigint, to: bigint, rank: int, label: string>"


def detections(words: Column, lowered: Column, signatures: tuple[Signature, ...]) -> Column:
    """Detections (start, to, rank, label) of every signature of which a keyword occurs: to is the end and rank the priority, both
    negative, so that sorting puts what may contain another one first. A label's rules are one alternation, the first that fits wins."""
    none = F.expr(f"cast(array() as array<{_HIT}>)")

    def of(s: Signature) -> Column:
        likely = F.lit(False)
        for k in s.keywords:
            likely = likely | F.contains(lowered, F.lit(k))
        ordered = [p for p, _ in sorted(s.rules, key=lambda r: -r[0])]

        def rank(value: Column) -> Column:
            out = F.lit(-ordered[-1])
            for priority in sorted(set(ordered))[1:]:
                out = F.when(value.rlike(f"(?i)^{any_of([r for p, r in s.rules if p == priority])}$"), F.lit(-priority)).otherwise(out)
            return out

        found = places(words, any_of([r for _, r in sorted(s.rules, key=lambda r: -r[0])]))
        return F.when(likely, F.transform(found, lambda p: F.struct(p["start"].alias("start"), (-p["end"]).alias("to"), rank(p["value"]).alias("rank"), F.lit(s.label).alias("label")))).otherwise(none)

    return F.flatten(F.array(*(of(s) for s in signatures)))


def unsuppressed(hits: Column) -> Column:
    """Hits not contained in one of higher priority, or of the same priority and longer.

    In order of start, then end from the far to the near, all that may contain a hit come before it, and of each priority only
    the one that reaches farthest (the first of those) counts: one sweep.
    """
    none = F.struct(F.lit(0).cast("long").alias("to"), F.lit(-1).cast("long").alias("start"))
    state = F.struct(*(none.alias(f"p{p}") for p in PRIORITIES))

    def step(s: Column, h: Column) -> Column:
        return F.struct(*(F.when((h["rank"] == -p) & (h["to"] < s[f"p{p}"]["to"]), F.struct(h["to"].alias("to"), h["start"].alias("start"))).otherwise(s[f"p{p}"]).alias(f"p{p}") for p in PRIORITIES))

    def emit(s: Column, h: Column) -> Column:
        beaten = F.lit(False)
        for p in PRIORITIES:
            far = s[f"p{p}"]
            longer = (far["to"] != h["to"]) | (far["start"] != h["start"])
            beaten = beaten | ((far["start"] >= 0) & (far["to"] <= h["to"]) & ((h["rank"] > -p) | ((h["rank"] == -p) & longer)))
        return F.struct(h["start"].alias("start"), (-h["to"]).alias("end"), h["label"].alias("label"), beaten.alias("beaten"))

    swept = scan(F.array_sort(hits), state, step, emit, "struct<start: bigint, end: bigint, label: string, beaten: boolean>")
    return F.filter(swept, lambda h: ~h["beaten"])


def covered(spans: Column) -> Column:
    """Words that lie in at least one span."""
    zero = F.struct(F.lit(0).cast("long").alias("to"), F.lit(0).cast("long").alias("n"))
    return F.aggregate(F.array_sort(spans), zero, lambda s, x: F.struct(F.greatest(s["to"], x["end"]).alias("to"), (s["n"] + F.greatest(F.lit(0).cast("long"), x["end"] - F.greatest(s["to"], x["start"]))).alias("n")), lambda s: s["n"])


def license_labels(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", signatures: tuple[Signature, ...] = SIGNATURES) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score (the share of words in detections)."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    step = docs.select(F.col(id_col).alias("doc_id"), words_of(text).alias("words"))
    step = step.select("doc_id", "words", F.lower("words").alias("lowered"), count_words(F.col("words")).alias("n_words"))
    none = F.expr(f"cast(array() as array<{_PLACE}>)")
    base = {label: F.when(F.contains("lowered", F.lit(f" {phrase} ")), places(F.col("words"), phrase)).otherwise(none) for phrase, label in BASE}
    base_places = F.struct(*(c.alias(f"b{i}") for i, c in enumerate(base.values()))).alias("base")
    hits = detections(F.col("words"), F.col("lowered"), signatures)
    step = step.select("doc_id", "n_words", base_places, hits.alias("hits"))
    step = step.select("doc_id", "n_words", "base", F.when(F.size("hits") > 0, unsuppressed(F.col("hits"))).otherwise(F.expr("cast(array() as array<struct<start: bigint, end: bigint, label: string, beaten: boolean>>)")).alias("hits"))
    lists = [F.col(f"base.b{i}") for i in range(len(base))]
    spans_only = lambda c: F.transform(c, lambda p: F.struct(p["start"].alias("start"), p["end"].alias("end")))
    starts = F.transform(F.concat(*lists), lambda p: p["start"])
    labels = F.array_compact(F.array(*(F.when(F.size(c) > 0, F.lit(label)) for c, label in zip(lists, base))))
    spans = F.concat(*map(spans_only, lists), spans_only(F.col("hits")))
    return step.select(
        "doc_id",
        "n_words",
        F.size(starts).cast("long").alias("n_base"),
        F.array_min(starts).alias("first_word"),
        F.array_max(starts).alias("last_word"),
        F.array_join(F.array_sort(labels), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_distinct(F.concat(labels, F.transform("hits", lambda h: h["label"])))), ",").alias("labels"),
        F.when(F.col("n_words") > 0, covered(spans) / F.col("n_words")).otherwise(0.0).cast("double").alias("score"),
    )
