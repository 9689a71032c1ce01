"""License scans with ordered signature rules.

A rule is a regular expression over lower-cased text, a label and a priority. Signatures are written
as words; between two words any short run of spaces, line breaks, comment signs and punctuation may
stand. The longest run of plain words in a signature is its keyword: an automaton finds which
keywords a text has, once such runs are folded to one space, and only their rules run. A
keyword is part of everything its rule matches, so the filter never hides a detection. Detections that
lie inside a detection of higher priority, or inside a longer one of equal priority, are
suppressed. Phrases that the contract fixes are found word by word besides.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import whole


class Rule(NamedTuple):
    label: str
    keyword: str
    priority: int
    pattern: str


#: Phrases whose words stand consecutively, and their labels.
PHRASES = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}

#: Families as (label, names as written in notices, versions).
FAMILIES = [
    ("gpl", ["gnu general public licen[cs]e", "gnu gpl"], ["1", "2", "3"]),
    ("lgpl", ["gnu lesser general public licen[cs]e", "gnu lgpl"], ["2.1", "3"]),
    ("lgpl", ["gnu library general public licen[cs]e"], ["2"]),
    ("agpl", ["gnu affero general public licen[cs]e", "affero gpl"], ["1", "3"]),
    ("fdl", ["gnu free documentation licen[cs]e"], ["1.1", "1.2", "1.3"]),
    ("apache", ["apache licen[cs]e", "apache software licen[cs]e"], ["1.0", "1.1", "2.0"]),
    ("mpl", ["mozilla public licen[cs]e"], ["1.0", "1.1", "2.0"]),
    ("epl", ["eclipse public licen[cs]e"], ["1.0", "2.0"]),
    ("cpl", ["common public licen[cs]e"], ["0.5", "1.0"]),
    ("cddl", ["common development and distribution licen[cs]e"], ["1.0", "1.1"]),
    ("eupl", ["european union public licen[cs]e"], ["1.0", "1.1", "1.2"]),
    ("artistic", ["artistic licen[cs]e"], ["1.0", "2.0"]),
    ("osl", ["open software licen[cs]e"], ["1.0", "2.0", "2.1", "3.0"]),
    ("afl", ["academic free licen[cs]e"], ["1.1", "1.2", "2.0", "2.1", "3.0"]),
    ("bsl", ["boost software licen[cs]e"], ["1.0"]),
    ("zpl", ["zope public licen[cs]e"], ["1.1", "2.0", "2.1"]),
    ("lppl", ["latex project public licen[cs]e"], ["1.0", "1.1", "1.2", "1.3"]),
    ("python", ["python software foundation licen[cs]e", "psf licen[cs]e"], ["2"]),
    ("php", ["php licen[cs]e"], ["3.0", "3.01"]),
    ("ofl", ["sil open font licen[cs]e"], ["1.0", "1.1"]),
    ("ecl", ["educational community licen[cs]e"], ["1.0", "2.0"]),
    ("odbl", ["open database licen[cs]e"], ["1.0"]),
    ("mit", ["mit licen[cs]e", "mit/x11 licen[cs]e", "expat licen[cs]e"], []),
    ("bsd", ["bsd licen[cs]e", "[234] clause bsd", "bsd [0234] clause"], []),
    ("isc", ["isc licen[cs]e"], []),
    ("zlib", ["zlib licen[cs]e", "zlib/libpng licen[cs]e"], []),
    ("unlicense", ["the unlicense"], []),
    ("wtfpl", ["wtfpl"], ["1", "2"]),
]
#: Standard short identifiers as (label, identifier stem, versions).
IDENTIFIERS = [
    ("gpl", "gpl", ["1.0", "2.0", "3.0"]), ("lgpl", "lgpl", ["2.0", "2.1", "3.0"]), ("agpl", "agpl", ["1.0", "3.0"]),
    ("fdl", "gfdl", ["1.1", "1.2", "1.3"]), ("apache", "apache", ["1.0", "1.1", "2.0"]), ("mpl", "mpl", ["1.0", "1.1", "2.0"]),
    ("epl", "epl", ["1.0", "2.0"]), ("cddl", "cddl", ["1.0", "1.1"]), ("eupl", "eupl", ["1.0", "1.1", "1.2"]),
    ("artistic", "artistic", ["1.0", "2.0"]), ("osl", "osl", ["1.0", "2.0", "2.1", "3.0"]), ("afl", "afl", ["1.1", "1.2", "2.0", "2.1", "3.0"]),
    ("bsl", "bsl", ["1.0"]), ("ofl", "ofl", ["1.0", "1.1"]), ("zpl", "zpl", ["1.1", "2.0", "2.1"]), ("mit", "mit", []), ("isc", "isc", []),
    ("bsd", "bsd-2-clause", []), ("bsd", "bsd-3-clause", []), ("zlib", "zlib", []), ("unlicense", "unlicense", []), ("cc0", "cc0", ["1.0"]),
]
#: Signatures of license texts and notices: (label, priority, words). One sentence or clause each that is
#: particular to its license; regular expressions stand only for a whole word.
SIGNATURES = [
    ("mit", 60, "permission is hereby granted free of charge to any person obtaining a copy of this software"),
    ("mit", 60, "permission is hereby granted free of charge to any person obtaining a copy"),
    ("mit", 55, "to use copy modify merge publish distribute sublicense and/or sell copies of the software"),
    ("mit", 55, "the above copyright notice and this permission notice shall be included in all copies or substantial portions"),
    ("x11", 58, "shall not be used in advertising or otherwise to promote the sale use or other dealings in this software without prior written authorization"),
    ("isc", 60, "permission to use copy modify and distribute this software for any purpose with or without fee is hereby granted"),
    ("isc", 60, "permission to use copy modify and/or distribute this software for any purpose with or without fee is hereby granted"),
    ("isc", 55, "the software is provided as is and the author disclaims all warranties with regard to this software"),
    ("hpnd", 58, "permission to use copy modify and distribute this software and its documentation for any purpose and without fee is hereby granted"),
    ("bsd", 60, "redistribution and use in source and binary forms with or without modification are permitted provided that"),
    ("bsd", 60, "redistribution and use in source and binary forms with or without modification"),
    ("bsd", 55, "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer"),
    ("bsd", 55, "redistributions in binary form must reproduce the above copyright notice this list of conditions"),
    ("bsd", 55, "may be used to endorse or promote products derived from this software without specific prior written permission"),
    ("bsd", 62, "all advertising materials mentioning features or use of this software must display the following acknowledgement"),
    ("zlib", 60, "this software is provided as-is without any express or implied warranty"),
    ("zlib", 60, "the origin of this software must not be misrepresented"),
    ("zlib", 58, "altered source versions must be plainly marked as such and must not be misrepresented as being the original software"),
    ("unlicense", 60, "this is free and unencumbered software released into the public domain"),
    ("unlicense", 58, "anyone is free to copy modify publish use compile sell or distribute this software"),
    ("wtfpl", 60, "do what the fuck you want to public licen[cs]e"),
    ("beerware", 60, "the beer-ware licen[cs]e"),
    ("beerware", 58, "if we meet some day and you think this stuff is worth it you can buy me a beer in return"),
    ("gpl", 60, "this program is free software you can redistribute it and/or modify it under the terms of the gnu general public licen[cs]e"),
    ("gpl", 58, "either version 2 of the licen[cs]e or at your option any later version"),
    ("gpl", 58, "either version 3 of the licen[cs]e or at your option any later version"),
    ("gpl", 58, "you should have received a copy of the gnu general public licen[cs]e along with this program"),
    ("gpl", 58, "when we speak of free software we are referring to freedom not price"),
    ("gpl", 58, "the licenses for most software are designed to take away your freedom to share and change it"),
    ("lgpl", 62, "this library is free software you can redistribute it and/or modify it under the terms of the gnu lesser general public licen[cs]e"),
    ("lgpl", 62, "this library is free software you can redistribute it and/or modify it under the terms of the gnu library general public licen[cs]e"),
    ("lgpl", 58, "you should have received a copy of the gnu lesser general public licen[cs]e along with this library"),
    ("lgpl", 58, "linking a work that uses the library with the library"),
    ("agpl", 60, "you should have received a copy of the gnu affero general public licen[cs]e"),
    ("agpl", 58, "interacting with it remotely through a computer network an opportunity to receive the corresponding source"),
    ("gpl-exception", 58, "as a special exception to the gnu general public licen[cs]e"),
    ("gpl-exception", 58, "as a special exception the copyright holders give permission to link the code"),
    ("gpl-exception", 58, "linking this library statically or dynamically with other modules is making a combined work"),
    ("fdl", 60, "permission is granted to copy distribute and/or modify this document under the terms of the gnu free documentation licen[cs]e"),
    ("fdl", 58, "with no invariant sections no front-cover texts and no back-cover texts"),
    ("apache", 60, "licensed under the apache licen[cs]e version 2.0 the licen[cs]e"),
    ("apache", 58, "you may not use this file except in compliance with the licen[cs]e"),
    ("apache", 58, "licensed to the apache software foundation asf under one or more contributor licen[cs]e agreements"),
    ("apache", 58, "subject to the terms and conditions of this licen[cs]e each contributor hereby grants to you a perpetual worldwide"),
    ("apache", 58, "this product includes software developed by the apache software foundation"),
    ("mpl", 60, "this source code form is subject to the terms of the mozilla public licen[cs]e"),
    ("mpl", 60, "the contents of this file are subject to the mozilla public licen[cs]e"),
    ("mpl", 55, "if a copy of the mpl was not distributed with this file you can obtain one at"),
    ("epl", 60, "this program and the accompanying materials are made available under the terms of the eclipse public licen[cs]e"),
    ("epl", 58, "the accompanying program is provided under the terms of this eclipse public licen[cs]e"),
    ("cpl", 58, "the accompanying program is provided under the terms of this common public licen[cs]e"),
    ("ipl", 58, "the accompanying program is provided under the terms of this ibm public licen[cs]e"),
    ("cddl", 60, "the contents of this file are subject to the terms of the common development and distribution licen[cs]e"),
    ("cddl", 58, "you can obtain a copy of the licen[cs]e at usr/src/opensolaris.licen[cs]e"),
    ("eupl", 60, "licensed under the eupl version 1.[012]"),
    ("eupl", 58, "licensed under the eupl"),
    ("artistic", 58, "the intent of this document is to state the conditions under which a package may be copied"),
    ("artistic", 58, "same terms as perl itself"),
    ("bsl", 60, "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation"),
    ("bsl", 58, "distributed under the boost software licen[cs]e"),
    ("openssl", 60, "this product includes software developed by the openssl project"),
    ("openssl", 58, "this product includes cryptographic software written by eric young"),
    ("php", 58, "this source file is subject to version 3.0[0-9] of the php licen[cs]e"),
    ("php", 58, "this product includes php software freely available from"),
    ("python", 58, "psf hereby grants licensee a nonexclusive royalty-free world-wide licen[cs]e"),
    ("python", 58, "this licen[cs]e agreement is between the python software foundation"),
    ("ruby", 58, "you may make and give away verbatim copies of the source form of the software without restriction"),
    ("tcl", 58, "the authors hereby grant permission to use copy modify distribute and licen[cs]e this software and its documentation for any purpose"),
    ("vim", 58, "there are no restrictions on distributing unmodified copies of vim"),
    ("ncsa", 60, "university of illinois/ncsa open source licen[cs]e"),
    ("ncsa", 58, "to deal with the software without restriction including without limitation the rights to use copy modify"),
    ("w3c", 58, "by obtaining using and/or copying this work you the licensee agree that you have read understood and will comply"),
    ("unicode", 58, "permission is hereby granted free of charge to any person obtaining a copy of the unicode data files"),
    ("icu", 56, "icu licen[cs]e"),
    ("curl", 58, "except as contained in this notice the name of a copyright holder shall not be used in advertising"),
    ("libpng", 58, "this code is released under the libpng licen[cs]e"),
    ("ijg", 60, "this software is based in part on the work of the independent jpeg group"),
    ("freetype", 58, "portions of this software are copyright .{1,9} the freetype project"),
    ("ofl", 60, "this font software is licensed under the sil open font licen[cs]e"),
    ("ofl", 58, "the font software may not be sold by itself"),
    ("lppl", 60, "this work may be distributed and/or modified under the conditions of the latex project public licen[cs]e"),
    ("lppl", 56, "this work has the lppl maintenance status"),
    ("postgresql", 60, "permission to use copy modify and distribute this software and its documentation for any purpose without fee and without a written agreement"),
    ("ms-pl", 60, "microsoft public licen[cs]e"),
    ("ms-rl", 60, "microsoft reciprocal licen[cs]e"),
    ("cecill", 58, "governed by the cecill licen[cs]e"),
    ("cecill", 58, "abiding by the rules of distribution of free software"),
    ("qpl", 56, "the q public licen[cs]e"),
    ("sleepycat", 58, "redistributions in any form must be accompanied by information on how to obtain complete source code"),
    ("json", 60, "the software shall be used for good not evil"),
    ("odbl", 60, "this database is made available under the open database licen[cs]e"),
    ("odc-by", 58, "open data commons attribution licen[cs]e"),
    ("pddl", 58, "public domain dedication and licen[cs]e"),
    ("cc0", 60, "the person who associated a work with this deed has dedicated the work to the public domain"),
    ("cc0", 60, "creative commons zero"),
    ("cc0", 58, "to the extent possible under law"),
    ("cc-by-nc-nd", 66, "creative commons attribution noncommercial noderiv(?:ative)?s"),
    ("cc-by-nc-nd", 66, "creative commons attribution non commercial no derivatives"),
    ("cc-by-nc-sa", 66, "creative commons attribution noncommercial sharealike"),
    ("cc-by-nc-sa", 66, "creative commons attribution non commercial share alike"),
    ("cc-by-nc", 64, "creative commons attribution noncommercial"),
    ("cc-by-nc", 64, "creative commons attribution non commercial"),
    ("cc-by-nd", 64, "creative commons attribution noderiv(?:ative)?s"),
    ("cc-by-nd", 64, "creative commons attribution no derivatives"),
    ("cc-by-sa", 64, "creative commons attribution sharealike"),
    ("cc-by-sa", 64, "creative commons attribution share alike"),
    ("cc-by", 62, "creative commons attribution"),
    ("bsl-1.1", 58, "business source licen[cs]e 1.1"),
    ("sspl", 60, "server side public licen[cs]e"),
    ("elastic", 60, "elastic licen[cs]e 2.0"),
    ("commons-clause", 60, "commons clause licen[cs]e condition"),
    ("polyform", 60, "polyform (?:noncommercial|shield|strict|perimeter) licen[cs]e"),
    ("openrail", 60, "(?:bigscience|creativeml) open rail-?m?"),
    ("public-domain", 20, "(?:placed|released|dedicated) (?:in|into|to) the public domain"),
    ("public-domain", 20, "this (?:file|code|software|work) is in the public domain"),
    ("proprietary", 24, "this software is the confidential and proprietary information of"),
    ("proprietary", 24, "unauthorized copying of this file via any medium is strictly prohibited"),
    ("proprietary", 24, "contains trade secrets and proprietary information"),
    ("proprietary", 22, "no part of this publication may be reproduced"),
    ("proprietary", 22, "may not be reproduced or transmitted in any form"),
    ("proprietary", 20, "all rights reserved"),
    ("non-commercial", 24, "for non-commercial use only"),
    ("non-commercial", 24, "for personal and non-commercial use"),
    ("copyright", 20, "copyright (?:©|c) (?:19|20)[0-9][0-9]"),
    ("copyright", 20, "copyright (?:19|20)[0-9][0-9]"),
]
#: What may stand between the words of a signature, and what is folded to one space before keywords are looked for.
_BREAK = r"[ \t\r\n*#/,.()\"'-]"
_GAP = _BREAK + "{1,12}"
_FOLDED = re.compile(_BREAK + "+")
_PLAIN = re.compile(r"[a-z0-9./-]+")


def folded(lowered: str) -> str:
    """A text with every run of breaks as one space: where keywords are looked for."""
    return _FOLDED.sub(" ", lowered)


def signature(label: str, priority: int, words: str, head: str = r"(?<![a-z0-9])", tail: str = r"(?![a-z0-9])") -> Rule:
    """The rule of words with gaps between them; its keyword is the longest run of plain ones."""
    patterns, runs = [], [[]]
    for word in words.split(" "):
        # breaks inside a plain word are gaps as well
        parts = [p for p in _FOLDED.split(word) if p] if _PLAIN.fullmatch(word) else [None]
        patterns.append(_GAP.join(map(re.escape, parts)) if parts != [None] else word)
        if parts != [None]:
            runs[-1] += parts
            continue
        lead = re.match(r"[a-z]*", word).group(0)
        if len(lead) > 2 and word[len(lead) : len(lead) + 1] == "[":  # a word that is plain up to a choice of letters
            runs[-1].append(lead)
        runs.append([])
    keyword = max((" ".join(r) for r in runs), key=len)
    if not keyword:
        raise ValueError(f"no plain word in {words!r}")
    return Rule(label, keyword, priority, head + _GAP.join(patterns) + tail)


def build_rules() -> list[Rule]:
    """The ordered rules: identifiers first, then versioned names, sentences, plain names."""
    rules = [signature(*s) for s in SIGNATURES]
    some = r"[ \t\r\n]"
    for label, stem, versions in IDENTIFIERS:
        for tail in versions or [""]:
            name = f"{stem}-{tail}" if tail else stem
            keyword, spelled = folded(name), re.escape(name)
            end = r"(?:-only|-or-later|\+)?(?![a-z0-9.-])"
            rules.append(Rule(label, keyword, 90, rf"spdx-license-identifier:{some}{{0,8}}{spelled}{end}"))
            rules.append(Rule(label, keyword, 70, rf"\"?license\"?{some}{{0,4}}[:=]{some}{{0,4}}\"?{spelled}{end}"))
    for label, names, versions in FAMILIES:
        for name in names:
            for version in versions:
                number = re.escape(version.removesuffix(".0")) + (r"(?:\.0)?" if version.endswith(".0") or "." not in version else "")
                rules.append(signature(label, 80, name, tail=rf"{_GAP}(?:as published[^\n]{{0,60}}?)?(?:v|ver|version)?{_BREAK}{{0,6}}{number}(?![0-9])"))
                rules.append(signature(label, 85, name, rf"(?:under|terms of)(?: the)?{_GAP}", rf"{_GAP}(?:v|version)[ .]{{0,2}}{number}(?![0-9])"))
            rules.append(signature(label, 40, name))
            given = rf"(?:licen[cs]ed|released|distributed|available|published)[ \n]under(?: the)?(?: terms of)?(?: the)?{_GAP}"
            rules.append(signature(label, 50, name, given))
    marks = [("cc-by-nc-nd", "nc nd"), ("cc-by-nc-sa", "nc sa"), ("cc-by-nc", "nc"), ("cc-by-nd", "nd"), ("cc-by-sa", "sa"), ("cc-by", "")]
    for n, (label, mark) in enumerate(marks):
        name = f"cc by {mark}".strip()
        rules.append(signature(label, 65 - n, name, tail=rf"(?![a-z0-9])(?!{_GAP}(?:nc|nd|sa)(?![a-z0-9]))"))
        for version in ["1.0", "2.0", "2.5", "3.0", "4.0"]:
            rules.append(signature(label, 80 - n, f"{name} {version}", tail=r"(?![0-9])"))
            rules.append(signature(label, 80 - n, f"creativecommons.org/licenses/by/{mark.replace(' ', '/')}/{version}".replace("//", "/"), tail=r"(?![0-9])"))
    rules.append(signature("cc0", 65, "cc0"))
    rules.append(signature("cc0", 66, "cc0 1.0"))
    rules.append(signature("cc0", 80, "creativecommons.org/publicdomain/zero/1.0"))
    return sorted(rules, key=lambda r: -r.priority)


class Detection(NamedTuple):
    start: int
    end: int
    label: str
    priority: int


class Scanner:
    """Compiled rules behind the automaton of their keywords; ``gated`` off runs them all."""

    def __init__(self, rules: list[Rule] | None = None, gated: bool = True) -> None:
        import ahocorasick

        self.rules, self.gated = build_rules() if rules is None else rules, gated
        self.compiled: dict[int, re.Pattern] = {}
        by_keyword: dict[str, list[int]] = {}
        for n, rule in enumerate(self.rules):
            by_keyword.setdefault(rule.keyword, []).append(n)
        self.by_keyword = by_keyword
        self.automaton = ahocorasick.Automaton()
        for keyword in by_keyword:
            self.automaton.add_word(keyword, keyword)
        if by_keyword:
            self.automaton.make_automaton()

    def asked(self, lowered: str) -> list[int]:
        """Numbers of the rules that run over a text, in order."""
        if not self.gated or not self.rules:
            return list(range(len(self.rules)))
        seen = {k for _, k in self.automaton.iter(folded(lowered))}
        return sorted(n for k in seen for n in self.by_keyword[k])

    def detections(self, lowered: str) -> list[Detection]:
        """Detections that stand, by place, in a text with A-Z lower-cased."""
        found = []
        for n in self.asked(lowered):
            rule = self.rules[n]
            pattern = self.compiled.get(n) or self.compiled.setdefault(n, re.compile(rule.pattern))
            found += [Detection(m.start(), m.end(), rule.label, rule.priority) for m in pattern.finditer(lowered)]
        return suppressed(found)


def suppressed(found: list[Detection]) -> list[Detection]:
    """Detections without those inside one of higher priority, or inside a longer equal one."""
    kept: list[Detection] = []
    starts: list[int] = []
    furthest: list[int] = []  # running maximum of ends over kept ones by start
    for level in sorted({d.priority for d in found}, reverse=True):
        mine = sorted({d for d in found if d.priority == level}, key=lambda d: (d.start, -d.end, d.label))
        fresh, reach = [], (-1, -1)
        for d in mine:
            i = bisect_left(starts, d.start + 1)
            if i and furthest[i - 1] >= d.end:
                continue
            if reach[1] >= d.end and (d.start, d.end) != reach:
                continue
            fresh.append(d)
            if d.end > reach[1]:
                reach = (d.start, d.end)
        kept = sorted(kept + fresh)
        starts = [d.start for d in kept]
        furthest = np.maximum.accumulate([d.end for d in kept]).tolist() if kept else []
    return kept


_WORD_BYTE = np.zeros(256, dtype=bool)
_WORD_BYTE[48:58] = _WORD_BYTE[97:123] = True
_WORD_BYTE[128:] = True


def count_words(lowered: bytes) -> int:
    """Runs of digits, letters and non-ASCII octets in UTF-8."""
    inside = _WORD_BYTE[np.frombuffer(lowered, dtype=np.uint8)]
    return int(inside[:1].sum() + np.count_nonzero(inside[1:] & ~inside[:-1]))


_WORDS = re.compile(rb"[0-9a-z\x80-\xff]+")
_PHRASE_WORDS = {tuple(p.encode().split()): label for p, label in PHRASES.items()}
_PHRASE_ENDS = sorted({p[-1] for p in _PHRASE_WORDS})


def phrase_places(lowered: bytes) -> list[tuple[int, str]]:
    """(first word's number, label) of every place where a phrase's words stand consecutively."""
    if not any(e in lowered for e in _PHRASE_ENDS):
        return []
    words = _WORDS.findall(lowered)
    places = []
    for phrase, label in _PHRASE_WORDS.items():
        at = -1
        first = phrase[0]
        try:
            while True:
                at = words.index(first, at + 1)
                if tuple(words[at : at + len(phrase)]) == phrase:
                    places.append((at, label))
        except ValueError:
            pass
    return sorted(places)


_RESULT_DDL = (
    "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, "
    "labels string, score double, detections array<struct<start:int,end:int,label:string,priority:int>>"
)


def scan(docs: DataFrame, rules: list[Rule] | None = None) -> DataFrame:
    """Licenses named in every whole text of ``docs`` (doc_id, text, ...).

    (doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, detections):
    detections carry code-point spans; ``score`` is the highest priority found over 100, at
    least 0.4 where a phrase stands, 0 without any. Null texts are empty; repeated rows each
    get a row; other columns are ignored. An empty table gives an empty result.
    """
    kind = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("label", pa.string()), ("priority", pa.int32())]))
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(rules)
        lowering = str.maketrans(upper, lower)
        for batch in batches:
            out: list[list] = [[] for _ in range(8)]
            for text in batch.column(1):
                text = text.as_py()
                octets = text.encode("utf-8", "surrogatepass").lower()
                places = phrase_places(octets)
                found = scanner.detections(text.lower() if text.isascii() else text.translate(lowering))
                base = {label for _, label in places}
                score = max([0.4 if places else 0.0, *(d.priority / 100 for d in found)])
                values = (
                    count_words(octets),
                    len(places),
                    places[0][0] if places else None,
                    places[-1][0] if places else None,
                    ",".join(sorted(base)),
                    ",".join(sorted(base | {d.label for d in found})),
                    score,
                    [d._asdict() for d in found],
                )
                for column, value in zip(out, values):
                    column.append(value)
            kinds = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64(), kind]
            names = ["n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "detections"]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array(c, k) for c, k in zip(out, kinds))], ["doc_id", *names]
            )

    return docs.select(F.col("doc_id").cast("long"), whole().alias("text")).mapInArrow(run, _RESULT_DDL)
