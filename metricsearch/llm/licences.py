"""Licence scans by sentence rules: sentences are named first, then the order of their names is matched.

A text is cut into pieces, each is normalised (lower case, words and version numbers only) and looked up among known
licence sentences; what is not known has no name. Line breaks, comment signs and semicolons may stand inside a sentence,
so a known sentence may take several adjacent pieces, up to a full stop or a blank line. The names found, in order, are
matched against ordered rules: a rule is a sequence of names, and the first rule that fits at a place, the longest
first, takes its sentences.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

# Patterns of normalised sentences of public licences and notices, by the name of the sentence.
SENTENCES = {
    "apache2": r"(?:this (?:work|file|software|project|code) is )?(?:licensed|released|distributed) under (?:the terms of )?the apache (?:software )?licen[sc]e,? (?:version |v)?2(?:\.0)?(?: the license)?",
    "apache2-short": r"(?:spdx-license-identifier |license )apache-2\.0",
    "apache-comply": r"you may not use this file except in compliance with the license",
    "apache-copy": r"you may obtain a copy of the license at.*",
    "apache-asis": r"unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis.*",
    "apache-see": r"see the license for the specific language governing permissions and limitations under the license",
    "mit": r"(?:this (?:work|file|software|project|code) is )?(?:released|licensed|distributed) under (?:the terms of )?the mit licen[sc]e",
    "mit-short": r"(?:spdx-license-identifier |license )mit",
    "mit-grant": r"permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files.*",
    "mit-notice": r"the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    "asis": r"(?:the|this) software is provided as is without warranty of any kind.*",
    "no-liability": r"in no event shall the (?:authors|copyright holders|copyright owner|author|regents).* be liable.*",
    "isc-grant": r"permission to use copy modify and(?: or)? distribute this software for any purpose with or without fee is hereby granted.*",
    "bsd-grant": r"redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    "bsd-source": r"(?:1 )?redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    "bsd-binary": r"(?:2 )?redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer.*",
    "bsd-names": r"(?:3 )?neither the name.* nor the names of its contributors may be used to endorse or promote products.*",
    "bsd-asis": r"this software is provided by the (?:copyright holders and contributors|author|regents and contributors) as is.*",
    "bsd": r"(?:this (?:work|file|software|project|code) is )?(?:released|licensed|distributed) under (?:the terms of )?(?:the|a) (?P<variant>[23])-clause bsd licen[sc]e",
    "gpl": r"this (?:work|file|software|program|project) is (?:licensed|released|distributed) under (?:the terms of )?the gnu general public licen[sc]e,? (?:version |v)(?P<version>[123])(?:\.0)?(?P<later> or (?:at your option )?any later version| or later)?",
    "gpl-free": r"this (?:program|file|library) is free software you can redistribute it and(?: or)? modify it under the terms of the gnu general public license as published by the free software foundation either version (?P<version>[123]) of the license or at your option any later version",
    "lgpl": r"(?:this (?:work|file|software|library|project) is )?(?:licensed|released|distributed) under (?:the terms of )?the gnu (?:lesser|library) general public licen[sc]e,? (?:version |v)(?P<version>[23](?:\.[01])?)(?P<later> or (?:at your option )?any later version| or later)?",
    "lgpl-free": r"this (?:program|file|library|software) is free software you can redistribute it and(?: or)? modify it under the terms of the gnu (?:lesser|library) general public license as published by the free software foundation either version (?P<version>[23](?:\.[01])?) of the license or at your option any later version",
    "agpl-free": r"this (?:program|file|library|software) is free software you can redistribute it and(?: or)? modify it under the terms of the gnu affero general public license as published by the free software foundation either version (?P<version>[13]) of the license or at your option any later version",
    "agpl": r"(?:this (?:work|file|software|program|project) is )?(?:licensed|released|distributed) under (?:the terms of )?the gnu affero general public licen[sc]e,? (?:version |v)(?P<version>[13])(?P<later> or (?:at your option )?any later version| or later)?",
    "mpl": r"(?:this (?:work|file|software|project|source code form) is )?(?:licensed|released|distributed|subject)(?: under| to) the terms of the mozilla public licen[sc]e,? (?:version |v) ?(?P<version>[12]\.[01])",
    "cc": r"(?:this (?:work|file|text|article) is )?(?:licensed|released|distributed) under (?:a |the )?(?:cc|creative commons) (?P<kind>by(?:-nc)?(?:-sa|-nd)?)(?: licen[sc]e)? (?P<version>[1-4]\.[05])(?: international| licen[sc]e)*",
    "cc0": r"(?:to the extent possible under law.*|(?=.* cc0)[^\x1f]*(?:licensed|released|dedicated).* cc0(?: 1\.0)?(?: universal)?.*)",
    "spdx": r"spdx-license-identifier (?P<id>[\w.+-]+(?: (?:or|and|with) [\w.+-]+)*)",
    "public-domain": r"this (?:work|file|software) (?:is|has been placed) in the public domain",
    "rights": r"all rights reserved",
}

# Rules in order, a licence and the names of its sentences. Braces take what the first sentence names.
RULES = (
    ("Apache-2.0", ("apache2", "apache-comply", "apache-copy", "apache-asis", "apache-see")),
    ("MIT", ("mit-grant", "mit-notice", "asis", "no-liability")),
    ("MIT", ("mit-grant", "mit-notice", "asis")),
    ("MIT", ("mit-grant", "mit-notice")),
    ("BSD-3-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-names")),
    ("BSD-2-Clause", ("bsd-grant", "bsd-source", "bsd-binary")),
    ("ISC", ("isc-grant", "asis")),
    ("ISC", ("isc-grant",)),
    ("Apache-2.0", ("apache2",)),
    ("Apache-2.0", ("apache2-short",)),
    ("MIT", ("mit",)),
    ("MIT", ("mit-short",)),
    ("BSD-{variant}-Clause", ("bsd",)),
    ("GPL-{version}.0{later}", ("gpl",)),
    ("GPL-{version}.0-or-later", ("gpl-free",)),
    ("LGPL-{version}{later}", ("lgpl",)),
    ("LGPL-{version}-or-later", ("lgpl-free",)),
    ("AGPL-{version}.0{later}", ("agpl",)),
    ("AGPL-{version}.0-or-later", ("agpl-free",)),
    ("MPL-{version}", ("mpl",)),
    ("CC-{kind}-{version}", ("cc",)),
    ("CC0-1.0", ("cc0",)),
    ("{id}", ("spdx",)),
    ("public-domain", ("public-domain",)),
    ("proprietary", ("rights",)),
)

_SOFT = "\x1f"  # stands between normalised pieces that may be one sentence
_KNOWN = [(name, regex.compile(f"(?:{pattern.replace('.*', '.*?').replace(' ', f'[ {_SOFT}]')})(?={_SOFT}|\\Z)")) for name, pattern in SENTENCES.items()]
_WORTH = regex.compile(r"licen[sc]|permission|redistribut|warrant|copyright|liable|spdx|public\W+domain|all\W+rights|apache|extent\W+possible|cc0|neither\W+the\W+name|provided\W+(?:as|by)", regex.I)
_BARE = regex.compile(r"^[ \t]*+(?:[*#/;%!<>=~|_-]++|dnl|rem)[ \t\r]*+$", regex.M | regex.I)  # lines of comment signs are blank lines
_LEADER = regex.compile(r"^[ \t]*+(?:dnl|rem)(?=[ \t])", regex.M | regex.I)  # comment signs that are words
_CUT = regex.compile(r"(?<=[.!?;])\s+|\n\s*\n|\n(?=[A-Z0-9*#/-])|\n(?=[ \t]*+(?:[*#/;%!A-Z0-9]|--|<!--))")
_ENDS = regex.compile(r"(?<![^\W\d_])v\.$|;$", regex.I)  # what looks like an end and may stand inside a sentence
_DROP = regex.compile(r"[^a-z0-9.+\- ]+")
_OWNER = regex.compile(r"^(?:copyright )?(?:\(c\)|©|copyright)?[^.]*?\b(?:19|20)\d\d[^.]*$")


def normalise(sentence: str) -> str:
    """Lower-case words and numbers with single spaces; comment signs, quotes and final points go."""
    s = _DROP.sub(" ", sentence.lower())
    return " ".join(x.strip(".") if not x[:1].isdigit() else x.rstrip(".") for x in s.split() if x.strip(".-+"))


def _sentences(text: str) -> Iterator[tuple[int, list[str]]]:
    """(place of the first, pieces) of each stretch of pieces between full stops and blank lines."""
    text = _LEADER.sub("#", _BARE.sub("", text))
    pieces: list[str] = []
    at = place = 0
    for cut in _CUT.finditer(text):
        pieces.append(text[at : cut.start()])
        at = cut.end()
        if cut[0].count("\n") > 1 or (pieces[-1].endswith((".", "!", "?")) and not _ENDS.search(pieces[-1][-3:])):
            yield place, pieces
            place, pieces = place + len(pieces), []
    yield place, [*pieces, text[at:]]


def name_sentences(text: str) -> list[tuple[int, str, dict[str, str]]]:
    """(place, name, named parts) of the known sentences of a text, in order; the place is that of the first piece."""
    out = []
    for first, pieces in _sentences(text):
        if not _WORTH.search(" ".join(pieces)):
            continue
        plain = [(place, x) for place, raw in enumerate(pieces, first) if (x := normalise(raw))]
        joined, at, free = _SOFT.join(x for _, x in plain), 0, 0
        for place, x in plain:
            if at >= free:
                for name, pattern in _KNOWN:
                    if m := pattern.match(joined, at):
                        out.append((place, name, {k: v.replace(_SOFT, " ") if v else "" for k, v in m.groupdict().items()}))
                        free = m.end()
                        break
            at += len(x) + 1
    return out


def match_rules(found: list[tuple[int, str, dict[str, str]]]) -> list[tuple[str, int]]:
    """(licence, place of its first sentence): at each name, the longest rule that fits; equal ones by their order."""
    names, out, i = [x[1] for x in found], [], 0
    while i < len(names):
        fits = [(licence, seq) for licence, seq in RULES if tuple(names[i : i + len(seq)]) == seq]
        if not fits:
            i += 1
            continue
        licence, seq = max(fits, key=lambda x: len(x[1]))
        if licence.startswith("LGPL") and "." not in found[i][2]["version"]:
            licence = licence.replace("{version}", "{version}.0")
        parts = {k: ("-or-later" if v else "-only") if k == "later" else v.upper() if k == "kind" else v for k, v in found[i][2].items()}
        out.append((licence.format(**parts), found[i][0]))
        i += len(seq)
    return out


def scan_text(text: str | None) -> tuple[list[str], list[int], list[str]]:
    """Licences in order of appearance, the sentence each begins at, and the names of all known sentences."""
    if not text or not _WORTH.search(text):
        return [], [], []
    found = name_sentences(text)
    hits = match_rules(found)
    return [x for x, _ in hits], [y for _, y in hits], [x[1] for x in found]


def scan(docs: DataFrame) -> DataFrame:
    """(doc_id, licences, places, sentences) of every row of ``docs`` (doc_id, text; other columns are left out).

    ``licences`` in order of appearance, repeats included; null, empty and other texts have empty lists. Texts are
    scanned whole. Repeated rows come out each. No row is shuffled.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [scan_text(x) for x in batch["text"].to_pylist()]
            kinds = [pa.list_(pa.string()), pa.list_(pa.int32()), pa.list_(pa.string())]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], *(pa.array([r[i] for r in rows], kinds[i]) for i in range(3))], ["doc_id", "licences", "places", "sentences"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, licences array<string>, places array<int>, sentences array<string>")
