"""Licence recognition by sentence rules.

Known licence sentences are looked up word by word in a tree of the table, over the lines of a paragraph, from where a
sentence may start to where one may end. They are mapped to identifiers, and a document's sequence of identifiers is matched
against ordered rules. The knowledge is two small tables, so documents are scanned once where they lie.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilgrid.llm.common import text_slices

#: A sentence ends at marks before white space and may end at a new line: a known one goes on over the lines of its paragraph.
SENTENCE_END = r"[.!?]+(?:[ \t\x0b\x0c\r\n]+|$)|\n+"
#: Where a known sentence may also end, and the next one start, within a sentence: notices on one line have no other mark there.
CLAUSE_END = r"[;:][\"')\]]*[ \t\x0b\x0c\r]+"
#: A copyright line on one line with its notice: any word with a capital after it may start a sentence.
COPYRIGHT = r"(?:copyright|\(c\)|©)[^a-z0-9]*(?:\(c\)[^a-z0-9]*)?(?:[0-9]{4}|year|yyyy)"

#: Words whose full stop ends no sentence.
ABBREVIATIONS = ("v",)
#: Most words that a slot in a known sentence takes.
SLOT_WORDS = 20
SLOT = "{}"

#: Known licence sentences, normalised, and their identifiers; {} is a slot for a name.
SENTENCES = {
    "released under the mit license": "mit-note",
    "licensed under the mit license": "mit-note",
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction": "mit-grant",
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions": "mit-grant",
    "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software": "mit-notice",
    "the software is provided as is without warranty of any kind express or implied": "as-is",
    "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement": "as-is",
    "licensed under the apache license version 2 0": "apache-note",
    "licensed under the apache license version 2 0 the license": "apache-note",
    "you may not use this file except in compliance with the license": "apache-terms",
    "you may obtain a copy of the license at": "apache-copy",
    "this work is licensed under the gnu general public license version 3": "gpl3-note",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation": "gpl-free",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version": "gpl-free",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version": "gpl-free",
    "this work is licensed under the gnu general public license version 2": "gpl2-note",
    "licensed under cc by nc 4 0": "by-nc-note",
    "licensed under cc by 4 0": "by-note",
    "licensed under cc by sa 4 0": "by-sa-note",
    "all rights reserved": "reserved",
    "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met": "bsd-grant",
    "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer": "bsd-source",
    "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution": "bsd-binary",
    "neither the name of {} nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission": "bsd-names",
    "neither the name of {} nor the names of {} may be used to endorse or promote products derived from this software without specific prior written permission": "bsd-names",
    "this software is provided by {} as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed": "bsd-disclaimer",
    "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies": "isc-grant",
    "permission to use copy modify and distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies": "isc-grant",
    "the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness": "isc-disclaimer",
    "the software is provided as is and {} disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness": "isc-disclaimer",
    "this source code form is subject to the terms of the mozilla public license v 2 0": "mpl-terms",
    "if a copy of the mpl was not distributed with this file you can obtain one at": "mpl-copy",
    "if a copy of the mpl was not distributed with this file you can obtain one at https mozilla org mpl 2 0": "mpl-copy",
    "if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0": "mpl-copy",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license version 2 as published by the free software foundation": "gpl2-only",
    "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2 1 of the license or at your option any later version": "lgpl21-free",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version": "lgpl3-free",
    "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version": "lgpl3-free",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version": "agpl3-free",
}

#: Licences that a line "SPDX-License-Identifier:" may name.
SPDX = ("0BSD", "AGPL-3.0-only", "AGPL-3.0-or-later", "Apache-2.0", "BSD-2-Clause", "BSD-3-Clause", "BSL-1.0", "CC-BY-4.0", "CC-BY-SA-4.0", "CC0-1.0", "EPL-2.0", "GPL-2.0", "GPL-2.0-only", "GPL-2.0-or-later", "GPL-3.0", "GPL-3.0-only", "GPL-3.0-or-later", "ISC", "LGPL-2.1-only", "LGPL-2.1-or-later", "LGPL-3.0-only", "LGPL-3.0-or-later", "MIT", "MPL-2.0", "Unlicense", "Zlib")

#: Fixed values: (rule, licence, identifiers in the order they must follow each other among the known sentences).
RULES = (
    ("apache-header", "Apache-2.0", ("apache-note", "apache-terms", "apache-copy")),
    ("apache-line", "Apache-2.0", ("apache-note",)),
    ("by-line", "CC-BY-4.0", ("by-note",)),
    ("by-nc-line", "CC-BY-NC-4.0", ("by-nc-note",)),
    ("by-sa-line", "CC-BY-SA-4.0", ("by-sa-note",)),
    ("gpl2-line", "GPL-2.0", ("gpl2-note",)),
    ("gpl3-line", "GPL-3.0", ("gpl3-note",)),
    ("gpl-text", "GPL", ("gpl-free",)),
    ("mit-text", "MIT", ("mit-grant", "mit-notice", "as-is")),
    ("mit-line", "MIT", ("mit-note",)),
    ("reserved-line", "Proprietary", ("reserved",)),
    ("bsd3-text", "BSD-3-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-names", "bsd-disclaimer")),
    ("bsd2-text", "BSD-2-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-disclaimer")),
    ("isc-text", "ISC", ("isc-grant", "isc-disclaimer")),
    ("mpl-header", "MPL-2.0", ("mpl-terms", "mpl-copy")),
    ("mpl-line", "MPL-2.0", ("mpl-terms",)),
    ("gpl2-only-text", "GPL-2.0-only", ("gpl2-only",)),
    ("lgpl21-text", "LGPL-2.1-or-later", ("lgpl21-free",)),
    ("lgpl3-text", "LGPL-3.0-or-later", ("lgpl3-free",)),
    ("agpl3-text", "AGPL-3.0-or-later", ("agpl3-free",)),
)

FOUND = "doc_id long, license string, rule string, first_sentence int, last_sentence int, sentence_ids string, matched string"


@dataclass(frozen=True)
class Match:
    license: str
    rule: str
    first: int
    last: int
    ids: tuple[str, ...]
    text: str


def normalise(sentence: str) -> str:
    """Letters a-z and digits after lower-casing A-Z; anything else becomes one space."""
    return re.sub("[^a-z0-9]+", " ", sentence.translate(_LOWER)).strip(" ")


_LOWER = {k: k + 32 for k in range(65, 91)}


def spdx_sentence(name: str) -> str:
    return "spdx license identifier " + normalise(name)


def known_tables(sentences=SENTENCES, rules=RULES, spdx=SPDX):
    """(sentences, rules) with one of each for every identifier line."""
    return dict(sentences) | {spdx_sentence(x): f"spdx {x}" for x in spdx}, (*rules, *(("spdx-line", x, (f"spdx {x}",)) for x in spdx))


def gate_words(sentences) -> list[str]:
    """A few words such that every known sentence has one of them: a text without any is not looked at closer."""
    left, out = [{w for w in s.split() if w != SLOT and len(w) > 5} or set(s.split()) for s in sentences], []
    while left:
        out.append(max(sorted({w for s in left for w in s}), key=lambda w: sum(w in s for s in left)))
        left = [s for s in left if out[-1] not in s]
    return out


def scanner(sentences=SENTENCES, rules=RULES, spdx=SPDX):
    """A function of one text that lists its matches: left to right, the longest sentence and rule that fit, without overlap."""
    sentences, rules = known_tables(sentences, rules, spdx)
    cut, clause, copyright_line = re.compile(SENTENCE_END), re.compile(CLAUSE_END), re.compile(COPYRIGHT, re.IGNORECASE)
    word = re.compile("([A-Za-z0-9]+)([^A-Za-z0-9]*)")
    ordered = sorted(rules, key=lambda r: (-len(r[2]), r[0]))
    tree: dict = {}
    for sentence, name in sentences.items():
        node = tree
        for w in sentence.split():
            node = node.setdefault(w, {})
        node[""] = name
    gates = gate_words(sentences)
    starts = sorted({"[^A-Za-z0-9]+".join(s.split()[:2]) for s in sentences})
    hint = re.compile(f"(?<![A-Za-z0-9])(?=(?:{'|'.join(starts)})(?![A-Za-z0-9]))", re.IGNORECASE | re.ASCII)

    def step(states: list[tuple[dict, int]], w: str) -> list[tuple[dict, int]]:
        """Nodes after one more word, with the words that their open slot has taken (0: none is open); full words first."""
        out = [(node[w], 0) for node, _ in states if w in node]
        for node, taken in states:
            if SLOT in node:
                out.append((node[SLOT], 1))
            if 0 < taken < SLOT_WORDS:
                out.append((node, taken + 1))
        return out

    def opening(text: str, at: int, first: int) -> int | None:
        """Where the text of a sentence whose first word is at ``at`` starts; None if none may start there. Its piece starts at ``first``."""
        left = at
        while left > first and not (text[left - 1].isascii() and text[left - 1].isalnum()):
            left -= 1
        if left == first:
            return first
        if ends := list(clause.finditer(text, left, at)):
            return ends[-1].end()
        return at if text[at - 1].isspace() and text[at].isupper() and copyright_line.search(text, first, at) else None

    def known_at(text: str, at: int) -> tuple[str, int, int] | None:
        """The longest known sentence from ``at``: identifier, start of its last word, end of its text."""
        found, states, m = None, [(tree, 0)], word.match(text, at)
        while m and (states := step(states, normalise(m[1]))):
            gap = m[2] if m.end() == len(text) else m[2] + "x"  # the next word follows: no mark stands at the end
            ends = [] if m[1].lower() in ABBREVIATIONS and gap.startswith(".") else list(cut.finditer(gap))
            if node := next((n for n, taken in states if "" in n and not taken), None):
                stop = ends[0].start() if ends else len(m[2]) if m.end() == len(text) else None
                if stop is None and (c := clause.search(m[2])):
                    stop = c.start()
                elif stop is None and m[2][-1] in " \t<(" and text[m.end() : m.end() + 8].lower().startswith(("http://", "https://")):
                    stop = 0
                if stop is not None:
                    found = (node[""], m.start(), m.start(2) + stop)
            if m[2].count("\n") > 1 or any(e[0][0] != "\n" for e in ends):
                break
            m = word.match(text, m.end())
        return found

    def scan(text: str | None) -> list[Match]:
        if not text or not any(map(text.lower().__contains__, gates)) or not (places := [m.start() for m in hint.finditer(text)]):
            return []
        pieces, known, end = [0, *(m.end() for m in cut.finditer(text))], [], 0
        number = lambda at: bisect_right(pieces, at) - 1
        for at in places:
            if at >= end and (start := opening(text, at, pieces[number(at)])) is not None and (hit := known_at(text, at)):
                name, last, end = hit
                known.append((number(at), number(last), name, text[start:end]))
        out, k = [], 0
        while k < len(known):
            for rule, licence, ids in ordered:
                run = known[k : k + len(ids)]
                if tuple(x[2] for x in run) == ids:
                    out.append(Match(licence, rule, run[0][0], run[-1][1], ids, " ".join(x[3].strip() for x in run)))
                    k += len(ids) - 1
                    break
            k += 1
        return out

    return scan


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", sentences=SENTENCES, rules=RULES, spdx=SPDX) -> DataFrame:
    """One row per match: licence, rule, sentence numbers (from 0; each line of a wrapped sentence counts), identifiers and the sentences matched.

    Whole texts are read. Null, empty and licence-free texts give no row; a licence stated twice gives two rows, repeated rows
    repeat theirs, a null doc_id is kept as null, an empty table gives no rows, other columns aren't read.
    """
    scan = scanner(sentences, rules, spdx)
    names = [x.split()[0] for x in FOUND.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in text_slices(batches):
            rows = [(i, m.license, m.rule, m.first, m.last, " ".join(m.ids), m.text) for i, t in zip(part.column(0).to_pylist(), texts, strict=True) for m in scan(t)]
            types = [pa.int64(), pa.string(), pa.string(), pa.int32(), pa.int32(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], type=t) for k, t in enumerate(types)], names=names)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, FOUND)
