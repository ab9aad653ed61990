"""License scans by sentence rules.

A text is cut into sentences; each is normalised and looked up among known license sentences. The identifiers found, in
order of the text, are matched against ordered rules: a rule is a sequence of identifiers that must follow each other with
at most ``GAP`` unknown sentences between. Rules are tried in their order at each place, and identifiers are used once.
Sentences that name a license (``NAMED``, ``MENTIONS``) and SPDX lines are identifiers with a rule of their own.

A text's units end at full stops and the like before white space and at blank lines; their lines are entries. A license text
may be wrapped over lines, hold sentence ends itself, or follow a line without a full stop, so a known sentence may start
and end with any entry: its words are followed through a tree of the known ones, the longest first, with at most as many
steps as the longest has words. What is left of a unit before, between or after known sentences is one unknown sentence,
however many lines it has. So the time of a scan is in proportion to the text.

Defined results: a sentence holds a letter or digit; a null or empty text has none; repeated rows are reported as often as
they occur; a null doc_id stays null; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusforge.engine import arrow_map, batch

# Public license sentences and their identifiers, in the wording of the licenses.
SENTENCES = {
    "mit-grant": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "mit-notice": "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "mit-warranty": "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT.",
    "apache-header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License.",
    "apache-copy": "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
    "apache-warranty": "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    "gpl-free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "gpl2-free": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    "gpl-warranty": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.",
    "bsd-grant": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "bsd-source": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "bsd-binary": "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "bsd-endorse": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "reserved": "All rights reserved.",
    "isc-grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "isc-warranty": "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS.",
    "mpl2-header": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "mpl2-copy": "If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
    "lgpl21-free": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    "agpl3-free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "unlicense-free": "This is free and unencumbered software released into the public domain.",
    "unlicense-any": "Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "zlib-warranty": "This software is provided 'as-is', without any express or implied warranty.",
    "zlib-grant": "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
    "boost-header": "Distributed under the Boost Software License, Version 1.0.",
    "epl2-header": "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0/",
}
# Names under which texts mention a license, and its identifier.
NAMED = {
    "the MIT License": "MIT", "the Apache License, Version 2.0": "Apache-2.0", "the GNU General Public License, version 3": "GPL-3.0-only", "the GNU General Public License, version 2": "GPL-2.0-only",
    "the GNU Lesser General Public License, version 3": "LGPL-3.0-only", "the GNU Affero General Public License, version 3": "AGPL-3.0-only", "the BSD 2-Clause License": "BSD-2-Clause",
    "the BSD 3-Clause License": "BSD-3-Clause", "the ISC License": "ISC", "the Mozilla Public License, version 2.0": "MPL-2.0", "the Eclipse Public License 2.0": "EPL-2.0", "the Unlicense": "Unlicense",
    "CC0 1.0": "CC0-1.0", "CC BY 4.0": "CC-BY-4.0", "CC BY-SA 4.0": "CC-BY-SA-4.0", "CC BY-NC 4.0": "CC-BY-NC-4.0", "CC BY-NC-SA 4.0": "CC-BY-NC-SA-4.0", "CC BY-ND 4.0": "CC-BY-ND-4.0",
    "a Creative Commons Attribution 4.0 International License": "CC-BY-4.0", "a Creative Commons Attribution-ShareAlike 4.0 International License": "CC-BY-SA-4.0",
    "a Creative Commons Attribution-NonCommercial 4.0 International License": "CC-BY-NC-4.0",
}
# How sentences that name a license begin.
MENTIONS = ("Licensed under", "Released under", "Distributed under", "This work is licensed under", "This project is licensed under", "This software is licensed under")
# Rules in the order in which they are tried.
RULES = (
    ("MIT", ("mit-grant", "mit-notice", "mit-warranty")),
    ("Apache-2.0", ("apache-header", "apache-copy", "apache-warranty")),
    ("Apache-2.0", ("apache-header", "apache-copy")),
    ("GPL-3.0-or-later", ("gpl-free", "gpl-warranty")),
    ("GPL-2.0-or-later", ("gpl2-free", "gpl-warranty")),
    ("BSD-3-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-endorse")),
    ("BSD-2-Clause", ("bsd-grant", "bsd-source", "bsd-binary")),
    ("MIT", ("mit-grant", "mit-notice")),
    ("Apache-2.0", ("apache-header",)),
    ("GPL-3.0-or-later", ("gpl-free",)),
    ("GPL-2.0-or-later", ("gpl2-free",)),
    ("LGPL-2.1-or-later", ("lgpl21-free",)),
    ("AGPL-3.0-or-later", ("agpl3-free", "gpl-warranty")),
    ("AGPL-3.0-or-later", ("agpl3-free",)),
    ("ISC", ("isc-grant", "isc-warranty")),
    ("ISC", ("isc-grant",)),
    ("MPL-2.0", ("mpl2-header", "mpl2-copy")),
    ("MPL-2.0", ("mpl2-header",)),
    ("Unlicense", ("unlicense-free", "unlicense-any")),
    ("Unlicense", ("unlicense-free",)),
    ("Zlib", ("zlib-warranty", "zlib-grant")),
    ("BSL-1.0", ("boost-header",)),
    ("EPL-2.0", ("epl2-header",)),
)
#: Unknown sentences that may stand between two of a rule.
GAP = 2

_END = re.compile(r"(?<=[.!?:;。！？])[ \t]+|(?<=[.!?:;。！？])\n|\n[ \t]*\n")
_WORD = re.compile(r"[^\W_]+")


def words_of(sentence: str) -> list[str]:
    """Words in lower case: letters and digits alone."""
    return _WORD.findall(sentence.lower())


def known_sentences() -> dict[str, list[str]]:
    """Texts of each identifier: the license sentences, mentions of licenses by name, SPDX lines."""
    out = {name: [text] for name, text in SENTENCES.items()}
    for license_name, spdx in NAMED.items():
        out.setdefault(f"named:{spdx}", []).extend(f"{verb} {license_name}." for verb in MENTIONS)
    for spdx in sorted({*NAMED.values(), *(x for x, _ in RULES)}):
        out.setdefault(f"named:{spdx}", []).append(f"SPDX-License-Identifier: {spdx}")
    return out


def known_rules() -> tuple:
    """The ordered rules, then one for each license that may be named."""
    return (*RULES, *((name.partition(":")[2], (name,)) for name in known_sentences() if name.startswith("named:")))


class Recogniser:
    def __init__(self, sentences: dict[str, str | list[str]] | None = None, rules=None, gap: int = GAP):
        sentences = known_sentences() if sentences is None else sentences
        self.rules, self.gap = known_rules() if rules is None else rules, gap
        self.tree: dict = {}
        for name, texts in sentences.items():
            for text in [texts] if isinstance(texts, str) else texts:
                node = self.tree
                for w in words_of(text):
                    node = node.setdefault(w, {})
                node[""] = name
        self.by_first: dict[str, list] = {}
        for license_, rule in self.rules:
            self.by_first.setdefault(rule[0], []).append((license_, rule))

    def _known(self, entries: list[tuple[int, str]], cut: dict[int, list[str]], at: int) -> tuple[str, int] | None:
        """The longest known sentence that starts at an entry, and the entry after it."""
        node, found, i = self.tree, None, at
        while i < len(entries):
            if i not in cut:
                cut[i] = words_of(entries[i][1])
            words = cut[i]
            if i == at and len(words) > 1 and words[0].isdigit():
                words = words[1:]  # the number of a list
            for w in words:
                node = node.get(w)
                if node is None:
                    return found
            i += 1
            if "" in node:
                found = node[""], i
        return found

    def sentences(self, text: str | None) -> list[str | None]:
        """Identifiers of the sentences in order; ``None`` for unknown ones."""
        entries = [(k, line) for k, unit in enumerate(_END.split(text or "")) for line in unit.split("\n") if _WORD.search(line)]
        out: list[str | None] = []
        cut: dict[int, list[str]] = {}
        at, unknown = 0, -1
        while at < len(entries):
            unit, line = entries[at]
            first = _WORD.search(line)[0].lower()
            hit = self._known(entries, cut, at) if first in self.tree or first.isdigit() else None
            if hit is not None:
                out.append(hit[0])
                at, unknown = hit[1], -1
                continue
            if unknown != unit:
                out.append(None)
                unknown = unit
            at += 1
        return out

    def licenses(self, ids: list[str | None]) -> list[str]:
        """Rules that match, in order of the text."""
        found, used = [], set()
        for i, name in enumerate(ids):
            if name is None or i in used:
                continue
            for license_, rule in self.by_first.get(name, ()):
                if (taken := self._match(ids, i, rule, used)) is not None:
                    found.append(license_)
                    used.update(taken)
                    break
        return found

    def _match(self, ids, i: int, rule, used) -> list[int] | None:
        if ids[i] != rule[0]:
            return None
        taken = [i]
        for want in rule[1:]:
            j = taken[-1] + 1
            while j < len(ids) and ids[j] is None and j - taken[-1] <= self.gap:
                j += 1
            if j >= len(ids) or ids[j] != want or j in used:
                return None
            taken.append(j)
        return taken


def _scan(batches):
    r = Recogniser()
    for rows in batches:
        known, licenses, total = [], [], []
        for text in rows.column(1).to_pylist():
            ids = r.sentences(text)
            total.append(len(ids))
            known.append([x for x in ids if x is not None])
            licenses.append(r.licenses(ids) if known[-1] else [])
        yield batch(
            doc_id=rows.column(0), n_sentences=pa.array(total, pa.int64()), sentence_ids=pa.array(known, pa.list_(pa.string())), licenses=pa.array(licenses, pa.list_(pa.string()))
        )


def scan(docs: DataFrame) -> DataFrame:
    """(doc_id, n_sentences, sentence_ids, licenses) of every document."""
    source = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return arrow_map(source, _scan, "doc_id long, n_sentences long, sentence_ids array<string>, licenses array<string>")
