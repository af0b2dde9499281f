"""Licence scan by sentence rules: normalised sentences become known sentence ids, id sequences match ordered rules.

A sentence is what stands between full stops, question or exclamation marks before white space, or line ends. A line that
ends within a sentence goes on in the next ones, so a phrase may run over line ends of a paragraph (up to an empty line); it
belongs to the line in which it begins and its span ends where the line does in which it ends. It is normalised to
lower-case ASCII words and digits with single blanks (a plus sign after a version reads "or later"); a sentence id is given
where one of its phrases stands in it as whole words. The ids of a document, in order of place, are matched against the
rules: longer rules first, each id used once, other sentences allowed between a rule's ids up to `GAP`. A start whose
sequence breaks off gives way to the next one. An SPDX tag is a sentence by itself: each licence of its expression is
reported (operators and exceptions are not), known ones in their usual spelling, GNU ones without a suffix as "only".
Null or empty text: no licence. Repeated rows are equal; licences that begin at the same place are in alphabetical order.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutstream.llm.common import batched

#: Names of the GNU licences, normalised; each has an "only" and an "or later" identifier.
GNU = {
    "GPL-2.0": ("gnu general public license version 2", "gnu gpl version 2", "gpl version 2", "gplv2", "gpl v2", "gpl 2 0"),
    "GPL-3.0": ("gnu general public license version 3", "gnu gpl version 3", "gpl version 3", "gplv3", "gpl v3", "gpl 3 0"),
    "LGPL-2.1": ("gnu lesser general public license version 2 1", "lgpl version 2 1", "lgplv2 1", "lgpl 2 1"),
    "LGPL-3.0": ("gnu lesser general public license version 3", "lgpl version 3", "lgplv3", "lgpl 3 0"),
    "AGPL-3.0": ("gnu affero general public license version 3", "agpl version 3", "agplv3", "agpl 3 0"),
}
_LATER = ("or later", "or any later version", "or at your option any later version")
#: Licence identifiers and the names that a grant sentence may give them, normalised.
NAMES = {
    "Apache-2.0": ("apache license version 2 0", "apache license 2 0", "apache software license 2 0", "apache 2 0", "apache 2"),
    "MIT": ("mit license", "mit licence", "expat license"),
    "BSD-2-Clause": ("bsd 2 clause", "simplified bsd license", "two clause bsd"),
    "BSD-3-Clause": ("bsd 3 clause", "new bsd license", "revised bsd license", "three clause bsd"),
    "MPL-2.0": ("mozilla public license version 2 0", "mozilla public license 2 0", "mpl 2 0"),
    "EPL-2.0": ("eclipse public license version 2 0", "eclipse public license 2 0", "epl 2 0"),
    "CDDL-1.0": ("common development and distribution license version 1 0", "cddl 1 0"),
    "Artistic-2.0": ("artistic license 2 0", "artistic 2 0"),
    "BSL-1.0": ("boost software license version 1 0", "boost software license 1 0"),
    "Zlib": ("zlib license",),
    "ISC": ("isc license", "isc licence"),
    "Unlicense": ("the unlicense",),
    "CC0-1.0": ("cc0 1 0", "cc0"),
    "CC-BY-NC-ND-4.0": ("cc by nc nd 4 0", "creative commons attribution noncommercial noderivatives 4 0"),
    "CC-BY-NC-SA-4.0": ("cc by nc sa 4 0", "creative commons attribution noncommercial sharealike 4 0"),
    "CC-BY-NC-4.0": ("cc by nc 4 0", "creative commons attribution noncommercial 4 0"),
    "CC-BY-SA-4.0": ("cc by sa 4 0", "creative commons attribution sharealike 4 0"),
    "CC-BY-ND-4.0": ("cc by nd 4 0", "creative commons attribution noderivatives 4 0"),
    "CC-BY-4.0": ("cc by 4 0", "creative commons attribution 4 0"),
    **{f"{k}-only": names for k, names in GNU.items()},
    **{f"{k}-or-later": tuple(f"{n} {x}" for n in names for x in _LATER) for k, names in GNU.items()},
}
#: Other sentences of licence texts, by id.
SENTENCES = {
    "apache-comply": ("you may not use this file except in compliance with the license",),
    "apache-copy": ("you may obtain a copy of the license at",),
    "apache-as-is": ("distributed on an as is basis without warranties or conditions of any kind",),
    "mit-permission": ("permission is hereby granted free of charge to any person obtaining a copy",),
    "mit-notice": ("permission notice shall be included in all copies or substantial portions",),
    "boost-permission": ("permission is hereby granted free of charge to any person or organization obtaining a copy",),
    "as-is": ("is provided as is without warranty of any kind", "are provided as is without warranty of any kind", "is provided as is and the author disclaims all warranties"),
    "isc-permission": ("permission to use copy modify and or distribute this software for any purpose",),
    "zlib-permission": ("permission is granted to anyone to use this software for any purpose including commercial applications",),
    "zlib-origin": ("the origin of this software must not be misrepresented",),
    "zlib-altered": ("altered source versions must be plainly marked as such",),
    "bsd-permission": ("redistribution and use in source and binary forms with or without modification are permitted",),
    "bsd-source": ("redistributions of source code must retain the above copyright notice",),
    "bsd-binary": ("redistributions in binary form must reproduce the above copyright notice",),
    "bsd-names": ("may be used to endorse or promote products derived from",),
    "bsd-as-is": ("provided by the copyright holders and contributors as is",),
    "gpl-redistribute": ("redistribute it and or modify it under the terms of the gnu general public license",),
    "lgpl-redistribute": ("redistribute it and or modify it under the terms of the gnu lesser general public license",),
    "agpl-redistribute": ("redistribute it and or modify it under the terms of the gnu affero general public license",),
    "version-2-or-later": ("either version 2 of the license or at your option any later version", "either version 2 of the license or any later version"),
    "version-2.1-or-later": ("either version 2 1 of the license or at your option any later version", "either version 2 1 of the license or any later version"),
    "version-3-or-later": ("either version 3 of the license or at your option any later version", "either version 3 of the license or any later version"),
    "version-2": ("free software foundation version 2 of the license", "free software foundation version 2"),
    "version-3": ("free software foundation version 3 of the license", "free software foundation version 3"),
    "or-later": ("or at your option any later version", "or any later version"),
    "in-hope": ("in the hope that it will be useful but without any warranty",),
    "free-and-unencumbered": ("this is free and unencumbered software",),
    "reserved": ("all rights reserved",),
    "public-domain": ("released into the public domain", "dedicated to the public domain"),
}
#: Verbs of a grant sentence.
VERBS = ("licensed under", "licenced under", "released under", "distributed under", "available under", "provided under", "published under", "covered by")
FILLER = r"(?: the)?(?: terms of)?(?: the| a)?"
#: Ordered rules: identifier and the sequence of sentence ids; grants come from NAMES.
RULES: list[tuple[str, tuple[str, ...]]] = [
    ("BSD-3-Clause", ("bsd-permission", "bsd-source", "bsd-binary", "bsd-names", "bsd-as-is")),
    ("BSD-3-Clause", ("bsd-permission", "bsd-source", "bsd-binary", "bsd-names")),
    ("BSD-2-Clause", ("bsd-permission", "bsd-source", "bsd-binary", "bsd-as-is")),
    ("BSD-2-Clause", ("bsd-permission", "bsd-source", "bsd-binary")),
    ("Apache-2.0", ("grant:Apache-2.0", "apache-comply", "apache-copy", "apache-as-is")),
    ("Apache-2.0", ("grant:Apache-2.0", "apache-comply")),
    ("Zlib", ("zlib-permission", "zlib-origin", "zlib-altered")),
    ("MIT", ("mit-permission", "mit-notice", "as-is")),
    ("MIT", ("mit-permission", "mit-notice")),
    ("ISC", ("isc-permission", "as-is")),
    ("Unlicense", ("free-and-unencumbered", "public-domain")),
    *((f"{family}-{v}{tail}", (f"{family.lower()}-redistribute", f"version-{short}{later}", *hope)) for family, v, short in (("GPL", "2.0", "2"), ("GPL", "3.0", "3"), ("LGPL", "2.1", "2.1"), ("LGPL", "3.0", "3"), ("AGPL", "3.0", "3")) for tail, later in (("-or-later", "-or-later"), ("-only", "")) for hope in (("in-hope",), ())),
    *((f"{k}-or-later", (f"grant:{k}-only", "or-later")) for k in GNU),
    ("MIT", ("mit-permission",)),
    ("ISC", ("isc-permission",)),
    ("BSL-1.0", ("boost-permission",)),
    *((k, (f"grant:{k}",)) for k in NAMES),
    ("LicenseRef-public-domain", ("public-domain",)),
    ("LicenseRef-proprietary", ("reserved",)),
]
_ORDERED = sorted(RULES, key=lambda r: -len(r[1]))
GAP = 6
_WRAP = re.compile(r"\r\n?|\n")
_SPLIT = re.compile(r"[.!?]+(?=\s|$)|[\r\n]+")
_OTHER = re.compile(r"[^a-z0-9]+")
_PLUS = re.compile(r"(?<=[0-9])\+")
_SPDX = re.compile(r"SPDX-License-Identifier:[ \t]*([^\r\n]*)", re.IGNORECASE | re.ASCII)
_TOKEN = re.compile(r"[A-Za-z0-9][A-Za-z0-9.+-]*")
_GRANT = re.compile(r"\b(?:" + "|".join(VERBS) + ")" + FILLER + r" (" + "|".join(sorted((n for names in NAMES.values() for n in names), key=len, reverse=True)) + r")\b")
_OF_NAME = {n: k for k, names in NAMES.items() for n in names}
_SPELLING = {k.lower(): k for k in NAMES}
_PHRASES = [(re.compile(r"\b(?:" + "|".join(p) + r")\b"), k) for k, p in SENTENCES.items()]
#: What stands in every phrase and before every granted name: the longest word of each, so nothing known is passed over.
_QUICK = re.compile("|".join(sorted({max(p.split(), key=len) for p in (*VERBS, *(x for xs in SENTENCES.values() for x in xs))})), re.IGNORECASE | re.ASCII)


def spdx_licences(expression: str) -> list[str]:
    """The licences of an SPDX expression, in order."""
    out, skip = [], False
    for word in _TOKEN.findall(expression):
        if skip or word.upper() in ("AND", "OR", "WITH"):
            skip = word.upper() == "WITH"
            continue
        later, word = word.endswith("+"), word.rstrip("+.")
        low = word.lower()
        if low.upper() in GNU:
            word = low.upper() + ("-or-later" if later else "-only")
        out.append(_SPELLING.get(word.lower(), word))
        if word.lower() not in _SPELLING and not re.search(r"[0-9-]", word) and len(out) > 1:
            out.pop()  # a word of prose after the expression
    return out


def sentence_ids(text: str) -> list[tuple[int, int, int, str]]:
    """(sentence number, start, end, id) of the recognised sentences, in order."""
    if not _QUICK.search(text):
        return []
    out: list[tuple[int, int, int, str]] = []
    tags = [(m.start(), m.end(), name) for m in _SPDX.finditer(text) for name in spdx_licences(m.group(1))]
    held: list[tuple[int, int, int]] = []  # number, start, end of the lines of one sentence
    at, number = 0, 0
    for m in [*_SPLIT.finditer(text), None]:
        end = m.start() if m else len(text)
        blank = not text[at:end].strip()
        if not blank:
            held.append((number, at, end))
        if held and (blank or not (m and _WRAP.fullmatch(m.group()))):
            out += _joined_ids(text, held)
            held = []
        at = m.end() if m else end
        number += 1
    if tags:
        out = sorted([*out, *((0, a, b, f"spdx:{name}") for a, b, name in tags)], key=lambda x: x[1])
    return out


def _joined_ids(text: str, lines: list[tuple[int, int, int]]) -> list[tuple[int, int, int, str]]:
    """sentence_ids of the lines of one sentence."""
    if not _QUICK.search(text, lines[0][1], lines[-1][2]):
        return []
    plain, begins = "", []
    for _, a, b in lines:
        own = _OTHER.sub(" ", _PLUS.sub(" or later ", text[a:b].lower())).strip()
        plain += " " * bool(plain and own)
        begins.append(len(plain))
        plain += own
    hits = [(m, f"grant:{_OF_NAME[m.group(1)]}") for m in _GRANT.finditer(plain)]
    seen: set[tuple[int, str]] = set()  # a phrase counts once in each line
    out = []
    for m, k in sorted(hits + [(m, k) for p, k in _PHRASES for m in p.finditer(plain)], key=lambda x: x[0].start()):
        i, j = bisect_right(begins, m.start()) - 1, bisect_right(begins, m.end() - 1) - 1
        if k.startswith("grant:") or (i, k) not in seen:
            seen.add((i, k))
            out.append((lines[i][0], lines[i][1], lines[j][2], k))
    return out


def match_rules(ids: list[tuple[int, int, int, str]]) -> list[tuple[str, int, int]]:
    """(licence, start, end) of each rule that applies; every recognised sentence serves one rule at most."""
    used, out, present = set(), [(k[5:], a, b) for _, a, b, k in ids if k.startswith("spdx:")], {x[3] for x in ids}
    for name, sequence in _ORDERED:
        if not present.issuperset(sequence):
            continue
        first = 0
        while first < len(ids):
            chain, i = [], first
            for want in sequence:
                last = ids[chain[-1]][0] if chain else None
                i = next((j for j in range(i, len(ids)) if j not in used and ids[j][3] == want and (last is None or ids[j][0] - last <= GAP)), None)
                if i is None:
                    break
                chain.append(i)
                i += 1
            if not chain:
                break
            if len(chain) < len(sequence):
                first = chain[0] + 1  # a later start may have the whole sequence
                continue
            used.update(chain)
            out.append((name, ids[chain[0]][1], ids[chain[-1]][2]))
            first = chain[0] + 1
    return sorted(out, key=lambda x: (x[1], x[0]))


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, licenses (distinct, sorted, comma-joined), n_sentences (recognised), matches (licence:start:end)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, texts in batched(batches):
            ids = [sentence_ids(t) for t in texts]
            found = [match_rules(x) for x in ids]
            yield pa.RecordBatch.from_arrays([rows.column("doc_id"), pa.array([",".join(sorted({f[0] for f in x})) for x in found]), pa.array([len(x) for x in ids], pa.int64()), pa.array([",".join(f"{k}:{a}:{b}" for k, a, b in x) for x in found])], ["doc_id", "licenses", "n_sentences", "matches"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, licenses string, n_sentences long, matches string")


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Licences of every document."""
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
