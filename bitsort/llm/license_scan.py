"""License scans by ordered signature rules.

Rules are regular expressions over lower-cased text, made from families of licenses and the forms
in which texts name them (title, identifier line, notice, address, abbreviation).  A rule runs only
on texts that hold its keyword.  Overlapping detections are resolved in order of priority: a span
inside one of a better rule (or a longer one of the same rule order) is dropped.

Base phrases (two or three consecutive words) are found by word, and their labels always stay.

Defined results: a null text is empty; repeated rows are scanned each on their own; columns other
than doc_id and text are ignored, whatever their names; a text of any length is scanned as a whole;
an empty table gives no rows.
"""

from __future__ import annotations

import functools
import re
from collections.abc import Iterator
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitsort.llm.text import NOT_ALNUM, chunks

REPORT = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"
#: Base phrases and their labels; fixed values.
BASE = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
#: Families: label, words of the title (as a pattern), identifiers, a piece of the usual address.
FAMILIES = (
    ("mit", r"mit|expat|x11", ("mit", "x11", "mit-0"), "opensource.org/licenses/mit"),
    ("apache", r"apache(?: software)?", ("apache-1.0", "apache-1.1", "apache-2.0"), "apache.org/licenses"),
    ("lgpl", r"(?:gnu )?(?:lesser|library) general public", ("lgpl-2.0", "lgpl-2.1", "lgpl-3.0"), "gnu.org/licenses/lgpl"),
    ("agpl", r"(?:gnu )?affero general public", ("agpl-1.0", "agpl-3.0"), "gnu.org/licenses/agpl"),
    ("gpl", r"(?:gnu )?general public", ("gpl-1.0", "gpl-2.0", "gpl-3.0"), "gnu.org/licenses/gpl"),
    ("fdl", r"(?:gnu )?free documentation", ("gfdl-1.1", "gfdl-1.2", "gfdl-1.3"), "gnu.org/licenses/fdl"),
    ("bsd", r"(?:modified |simplified |new )?bsd|berkeley software distribution", ("0bsd", "bsd-1-clause", "bsd-2-clause", "bsd-3-clause", "bsd-4-clause"), "opensource.org/licenses/bsd"),
    ("mpl", r"mozilla public", ("mpl-1.0", "mpl-1.1", "mpl-2.0"), "mozilla.org/mpl"),
    ("epl", r"eclipse public", ("epl-1.0", "epl-2.0"), "eclipse.org/legal/epl"),
    ("cddl", r"common development and distribution", ("cddl-1.0", "cddl-1.1"), "opensource.org/licenses/cddl"),
    ("cpl", r"common public", ("cpl-1.0",), "opensource.org/licenses/cpl"),
    ("eupl", r"european union public", ("eupl-1.1", "eupl-1.2"), "eupl.eu"),
    ("isc", r"isc|internet systems consortium", ("isc",), "opensource.org/licenses/isc"),
    ("zlib", r"zlib(?:/libpng)?", ("zlib", "zlib-acknowledgement"), "zlib.net/zlib_license"),
    ("bsl", r"boost software", ("bsl-1.0",), "boost.org/license"),
    ("artistic", r"artistic", ("artistic-1.0", "artistic-2.0"), "perlfoundation.org/artistic"),
    ("python", r"python(?: software foundation)?|psf", ("psf-2.0", "python-2.0"), "docs.python.org/license"),
    ("postgresql", r"postgresql", ("postgresql",), "postgresql.org/about/licence"),
    ("php", r"php", ("php-3.0", "php-3.01"), "php.net/license"),
    ("unlicense", r"unlicense|the unlicense", ("unlicense",), "unlicense.org"),
    ("wtfpl", r"do what the f\w* you want to public", ("wtfpl",), "wtfpl.net"),
    ("ofl", r"(?:sil )?open font", ("ofl-1.0", "ofl-1.1"), "scripts.sil.org/ofl"),
    ("openssl", r"openssl", ("openssl",), "openssl.org/source/license"),
    ("ms-pl", r"microsoft (?:public|reciprocal)", ("ms-pl", "ms-rl"), "opensource.org/licenses/ms-pl"),
    ("odbl", r"open (?:data commons open )?database", ("odbl-1.0", "odc-by-1.0"), "opendatacommons.org/licenses"),
    ("cc0", r"creative commons zero|cc0(?: 1\.0)?(?: universal)?", ("cc0-1.0",), "creativecommons.org/publicdomain/zero"),
)
#: Creative Commons forms: suffix of the abbreviation and words of the full name.
COMMONS = (
    ("cc-by-nc-nd", "by-nc-nd", r"attribution[- ]non-?commercial[- ]no ?deriv\w*"),
    ("cc-by-nc-sa", "by-nc-sa", r"attribution[- ]non-?commercial[- ]share ?alike"),
    ("cc-by-nc", "by-nc", r"attribution[- ]non-?commercial"),
    ("cc-by-nd", "by-nd", r"attribution[- ]no ?deriv\w*"),
    ("cc-by-sa", "by-sa", r"attribution[- ]share ?alike"),
    ("cc-by", "by", r"attribution"),
)
#: Sentences that stand only in the texts of a license: label, a word that all forms have, and pattern.
CLAUSES = (
    ("mit", "granted", r"permission is hereby granted, free of charge, to any person obtaining a copy"),
    ("isc", "permission", r"permission to use, copy, modify, and(?:/or)? distribute this software for any purpose"),
    ("bsd", "redistribution", r"redistribution and use in source and binary forms, with or without modification"),
    ("bsd", "contributors", r"neither the name of .{1,120}? nor the names of its contributors"),
    ("gpl", "redistribute", r"this program is free software[:;,] you can redistribute it"),
    ("lgpl", "redistribute", r"this library is free software[:;,] you can redistribute it"),
    ("zlib", "as-is", r"this software is provided 'as-is', without any express or implied warranty"),
    ("unlicense", "unencumbered", r"this is free and unencumbered software released into the public domain"),
    ("bsl", "granted", r"permission is hereby granted, free of charge, to any person or organization obtaining a copy"),
    ("public-domain", "domain", r"(?:released|placed|dedicated) (?:in|into|to) the public domain"),
    ("proprietary", "reserved", r"all rights reserved"),
    ("proprietary", "confidential", r"(?:proprietary and )?confidential information of"),
)


@dataclass(frozen=True)
class Rule:
    label: str
    keyword: str
    pattern: re.Pattern
    score: float


@functools.lru_cache(maxsize=1)
def rules() -> tuple[Rule, ...]:
    """All rules, best first."""
    b, e = r"(?<![\w-])", r"(?![\w])"
    word = r"licen[cs]e"
    out: list[tuple[str, str, str, float]] = []
    for label, _, ids, _ in FAMILIES:
        for x in ids:
            out.append((label, "spdx", rf"spdx-license-identifier:\s*{re.escape(x)}(?:-only|-or-later|\+)?{e}", 1.0))
    for label, suffix, _ in COMMONS:
        out.append((label, "spdx", rf"spdx-license-identifier:\s*cc-{suffix}-\d\.\d", 1.0))
    out += [(label, keyword, pattern.replace(" ", r"\s+"), 0.99) for label, keyword, pattern in CLAUSES]
    for label, _, _, url in FAMILIES:
        out.append((label, url.split("/")[0], rf"(?:https?://)?(?:www\.)?{re.escape(url)}[\w./-]*", 0.97))
    for label, suffix, _ in COMMONS:
        out.append((label, "creativecommons.org", rf"creativecommons\.org/licenses/{suffix}/[\d.]+", 0.97))
    for label, title, _, _ in FAMILIES:
        title = title.replace(" ", r"\s+")
        out.append((label, "licen", rf"{b}(?:licensed|released|distributed|published|available|made available)\s+under\s+(?:the\s+)?(?:terms\s+of\s+(?:the\s+)?)?(?:{title})\s+{word}(?:,?\s+(?:version|v\.?)\s*\d[\d.]*)?", 0.95))
    for label, title, _, _ in FAMILIES:
        title = title.replace(" ", r"\s+")
        out.append((label, "licen", rf"{b}(?:{title})\s+{word}(?:,?\s+(?:version|v\.?)\s*\d[\d.]*)?", 0.9))
        out.append((label, "licen", rf"{word}:\s*(?:{title}){e}", 0.85))
    for label, suffix, name in COMMONS:
        short, name = suffix.replace("-", "[- ]"), name.replace(" ", r"\s+")
        out.append((label, "cc", rf"{b}(?:licensed\s+under\s+)?(?:a\s+|the\s+)?cc[- ]{short}(?:[- ]\d(?:\.\d)?)?{e}", 0.9))
        out.append((label, "commons", rf"creative\s+commons\s+{name}(?:\s+\d\.\d)?(?:\s+\w+)?(?:\s+{word})?", 0.93))
    for label, _, ids, _ in FAMILIES:
        for x in ids:
            if any(c.isdigit() for c in x) and "-" in x:
                out.append((label, x[: x.index("-") + 1], rf"{b}{re.escape(x)}(?:-only|-or-later|\+)?{e}", 0.8))
    for label in ("lgpl", "agpl", "gpl", "mpl", "epl", "bsd"):
        out.append((label, label, rf"{b}(?:gnu\s+)?{label}\s*v?\d(?:\.\d)?\+?{e}", 0.75))
    return tuple(Rule(label, keyword, re.compile(pattern, re.S), score) for label, keyword, pattern, score in out)


@functools.lru_cache(maxsize=1)
def _keywords() -> ahocorasick.Automaton:
    found = ahocorasick.Automaton()
    for word in {r.keyword for r in rules()}:
        found.add_word(word, word)
    found.make_automaton()
    return found


def detect(text: str) -> list[tuple[int, int, str, float]]:
    """(start, end, label, score) of the detections in a lower-cased text that no better one holds."""
    here = {w for _, w in _keywords().iter(text)}
    found: list[tuple[int, int, str, float]] = []
    for rule in rules():  # best first
        if rule.keyword in here:
            for m in rule.pattern.finditer(text):
                if not any(s <= m.start() and m.end() <= e for s, e, _, _ in found):
                    found = [x for x in found if not (m.start() <= x[0] and x[1] <= m.end() and x[3] <= rule.score)]
                    found.append((*m.span(), rule.label, rule.score))
    return sorted(found)


def _gate() -> re.Pattern:
    """A cheap test on bytes: a text without it meets no rule.  Keywords that many words hold stand with what must follow."""
    follow = {"cc": r"(?<![\w-])cc[- ]by"} | {x: rf"{x}\s*v?\d|{x}-" for x in ("lgpl", "agpl", "gpl", "mpl", "epl", "bsd")}
    return re.compile("|".join(follow.get(k, re.escape(k)) for k in sorted({r.keyword for r in rules()})).encode())


_GATE = _gate()
_SEP, _IN = rb"[\x00-\x2f\x3a-\x60\x7b-\x7f]+", rb"[0-9a-z\x80-\xff]"
_BASE = re.compile(rb"(?<!" + _IN + rb")(?:" + rb"|".join(b"(" + _SEP.join(p.encode().split()) + b")" for p in BASE) + rb")(?!" + _IN + rb")")


def scan(ids: list, column: pa.Array) -> Iterator[tuple]:
    """A report row for each text."""
    labels = list(BASE.values())
    for chunk in chunks(column, NOT_ALNUM, lower=True):
        data, edge = chunk.data.tobytes(), chunk.edges
        for k, (i, j) in enumerate(zip(chunk.ptr[:-1].tolist(), chunk.ptr[1:].tolist(), strict=True)):
            own = data[edge[k] : edge[k + 1]]
            row = [ids[chunk.first + k], j - i, 0, None, None, "", "", 0.0]
            if _GATE.search(own):
                places, base = [], set()
                if b"license" in own:
                    for m in _BASE.finditer(own):
                        places.append(int(np.searchsorted(chunk.start[i:j], edge[k] + m.start())))
                        base.add(labels[m.lastindex - 1])
                found = detect(own.decode("utf-8", "replace"))
                if places:
                    row[2:5] = len(places), min(places), max(places)
                row[5], row[6] = ",".join(sorted(base)), ",".join(sorted(base | {x[2] for x in found}))
                row[7] = max([x[3] for x in found] + [0.9] * bool(places), default=0.0)
            yield tuple(row)


def license_report(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64()] * 5 + [pa.string()] * 2 + [pa.float64()]
        for batch in batches:
            cols = list(zip(*scan(batch.column(0).to_pylist(), batch.column(1)), strict=True)) or [[]] * 8
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], [x.split()[0] for x in REPORT.split(", ")])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, REPORT)
