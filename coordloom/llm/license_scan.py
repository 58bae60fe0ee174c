"""License scans with ordered signature rules.

A text is lower-cased (A-Z), cut into words and joined again by single blanks, in bytes: every
non-ASCII byte belongs to a word, so UTF-8 needs no decoding. Rules are regular expressions over
that normal form, each gated by a keyword that any match must hold. Detections are ordered by
priority, then length, then start; one that lies inside a kept detection is suppressed, except those
of the base phrases, which are always reported.

Defined cases: a null or empty text has no words, no places and score 0.0; rows that repeat are
scanned one by one, null ids too; very long texts take time in proportion to their length and, for suppression, n log n in their detections;
of detections of equal priority, length and start the rule that comes first in the book is kept; an empty table gives an empty result; other columns aren't read, whatever their names.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

from pyspark.sql import DataFrame

# The base phrases and their labels.
BASE_PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}

_NOT_WORD = bytes(b for b in range(128) if not (48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122))
_NORMAL = bytes.maketrans(_NOT_WORD + bytes(range(65, 91)), b" " * len(_NOT_WORD) + bytes(range(97, 123)))

SCHEMA = (
    "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, "
    "n_detections long, detections array<struct<rule:string,label:string,first_word:long,n_words:long>>"
)


@dataclass(frozen=True)
class Rule:
    """``keyword`` is in every text that ``pattern`` matches; a lower ``priority`` number wins."""

    name: str
    label: str
    keyword: str
    pattern: str
    priority: int
    base: bool = False


#: Licences named by family: label, names as regular expressions over normal words, versions.
_FAMILIES: tuple[tuple[str, tuple[str, ...], tuple[str, ...]], ...] = (
    ("apache", ("apache (?:software )?license", "asl", "apache"), ("1 0", "1 1", "2 0", "2")),
    ("gpl", ("(?:gnu )?general public license", "gnu gpl", "gpl"), ("1", "1 0", "2", "2 0", "3", "3 0")),
    ("lgpl", ("(?:gnu )?(?:lesser|library) general public license", "lgpl"), ("2", "2 0", "2 1", "3", "3 0")),
    ("agpl", ("(?:gnu )?affero general public license", "agpl"), ("1", "1 0", "3", "3 0")),
    ("mpl", ("mozilla public license", "mpl"), ("1 0", "1 1", "2 0", "2")),
    ("epl", ("eclipse public license", "epl"), ("1 0", "2 0", "2")),
    ("cddl", ("common development and distribution license", "cddl"), ("1 0", "1 1")),
    ("cpl", ("common public license", "cpl"), ("0 5", "1 0")),
    ("eupl", ("european union public licen[cs]e", "eupl"), ("1 0", "1 1", "1 2")),
    ("osl", ("open software license", "osl"), ("1 0", "2 0", "2 1", "3 0")),
    ("afl", ("academic free license", "afl"), ("1 1", "1 2", "2 0", "2 1", "3 0")),
    ("artistic", ("artistic license",), ("1 0", "2 0")),
    ("bsl", ("boost software license", "bsl"), ("1 0",)),
    ("psf", ("python software foundation license", "psf license"), ("2", "2 0")),
    ("zpl", ("zope public license", "zpl"), ("1 1", "2 0", "2 1")),
    ("ofl", ("(?:sil )?open font license", "ofl"), ("1 0", "1 1")),
    ("lppl", ("latex project public license", "lppl"), ("1 0", "1 1", "1 2", "1 3")),
    ("cecill", ("cecill(?: [bc])?",), ("1 0", "1 1", "2 0", "2 1")),
    ("bsd", ("bsd", "berkeley software distribution license"), ()),
    ("mit", ("mit", "expat license", "x11 license"), ()),
    ("isc", ("isc license",), ()),
    ("zlib", ("zlib license", "zlib libpng license"), ()),
    ("unlicense", ("the unlicense",), ()),
    ("wtfpl", ("wtfpl", "do what the fuck you want to public license"), ("1", "2")),
    ("cc0", ("cc0", "creative commons zero"), ("1 0",)),
    ("cc-by", ("cc by", "creative commons attribution"), ("1 0", "2 0", "2 5", "3 0", "4 0")),
    ("cc-by-sa", ("cc by sa", "creative commons attribution share ?alike"), ("1 0", "2 0", "2 5", "3 0", "4 0")),
    ("cc-by-nc", ("cc by nc", "creative commons attribution non ?commercial"), ("1 0", "2 0", "2 5", "3 0", "4 0")),
    ("cc-by-nd", ("cc by nd", "creative commons attribution no ?deriv(?:ative)?s?"), ("1 0", "2 0", "2 5", "3 0", "4 0")),
    ("ms-pl", ("microsoft public license", "ms pl"), ()),
    ("ms-rl", ("microsoft reciprocal license", "ms rl"), ()),
    ("ncsa", ("university of illinois ncsa open source license", "ncsa license"), ()),
    ("openssl", ("openssl license",), ()),
    ("php", ("php license",), ("3 0", "3 01")),
    ("ruby", ("ruby license",), ()),
    ("vim", ("vim license",), ()),
    ("w3c", ("w3c (?:software )?(?:notice and )?license",), ()),
    ("odbl", ("open (?:data commons )?(?:open )?database license", "odbl"), ("1 0",)),
    ("sspl", ("server side public license", "sspl"), ("1",)),
    ("busl", ("business source license", "busl"), ("1 1",)),
)

#: Notices and grants in the words of the licences themselves: label, pattern, keyword.
_NOTICES: tuple[tuple[str, str, str], ...] = (
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy", "hereby granted"),
    ("mit", "released under (?:the )?mit", "released under"),
    ("mit", "(?:licensed|distributed) under (?:the )?(?:terms of the )?mit", "under"),
    ("isc", "permission to use copy modify and (?:or )?distribute this software for any purpose with or without fee", "with or without fee"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution and use"),
    ("bsd", "neither the name of .{1,80}? nor the names of its contributors may be used", "neither the name of"),
    ("bsd-2-clause", "(?:bsd 2 clause|2 clause bsd|simplified bsd|freebsd) license", "bsd"),
    ("bsd-3-clause", "(?:bsd 3 clause|3 clause bsd|new bsd|revised bsd|modified bsd) license", "bsd"),
    ("bsd-4-clause", "(?:bsd 4 clause|4 clause bsd|original bsd) license", "bsd"),
    ("apache", "licensed under the apache license", "licensed under the apache"),
    ("apache", "you may not use this file except in compliance with the license", "except in compliance"),
    ("apache", "www apache org licenses license 2 0", "www apache org"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license", "this program is free software"),
    ("gpl", "www gnu org (?:licenses|copyleft) gpl", "www gnu org"),
    ("lgpl", "www gnu org (?:licenses|copyleft) lgpl", "www gnu org"),
    ("agpl", "www gnu org licenses agpl", "www gnu org"),
    ("mpl", "this source code form is subject to the terms of the mozilla public license", "source code form is subject"),
    ("epl", "this program and the accompanying materials are made available under the terms of the eclipse public license", "accompanying materials"),
    ("bsl", "permission is hereby granted free of charge to any person or organization obtaining a copy", "person or organization"),
    ("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable", "without any express or implied"),
    ("unlicense", "this is free and unencumbered software released into the public domain", "unencumbered"),
    ("public-domain", "(?:released|placed|dedicated) (?:in|into|to) the public domain", "the public domain"),
    ("cc0", "creativecommons org publicdomain zero", "creativecommons org"),
    ("cc-by", "creativecommons org licenses by [0-9]", "creativecommons org"),
    ("cc-by-sa", "creativecommons org licenses by sa", "creativecommons org"),
    ("cc-by-nc", "creativecommons org licenses by nc", "creativecommons org"),
    ("cc-by-nd", "creativecommons org licenses by nd", "creativecommons org"),
    ("wtfpl", "everyone is permitted to copy and distribute verbatim or modified copies of this license document", "verbatim or modified copies"),
    ("proprietary", "all rights reserved (?:no part of|unauthori[sz]ed)", "all rights reserved"),
    ("proprietary", "confidential and proprietary (?:information|property)", "confidential and proprietary"),
)

#: Ways to name a licence with its version. {n}: name, {v}: version.
_FORMS = ("spdx license identifier {n} {v}", "{n} (?:version |v |v)?{v}", "{n} (?:version |v |v)?{v} (?:or|and) (?:any )?later", "under (?:the )?(?:terms of )?(?:the )?{n} (?:version |v |v)?{v}")
_PLAIN_FORMS = ("spdx license identifier {n}", "(?:licensed|released|distributed|available) under (?:the )?(?:terms of )?(?:the )?{n}", "{n} licensed")


def _keyword(pattern: str) -> str:
    """The longest run of characters that every match must hold: outside groups and classes, and not optional."""
    runs, depth, k = [""], 0, 0
    pattern = pattern.replace("(?:", "(")
    while k < len(pattern):
        ch = pattern[k]
        if ch == "[":
            k = pattern.index("]", k)
            runs.append("")
        elif ch in "()":
            depth += 1 if ch == "(" else -1
            runs.append("")
        elif ch in ".?{":
            runs[-1] = runs[-1][:-1] if ch == "?" else runs[-1]
            k = pattern.index("}", k) if ch == "{" else k
            runs.append("")
        elif not depth:
            runs[-1] += ch
        k += 1
    return max((r.strip() for r in runs), key=len)


@lru_cache(maxsize=1)
def rules() -> tuple[Rule, ...]:
    """Base phrases, notices, then families times versions times forms: several hundred rules."""
    out = [Rule(f"base:{label}", label, phrase, re.escape(phrase).replace(r"\ ", " "), 0, True) for phrase, label in BASE_PHRASES.items()]
    out += [Rule(f"notice:{k}", label, keyword, pattern, 1) for k, (label, pattern, keyword) in enumerate(_NOTICES)]
    for label, names, versions in _FAMILIES:
        for k, name in enumerate(names):
            group = f"(?:{name})"
            for version in versions:
                for f, form in enumerate(_FORMS):
                    pattern = form.format(n=group, v=version)
                    out.append(Rule(f"{label}:{k}:{version}:{f}", f"{label}-{version.replace(' ', '.')}", _gate(name, pattern), pattern, 2 + (f == 1)))
            for f, form in enumerate(_PLAIN_FORMS):
                out.append(Rule(f"{label}:{k}:any:{f}", label, _gate(name, form), form.format(n=group), 4))
            if len(name.split()) > 2:
                out.append(Rule(f"{label}:{k}:name", label, _keyword(name), name, 5))
    return tuple(out)


def _gate(name: str, form: str) -> str:
    return max(_keyword(name), _keyword(form.replace("{n}", "(x)").replace("{v}", "(x)")), key=len)


class _Cover:
    """Kept intervals: does one of them hold (start, stop)? A tree of running maxima over the starts that can occur; log time a question."""

    def __init__(self, starts: list[int]):
        self.place = {x: k + 1 for k, x in enumerate(sorted(set(starts)))}
        self.best = [-1] * (len(self.place) + 1)

    def add(self, start: int, stop: int) -> None:
        k = self.place[start]
        while k < len(self.best):
            self.best[k] = max(self.best[k], stop)
            k += k & -k

    def holds(self, start: int, stop: int) -> bool:
        k = self.place[start]
        while k:
            if self.best[k] >= stop:
                return True
            k -= k & -k
        return False


class Scanner:
    """Compiled rules grouped by keyword. One pass of an automaton over the text finds the shortest keywords of the book in it; only groups whose keyword holds
    one of those are looked at. Everything is derived from the book, so any rule whose matches hold its keyword is found."""

    def __init__(self, book: tuple[Rule, ...] | None = None):
        import ahocorasick

        book = rules() if book is None else book
        self.groups: dict[bytes, list[tuple[re.Pattern[bytes], int, Rule]]] = {}
        for order, rule in enumerate(book):
            bounded = re.compile(b"(?<= )(?:" + rule.pattern.encode() + b")(?= )")
            self.groups.setdefault(rule.keyword.strip().encode(), []).append((bounded, order, rule))
        self.always = self.groups.pop(b"", [])
        # bytes as characters of the same number: the automaton takes strings
        names = [k.decode("latin-1") for k in self.groups]
        self.least = [k for k in names if not any(o != k and o in k for o in names)]
        self.opens = {k: [n.encode("latin-1") for n in names if k in n] for k in self.least}
        self.gate = ahocorasick.Automaton()
        for k in self.least:
            self.gate.add_word(k, k)
        if self.least:
            self.gate.make_automaton()

    def _candidates(self, normal: bytes) -> list:
        seen = {k for _, k in self.gate.iter(normal.decode("latin-1"))} if self.least else set()
        keys = {key for k in seen for key in self.opens[k]}
        return [self.always, *(self.groups[key] for key in keys if key in normal)]

    def scan(self, text: bytes) -> tuple:
        words = text.translate(_NORMAL).split()
        n = len(words)
        found: list[tuple[int, int, int, int, Rule]] = []
        if n:
            normal = b" " + b" ".join(words) + b" "
            for group in self._candidates(normal):
                for pattern, order, rule in group:
                    found += [(rule.priority, m.start() - m.end(), m.start(), order, rule) for m in pattern.finditer(normal)]
        if not found:
            return n, 0, None, None, "", "", 0.0, 0, []
        found.sort(key=lambda x: x[:4])
        cover = _Cover([x[2] for x in found])
        kept: list[tuple[int, int, Rule]] = []
        for _, minus, start, _, rule in found:
            if rule.base or not cover.holds(start, start - minus):
                kept.append((start, start - minus, rule))
                cover.add(start, start - minus)
        kept.sort(key=lambda x: (x[0], x[1], x[2].name))
        at, done, rows = 0, 0, []  # word index of each start, counted once from left to right
        for start, stop, rule in kept:
            at, done = at + normal.count(b" ", done, start), max(done, start)
            rows.append((rule.name, rule.label, at - 1, normal.count(b" ", start, stop) + 1))
        base = [r for r, (_, _, rule) in zip(rows, kept, strict=True) if rule.base]
        covered, end = 0, 0
        for _, _, first, size in rows:
            covered += max(0, first + size - max(first, end))
            end = max(end, first + size)
        return (
            n, len(base), min((r[2] for r in base), default=None), max((r[2] for r in base), default=None),
            ",".join(sorted({r[1] for r in base})), ",".join(sorted({r[1] for r in rows})), covered / (covered + 4.0), len(rows), rows,
        )


def scan_licenses(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", book: tuple[Rule, ...] | None = None) -> DataFrame:
    """One row per input row, by the rules of ``book`` (default: ``rules()``). ``score`` is c / (c + 4) with c the words that detections cover: 0 without any, near 1 for a full licence."""

    def scan(batches: Iterator) -> Iterator:
        import pyarrow as pa

        scanner, schema = Scanner(book), None
        for batch in batches:
            texts = batch.column(1).cast(pa.large_binary())
            rows = [scanner.scan(x.as_py() or b"") for x in texts]
            columns = [batch.column(0).cast(pa.int64()), *([r[k] for r in rows] for k in range(8)), [[dict(zip(("rule", "label", "first_word", "n_words"), d, strict=True)) for d in r[8]] for r in rows]]
            schema = schema or pa.schema([
                ("doc_id", pa.int64()), *((c, pa.int64()) for c in ("n_words", "n_base", "first_word", "last_word")), ("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64()), ("n_detections", pa.int64()),
                ("detections", pa.list_(pa.struct([("rule", pa.string()), ("label", pa.string()), ("first_word", pa.int64()), ("n_words", pa.int64())]))),
            ])
            yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, t.type) for c, t in zip(columns, schema, strict=True)], schema=schema)

    from pyspark.sql import functions as F

    return docs.select(F.col(f"`{doc_id}`").cast("long").alias("doc_id"), F.col(f"`{text}`").alias("text")).mapInArrow(scan, SCHEMA)
