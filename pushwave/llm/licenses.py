"""License scan by ordered signature rules (operator 9).

A text becomes its words (digits, a-z after lower-casing, and everything beyond ASCII), joined by
single spaces. Rules are regexes over that line. A rule is tried only if one of its gate words is
among the text's words. Detections are ordered by priority, then length; one whose interval lies inside
an accepted interval is dropped. The three base phrases are counted apart and always stay.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from dataclasses import dataclass
from functools import cache
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.llm.common import WORD_BYTES, Batches, raw, table

#: Phrases of the base count and their labels.
BASE = (("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc"))

#: Label, regex of the name in words, gate words (every alternative holds one of them).
FAMILIES = (
    ("mit", r"(?:mit|expat)", "mit"), ("mit", r"expat", "expat"), ("apache-2", r"apache(?: software)?(?: license)?(?: version)?(?: v)? ?2(?: 0)?", "apache|apache2"), ("apache-1.1", r"apache(?: software)?(?: license)?(?: version)? 1 1", "apache"),
    ("gpl-3", r"(?:gnu )?(?:gpl|general public license)(?: version)?(?: v)? ?3(?: 0)?", "gpl|gpl3"), ("gpl-3", r"gplv3", "gplv3"), ("gpl-3", r"(?:gnu )?general public license(?: version)?(?: v)? ?3(?: 0)?", "general"),
    ("gpl-2", r"(?:gnu )?gpl(?: version)?(?: v)? ?2(?: 0)?", "gpl|gpl2"), ("gpl-2", r"gplv2", "gplv2"), ("gpl-2", r"(?:gnu )?general public license(?: version)?(?: v)? ?2(?: 0)?", "general"),
    ("lgpl-2.1", r"(?:gnu )?lgpl(?: version)?(?: v)? ?2 1", "lgpl|lgpl2"), ("lgpl-3", r"(?:gnu )?lgpl(?: version)?(?: v)? ?3(?: 0)?", "lgpl|lgpl3"), ("lgpl", r"(?:gnu )?(?:lesser|library) general public license", "general"),
    ("agpl-3", r"(?:gnu )?agpl(?: version)?(?: v)? ?3(?: 0)?", "agpl|agpl3"), ("agpl-3", r"(?:gnu )?affero general public license(?: version)?(?: v)? ?3(?: 0)?", "affero"),
    ("bsd-2", r"(?:bsd 2 clause|2 clause bsd|simplified bsd|freebsd)", "bsd|freebsd"), ("bsd-3", r"(?:bsd 3 clause|3 clause bsd|new bsd|modified bsd|revised bsd)", "bsd"), ("bsd-4", r"(?:bsd 4 clause|4 clause bsd|original bsd)", "bsd"),
    ("mpl-2", r"(?:mozilla public license|mpl)(?: version)?(?: v)? ?2(?: 0)?", "mozilla"), ("mpl-2", r"mpl(?: version)?(?: v)? ?2(?: 0)?", "mpl|mpl2"), ("mpl-1.1", r"(?:mozilla public license|mpl)(?: version)? 1 1", "mozilla|mpl"),
    ("epl-1", r"eclipse public license(?: version)?(?: v)? ?1(?: 0)?", "eclipse"), ("epl-2", r"eclipse public license(?: version)?(?: v)? ?2(?: 0)?", "eclipse"), ("cddl-1", r"(?:cddl|common development and distribution license)(?: version)? 1(?: 0)?", "cddl|distribution"),
    ("isc", r"isc", "isc"), ("zlib", r"zlib(?: libpng)?", "zlib"), ("unlicense", r"unlicense", "unlicense"), ("wtfpl", r"wtfpl", "wtfpl"), ("bsl-1", r"boost software license(?: version)?(?: 1 0)?", "boost"),
    ("artistic-2", r"artistic license(?: version)? ?2(?: 0)?", "artistic"), ("artistic-1", r"artistic license(?: version)? 1(?: 0)?", "artistic"), ("psf", r"python software foundation", "python"), ("ofl-1.1", r"(?:sil )?open font(?: license)?(?: version)?(?: 1 1)?", "font"),
    ("eupl-1.2", r"european union public licen[cs]e(?: version)?(?: v)?(?: 1 2)?", "european"), ("ms-pl", r"microsoft public license", "microsoft"), ("ms-rl", r"microsoft reciprocal license", "microsoft"), ("postgresql", r"postgresql", "postgresql"),
    ("cc0-1", r"(?:cc0|cc zero)(?: 1 0)?(?: universal)?", "cc0|zero"), ("cc-by", r"(?:cc by|creative commons attribution)(?: [1-4] 0)?", "cc"), ("cc-by", r"creative commons attribution(?: [1-4] 0)?", "creative"),
    ("cc-by-sa", r"(?:cc by sa|creative commons attribution share ?alike)(?: [1-4] 0)?", "cc"), ("cc-by-sa", r"creative commons attribution share ?alike(?: [1-4] 0)?", "creative"), ("cc-by-nd", r"(?:cc by nd|creative commons attribution no ?deriv(?:ative)?s)(?: [1-4] 0)?", "cc|creative"),
    ("cc-by-nc", r"(?:cc by nc|creative commons attribution non ?commercial)(?: [1-4] 0)?", "cc"), ("cc-by-nc", r"creative commons attribution non ?commercial(?: [1-4] 0)?", "creative"), ("cc-by-nc-sa", r"cc by nc sa(?: [1-4] 0)?", "cc"), ("cc-by-nc-nd", r"cc by nc nd(?: [1-4] 0)?", "cc"),
)

#: Priority, confidence, form around the name.
FORMS = (
    (90, 1.0, r"spdx license identifier {}"),
    (80, 0.98, r"(?:licen[cs]ed|released|distributed|published|available|provided) under (?:the )?(?:terms of )?(?:the )?{}(?: licen[cs]e)?"),
    (75, 0.95, r"(?:subject to|governed by|covered by) (?:the )?(?:terms of )?(?:the )?{}(?: licen[cs]e)?"),
    (70, 0.9, r"under (?:the )?(?:terms of )?(?:the )?{}(?: licen[cs]e)?"),
    (60, 0.85, r"licen[cs]e (?:is )?(?:the )?{}"),
    (50, 0.8, r"(?:the )?{} licen[cs]e"),
    (40, 0.6, r"{} (?:terms|agreement|text|copying)"),
)

#: Rules of one form: priority, confidence, label, regex, gate word.
SINGLE = (
    (85, 0.97, "mit", r"permission is hereby granted free of charge to any person obtaining a copy", "hereby"),
    (85, 0.97, "isc", r"permission to use copy modify and or distribute this software for any purpose", "permission"),
    (85, 0.97, "bsd", r"redistribution and use in source and binary forms with or without modification", "redistribution"),
    (85, 0.97, "gpl", r"free software you can redistribute it and or modify it under the terms of the gnu", "gnu"),
    (84, 0.95, "cc-by-nc", r"cc by nc(?: [1-4] 0)?", "cc"), (86, 0.96, "cc-by-nc-sa", r"cc by nc sa(?: [1-4] 0)?", "cc"), (86, 0.96, "cc-by-nc-nd", r"cc by nc nd(?: [1-4] 0)?", "cc"),
    (82, 0.9, "cc-by-sa", r"cc by sa(?: [1-4] 0)?", "cc"), (82, 0.9, "cc-by-nd", r"cc by nd(?: [1-4] 0)?", "cc"), (65, 0.8, "cc-by", r"cc by [1-4] 0", "cc"),
    (83, 0.95, "apache-2", r"apache license version 2(?: 0)?", "apache"), (30, 0.5, "proprietary", r"all rights reserved", "reserved"), (35, 0.6, "public-domain", r"(?:in|into|to) the public domain", "domain"),
    (35, 0.6, "proprietary", r"(?:strictly )?confidential and proprietary", "proprietary"), (20, 0.3, "notice", r"copyright (?:c )?(?:19|20)\d\d", "copyright"), (20, 0.3, "notice", r"see (?:the )?(?:file )?(?:licen[cs]e|copying)(?: file)? for", "see"),
)

@dataclass(frozen=True)
class Rule:
    priority: int
    confidence: float
    label: str
    pattern: re.Pattern
    gates: tuple[bytes, ...]


@cache
def rules() -> tuple[Rule, ...]:
    """All rules in order of priority; a pattern begins and ends at word borders."""
    made = [(p, c, label, form.format(name), gate) for (label, name, gate), (p, c, form) in product(FAMILIES, FORMS)]
    made += SINGLE
    out = [Rule(p, c, label, re.compile(rf"(?<= )(?:{body})(?= )".encode()), tuple(gate.encode().split(b"|"))) for p, c, label, body, gate in made]
    return tuple(sorted(out, key=lambda r: -r.priority))


@cache
def _gates() -> dict[bytes, list[Rule]]:
    out: dict[bytes, list[Rule]] = {}
    for r in rules():
        for gate in r.gates:
            out.setdefault(gate, []).append(r)
    return out


@dataclass(frozen=True)
class Finding:
    """first and last: word numbers from 0."""

    label: str
    first: int
    last: int
    priority: int
    confidence: float


def words_line(text: bytes | None) -> bytes:
    """The words, each between single spaces; of no words: one space."""
    words = (text or b"").translate(WORD_BYTES).split()
    return b" " + b"".join(w + b" " for w in words)


def base_places(line: bytes) -> list[tuple[int, str]]:
    """(first word, label) of every place of a base phrase."""
    out, word = [], None
    for phrase, label in BASE:
        needle, at = b" " + phrase.encode() + b" ", -1
        while (at := line.find(needle, at + 1)) >= 0:
            word = _word_starts(line) if word is None else word
            out.append((bisect_left(word, at + 1), label))
    return sorted(out)


def _word_starts(line: bytes) -> list[int]:
    """Where the words of a line start, ascending."""
    return (np.flatnonzero(np.frombuffer(line, np.uint8) == 32)[:-1] + 1).tolist()


def uncontained(hits: list[tuple[int, int]]) -> list[int]:
    """Places of the hits (first, end), given best first, that no better kept hit contains.

    A hit is contained if a kept one starts at or before it and ends at or behind its end, so the greatest
    end of the kept ones up to each start decides; a tree of prefix maxima has it in logarithmic time.
    """
    starts = sorted({s for s, _ in hits})
    reach = [0] * (len(starts) + 1)  # prefix maxima of ends by start, as a binary indexed tree
    kept = []
    for i, (s, e) in enumerate(hits):
        at = place = bisect_left(starts, s) + 1
        best = 0
        while at:
            best = max(best, reach[at])
            at &= at - 1
        if best >= e:
            continue
        kept.append(i)
        while place < len(reach):
            reach[place] = max(reach[place], e)
            place += place & -place
    return kept


def detect(line: bytes, words: list[bytes]) -> list[Finding]:
    """What the rules find after suppression, by place."""
    gates = _gates()
    if gates.keys().isdisjoint(words):
        return []
    tried = sorted({r: None for g in sorted(gates.keys() & set(words)) for r in gates[g]}, key=lambda r: -r.priority)
    raw_hits = [(r.priority, m.end() - m.start(), -m.start(), r, m.start(), m.end()) for r in tried for m in r.pattern.finditer(line)]
    raw_hits.sort(key=lambda h: h[:3], reverse=True)
    if not raw_hits:
        return []
    word, out = _word_starts(line), []
    for i in uncontained([(s, e) for _, _, _, _, s, e in raw_hits]):
        priority, _, _, r, s, e = raw_hits[i]
        first = bisect_left(word, s)
        out.append(Finding(r.label, first, bisect_left(word, e) - 1, priority, r.confidence))
    return sorted(out, key=lambda f: (f.first, f.last))


SCHEMA = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"


def scan(docs: DataFrame) -> DataFrame:
    """One row a document: n_words, n_base, first_word, last_word, base_labels, labels, score, findings.

    Null, empty and wordless texts have no words, empty label strings and score 0. Every row is
    scanned for itself, so repeated rows repeat. score is the best confidence of a detection, 1
    with a base phrase. findings: the surviving detections as structs. Other columns are not read.
    """

    def run(batches: Batches) -> Batches:
        fields = [("label", pa.string()), ("first", pa.int64()), ("last", pa.int64()), ("priority", pa.int64()), ("confidence", pa.float64())]
        schema = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_base", pa.int64()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64()), ("findings", pa.list_(pa.struct(fields)))])
        for b in batches:
            rows = []
            for doc_id, text in zip(b.column("doc_id").to_pylist(), raw(b, "text"), strict=True):
                line = words_line(text)
                words = line.split()
                base = base_places(line)
                found = detect(line, words)
                own = {label for _, label in base}
                every = own | {f.label for f in found}
                score = 1.0 if base else max((f.confidence for f in found), default=0.0)
                rows.append((doc_id, len(words), len(base), base[0][0] if base else None, base[-1][0] if base else None, ",".join(sorted(own)), ",".join(sorted(every)), score, [vars(f) for f in found]))
            yield table(schema, *zip(*rows, strict=True)) if rows else table(schema, *([] for _ in schema))

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, SCHEMA + ", findings array<struct<label string, first long, last long, priority long, confidence double>>")
