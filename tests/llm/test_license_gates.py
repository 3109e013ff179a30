"""The gated scan equals the ungated one on every alternative of every rule's name."""

from itertools import product
from re import _constants as c
from re import _parser as parser

import numpy as np

from pushwave.llm import licenses


def _examples(tree) -> list[str]:
    """All strings of a pattern made of letters, sets, groups, branches and optional parts."""
    parts = []
    for op, arg in tree:
        if op is c.LITERAL:
            parts.append([chr(arg)])
        elif op is c.IN:
            first = arg[0]
            parts.append([chr(first[1] if first[0] is c.LITERAL else first[1][0])] if first[0] is not c.CATEGORY else ["7"])
        elif op is c.SUBPATTERN:
            parts.append(_examples(arg[3]))
        elif op is c.BRANCH:
            parts.append([x for branch in arg[1] for x in _examples(branch)])
        elif op is c.MAX_REPEAT:
            assert arg[:2] == (0, 1)
            parts.append(["", *_examples(arg[2])])
        else:
            raise AssertionError(op)
    return ["".join(p) for p in product(*parts)]


def test_gated_scan_equals_ungated(monkeypatch):
    names = {x for _, name, _ in licenses.FAMILIES for x in _examples(parser.parse(name))}
    lines = [f"we say licensed under the {x} license here" for x in sorted(names)]
    lines += [x for *_, body, _ in licenses.SINGLE for x in _examples(parser.parse(body))]
    lines = [licenses.words_line(x.encode()) for x in lines]
    gated = [licenses.detect(line, line.split()) for line in lines]
    every = {b"": list(licenses.rules())}
    monkeypatch.setattr(licenses, "_gates", lambda: every)
    assert gated == [licenses.detect(line, [b""]) for line in lines]
    assert all(gated)


def test_names_that_had_no_gate():
    want = {"licensed under the freebsd license": "bsd-2", "common development and distribution license version 1 license": "cddl-1", "licensed under mpl 1 1": "mpl-1.1", "licensed under cc zero": "cc0-1", "under creative commons attribution no derivatives license": "cc-by-nd", "licensed under gpl2": "gpl-2"}
    for text, label in want.items():
        line = licenses.words_line(text.encode())
        assert {f.label for f in licenses.detect(line, line.split())} == {label}


def test_suppression_equals_brute_force():
    rng = np.random.default_rng(1)
    for n in (0, 1, 7, 300):
        hits = [(int(a), int(a + b)) for a, b in zip(rng.integers(0, 60, n), rng.integers(1, 30, n), strict=True)]
        want, taken = [], []
        for i, (s, e) in enumerate(hits):
            if not any(a <= s and e <= b for a, b in taken):
                taken.append((s, e))
                want.append(i)
        assert licenses.uncontained(hits) == want


def test_places_are_word_numbers():
    text = b"x, y under the MIT license. " * 500
    line = licenses.words_line(text)
    places = licenses.base_places(line)
    assert [p for p, _ in places] == [2 + 6 * i for i in range(500)]
    found = licenses.detect(line, line.split())
    words = line.split()
    assert len(found) >= 500 and all(b"mit" in words[f.first : f.last + 1] for f in found if f.label == "mit")
