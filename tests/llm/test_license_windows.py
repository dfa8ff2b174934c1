"""Altered and repeated notices against a plain longest common subsequence."""

import random

from geopages.llm.license_scan import LEAST_COVERAGE, TEMPLATES, scan, words
from geopages.llm.license_texts import FULL_TEXTS

PROSE = "the quiet harbour of the old town kept its lamps burning and any ship that came in was met by a person with a copy".split()


def _lcs(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        new = [0]
        for j, y in enumerate(b):
            new.append(row[j] + 1 if x == y else max(row[j + 1], new[j]))
        row = new
    return row[-1]


def _found(text):
    out = {}
    for x in scan(text):
        out.setdefault(x["license"], x["coverage"])
    return out


def test_notices_without_their_first_mark():
    assert _found("This work is licensed under the General Public License, version 3") == {"GPL-3.0": 11 / 12}
    assert "BSD-3-Clause" in _found(TEMPLATES["BSD-3-Clause"][0].replace("Redistribution", "Redistributions"))
    for name in ("MIT-text", "ISC"):
        assert name in _found(TEMPLATES[name][0].replace("granted", "given"))


def test_notice_twice_in_a_row():
    for name, (t, _) in TEMPLATES.items():
        assert _found(" ".join([*PROSE, t, t, *PROSE])).get(name) == 1, name


def test_altered_notices_against_plain_lcs():
    r = random.Random(8)
    hits = 0
    for _ in range(400):
        name = r.choice(list(TEMPLATES))
        t = words(TEMPLATES[name][0])
        parts = []
        for _ in range(r.choice([1, 1, 2])):
            w = list(t)
            for _ in range(r.choice([0, 1, 1, 2, 3])):
                i = r.randrange(len(w))
                w[i : i + 1] = r.choice([[], ["other"], [w[i], r.choice(t)], [r.choice(t)]])
            parts += w
        text = [*r.choices(PROSE, k=r.randrange(12)), *parts, *r.choices(PROSE, k=r.randrange(12))]
        n = len(t)
        want = max(_lcs(t, text[i : i + 2 * n + 1]) for i in range(len(text))) / n
        got = _found(" ".join(text)).get(name, 0)
        assert got == (want if want >= LEAST_COVERAGE else 0), (name, got, want, text)
        hits += got > 0
    assert hits > 100


def test_every_place_of_a_license():
    mit, gpl = TEMPLATES["MIT"][0], TEMPLATES["GPL-3.0"][0]
    text = " ".join([*PROSE, mit, *PROSE, gpl, *PROSE, mit, mit, "released under some license", *PROSE])
    got = scan(text)
    assert [x["license"] for x in got] == ["MIT"] * 3 + ["GPL-3.0"]
    spans = sorted((x["first_word"], x["last_word"]) for x in got)
    assert all(a[1] < b[0] for a, b in zip(spans, spans[1:])) and all(x["coverage"] == 1 for x in got)
    w = words(text)
    assert all(w[x["first_word"] : x["last_word"] + 1] == words(TEMPLATES[x["license"]][0]) for x in got)


def test_full_texts():
    for name, (t, _) in FULL_TEXTS.items():
        w = words(t)
        cut = " ".join([*PROSE, *w[: len(w) // 2], "changed", *w[len(w) // 2 + 4 :], *PROSE])
        got = _found(cut)
        assert got[name] == (len(w) - 4) / len(w), name
        assert name not in _found(" ".join(w[: len(w) // 2]))
    # a text and the shorter one within it are both told
    assert {"BSD-2-Clause-full", "BSD-3-Clause-full", "BSD-3-Clause"} <= set(_found(FULL_TEXTS["BSD-3-Clause-full"][0]))


def test_a_very_long_text_with_repeats():
    text = " ".join(PROSE * 3000 + [TEMPLATES["ISC"][0]] * 5 + PROSE * 3000)
    assert [x["license"] for x in scan(text)] == ["ISC"] * 5
