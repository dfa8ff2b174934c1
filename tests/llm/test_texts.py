import random
import re

import numpy as np
import pytest

from geopages.llm.license_scan import align, find_licenses, increasing, scan
from geopages.llm.surrogates import with_surrogates
from geopages.llm.token_counts import RULES, _encoder, section_tokens, vocabulary


@pytest.mark.parametrize("rule", RULES)
def test_tokens_against_a_walk_over_each_byte(spark, rule):
    docs = [(1, "The first line.\nSecond öne 😀\n\n\n  end"), (2, None), (3, ""), (4, "\n"), (5, "x" * 300 + "\n" + "größe " * 50), (None, "a\r\n\r\nb"), (1, "again")]
    got = section_tokens(spark.createDataFrame(docs, "doc_id long, text string"), rule).collect()
    encoder, size = _encoder(*vocabulary())
    want = []
    for d, t in docs:
        raw = (t or "").encode()
        line = [raw[:i].count(b"\n") for i in range(len(raw))]
        n = [0.0] * max(1, len(set(line)))
        at = 0
        for token in encoder.encode_ordinary(t or ""):
            own = line[at : at + size[token]]
            at += size[token]
            for s in {"first": own[:1], "last": own[-1:], "most": [max(sorted(set(own)), key=own.count)], "share": own}[rule]:
                n[s] += 1 / len(own) if rule == "share" else 1
        want += [(d, i, round(x, 6)) for i, x in enumerate(n)]
    key = lambda x: str(x)
    assert sorted(((r.doc_id, r.section, round(r.n_tokens, 6)) for r in got), key=key) == sorted(want, key=key)
    assert section_tokens(spark.createDataFrame([], "doc_id long, text string"), rule).collect() == []


def test_increasing_is_longest():
    r = random.Random(1)
    for _ in range(100):
        p = list(enumerate(r.sample(range(50), 9)))
        best = max(len(s) for m in range(512) if (s := [b for i, b in p if m >> i & 1]) == sorted(s))
        got = increasing(p)
        assert len(got) == best and [b for _, b in got] == sorted(b for _, b in got)


def test_align_and_scan(spark):
    a, b = "a b c d e f g".split(), "x a b y d e z g".split()
    assert align(a, b) == [(0, 1), (1, 2), (3, 4), (4, 5), (6, 7)]
    text = "Foo bar. " * 30 + "licensed UNDER the   Apache license (version 2.0) and more " + "under the " * 20
    assert [x["license"] for x in scan(text)] == ["Apache-2.0"] and scan("apache is a word") == [] and scan(None) == []
    docs = [(1, text), (2, None), (3, ""), (1, text), (4, "This work is licensed under the GNU General Public License, version 3. Licensed under CC BY-NC 4.0.")]
    got = {r.doc_id: [x.license for x in r.licenses] for r in find_licenses(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == {1: ["Apache-2.0"], 2: [], 3: [], 4: ["GPL-3.0", "CC-BY-NC-4.0"]}


def test_surrogates(spark):
    docs = [
        (1, "a.b44@mail7.example.com wrote to A.B44@mail7.example.com, not réeux.09@mail2.example.com."),
        (2, "call +1 (811) 555-3281 or +1-811-555-3281; card 4652511922028856 = 4652 5119 2202 8856!"),
        (3, "from 196.3.67.149 key = \"08813ad77930c5f691325605b62c9dfd1b407297\" 12.5 version 2.0."),
        (4, "Mrs. Ada Stone met Mr Karl Stone; Mrs Ada Stone left. Г-жа Анна Петрова тоже."),
        (5, None), (6, ""), (7, "nothing here 1234"), (2, "call +1 (811) 555-3281 or +1-811-555-3281; card 4652511922028856 = 4652 5119 2202 8856!"), (None, "1.2.3.4"),
    ]
    got = {}
    rows = with_surrogates(spark.createDataFrame([(*d, 1) for d in docs], "doc_id long, text string, new int"), "k").collect()
    assert len(rows) == len(docs)
    for r in rows:
        got[r.doc_id] = r.text
    e = re.findall(r"\S+@\S+", got[1])
    assert e[0].lower() == e[1].lower().rstrip(",") and e[0] != e[2] and all(".example.net" in x for x in e)
    assert re.fullmatch(r"call \+1 \(\d{3}\) \d{3}-\d{4} or \+1-\d{3}-\d{3}-\d{4}; card \d{16} = \d{4} \d{4} \d{4} \d{4}!", got[2])
    n = re.sub(r"\D", "", got[2])
    assert n[:11] == n[11:22] and n[22:38] == n[38:54] and "811" not in got[2][:12] and n[22] == "4"
    assert re.fullmatch(r'from 10(\.\d{1,3}){3} key = "[0-9a-f]{40}" 12\.5 version 2\.0\.', got[3]) and "08813a" not in got[3]
    m = re.fullmatch(r"(Mrs\. \w+ \w+) met (Mr \w+ \w+); (Mrs \w+ \w+) left\. (Г-жа [А-Яа-я]+ [А-Яа-я]+) тоже\.", got[4])
    assert m and m[1].replace(".", "") == m[3] and "Stone" not in got[4] and "Петрова" not in got[4]
    assert got[5] is None and got[6] == "" and got[7] == docs[6][1] and got[None].startswith("10.")
    assert with_surrogates(spark.createDataFrame([], "doc_id long, text string"), "k").collect() == []


def test_surrogates_stay_distinct(spark):
    docs = [(i, " ".join(f"Mr Ab{chr(97 + i % 26)}{chr(97 + j % 26)}{'x' * (j // 26)}" for j in range(60)) + f" 10.0.{i}.{i}") for i in range(40)]
    rows = with_surrogates(spark.createDataFrame(docs, "doc_id long, text string"), "k").collect()
    seen = {}
    for d, t in docs:
        new = next(r.text for r in rows if r.doc_id == d)
        for a, b in zip(re.findall(r"Mr \w+|[\d.]{7,}", t), re.findall(r"Mr \w+|[\d.]{7,}", new), strict=True):
            assert seen.setdefault(a, b) == b
    assert len(set(seen.values())) == len(seen) and not set(seen) & set(seen.values())
    assert np.all([r.n_entities == 61 for r in rows])
