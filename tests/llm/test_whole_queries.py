"""The registered queries that SQL doesn't express, whole, against brute force that shares no code with them."""

import re
from collections import Counter, defaultdict

import __spark_entry__ as entry
import numpy as np
import pytest
import regex

from geopages.llm import mixing, surrogates
from geopages.llm.license_scan import LEAST_COVERAGE, TEMPLATES
from geopages.llm.token_counts import _encoder, vocabulary

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def docs(spark):
    return [tuple(r) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "source").collect()]


def _rows(spark, name):
    return entry.queries()[name](spark, SF).collect()


def test_op4_shards_are_runs_of_the_table(spark, docs):
    rows = {r.doc_id: r for r in _rows(spark, "op4_sharding")}
    order = [rows[d].shard_id for d, _, _ in docs]
    assert len(rows) == len(docs) and order == sorted(order)
    held = Counter(order)
    assert all(r.shard_rows == held[r.shard_id] for r in rows.values())


def test_op5_every_token_once(spark, docs):
    encoder, size = _encoder(*vocabulary())
    want = []
    for d, t, _ in docs:
        raw = t.encode()
        lines = raw.split(b"\n")
        lines = [x + b"\n" for x in lines[:-1]] + ([lines[-1]] if lines[-1] or len(lines) == 1 else [])
        starts = [0]
        for x in lines[:-1]:
            starts.append(starts[-1] + len(x))
        line_of = np.repeat(np.arange(len(lines)), [len(x) for x in lines])
        n, crossing, at = [0] * len(lines), [0] * len(lines), 0
        for token in encoder.encode_ordinary(t):
            a, b = line_of[at], line_of[at + size[token] - 1]
            n[a] += 1
            crossing[a] += a != b
            at += size[token]
        want += [(d, i, starts[i], len(x), n[i], crossing[i]) for i, x in enumerate(lines)]
    assert sorted(map(tuple, _rows(spark, "op5_token_counts"))) == sorted(want)


def _java(p):
    return p.replace(r"\p{IsCyrillic}", r"\p{Cyrillic}").replace(r"\d", "[0-9]").replace(r"[^[0-9].]", r"[^0-9.]")


def test_op7_entity_by_entity(spark, docs):
    kinds = {k: regex.compile(_java(p)) for k, p in surrogates.PATTERNS.items()}
    every = regex.compile("|".join(f"(?P<{k}>{_java(p)})" for k, p in surrogates.PATTERNS.items()))
    new = {r.doc_id: r for r in _rows(spark, "op7_surrogates")}
    assert set(new) == {d for d, _, _ in docs}
    said, n_found = {}, Counter()
    for d, t, _ in docs:
        got, at, end = new[d].text, 0, 0
        found = list(every.finditer(t))
        assert new[d].n_entities == len(found)
        for m, nxt in zip(found, [*found[1:], None]):
            kind = m.lastgroup
            n_found[kind] += 1
            between = t[end : m.start()]
            assert got[at : at + len(between)] == between
            at, end = at + len(between), m.end()
            rest = t[end : nxt.start()] if nxt else t[end:]
            if kind in ("phone", "identity", "card", "secret"):
                put = got[at : at + len(m[0])]
                assert re.sub("[0-9]", "0", put) == re.sub("[0-9]", "0", m[0]) or kind == "secret"
            else:
                put = got[at:] if not nxt and not rest else got[at : got.index(rest[:40], at) if rest else len(got)]
            assert kinds[kind].fullmatch(put), (kind, m[0], put)
            form = re.sub(r"\D", "", m[0]) if kind in ("phone", "identity", "card") else m[0].lower() if kind == "email" else m[0]
            form_new = re.sub(r"\D", "", put) if kind in ("phone", "identity", "card") else put
            assert said.setdefault((kind, form), form_new) == form_new != form
            at += len(put)
        assert got[at:] == t[end:]
    assert len({(k, v) for (k, _), v in said.items()}) == len(said) and len(n_found) >= 4


def test_op7_long_secrets_keep_length_and_stay_apart(spark):
    long = ["sk-" + "aB3" * 70, "sk-" + "aB3" * 69 + "aB4", "0123456789abcdef" * 40, "0123456789abcdef" * 39 + "0123456789abcde0"]
    texts = [f"key {x}." for x in long] + ["x" * 300_000 + " end", "mark \ufdd0 a@b.example.org \ufdd1 and c@d.example.org"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    out = {r.doc_id: r.text for r in surrogates.with_surrogates(df, "k").collect()}
    assert all(len(out[i]) == len(texts[i]) and out[i] != texts[i] for i in range(4)) and len({out[i] for i in range(4)}) == 4
    assert out[4] == texts[4] and re.fullmatch("mark \ufdd0 \\S+@\\S+ \ufdd1 and \\S+@\\S+", out[5]) and "@b." not in out[5]


def _lcs(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        new = [0]
        for j, y in enumerate(b):
            new.append(row[j] + 1 if x == y else max(row[j + 1], new[j]))
        row = new
    return row[-1]


def test_op8_against_every_window(spark, docs):
    got = {r.doc_id: dict(zip(r.licenses, r.coverage_permille)) for r in _rows(spark, "op8_license_scan")}
    assert set(got) == {d for d, _, _ in docs}
    for d, t, _ in docs:
        own = re.findall(r"[^\W_]+", t.lower())
        for name, (template, _) in TEMPLATES.items():
            w = re.findall(r"[^\W_]+", template.lower())
            n, have = len(w), Counter(w)
            best, inside, common = 0, Counter(), 0
            at = [i for i, x in enumerate(own) if x in have]
            for k, i in enumerate(at):  # windows that start with a template's word
                near = [own[j] for j in at[k : k + 2 * n + 1] if j <= i + 2 * n]
                if sum((Counter(near) & have).values()) >= LEAST_COVERAGE * n:
                    best = max(best, _lcs(w, near))
            want = round(best / n * 1000) if best / n >= LEAST_COVERAGE else None
            assert got[d].get(name) == want, (d, name)


def test_op10_against_a_walk_over_slots(spark, docs):
    rows = _rows(spark, "op10_mixing")
    assert sorted(r.doc_id for r in rows) == sorted(d for d, _, _ in docs)
    weights = dict(mixing.TARGETS) | {"": mixing.REST_WEIGHT}
    by = defaultdict(list)
    for r in rows:
        by[r.source if r.source in mixing.TARGETS else ""].append(r)
    left = {s: -(-len(v) // mixing.BLOCK) for s, v in by.items()}
    t, start, given, owner = 0, 0, dict.fromkeys(left, 0), []
    while left:
        total = sum(weights[s] for s in left)
        x = t - start
        ready = [s for s in left if given[s] * total // weights[s] <= x]
        s = min(ready, key=lambda s: (-(-(given[s] + 1) * total // weights[s]), -weights[s], s))
        owner.append(s)
        given[s] += 1
        left[s] -= 1
        t += 1
        if not left[s]:
            del left[s]
            start, given = t, dict.fromkeys(left, 0)
    slots = defaultdict(list)
    for i, s in enumerate(owner):
        slots[s].append(i)
    for s, v in by.items():
        v.sort(key=lambda r: r.position)
        for i, r in enumerate(v):
            assert (r.block, r.slot, r.position) == (i // mixing.BLOCK, slots[s][i // mixing.BLOCK], slots[s][i // mixing.BLOCK] * mixing.BLOCK + i % mixing.BLOCK)
            assert r.release <= r.slot < r.deadline


@pytest.mark.parametrize("limit", [0, 10**9])
def test_mixing_columns_of_any_name_and_both_plans(spark, monkeypatch, limit):
    monkeypatch.setattr(mixing, "BROADCAST_ROWS", limit)
    df = spark.range(500).selectExpr("id as doc_id", "concat('src', id % 3) as source", "id as _mix", "id as `a.b`", "id as _src", "id as slots", "id as `c``d`")
    out = mixing.mixed(df)
    assert out.columns == df.columns and sorted(r["a.b"] for r in out.collect()) == list(range(500))
    rows = mixing.schedule(df).collect()
    assert sorted(r["__mix"].position for r in rows)[0] == 0 and all(r["_mix"] == r["doc_id"] for r in rows)
