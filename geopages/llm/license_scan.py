"""License scans by patience alignment.

A text's words and a template's are aligned on anchors: words that stand exactly once
in both, kept in a longest increasing subsequence; each gap between anchors is aligned
again in the same way, and runs of equal words next to an anchor are taken in; a gap
without anchors, and a window in which anchors keep a longer alignment out, take a longest
common subsequence. The share of the template's words that are aligned is its coverage.

A license is found in any window of twice the template's words and one where coverage
reaches the threshold, so it is seen against its own surroundings anywhere in a long text.
Windows are looked at around seeds: the template's rarest words, at one place more than the
threshold allows to be missing, so that no alignment that reaches it is without one. The
size of a window's longest common subsequence, by operations on the bits of one number,
tells first whether it does. Of all windows of a license the fullest is taken first; its
stretch of words is taken out and the rest is looked at again, so every place comes out.
Templates are notices and, beside them, full texts of short licenses.

Results by case: a null, empty or wordless text has no licenses; equal rows get equal
results, one for each; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache
from heapq import heapify, heappop, heappush

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ._common import table
from .license_texts import FULL_TEXTS

# Notices by which works name their license, and the words that mark them.
TEMPLATES = {
    "MIT": ("Released under the MIT License.", ("mit",)),
    "Apache-2.0": ("Licensed under the Apache License, Version 2.0.", ("apache",)),
    "GPL-3.0": ("This work is licensed under the GNU General Public License, version 3.", ("gnu",)),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.", ("cc",)),
    "CC-BY-SA-4.0": ("Licensed under CC BY-SA 4.0.", ("cc",)),
    "BSD-3-Clause": ("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met", ("redistribution",)),
    "MIT-text": ("Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files", ("granted",)),
    "ISC": ("Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted", ("granted",)),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.", ("mozilla",)),
}
#: Words that many texts hold; seeds are taken from them last.
COMMON = frozenset("a an and any are binary by charge code conditions copy distribute distribution documentation fee files following for form forms free general in is met modify notice of or person provided public purpose software source subject term terms that the this to use version with without work 0 2 3 4".split())
ALL_TEMPLATES = TEMPLATES | FULL_TEXTS
WORD = re.compile(r"[^\W_]+")
LEAST_COVERAGE = 0.9


def words(text: str) -> list[str]:
    return WORD.findall(text.lower())


def increasing(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Of pairs sorted by their first numbers, a longest run whose second numbers increase; by patience piles."""
    tops: list[int] = []
    piles: list[int] = []
    back: list[int] = []
    for i, (_, b) in enumerate(pairs):
        k = bisect_left(tops, b)
        back.append(piles[k - 1] if k else -1)
        if k == len(tops):
            tops.append(b)
            piles.append(i)
        else:
            tops[k], piles[k] = b, i
    out, i = [], piles[-1] if piles else -1
    while i >= 0:
        out.append(pairs[i])
        i = back[i]
    return out[::-1]


def common(a: list[str], b: list[str]) -> list[tuple[int, int]]:
    """Places of a longest common subsequence, by dynamic programming."""
    best = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i in range(len(a) - 1, -1, -1):
        row, below = best[i], best[i + 1]
        for j in range(len(b) - 1, -1, -1):
            row[j] = below[j + 1] + 1 if a[i] == b[j] else max(below[j], row[j + 1])
    out, i, j = [], 0, 0
    while i < len(a) and j < len(b):
        if a[i] == b[j]:
            out.append((i, j))
            i, j = i + 1, j + 1
        elif best[i + 1][j] >= best[i][j + 1]:
            i += 1
        else:
            j += 1
    return out


def align(a: list[str], b: list[str]) -> list[tuple[int, int]]:
    """Aligned places of ``a`` and ``b``, both increasing."""
    out: list[tuple[int, int]] = []
    todo = [(0, len(a), 0, len(b))]
    while todo:
        a0, a1, b0, b1 = todo.pop()
        while a0 < a1 and b0 < b1 and a[a0] == b[b0]:
            out.append((a0, b0))
            a0, b0 = a0 + 1, b0 + 1
        while a0 < a1 and b0 < b1 and a[a1 - 1] == b[b1 - 1]:
            a1, b1 = a1 - 1, b1 - 1
            out.append((a1, b1))
        if a0 == a1 or b0 == b1:
            continue
        once_a, once_b = Counter(a[a0:a1]), Counter(b[b0:b1])
        where = {w: j for j, w in enumerate(b[b0:b1], b0) if once_b[w] == 1}
        anchors = increasing([(i, where[w]) for i, w in enumerate(a[a0:a1], a0) if once_a[w] == 1 and w in where])
        if not anchors:
            out += [(a0 + i, b0 + j) for i, j in common(a[a0:a1], b[b0:b1])]
            continue
        out += anchors
        edges = [(a0 - 1, b0 - 1), *anchors, (a1, b1)]
        todo += [(p + 1, r, q + 1, s) for (p, q), (r, s) in zip(edges, edges[1:], strict=False)]
    return sorted(out)


def _lcs_size(a: list[str], masks: dict[str, int], n: int) -> int:
    """Length of a longest common subsequence of ``a`` and a template of ``n`` words, given by its places as bits for each word."""
    full = (1 << n) - 1
    v = full
    for w in a:
        if m := masks.get(w):
            u = v & m
            v = ((v + u) | (v - u)) & full
    return n - v.bit_count()


@dataclass(frozen=True)
class Template:
    words: list[str]
    #: Aligned words from which coverage reaches the threshold.
    need: int
    #: The words at as many places, the rarest ones, as may be missing and one more: one of them is in every such alignment.
    seeds: frozenset[str]
    masks: dict[str, int]


def prepared(template: str, marks: tuple[str, ...], least: float) -> Template:
    t = words(template)
    n = len(t)
    need = max(1, next((k for k in range(n + 1) if k / n >= least), n + 1))
    rare = sorted(range(n), key=lambda i: (t[i] not in marks, t[i] in COMMON, -len(t[i]), i))
    masks: dict[str, int] = {}
    for i, w in enumerate(t):
        masks[w] = masks.get(w, 0) | 1 << i
    return Template(t, need, frozenset(t[i] for i in rare[: n - need + 1]), masks)


def _places(own: list[str], t: Template) -> Iterator[tuple[int, int, int]]:
    """First word, last word and aligned words of every place of a template, from the fullest; places don't overlap."""
    own, n = list(own), len(t.words)
    starts: set[int] = set()
    for i, w in enumerate(own):
        # any window that holds this seed lies within; a subsequence of it is one of the whole
        if w in t.seeds and _lcs_size(own[max(0, i - 2 * n) : i + 2 * n + 1], t.masks, n) >= t.need:
            starts.update(range(max(0, i - 2 * n), i + 1))
    size = {s: _lcs_size(own[s : s + 2 * n + 1], t.masks, n) for s in sorted(starts)}
    queue = [(-k, s) for s, k in size.items() if k >= t.need]
    heapify(queue)
    while queue:
        most, s = heappop(queue)
        most = -most
        if size[s] != most:
            continue
        # of the first windows that have the most, the last one: it starts with an aligned word
        while size.get(s + 1) == most:
            s += 1
        p = align(t.words, own[s : s + 2 * n + 1])
        if len(p) < most:  # the anchors kept a longer alignment out
            p = common(t.words, own[s : s + 2 * n + 1])
        first, last = s + p[0][1], s + p[-1][1]
        yield first, last, most
        own[first : last + 1] = [""] * (last + 1 - first)  # in no template
        for x in range(first - 2 * n, last + 1):
            if x in size:
                size[x] = _lcs_size(own[x : x + 2 * n + 1], t.masks, n)
                if size[x] >= t.need:
                    heappush(queue, (-size[x], x))


def scan(text: str | None, templates: dict | None = None, least: float = LEAST_COVERAGE) -> list[dict]:
    """Licenses of a text, by template, the fullest place first: name, coverage, first and last word of the aligned stretch."""
    low = (text or "").lower()
    out = []
    own: list[str] | None = None
    for name, (template, marks) in (templates or ALL_TEMPLATES).items():
        t = _prepared(template, marks, least)
        if not any(m in low for m in t.seeds):
            continue
        own = words(low) if own is None else own
        out += [{"license": name, "coverage": most / len(t.words), "first_word": i, "last_word": j} for i, j, most in _places(own, t)]
    return out


_prepared = cache(prepared)


FOUND = "doc_id long, licenses array<struct<license:string,coverage:double,first_word:int,last_word:int>>"
_KIND = pa.list_(pa.struct([("license", pa.string()), ("coverage", pa.float64()), ("first_word", pa.int32()), ("last_word", pa.int32())]))


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield pa.record_batch([b.column(0), pa.array([scan(t.as_py()) for t in b.column(1)], _KIND)], names=["doc_id", "licenses"])


def find_licenses(docs: DataFrame) -> DataFrame:
    return docs.selectExpr("cast(doc_id as long) as doc_id", "cast(text as string) as text").mapInArrow(_scan, FOUND)


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Licenses of each document in the order of the templates, the greatest coverage of each, and the number of places."""
    out = find_licenses(table(spark, sf_dir, "documents"))
    names = "array_distinct(licenses.license)"
    best = f"transform({names}, n -> cast(round(array_max(transform(filter(licenses, x -> x.license = n), x -> x.coverage)) * 1000) as int))"
    return out.selectExpr("doc_id", f"size({names}) as n_licenses", f"{names} as licenses", f"{best} as coverage_permille", "size(licenses) as n_places")
