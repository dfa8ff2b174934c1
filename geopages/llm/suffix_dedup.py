"""Suffix-array dedup: bytes of repeated 50-byte strings, first document kept.

A suffix array over every byte of the corpus would be many times its size. A
repeated string of ``width`` bytes shows at its anchor, so only suffixes at
anchors of repeats' edges are sorted (see ``_repeats``): those of one seed by
deep-shallow sorting, rightwards and, reversed, leftwards. Neighbours' common
prefixes cut either order into classes for every depth, and two windows are
equal where they are in the same right class and the same left class.

Results by case: a null or empty text has no bytes and loses none; texts under
``width`` bytes lose none; rows of one doc_id are scanned each, and none of them is
earlier than another; a null doc_id is later than all others; equal rows count once and
get equal results, one for each; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from . import _repeats as R
from . import _symbols as S
from ._common import Scratch, keyed, table
from .deep_shallow import deep_shallow_order

WIDTH, SEED = 50, 16


def _class_rows(rank_lcp: tuple[np.ndarray, np.ndarray], depth: int) -> np.ndarray:
    order, lcp = rank_lcp
    out = np.empty(len(order), np.int64)
    out[order] = np.cumsum(lcp < depth)
    return out


def _sorted_with_lcp(group: np.ndarray, strings: list[bytes], start: int, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Order of all rows, group after group, and each row's common prefix with the row before (-1 for the first of a group)."""
    n = len(group)
    order = np.empty(n, np.int64)
    at = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    for lo, hi in zip(at.tolist(), np.r_[at[1:], n].tolist(), strict=True):
        order[lo:hi] = deep_shallow_order(strings[lo:hi], start)
        order[lo:hi] += lo
    joined = np.frombuffer(b"".join(s.ljust(most, b"\0") for s in strings), np.uint8).reshape(n, most)[order]
    size = np.array([len(s) for s in strings])[order]
    lcp = np.full(n, -1, np.int64)
    if n > 1:
        differ = joined[1:] != joined[:-1]
        same = np.where(differ.any(1), differ.argmax(1), most)
        lcp[1:] = np.minimum(same, np.minimum(size[1:], size[:-1]))
    lcp[at] = -1
    return order, lcp


def resolve_by_suffix_order(group, doc, n_left, raw, at, spec, multi) -> tuple[np.ndarray, np.ndarray]:
    n, L = len(doc), spec.width
    data = raw.tobytes()
    mid = at[:-1] + n_left
    right = [data[m:e] for m, e in zip(mid.tolist(), at[1:].tolist(), strict=True)]
    left = [data[s:m][::-1] for s, m in zip(at[:-1].tolist(), mid.tolist(), strict=True)]
    by_right = _sorted_with_lcp(group, right, spec.seed, L)
    by_left = _sorted_with_lcp(group, left, 0, spec.left)
    n_right = at[1:] - mid
    lo, hi = np.full(n, -1, np.int64), np.full(n, -1, np.int64)
    for o in range(spec.left + 1):
        rows = np.flatnonzero((n_left >= o) & (n_right >= L - o))
        if not len(rows):
            continue
        key = _class_rows(by_right, L - o)[rows] * (n + 1) + _class_rows(by_left, o)[rows]
        by = np.argsort(key, kind="stable")
        new = np.flatnonzero(np.r_[True, key[by][1:] != key[by][:-1]])
        rank = doc[rows][by] >> spec.shift
        first = np.repeat(np.minimum.reduceat(rank, new), np.diff(np.r_[new, len(rows)]))
        hit = rows[by][first < rank]
        lo[hit] = np.where(lo[hit] < 0, o, lo[hit])
        hi[hit] = o
    return lo, hi


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in (x for y in batches for x in S.slices(y)):
        raw, at = S.raw_texts(b.column(1))
        size = np.diff(at)
        data = raw.tobytes()
        removed, spans, sha, kept = [], [], [], []
        for i, (s, e) in enumerate(R.span_arrays(b.column(2), size)):
            text = data[at[i] : at[i + 1]]
            if len(s):
                edges = [0, *np.stack([s, e], 1).ravel().tolist(), len(text)]
                text = b"".join(text[x:y] for x, y in zip(edges[::2], edges[1::2], strict=True))
            removed.append(int((e - s).sum()))
            spans.append(list(zip(s.tolist(), e.tolist(), strict=True)))
            sha.append(hashlib.sha256(text).hexdigest())
            kept.append(text)
        yield pa.record_batch(
            [b.column(0), pa.array(size), pa.array(removed, pa.int64()), pa.array([[{"start": x, "end": y} for x, y in v] for v in spans], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), pa.array(sha, pa.string()), pa.array(kept, pa.binary())],
            names=["doc", "n_bytes", "n_removed", "removed", "kept_sha256", "kept"],
        )


def remove_repeated_strings(docs: DataFrame, width: int = WIDTH, seed: int = SEED) -> DataFrame:
    """(doc_id, n_bytes, n_removed, removed, kept_sha256, kept): the spans taken out of each text and the bytes that stay.

    A byte goes if a ``width``-byte string over it also starts in a document with a
    smaller doc_id. ``kept`` is binary: a cut may split a character.
    """
    scratch = Scratch(docs.sparkSession, "suffix_dedup")
    keys = keyed(docs, scratch)
    rows, spec = keys.rows, R.Spec(width, seed, True, "bytes", keys.shift)
    spans = R.covered_intervals(rows, spec, resolve_by_suffix_order, scratch)
    out = R.with_spans(rows, spans).mapInArrow(_cut, "doc long, n_bytes long, n_removed long, removed array<struct<start:long,end:long>>, kept_sha256 string, kept binary")
    return keys.again(out)


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = remove_repeated_strings(table(spark, sf_dir, "documents"))
    return out.selectExpr("doc_id", "n_bytes", "n_removed", "cast(size(removed) as long) as n_spans", "kept_sha256")
