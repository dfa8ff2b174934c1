"""Substring dedup by seed and extend, over words.

Documents meet on winnowed anchors of ``seed`` words (see ``_repeats``). From a shared
anchor all its contexts are extended both ways, word by word: they fall into ever
smaller classes that agree so far, and a context without company leaves. Those that
still agree over ``width`` words in all repeat; their outermost windows, joined over a
text's anchors, are its maximal repeats. Words are 64-bit values of their bytes.

Results by case: null, empty and blank texts have no words; texts under ``width``
words lose none; rows of one doc_id with different texts are documents of their own;
equal rows count once and get equal results, one for each; an empty table gives no rows;
other columns are ignored.
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

WIDTH, SEED = 35, 9


def _extended(classes: np.ndarray, words: np.ndarray, first: np.ndarray, step: int, room: np.ndarray, reach: int) -> list[np.ndarray]:
    """Classes of matches after 0, 1, ... ``reach`` words from ``first`` in direction ``step``.

    Rows of one class agree on all words so far; a row leaves (-1) when nobody agrees with it or its text ends.
    """
    out = [classes]
    many = int(words.max()) + 1 if len(words) else 1
    for k in range(reach):
        rows = np.flatnonzero((out[-1] >= 0) & (room > k))
        now = np.full(len(classes), -1, np.int64)
        if len(rows):
            _, own, size = np.unique(out[-1][rows] * many + words[first[rows] + step * k], return_inverse=True, return_counts=True)
            now[rows] = np.where(size[own] > 1, own, -1)
        out.append(now)
    return out


def extend_both_ways(group, doc, n_left, raw, at, spec, multi) -> tuple[np.ndarray, np.ndarray]:
    """Contexts of one seed extended word by word, all of them at once: to the right over the seed and on, and to the left.

    A window reaches ``o`` words to the left and the rest to the right; it repeats where another
    context agrees on both. Word values are compared, no hashes of runs.
    """
    values, at = np.ascontiguousarray(raw).view(np.uint64), at // 8
    _, words = np.unique(values, return_inverse=True)
    n = len(doc)
    lo, hi = np.full(n, -1, np.int64), np.full(n, -1, np.int64)
    anchor = at[:-1] + n_left
    start = group.astype(np.int64)
    to_right = _extended(start, words, anchor, 1, at[1:] - anchor, spec.width)
    to_left = _extended(start, words, anchor - 1, -1, n_left, spec.left)
    for o in range(spec.left + 1):
        left, right = to_left[o], to_right[spec.width - o]
        rows = np.flatnonzero((left >= 0) & (right >= 0))
        if not len(rows):
            continue
        _, own, size = np.unique(left[rows] * (n + 1) + right[rows], return_inverse=True, return_counts=True)
        hit = rows[size[own] > 1]
        lo[hit] = np.where(lo[hit] < 0, o, lo[hit])
        hi[hit] = o
    return lo, hi


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in (x for y in batches for x in S.slices(y)):
        raw, borders = S.raw_texts(b.column(1))
        start, end, at = S.word_spans(raw, borders)
        data = raw.tobytes()
        n_words = np.diff(at)
        removed, spans, sha, kept = [], [], [], []
        for i, (s, e) in enumerate(R.span_arrays(b.column(2), n_words)):
            words = data[borders[i] : borders[i + 1]].translate(_TO_BLANK).split(b" ")
            words = [w for w in words if w]
            if len(s):
                edges = [0, *np.stack([s, e], 1).ravel().tolist(), len(words)]
                words = [w for x, y in zip(edges[::2], edges[1::2], strict=True) for w in words[x:y]]
            text = b" ".join(words)
            removed.append(int((e - s).sum()))
            spans.append(list(zip(s.tolist(), e.tolist(), strict=True)))
            sha.append(hashlib.sha256(text).hexdigest())
            kept.append(text)
        yield pa.record_batch(
            [b.column(0), pa.array(n_words), pa.array(removed, pa.int64()), pa.array([[{"start": x, "end": y} for x, y in v] for v in spans], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), pa.array(sha, pa.string()), pa.array(kept, pa.binary()).cast(pa.string())],
            names=["doc", "n_words", "n_removed", "removed", "kept_sha256", "kept"],
        )


_TO_BLANK = bytes(32 if c in S.SPACES else c for c in range(256))


def remove_repeated_passages(docs: DataFrame, width: int = WIDTH, seed: int = SEED) -> DataFrame:
    """(doc_id, n_words, n_removed, removed, kept_sha256, kept): word spans taken out of each text and what stays.

    A word goes if a window of ``width`` words over it also starts anywhere else,
    in the same document or another; no copy stays.
    """
    spec = R.Spec(width, seed, False, "words")
    scratch = Scratch(docs.sparkSession, "seed_extend")
    keys = keyed(docs, scratch)
    rows = keys.rows
    spans = R.covered_intervals(rows, spec, extend_both_ways, scratch)
    out = R.with_spans(rows, spans).mapInArrow(_cut, "doc long, n_words long, n_removed long, removed array<struct<start:long,end:long>>, kept_sha256 string, kept string")
    return keys.again(out)


def op9_seed_extend(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = remove_repeated_passages(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", "kept_sha256")
