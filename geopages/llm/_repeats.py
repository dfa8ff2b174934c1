"""Repeated windows of a corpus, found from winnowed anchors.

Both substring operators ask which windows of ``width`` symbols (bytes, words)
stand somewhere else too. Hashing every window would move many times the corpus,
so the work goes through *anchors*:

1. The anchor of a window is the rightmost least-hashed run of ``seed`` symbols
   in it. Equal windows have equal anchors at equal places, and neighbouring
   windows mostly share one, so anchors are sparse: about 2 of ``width - seed + 2``
   symbols.
2. An anchor's *context* reaches ``width - seed`` symbols to the left of the seed's
   first symbol and ``width`` to the right of it: every window that has this anchor
   lies within. Anchors meet by the hash of their seed; where whole contexts are
   equal, all windows in them repeat and nothing else need be known.
3. What is left are the edges of repeats: seeds that stand in several different
   contexts. Only one row for each such context is looked at symbol by symbol.

Equal contexts of one piece of a batch are settled within it, so a passage that
a third of all documents hold sends a row for each piece, not for each document.
Decisions stream through partitions sorted by seed with a few rows of state.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import _symbols as S
from ._common import Scratch, partitions

ANCHOR, COVER = 0, 1
ROWS = "kind byte, seed long, context long, doc long, a int, b int"
_ROWS = pa.schema([("kind", pa.int8()), ("seed", pa.int64()), ("context", pa.int64()), ("doc", pa.int64()), ("a", pa.int32()), ("b", pa.int32())])
FOUND = "kind byte, seed long, doc long, a int, b int, multi boolean"
_FOUND = pa.schema([("kind", pa.int8()), ("seed", pa.int64()), ("doc", pa.int64()), ("a", pa.int32()), ("b", pa.int32()), ("multi", pa.bool_())])
_LOW = S.U((1 << 22) - 1)


@dataclass(frozen=True)
class Spec:
    width: int
    seed: int
    #: True: a window counts where a document with a smaller id has it; False: where it stands anywhere else.
    earlier: bool
    #: "bytes" or "words".
    unit: str
    #: ``doc >> shift`` is the order of a document's id; documents of one id differ below.
    shift: int = 0

    @property
    def left(self) -> int:
        return self.width - self.seed

    def symbols(self, col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Symbol values (uint8 for bytes, uint64 for words) and the texts' borders."""
        raw, borders = S.raw_texts(col)
        if self.unit == "bytes":
            return raw, borders
        start, end, at = S.word_spans(raw, borders)
        return S.word_values(raw, start, end), at


def anchors(values: np.ndarray, borders: np.ndarray, spec: Spec) -> tuple[np.ndarray, ...]:
    """Of all texts in a batch: text number, anchor's place in it, seed hash, context hash, context's ends."""
    out = []
    L, k, left = spec.width, spec.seed, spec.left
    for i, j in S.blocks(borders):
        lo, hi = int(borders[i]), int(borders[j])
        if hi - lo < L:
            continue
        # one text longer than a block goes in pieces that overlap by what contexts need
        step = hi - lo if hi - lo <= 2 * S.BLOCK else S.BLOCK
        for at in range(lo, hi, step):
            s, e = max(lo, at - left), min(hi, at + step + 2 * L)
            w0, w1 = at, min(at + step, hi - L + 1)  # windows that start here
            if w1 <= w0 or e - s < L:
                continue
            piece = values[s:e]
            runs = S.Runs(S.BYTE_VALUE[piece] if spec.unit == "bytes" else piece)
            seeds = S.mix(runs.grams(k))
            key = (seeds & ~_LOW) | (_LOW - np.arange(len(seeds), dtype=np.uint64))
            first = S.windows_min(key, L - k + 1)
            ok = np.zeros(len(first), bool)
            ok[w0 - s : w1 - s] = True
            for b in borders[i + 1 : j]:  # no window crosses from one text into the next
                ok[max(0, b - s - L + 1) : max(0, b - s)] = False
            first = first[ok]
            if not len(first):
                continue
            first = first[np.r_[True, first[1:] != first[:-1]]]
            p = (_LOW - (first & _LOW)).astype(np.int64)
            text = np.searchsorted(borders, p + s, "right") - 1
            c0 = np.maximum(borders[text] - s, p - left)
            c1 = np.minimum(borders[text + 1] - s, p + L)
            shape = (p - c0) * 4096 + (c1 - p)
            context = S.mix(runs.of(c0, c1) + shape.astype(np.uint64) * S.U(0xC2B2AE3D27D4EB4F))
            base = borders[text] - s
            out.append((text, p - base, seeds[p], context, c0 - base, c1 - base))
    if not out:
        z = np.zeros(0, np.int64)
        return z, z, z.astype(np.uint64), z.astype(np.uint64), z, z
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _starts(*keys: np.ndarray) -> np.ndarray:
    """True at the first row of each run of equal keys."""
    new = np.zeros(len(keys[0]), bool)
    if len(new):
        new[0] = True
        for k in keys:
            new[1:] |= k[1:] != k[:-1]
    return new


def merged(doc: np.ndarray, s: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Unions of overlapping or touching intervals of each document."""
    if not len(doc):
        return doc, s, e
    o = np.lexsort((s, doc))
    doc, s, e = doc[o], s[o].astype(np.int64), e[o].astype(np.int64)
    number = np.cumsum(_starts(doc)) - 1
    span = int(e.max()) + 2
    reach = np.maximum.accumulate(number * span + e) - number * span
    new = _starts(doc)
    new[1:] |= s[1:] > reach[:-1]
    first = np.flatnonzero(new)
    last = np.r_[first[1:], len(doc)] - 1
    return doc[first], s[first], reach[last]


def _emit_anchors(spec: Spec) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (x for y in batches for x in S.slices(y)):
            ids = b.column(0).to_numpy(zero_copy_only=False)
            values, borders = spec.symbols(b.column(1))
            text, p, seed, context, c0, c1 = anchors(values, borders, spec)
            if not len(p):
                continue
            doc = ids[text]
            o = np.argsort(S.mix(seed ^ (context * S.U(0x9FB21C651E98DF25))), kind="stable")
            text, doc, p, seed, context, c0, c1 = (x[o] for x in (text, doc, p, seed, context, c0, c1))
            new = _starts(seed, context)
            at = np.flatnonzero(new)
            group = np.cumsum(new) - 1
            if spec.earlier:
                rank = doc >> spec.shift
                first = np.minimum.reduceat(rank, at)[group]
                done, send = rank > first, rank == first
                multi = np.zeros(len(doc), bool)
            else:
                multi = (np.diff(np.r_[at, len(doc)]) > 1)[group]
                done, send = multi, new
            d, s, e = merged(doc[done], c0[done], c1[done])
            n, m = int(send.sum()), len(d)
            yield pa.record_batch(
                [
                    pa.array(np.r_[np.full(n, ANCHOR, np.int8), np.full(m, COVER, np.int8)]),
                    pa.array(np.r_[seed[send], S.mix(d.astype(np.uint64) ^ S.mix(s.astype(np.uint64)))].view(np.int64)),
                    pa.array(np.r_[context[send], np.zeros(m, np.uint64)].view(np.int64)),
                    pa.array(np.r_[doc[send], d]),
                    pa.array(np.r_[p[send], s].astype(np.int32)),
                    pa.array(np.r_[multi[send].astype(np.int64), e].astype(np.int32)),
                ],
                schema=_ROWS,
            )

    return run


def _decide(spec: Spec) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Over rows sorted by seed, context and doc: covered anchors, and a row for each context of a seed that has several.

    State between batches: the first row of the last seed, the first row of its
    last context and edges not yet given, with what was already said of them.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            kind, seed, context, doc, a, c = (b.column(i).to_numpy(zero_copy_only=False) for i in range(6))
            cover = kind == COVER
            out_cover = (seed[cover], doc[cover], a[cover], c[cover])
            rows = [x[~cover] for x in (seed, context, doc, a)] + [c[~cover] > 0, np.zeros(int((~cover).sum()), bool), np.zeros(int((~cover).sum()), bool)]
            if held is not None:
                rows = [np.concatenate(x) for x in zip(held, rows, strict=True)]
            seed, context, doc, a, multi, said, told = rows  # said: covered already; told: given as an edge already
            n = len(seed)
            if not n:
                if len(out_cover[0]):
                    yield _found(out_cover, None)
                continue
            new_seed = _starts(seed)
            new = _starts(seed, context)
            at = np.flatnonzero(new)
            run_no = np.cumsum(new) - 1
            size = np.diff(np.r_[at, n])
            rank = doc >> spec.shift
            first_rank = rank[at][run_no]
            if spec.earlier:
                covered = rank > first_rank
                several = np.zeros(len(at), bool)
                edge_rows = rank == first_rank
            else:
                several = (size > 1) | np.maximum.reduceat(multi.astype(np.int8), at).astype(bool)
                covered = several[run_no]
                edge_rows = new
            seed_no = np.cumsum(new_seed) - 1
            contexts = np.bincount(seed_no[at])
            edge = edge_rows & (contexts[seed_no] > 1) & ~told
            tell = covered & ~said
            s = np.maximum(0, a[tell] - spec.left)
            # the context's right end may lie beyond the text; the last step cuts it to the text's length
            out = [np.r_[x, y] for x, y in zip(out_cover, (seed[tell], doc[tell], s, a[tell] + spec.width), strict=True)]
            yield _found(out, (seed[edge], doc[edge], a[edge], several[run_no][edge]))
            multi = multi | several[run_no]
            said, told = said | tell, told | edge
            last = int(np.flatnonzero(new_seed)[-1])
            # edges of a seed that has one context so far wait for a second one; they are of one doc_id
            wait = last + np.flatnonzero(edge_rows[last:] & ~told[last:])
            keep = sorted({last, int(at[-1]), *wait.tolist()})
            held = [x[keep] for x in (seed, context, doc, a, multi, said, told)]

    return run


def _found(cover, edge) -> pa.RecordBatch:
    n = len(cover[0])
    if edge is None:
        edge = (np.zeros(0, np.int64),) * 3 + (np.zeros(0, bool),)
    m = len(edge[0])
    return pa.record_batch(
        [
            pa.array(np.r_[np.full(n, COVER, np.int8), np.full(m, ANCHOR, np.int8)]),
            pa.array(np.r_[cover[0], edge[0]].astype(np.int64)),
            pa.array(np.r_[cover[1], edge[1]].astype(np.int64)),
            pa.array(np.r_[cover[2], edge[2]].astype(np.int32)),
            pa.array(np.r_[cover[3], np.zeros(m, np.int64)].astype(np.int32)),
            pa.array(np.r_[np.zeros(n, bool), edge[3]]),
        ],
        schema=_FOUND,
    )


def _contexts(spec: Spec) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Of documents with their edge anchors: each anchor's symbols on both sides."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (x for y in batches for x in S.slices(y)):
            ids = b.column(0).to_numpy(zero_copy_only=False)
            values, borders = spec.symbols(b.column(1))
            marks = b.column(2)
            at = marks.offsets.to_numpy()
            at = at - at[0]
            flat = marks.flatten()
            seed, p, multi = (flat.field(i).to_numpy(zero_copy_only=False) for i in range(3))
            text = np.repeat(np.arange(len(ids)), np.diff(at))
            base, end = borders[text], borders[text + 1]
            item = values.itemsize
            data = np.ascontiguousarray(values).view(np.uint8)
            for lo in range(0, len(p), 100_000):
                part = slice(lo, lo + 100_000)
                g = base[part] + p[part]
                c0, c1 = np.maximum(base[part], g - spec.left), np.minimum(end[part], g + spec.width)
                size = (c1 - c0) * item
                ends = np.cumsum(size)
                index = np.arange(int(ends[-1])) - np.repeat(ends - size, size) + np.repeat(c0 * item, size)
                blob = pa.Array.from_buffers(pa.binary(), len(g), [None, pa.py_buffer(np.r_[0, ends].astype(np.int32)), pa.py_buffer(data[index])])
                yield pa.record_batch([pa.array(seed[part]), pa.array(ids[text[part]]), pa.array(p[part]), pa.array((g - c0).astype(np.int32)), blob, pa.array(multi[part])], names=["seed", "doc", "p", "n_left", "symbols", "multi"])

    return run


CONTEXTS = "seed long, doc long, p int, n_left int, symbols binary, multi boolean"


def _settle(spec: Spec, resolve) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Over contexts sorted by seed: intervals of windows that other contexts of the seed hold too. Whole seeds at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for b in batches:
            seed = b.column(0).to_numpy()
            if not len(seed):
                continue
            cut = int(np.flatnonzero(_starts(seed))[-1])
            if cut == 0 and held and held[-1].column(0)[0].as_py() == seed[0]:
                held.append(b)
                continue
            held.append(b.slice(0, cut))
            yield from _settled(held, spec, resolve)
            held = [b.slice(cut)]
        yield from _settled(held, spec, resolve)

    return run


def _settled(parts: list[pa.RecordBatch], spec: Spec, resolve) -> Iterator[pa.RecordBatch]:
    t = pa.Table.from_batches(parts).combine_chunks() if parts else None
    if t is None or not t.num_rows:
        return
    b = t.to_batches()[0]
    seed, doc, p, n_left = (b.column(i).to_numpy() for i in range(4))
    raw, at = S.raw_texts(b.column(4))
    group = np.cumsum(_starts(seed)) - 1
    lo, hi = resolve(group, doc, n_left.astype(np.int64), raw, at, spec, b.column(5).to_numpy(zero_copy_only=False))
    hit = hi >= 0
    d, s, e = merged(doc[hit], p[hit] - hi[hit], p[hit] - lo[hit] + spec.width)
    yield pa.record_batch([pa.array(d), pa.array(s.astype(np.int32)), pa.array(e.astype(np.int32))], names=["doc", "a", "b"])


#: Contexts of one seed that one task compares at once; seeds with more go through ``window_keys``.
HOT_SEED = 50_000


def _window_keys(spec: Spec) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A row for each window of each context of a hot seed, under a 128-bit key of the window's symbols."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, len(b), 20_000):
                c = b.slice(lo, 20_000)
                doc, p, n_left = (c.column(i).to_numpy() for i in (1, 2, 3))
                raw, at = S.raw_texts(c.column(4))
                values = S.BYTE_VALUE[raw] if spec.unit == "bytes" else np.ascontiguousarray(raw).view(np.uint64)
                if spec.unit != "bytes":
                    at = at // 8
                runs, more = S.Runs(values), S.Runs(S.mix(values))
                for o in range(spec.left + 1):
                    s = at[:-1] + n_left - o
                    ok = (o <= n_left) & (s + spec.width <= at[1:])
                    s = s[ok]
                    if len(s):
                        yield pa.record_batch([pa.array(f.of(s, s + spec.width).view(np.int64)) for f in (runs, more)] + [pa.array(doc[ok]), pa.array((p[ok] - o).astype(np.int32)), c.column(5).filter(pa.array(ok))], names=["k1", "k2", "doc", "a", "multi"])

    return run


def covered_intervals(docs: DataFrame, spec: Spec, resolve, scratch: Scratch) -> DataFrame:
    """(doc, spans array<struct<a,b>>) of documents with repeated windows; ends may reach past the text.

    ``docs`` has (doc long, text string), one row for each doc. ``resolve`` settles
    the contexts of whole seeds: it returns the least and greatest distance from
    the anchor back to the start of a repeated window, -1 where there is none.
    """
    n = partitions(docs.sparkSession)
    rows = docs.mapInArrow(_emit_anchors(spec), ROWS)
    rows = rows.repartition(n, "seed").sortWithinPartitions("seed", "context", "doc")
    found = scratch.put(rows.mapInArrow(_decide(spec), FOUND), "found")
    edges = found.where(F.col("kind") == ANCHOR).groupBy("doc").agg(F.collect_list(F.struct("seed", F.col("a").alias("p"), "multi")).alias("marks"))
    contexts = scratch.put(docs.join(edges, "doc").select("doc", "text", "marks").mapInArrow(_contexts(spec), CONTEXTS), "contexts")
    hot = scratch.put(contexts.groupBy("seed").count().where(F.col("count") > HOT_SEED).select("seed"), "hot")
    cold = contexts.join(hot, "seed", "left_anti").repartition(n, "seed").sortWithinPartitions("seed")
    spans = found.where(F.col("kind") == COVER).select("doc", "a", "b").unionByName(cold.mapInArrow(_settle(spec, resolve), "doc long, a int, b int"))
    if hot.head(1):
        keys = contexts.join(hot, "seed", "left_semi").mapInArrow(_window_keys(spec), "k1 long, k2 long, doc long, a int, multi boolean")
        if spec.earlier:
            keys = keys.withColumn("rank", F.shiftright("doc", spec.shift))
            seen = keys.groupBy("k1", "k2").agg(F.min("rank").alias("first"))
            keys = keys.join(seen, ["k1", "k2"]).where("rank > first")
        else:
            seen = keys.groupBy("k1", "k2").agg(F.min(F.struct("doc", "a")).alias("x"), F.max(F.struct("doc", "a")).alias("y"), F.max("multi").alias("m")).where("x <> y or m").select("k1", "k2")
            keys = keys.join(seen, ["k1", "k2"])
        spans = spans.unionByName(keys.select("doc", "a", (F.col("a") + spec.width).alias("b")))
    return spans.groupBy("doc").agg(F.collect_list(F.struct("a", "b")).alias("spans"))


def with_spans(docs: DataFrame, spans: DataFrame) -> DataFrame:
    return docs.join(spans, "doc", "left").select("doc", "text", "spans")


def span_arrays(col: pa.Array, lengths: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Each document's merged, clipped spans."""
    for spans, n in zip(col, lengths, strict=True):
        if not spans.is_valid or not len(spans.values):
            yield np.zeros(0, np.int64), np.zeros(0, np.int64)
            continue
        a, b = spans.values.field(0).to_numpy().astype(np.int64), spans.values.field(1).to_numpy().astype(np.int64)
        _, s, e = merged(np.zeros(len(a), np.int64), a, np.minimum(b, n))
        yield s, e
