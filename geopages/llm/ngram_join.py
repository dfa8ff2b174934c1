"""N-gram Jaccard join: links of documents whose shingle sets are similar, and their components.

Sets are looked up through an inverted index of prefixes: tokens are ordered from
rare to frequent, and two sets of Jaccard similarity t share a token among the first
n - ceil(t n) + 1 of each. How frequent a token is comes from a table of counts of
fixed size over all documents. Work is saved by relations between sets, on two levels:

* *Index*: equal sets are one entry. Lists hold entries in narrow blocks of similar size.
  The smaller set of a pair probes: at the token's position in it, only so many tokens are
  left, and every block whose sets would need a larger overlap is skipped before the join.
  Entries whose own position leaves too few tokens are skipped in it.
* *Answers*: in a first round each entry is compared only with the few entries that
  stand next to it in most of its lists, its likeliest partners. Where that links
  them, it takes over the other's component as its own answer, and the second round
  compares entries of different components alone, so a group of near copies costs
  steps in proportion to its size, not its square, and no link between groups is lost.

Candidates are tested first by parity sketches (differing bits never exceed the
symmetric difference, so no link is lost), then exactly on whole sets.

Results by case: a null, empty or blank text has an empty set and is linked with
nothing; a text of fewer words than a shingle has its whole sequence as one; rows of
one doc_id with different texts are documents of their own; equal rows get equal results,
one for each, and one of them passes ``keep_one_of_each_group``; a null doc_id is later
than all others; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import _symbols as S
from ._common import Keyed, Scratch, keyed, partitions, table
from .components import connected_components

#: Counters of token frequency: their number bounds what is sent to the driver and back (1 MB of ranks).
COUNTERS, CHUNK = 1 << 20, 1 << 14
SKETCH_BITS = 1024
#: Blocks of set sizes between a size and the greatest that can be similar to it.
SIZE_BLOCKS = 4
#: Sets whose 64-bit class is shared by another set, at most; they are known by another half of their digest.
MOST_CLASHES = 100_000
#: Neighbours of an entry that the first round compares it with: those next to it in most lists. The second round has all others.
NEIGHBOURS = 4


def shingle_sets(batch: pa.RecordBatch, n: int) -> Iterator[np.ndarray]:
    """Each text's sorted distinct shingle hashes; A-Z are lower-cased first."""
    for part in S.slices(batch, most=2 << 20):
        raw, borders = S.raw_texts(part.column(1))
        raw = S.LOWER[raw]
        start, end, at = S.word_spans(raw, borders)
        w = S.word_values(raw, start, end)
        grams = np.zeros(max(0, len(w) - n + 1), np.uint64)
        for k in range(n):
            grams = S.mix(grams + w[k : k + len(grams)] * S.U(2 * k + 3))
        for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
            if b - a >= n:
                yield np.unique(grams[a : b - n + 1])
            elif b > a:
                h = np.full(1, b - a, np.uint64)
                for k in range(a, b):
                    h = S.mix(h * S.U(0x9E6C63D0876A9A47) + w[k])
                yield h
            else:
                yield np.zeros(0, np.uint64)


@dataclass(frozen=True)
class _Classes:
    """Numbers of sets: half of a 128-bit digest, the other half where that one is known to be shared."""

    shared: frozenset[int] = frozenset()
    bits: int = 64

    def of(self, s: np.ndarray) -> tuple[int, int]:
        """The set's class and the half that checks it."""
        low, high = np.frombuffer(hashlib.blake2b(s.tobytes(), digest_size=16).digest(), np.int64).tolist()
        low = low if self.bits == 64 else low & ((1 << self.bits) - 1)
        return (high, low) if low in self.shared else (low, high)


def _sketch(s: np.ndarray) -> np.ndarray:
    bits = np.bincount((s >> S.U(20)).astype(np.int64) % SKETCH_BITS, minlength=SKETCH_BITS) & 1
    return np.packbits(bits.astype(np.uint8)).view(np.int64)


def _may_differ(percent: int, a: str, b: str) -> str:
    """SQL: the sketches of two rows differ in no more bits than their sets may differ in tokens."""
    bits = " + ".join(f"bit_count({a}.sketch[{i}] ^ {b}.sketch[{i}])" for i in range(SKETCH_BITS // 64))
    return f"{bits} <= {a}.n + {b}.n - 2 * ceil({percent} * ({a}.n + {b}.n) / {100 + percent})"


_SETS = "doc long, n int, cls long, check long, sketch array<long>, chunk int, counts binary"


def _describe(n: int, number: _Classes) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A row for each document, and at the end of a task its token counts in chunks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(COUNTERS, np.int64)
        names = ["doc", "n", "cls", "check", "sketch", "chunk", "counts"]
        for b in batches:
            sizes, classes, sketches = [], [], []
            for s in shingle_sets(b, n):
                sizes.append(len(s))
                classes.append(number.of(s))
                sketches.append(_sketch(s))
                np.add.at(total, (s >> S.U(44)).astype(np.int64), 1)
            m = len(sizes)
            cls, check = zip(*classes, strict=True) if m else ((), ())
            yield pa.record_batch([b.column(0), pa.array(sizes, pa.int32()), pa.array(cls, pa.int64()), pa.array(check, pa.int64()), pa.array(sketches, pa.list_(pa.int64())), pa.nulls(m, pa.int32()), pa.nulls(m, pa.binary())], names=names)
        used = [c for c in range(COUNTERS // CHUNK) if total[c * CHUNK : (c + 1) * CHUNK].any()]
        m = len(used)
        if m:
            blobs = [total[c * CHUNK : (c + 1) * CHUNK].astype(np.uint32).tobytes() for c in used]
            yield pa.record_batch([pa.nulls(m, pa.int64()), pa.nulls(m, pa.int32()), pa.nulls(m, pa.int64()), pa.nulls(m, pa.int64()), pa.nulls(m, pa.list_(pa.int64())), pa.array(used, pa.int32()), pa.array(blobs, pa.binary())], names=names)

    return run


def _sum_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total: dict[int, np.ndarray] = {}
    for b in batches:
        for c, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            total[c] = total.get(c, 0) + np.frombuffer(blob, np.uint32).astype(np.float64)
    keys = sorted(total)
    # only the order matters: a rank of 0..255 on a logarithmic scale
    ranks = [np.minimum(255, np.log2(1 + total[c]) * 6).astype(np.uint8).tobytes() for c in keys]
    yield pa.record_batch([pa.array(keys, pa.int32()), pa.array(ranks, pa.binary())], names=["chunk", "ranks"])


def token_ranks(described: DataFrame) -> np.ndarray:
    """COUNTERS ranks of token frequency, from all documents; 1 MB whatever the input."""
    counts = described.where("chunk is not null").select("chunk", "counts").repartition(COUNTERS // CHUNK, "chunk")
    out = np.zeros(COUNTERS, np.uint8)
    for r in counts.mapInArrow(_sum_counts, "chunk int, ranks binary").collect():
        out[r.chunk * CHUNK : (r.chunk + 1) * CHUNK] = np.frombuffer(bytes(r.ranks), np.uint8)
    return out


def _postings(n: int, percent: int, ranks: np.ndarray, number: _Classes) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (x for y in batches for x in S.slices(y)):
            seen: set[int] = set()
            tokens, classes, sizes = [], [], []
            for s in shingle_sets(b, n):
                m = len(s)
                if not m or (c := number.of(s)[0]) in seen:
                    continue
                seen.add(c)
                p = m - -(-percent * m // 100) + 1
                tokens.append(s[np.argsort(ranks[s >> S.U(44)], kind="stable")[:p]])
                classes.append(c)
                sizes.append(m)
            if tokens:
                k = np.array([len(t) for t in tokens])
                at = np.arange(k.sum()) - np.repeat(np.cumsum(k) - k, k)
                yield pa.record_batch([pa.array(np.concatenate(tokens).view(np.int64)), pa.array(np.repeat(np.array(classes), k)), pa.array(np.repeat(np.array(sizes, np.int32), k)), pa.array(at.astype(np.int32))], names=["token", "cls", "n", "pos"])

    return run


def _lists(percent: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Of postings sorted by token, size and class: those of tokens with several classes, each with its neighbour in size.

    State between batches: the last row.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            rows = [b.column(i).to_numpy() for i in range(4)]
            if held is not None:
                rows = [np.concatenate(x) for x in zip(held[0], rows, strict=True)]
            token, cls, n, pos = rows
            new = np.ones(len(token), bool)
            new[1:] = (token[1:] != token[:-1]) | (cls[1:] != cls[:-1])
            token, cls, n, pos = (x[new] for x in rows)
            follows = np.zeros(len(token), bool)
            follows[1:] = token[1:] == token[:-1]
            before, size = np.r_[cls[:1], cls[:-1]], np.r_[n[:1], n[:-1]]
            if held is not None:
                follows[0], before[0], size[0] = held[1]
            shared = follows.copy()
            shared[:-1] |= follows[1:]
            held = [x[-1:] for x in (token, cls, n, pos)], (follows[-1], before[-1], size[-1])
            yield _listed(token[:-1], cls[:-1], n[:-1], pos[:-1], follows[:-1], before[:-1], size[:-1], shared[:-1], percent)
        if held is not None:
            (token, cls, n, pos), (f, p, z) = held
            yield _listed(token, cls, n, pos, np.array([f]), np.array([p]), np.array([z]), np.array([f]), percent)

    return run


def _listed(token, cls, n, pos, follows, before, size, shared, percent) -> pa.RecordBatch:
    near = follows & (size * 100 >= n * percent)
    return pa.record_batch(
        [pa.array(token[shared]), pa.array(cls[shared]), pa.array(n[shared]), pa.array(pos[shared]), pa.array(before[shared], mask=~near[shared])],
        names=["token", "cls", "n", "pos", "before"],
    )


def _verify(percent: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (x for y in batches for x in S.slices(y, 2)):
            ok = np.zeros(len(b), bool)
            for i, (x, y) in enumerate(zip(b.column(2), b.column(3), strict=True)):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                at = np.searchsorted(x, y)
                at[at == len(x)] = 0
                both = int((x[at] == y).sum())
                ok[i] = 100 * both >= percent * (len(x) + len(y) - both)
            keep = pa.array(ok)
            yield pa.record_batch([b.column(i).filter(keep) for i in (0, 1)], names=["u", "v"])

    return run


def _whole_sets(n: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (x for y in batches for x in S.slices(y)):
            yield pa.record_batch([b.column(0), pa.array([s.tobytes() for s in shingle_sets(b, n)], pa.binary())], names=["cls", "tokens"])

    return run


class _Join:
    def __init__(self, docs: DataFrame, n: int, percent: int, bits: int = 64):
        self.spark, self.n, self.percent = docs.sparkSession, n, percent
        self.scratch = Scratch(self.spark, "ngram_join")
        self.keys: Keyed = keyed(docs, self.scratch)
        self.docs = self.keys.rows
        self.parts = partitions(self.spark)
        self.number = _Classes(bits=bits)
        while True:
            described = self.scratch.put(self.docs.mapInArrow(_describe(n, self.number), _SETS), "sets")
            whole = described.where("chunk is null and n > 0").groupBy("cls").agg(F.min("doc").alias("doc"), F.first("n").alias("n"), F.first("sketch").alias("sketch"), F.min("check").alias("c0"), F.max("check").alias("c1"))
            self.classes = self.scratch.put(whole, "classes")
            clash = [r.cls for r in self.classes.where("c0 <> c1").select("cls").limit(MOST_CLASHES + 1).collect()]
            if not clash:
                break
            if len(clash) > MOST_CLASHES or self.number.shared & set(clash):
                raise RuntimeError("too many different sets share a digest")
            self.number = _Classes(self.number.shared | set(clash), bits)
        self.members = described.where("chunk is null").select("doc", "n", "cls")
        self.ranks = token_ranks(described)

    def links(self, pairs: DataFrame) -> DataFrame:
        """(u, v) of those pairs (a, b) of classes that are similar, checked on whole sets."""
        asked = pairs.select(F.explode(F.array("a", "b")).alias("cls")).distinct()
        texts = self.docs.join(self.classes.join(asked, "cls").select("cls", "doc"), "doc").select("cls", "text")
        sets = self.scratch.put(texts.mapInArrow(_whole_sets(self.n), "cls long, tokens binary"), "whole")
        wide = pairs.join(sets.select(F.col("cls").alias("a"), F.col("tokens").alias("x")), "a").join(sets.select(F.col("cls").alias("b"), F.col("tokens").alias("y")), "b").select("a", "b", "x", "y")
        out = self.scratch.put(wide.mapInArrow(_verify(self.percent), "u long, v long"), "links")
        self.scratch.drop(sets)
        return out

    def labels(self) -> DataFrame:
        """(cls, label) of every class that is linked with another."""
        percent = self.percent
        rows = self.docs.mapInArrow(_postings(self.n, percent, self.ranks, self.number), "token long, cls long, n int, pos int")
        rows = rows.repartition(self.parts, "token").sortWithinPartitions("token", "n", "cls")
        lists = self.scratch.put(rows.mapInArrow(_lists(percent), "token long, cls long, n int, pos int, before long"), "lists")
        near = lists.where("before is not null").groupBy("cls", "before").count()
        best = F.slice(F.sort_array(F.collect_list(F.struct("count", "before")), False), 1, NEIGHBOURS)
        near = near.groupBy("cls").agg(best.alias("best")).select("cls", F.explode("best.before").alias("before"))
        near = near.select(F.least("cls", "before").alias("a"), F.greatest("cls", "before").alias("b")).distinct()
        near = self.scratch.put(near, "near")
        sketch = self.classes.select("cls", "n", "sketch")
        plausible = near.join(sketch.alias("p"), F.expr("a = p.cls")).join(sketch.alias("e"), F.expr("b = e.cls")).where(_may_differ(percent, "p", "e"))
        plausible = self.scratch.put(plausible.select("a", "b"), "plausible")
        first = connected_components(self.links(plausible), self.scratch)
        first = self.scratch.put(first, "first")
        self.scratch.drop(plausible)
        # second round: lists that still hold several components
        label = lists.join(first.withColumnRenamed("node", "cls"), "cls", "left").select("token", "cls", "n", "pos", F.coalesce("component", "cls").alias("part"))
        label = self.scratch.put(label, "labelled")
        self.scratch.drop(lists)
        open_lists = label.groupBy("token").agg(F.min("part").alias("x"), F.max("part").alias("y")).where("x <> y").select("token")
        step = (100 / percent) ** (1 / SIZE_BLOCKS)
        block = F.floor(F.log("n") / F.log(F.lit(step)) + F.lit(1e-9)).cast("int")
        entry = label.join(open_lists, "token").join(sketch.select("cls", "sketch"), "cls").withColumn("block", block)
        entry = self.scratch.put(entry, "open")
        self.scratch.drop(label)
        # the least overlap with a set of a block is that with its smallest one, or one of the probe's own size
        smallest = lambda b: F.greatest(F.col("n"), F.ceil(F.pow(F.lit(step), b) * (1 - 1e-6)).cast("int"))
        within = lambda b: F.col("n") - F.col("pos") >= F.ceil(percent * (F.col("n") + smallest(b)) / (100 + percent))
        probe = entry.withColumn("block", F.explode(F.filter(F.sequence(F.col("block"), F.col("block") + SIZE_BLOCKS), within))).alias("p")
        meet = probe.join(entry.alias("e"), ["token", "block"]).where("p.part <> e.part and (p.n < e.n or (p.n = e.n and p.cls < e.cls))")
        least = f"ceil({percent} * (p.n + e.n) / {100 + percent})"
        meet = meet.where(f"100 * p.n >= {percent} * e.n and least(p.n - p.pos, e.n - e.pos) >= {least}").where(_may_differ(percent, "p", "e"))
        pairs = meet.select(F.least("p.cls", "e.cls").alias("a"), F.greatest("p.cls", "e.cls").alias("b")).distinct().join(near, ["a", "b"], "left_anti")
        pairs = self.scratch.put(pairs, "across")
        self.scratch.drop(entry, near)
        more = self.links(pairs)
        part = first.select(F.col("node"), "component")
        bridge = more.join(part.withColumnRenamed("node", "u").withColumnRenamed("component", "cu"), "u", "left").join(part.withColumnRenamed("node", "v").withColumnRenamed("component", "cv"), "v", "left")
        bridge = self.scratch.put(bridge.select("u", "v", F.coalesce("cu", "u").alias("cu"), F.coalesce("cv", "v").alias("cv")), "bridge")
        if not bridge.head(1):
            return first.select(F.col("node").alias("cls"), F.col("component").alias("label"))
        second = connected_components(bridge.select(F.col("cu").alias("u"), F.col("cv").alias("v")), self.scratch)
        nodes = first.unionByName(bridge.select(F.explode(F.array(F.struct(F.col("u").alias("node"), F.col("cu").alias("component")), F.struct(F.col("v").alias("node"), F.col("cv").alias("component")))).alias("x")).select("x.*")).distinct()
        second = second.select(F.col("node").alias("component"), F.col("component").alias("label"))
        return nodes.join(second, "component", "left").select(F.col("node").alias("cls"), F.coalesce("label", "component").alias("label"))

    def groups(self) -> DataFrame:
        """(doc, n_shingles, component, component_id): each document's group by its least key, and that key's doc_id; both null for a group of its own without shingles."""
        labels = self.scratch.put(self.labels(), "labels")
        whole = self.classes.select("cls", "doc").join(labels, "cls", "left").select("cls", "doc", F.coalesce("label", "cls").alias("label"))
        least = whole.groupBy("label").agg(F.min("doc").alias("component"))
        least = self.keys.ids(least.withColumn("component_id", F.col("component")), "component_id")
        whole = self.scratch.put(whole.join(least, "label").select("cls", "component", "component_id"), "components")
        out = self.members.join(whole.withColumnRenamed("cls", "_cls"), (F.col("cls") == F.col("_cls")) & (F.col("n") > 0), "left")
        return out.select("doc", F.col("n").cast("long").alias("n_shingles"), "component", "component_id")


def similar_groups(docs: DataFrame, shingle: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id): groups of documents reachable by links of at least ``percent`` / 100 Jaccard similarity.

    A group's id is its smallest doc_id.
    """
    join = _Join(docs, shingle, percent)
    out = join.keys.again(join.groups())
    return out.select("doc_id", "n_shingles", F.when(F.col("component").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def keep_one_of_each_group(docs: DataFrame, shingle: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` without the documents of each group but one of its smallest doc_id, and with one of equal rows; columns stay as they are."""
    join = _Join(docs, shingle, percent)
    kept = join.groups().where("component is null or doc = component").select("doc")
    return join.keys.one_of_equal(join.keys.matched(docs, kept, "left_semi"))


def op6_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_groups(table(spark, sf_dir, "documents"), shingle=3, percent=90)
