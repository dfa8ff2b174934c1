"""Mixing sources to target weights by Pfair scheduling.

Each source's documents, in a keyed random order, are cut into blocks. A source with
share w gives its k-th block the window [floor((k - 1) / w), ceil(k / w)) of slots: not
before its release, not after its deadline. Earliest deadline first fills one slot
after another; as the shares add up to one, every window is met, so after any number
of slots each source is less than one block away from its share. Shares are ratios of
whole numbers, so the schedule repeats after as many slots as their sum, and a block's
slot follows from one period by arithmetic. When a source has given all its blocks, a
new phase shares the slots among the others; no document is dropped or repeated.

Results by case: a null source, and one without a target, belong to the rest, which
has a weight of its own; equal rows are placed one after another; an empty table gives
no rows; other columns, whatever their names, pass through as they are.
"""

from __future__ import annotations

from math import ceil, gcd, log2

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ._common import column_of, table, unused

#: Target weights, as whole numbers; their sum is the longest period of the schedule.
TARGETS = {f"src{i}": 40 - 2 * i for i in range(20)}
REST, REST_WEIGHT = "", 4
BLOCK = 64
#: Rows that one task numbers at once, and the least number of buckets of a source as a power of two.
ROWS_PER_TASK, LEAST_BUCKETS = 20_000, 8
#: Counts of buckets are broadcast up to this many rows, else joined by a shuffle; the result is the same.
BROADCAST_ROWS = 200_000
LONGEST_PERIOD = 1 << 16


def period(weights: dict[str, int]) -> list[str]:
    """Sources of the slots of one period, by earliest deadline among released blocks."""
    total = sum(weights.values())
    given = dict.fromkeys(weights, 0)
    out = []
    for t in range(total):
        ready = [s for s, w in weights.items() if given[s] < w and given[s] * total // w <= t]
        s = min(ready, key=lambda s: (-(-(given[s] + 1) * total // weights[s]), -weights[s], s))
        given[s] += 1
        out.append(s)
    return out


def phases(blocks: dict[str, int], weights: dict[str, int]) -> list[dict]:
    """A row for each phase and source that takes part: where it starts, the source's first block and number of blocks, its slots in a period."""
    left = {s: n for s, n in blocks.items() if n > 0}
    done = dict.fromkeys(left, 0)
    start, out = 0, []
    while left:
        g = gcd(*(weights[s] for s in left))
        own = {s: weights[s] // g for s in left}
        total = sum(own.values())
        slots: dict[str, list[int]] = {s: [] for s in left}
        for t, s in enumerate(period(own)):
            slots[s].append(t)
        slot_of = lambda s, k: k // own[s] * total + slots[s][k % own[s]]
        end = min(slot_of(s, n - 1) for s, n in left.items()) + 1
        for s in list(left):
            n = end // total * own[s] + sum(t < end % total for t in slots[s])
            out.append({"src": s, "start": start, "first": done[s], "n": n, "share": own[s], "total": total, "slots": slots[s]})
            done[s] += n
            left[s] -= n
            if not left[s]:
                del left[s]
        start += end
    return out


def _source(docs: DataFrame, targets: dict[str, int]) -> Column:
    s = docs["source"].cast("string")
    return F.when(s.isin(list(targets)), s).otherwise(F.lit(REST))


def _scheduled(docs: DataFrame, targets: dict[str, int], rest_weight: int, block: int, seed: int = 17) -> DataFrame:
    """(_row: struct of the columns of ``docs``, _mix)."""
    weights = {**targets, REST: rest_weight}
    if sum(weights.values()) > LONGEST_PERIOD or any(w != int(w) or w < 1 for w in weights.values()):
        raise ValueError(f"weights must be whole numbers from 1 with a sum of up to {LONGEST_PERIOD}")
    n_rows = docs.count()
    buckets = 1 << max(LEAST_BUCKETS, ceil(log2(n_rows / ROWS_PER_TASK + 1)))
    order = F.xxhash64(F.lit(seed), docs["doc_id"])
    row = F.struct(*[column_of(docs, c) for c in docs.columns])
    d = docs.select(row.alias("_row"), _source(docs, targets).alias("_src"), order.alias("_h")).withColumn("_b", F.pmod("_h", F.lit(buckets)).cast("int"))
    # a source, hot or not, is numbered in buckets; what stands before a bucket comes from the counts
    sizes = docs.select(_source(docs, targets).alias("_src"), F.pmod(order, F.lit(buckets)).cast("int").alias("_b")).groupBy("_src", "_b").agg(F.count("*").alias("_n"))
    before = sizes.select("_src", "_b", (F.sum("_n").over(W.partitionBy("_src").orderBy("_b")) - F.col("_n")).alias("_before"))
    blocks = {r["_src"]: -(-r["n"] // block) for r in sizes.groupBy("_src").agg(F.sum("_n").alias("n")).collect()}  # a row for each target at most
    plan = docs.sparkSession.createDataFrame([tuple(p.values()) for p in phases(blocks, weights)], "_src string, start long, first long, n long, share long, total long, slots array<long>")
    within = W.partitionBy("_src", "_b").orderBy("_h", F.col("_row.doc_id"), F.xxhash64("_row"))
    d = d.withColumn("_i", F.row_number().over(within) - 1).join(F.broadcast(before) if buckets * len(weights) <= BROADCAST_ROWS else before, ["_src", "_b"])
    d = d.withColumn("_i", F.col("_i") + F.col("_before")).withColumn("_k", F.floor(F.col("_i") / block))
    d = d.join(F.broadcast(plan), (d["_src"] == plan["_src"]) & (F.col("_k") >= F.col("first")) & (F.col("_k") < F.col("first") + F.col("n")))
    k = F.col("_k") - F.col("first")
    slot = F.col("start") + F.floor(k / F.col("share")) * F.col("total") + F.get("slots", F.pmod(k, F.col("share")).cast("int"))
    mix = F.struct(
        F.col("_k").alias("block"),
        (F.col("start") + F.floor(k * F.col("total") / F.col("share"))).alias("release"),
        (F.col("start") + F.ceil((k + 1) * F.col("total") / F.col("share"))).alias("deadline"),
        slot.alias("slot"), (slot * block + F.pmod("_i", F.lit(block))).alias("position"),
    )
    return d.select("_row", mix.alias("_mix"))


def schedule(docs: DataFrame, targets: dict[str, int] = TARGETS, rest_weight: int = REST_WEIGHT, block: int = BLOCK, seed: int = 17) -> DataFrame:
    """``docs`` with one more column, ``_mix`` (with more underscores if that is taken): struct of block, release, deadline, slot and position (the order to read in)."""
    return _scheduled(docs, targets, rest_weight, block, seed).select("_row.*", F.col("_mix").alias(unused(docs, "_mix")))


def mixed(docs: DataFrame, targets: dict[str, int] = TARGETS, rest_weight: int = REST_WEIGHT, block: int = BLOCK) -> DataFrame:
    """``docs`` in the order of the schedule, over range partitions of it; columns stay as they are."""
    return _scheduled(docs, targets, rest_weight, block).orderBy("_mix.position").select("_row.*")


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = schedule(table(spark, sf_dir, "documents").select("doc_id", "source"))
    return d.select("doc_id", "source", "_mix.block", "_mix.release", "_mix.deadline", "_mix.slot", "_mix.position")
