"""Clustering before a write: bounded groups, total order, or rectangles from a sample."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import geom
from ..functions.curve import WORLD, Extent, curve_key
from ..sources.scratch import scratch_path

IN_PARTITION = (1 << 33) - 1


def with_key(df: DataFrame, curve: str, geometry: str = "geometry", extent: Extent = WORLD, bits: int = 16, centre: str = "box") -> DataFrame:
    df = df.withColumn("_at", geom.centre(F.col(geometry), centre))
    return df.withColumn("_key", curve_key(curve, F.col("_at.x"), F.col("_at.y"), extent, bits)).drop("_at").withMetadata("_key", {"bits": 2 * bits})


def grouped(df: DataFrame, group_size: int = 1_000_000, key: str = "_key") -> DataFrame:
    """Each ``group_size`` rows of a partition sorted among themselves: no shuffle, memory bound by the group (and spilled by Spark).

    Group and a key of ``with_key`` (null ones last) make one number where they fit, which Spark sorts by radix.
    """
    g = F.floor(F.monotonically_increasing_id().bitwiseAND(F.lit(IN_PARTITION)) / group_size)
    df = df.withColumn("_group", g)
    bits = df.schema[key].metadata.get("bits")
    if bits is None or bits + 1 + (IN_PARTITION // group_size).bit_length() > 62:
        return df.sortWithinPartitions("_group", F.col(key).asc_nulls_last())
    one = F.shiftleft("_group", bits + 1) + F.coalesce(F.col(key), F.lit(1 << bits))
    return df.withColumn("_order", one).sortWithinPartitions("_order").drop("_order")


def total(df: DataFrame, partitions: int | None = None, key: str = "_key", tie: str = "id") -> DataFrame:
    """All rows along the curve: one range shuffle; ties of the key can split."""
    by = [F.col(key).asc_nulls_last(), F.col(tie)]
    df = df.withColumn("_group", F.lit(0).cast("long"))
    return (df.repartitionByRange(partitions, *by) if partitions else df.repartitionByRange(*by)).sortWithinPartitions(*by)


def numbered(df: DataFrame, by: list[Column], name: str = "pos") -> DataFrame:
    """``df`` with each row's place (from 0) in the order of ``by``, which must leave no ties.

    One range shuffle, written as a table: places within a partition are counted as it streams
    by, and the partitions' offsets come from a row for each partition, so no task sees all rows.
    """
    spark, path = df.sparkSession, scratch_path(df.sparkSession, "numbered")
    d = df.repartitionByRange(*by).sortWithinPartitions(*by)
    d.select("*", F.spark_partition_id().alias("_part"), F.monotonically_increasing_id().bitwiseAND(F.lit(IN_PARTITION)).alias("_row")).write.parquet(path)
    d = spark.read.parquet(path)
    # as many rows as the shuffle has partitions
    starts = d.groupBy("_part").agg(F.count("*").alias("_n"))
    starts = starts.select("_part", (F.sum("_n").over(W.orderBy("_part")) - F.col("_n")).alias("_start"))
    return d.join(F.broadcast(starts), "_part").withColumn(name, F.col("_start") + F.col("_row")).drop("_part", "_row", "_start")


def before(df: DataFrame, value: str, pos: str = "pos", block: int = 1 << 16) -> DataFrame:
    """``df`` with ``_before``: ``value`` one place earlier in ``pos`` (null for the first), block by block; the first of a block gets the last of the block before it."""
    d = df.withColumn("_block", F.floor(F.col(pos) / block))
    ends = d.groupBy((F.col("_block") + 1).alias("_block")).agg(F.max_by(value, pos).alias("_last"))
    lag = F.lag(value).over(W.partitionBy("_block").orderBy(pos))
    first = F.col(pos) % block == 0
    return d.withColumn("_lag", lag).join(ends, "_block", "left").withColumn("_before", F.when(first, F.col("_last")).otherwise(F.col("_lag"))).drop("_block", "_lag", "_last")


def share(pos: Column, n: Column, k: int) -> Column:
    """Number of the part, of ``k`` as equal as can be (larger ones first), that holds place ``pos`` of ``n``."""
    small, more = F.floor(n / k), n % k
    head = more * (small + 1)
    return F.when(pos < head, F.floor(pos / (small + 1))).otherwise(more + F.floor((pos - head) / F.greatest(small, F.lit(1)))).cast("long")


def share_start(part: Column, n: Column, k: int) -> Column:
    """Place of the first row of a part of ``share``."""
    return part * F.floor(n / k) + F.least(part, n % k)


# rectangles


#: Most rows of a sample for rectangles, and rows of it that each rectangle should have: together they bound the tree that every task gets (some 100,000 nodes).
MOST_SAMPLED, SAMPLED_EACH = 1_000_000, 20


@dataclass(frozen=True)
class Splits:
    """Rectangles that tile the plane, as a tree of splits: of each node the axis (-1 at a leaf), the value, where the sides go on (a leaf: its number)."""

    axis: np.ndarray
    value: np.ndarray
    low: np.ndarray
    high: np.ndarray
    #: Rows that a leaf is meant to hold.
    capacity: int

    def leaf_of(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Numbers of the leaves that hold points; half-open, so each point has one."""
        node = np.zeros(len(x), np.int64)
        inner = np.flatnonzero(self.axis[node] >= 0)
        while len(inner):
            at = node[inner]
            v = np.where(self.axis[at] == 0, x[inner], y[inner])
            node[inner] = np.where(v < self.value[at], self.low[at], self.high[at])
            inner = inner[self.axis[node[inner]] >= 0]
        return self.low[node]

    def boxes(self) -> list[tuple[float, float, float, float]]:
        """Rectangles by their leaves' numbers; the outer ones are open to infinity."""
        inf = float("inf")
        out, todo = {}, [(0, (-inf, -inf, inf, inf))]
        while todo:
            i, r = todo.pop()
            a = int(self.axis[i])
            if a < 0:
                out[int(self.low[i])] = r
                continue
            left, right = list(r), list(r)
            left[2 + a] = right[a] = float(self.value[i])
            todo += [(int(self.low[i]), tuple(left)), (int(self.high[i]), tuple(right))]
        return [out[k] for k in sorted(out)]


def _best_split(p: np.ndarray, min_fill: float) -> tuple[int, float] | None:
    """Axis and value of a split as an R*-tree makes them: the axis of least margin over all allowed places, on it the place of least area.

    The tight boxes of the sides never overlap, since points of one value stay together.
    """
    least = max(1, int(min_fill * len(p)))
    best = None
    for axis in (0, 1):
        s = p[p[:, axis].argsort(kind="stable")]
        lo, hi = np.minimum.accumulate(s), np.maximum.accumulate(s)
        lo2, hi2 = np.minimum.accumulate(s[::-1])[::-1], np.maximum.accumulate(s[::-1])[::-1]
        at = np.arange(least, len(p) - least + 1)
        at = at[at < len(p)]
        at = at[s[at - 1, axis] < s[at, axis]]
        if len(at):
            first, second = hi[at - 1] - lo[at - 1], hi2[at] - lo2[at]
            margin = (first.sum(1) + second.sum(1)).mean()
            if best is None or margin < best[0]:
                k = int((first.prod(1) + second.prod(1)).argmin())
                best = margin, axis, float(s[at[k], axis])
    return best and best[1:]


def split_points(points: np.ndarray, capacity: int, min_fill: float = 0.3) -> Splits:
    """Splits of points (rows of x, y) until no rectangle holds more than ``capacity``, but for points in one place."""
    axis, value, low, high, leaves = [], [], [], [], 0
    todo = [(points, -1, False)]
    while todo:
        p, parent, is_high = todo.pop()
        i = len(axis)
        if parent >= 0:
            (high if is_high else low)[parent] = i
        split = _best_split(p, min_fill) if len(p) > capacity else None
        axis.append(-1 if split is None else split[0])
        value.append(0.0 if split is None else split[1])
        low.append(leaves if split is None else -1)
        high.append(-1)
        if split is None:
            leaves += 1
            continue
        side = p[:, split[0]] >= split[1]
        todo += [(p[side], i, True), (p[~side], i, False)]
    return Splits(np.array(axis, np.int8), np.array(value), np.array(low, np.int64), np.array(high, np.int64), capacity)


def rectangles(points: DataFrame, capacity: int = 10_000, min_fill: float = 0.3, seed: int = 7, most_sampled: int = MOST_SAMPLED) -> Splits:
    """Splits for ``capacity`` points a rectangle from a sample that grows with their number up to a bound.

    Beyond it the rectangles are made larger, as ``capacity`` of the result says; ``partitioned`` splits those again.
    """
    n = points.count()
    wanted = min(most_sampled, max(100_000, SAMPLED_EACH * -(-n // capacity)))
    share = min(1.0, wanted / max(n, 1))
    s = points.select("x", "y").where("x is not null and y is not null and not isnan(x) and not isnan(y)")
    s = s.sample(share, seed).limit(2 * wanted) if share < 1 else s
    s = np.array([(r.x, r.y) for r in s.collect()]).reshape(-1, 2)
    own = capacity if share == 1 else max(capacity, int(SAMPLED_EACH / share))
    tree = split_points(s, max(1, int(own * share)), min_fill)
    return Splits(tree.axis, tree.value, tree.low, tree.high, own)


def assign(points: DataFrame, tree: Splits) -> DataFrame:
    """``points`` with the number of their rectangle, by walks down the tree for whole batches: no join, no shuffle."""

    @F.arrow_udf(T.LongType())
    def leaf(x: pa.Array, y: pa.Array) -> pa.Array:
        nan = float("nan")
        return pa.array(tree.leaf_of(*(v.fill_null(nan).to_numpy(zero_copy_only=False) for v in (x, y))))

    return points.withColumn("cell", leaf(F.col("x").cast("double"), F.col("y").cast("double")))


def partitioned(points: DataFrame, capacity: int = 10_000, min_fill: float = 0.3, most_sampled: int = MOST_SAMPLED) -> DataFrame:
    """``points`` with ``cell``: rectangles of up to ``capacity`` points (more only in one place), however many points there are.

    Rectangles that turn out too full, by the luck or the bound of the sample, are split again by all their own points, each in one group.
    """
    tree = rectangles(points, capacity, min_fill, most_sampled=most_sampled)
    d = assign(points, tree)
    # as many rows as the tree has leaves at most
    full = [r.cell for r in d.groupBy("cell").count().where(F.col("count") > capacity).select("cell").collect()]
    if not full:
        return d

    def split(group: pa.Table) -> pa.Table:
        x, y = (group.column(a).combine_chunks().fill_null(float("nan")).to_numpy(zero_copy_only=False).astype(float) for a in "xy")
        real = ~(np.isnan(x) | np.isnan(y))
        own = split_points(np.stack([x[real], y[real]], 1), capacity, min_fill).leaf_of(x, y)
        first = group.column("cell").to_numpy()
        return group.set_column(group.schema.get_field_index("cell"), "cell", pa.array((first << 24) + own))

    cells = F.broadcast(d.sparkSession.createDataFrame([(c,) for c in full], "cell long"))
    again = d.join(cells, "cell", "left_semi").groupBy("cell").applyInArrow(split, d.schema)
    return d.join(cells, "cell", "left_anti").withColumn("cell", F.shiftleft("cell", 24)).select(d.columns).unionByName(again)


def grid(points: DataFrame, extent: Extent, cells: int) -> DataFrame:
    from ..functions.curve import cell

    n = (cells - 1).bit_length()
    return points.withColumn("cell", cell(F.col("y"), extent.y_min, extent.y_max, n) * (1 << n) + cell(F.col("x"), extent.x_min, extent.x_max, n))


def tiles(points: DataFrame, slabs: int, per_slab: int) -> DataFrame:
    """Sort-tile: slabs of equal counts along x, tiles of equal counts along y in each. Two range shuffles; ties go by id."""
    d = numbered(points, [F.col(c) for c in ("x", "y", "id")], "_x")
    n = F.lit(d.count())
    d = d.withColumn("slab", share(F.col("_x"), n, slabs)).drop("_x")
    d = numbered(d, [F.col(c) for c in ("slab", "y", "x", "id")], "_y")
    start = share_start(F.col("slab"), n, slabs)
    d = d.withColumn("tile", share(F.col("_y") - start, share_start(F.col("slab") + 1, n, slabs) - start, per_slab)).drop("_y")
    return d.withColumn("cell", F.col("slab") * per_slab + F.col("tile"))
