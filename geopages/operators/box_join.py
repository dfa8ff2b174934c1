"""Pairs of boxes that meet, by a grid of many levels.

A box belongs to the finest level at which it covers at most two cells along each axis, so
that neither large nor small boxes are copied often. It is also entered in the coarser levels
that the other side really uses. A pair meets at the coarser one of its two levels, in the cell
that holds the lower corner of the pair's intersection, and so comes out once. Cells with
many boxes are dealt out in parts. Nothing is broadcast and no side has a size limit.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.curve import WORLD, Extent, cell

BITS = 16
#: Boxes of the left side that one part of a cell holds, about.
PART = 100_000
LEFT = ("x_min", "y_min", "x_max", "y_max")
RIGHT = ("qx0", "qy0", "qx1", "qy1")


def _placed(df: DataFrame, names: tuple[str, ...], extent: Extent, side: str) -> DataFrame:
    """``df`` with a struct of the cells of its corners and the box's own shift (0 is the finest level). Boxes with a null or NaN bound meet nothing and go."""
    at = lambda v, axis: cell(F.col(v), getattr(extent, f"{axis}_min"), getattr(extent, f"{axis}_max"), BITS)
    x0, y0, x1, y1 = names
    for n in names:
        df = df.where(F.col(n).isNotNull() & ~F.isnan(F.col(n).cast("double")))
    df = df.where((F.col(x0) <= F.col(x1)) & (F.col(y0) <= F.col(y1)))
    c = F.struct(at(x0, "x").alias("x0"), at(y0, "y").alias("y0"), at(x1, "x").alias("x1"), at(y1, "y").alias("y1"))
    df = df.withColumn(f"_{side}", c)
    wide = F.greatest(F.col(f"_{side}.x1") - F.col(f"_{side}.x0"), F.col(f"_{side}.y1") - F.col(f"_{side}.y0"))
    return df.withColumn(f"_{side}shift", F.when(wide > 0, F.length(F.bin(wide))).otherwise(0))


def _entered(df: DataFrame, side: str, shifts: list[int]) -> DataFrame:
    """A row for each cell of the box at its own level and at those of ``shifts`` that are coarser."""
    c, own = F.col(f"_{side}"), F.col(f"_{side}shift")
    levels = F.array_distinct(F.concat(F.array(own), F.filter(F.array(*[F.lit(s) for s in shifts]).cast("array<int>"), lambda t: t > own)))
    span = lambda lo, hi, t: F.sequence(F.call_function("shiftright", lo, t), F.call_function("shiftright", hi, t))
    cells = F.flatten(F.transform(levels, lambda t: F.flatten(F.transform(span(c["x0"], c["x1"], t), lambda x: F.transform(span(c["y0"], c["y1"], t), lambda y: F.struct(t.alias("t"), x.alias("cx"), y.alias("cy")))))))
    return df.withColumn("_cell", F.explode(cells)).withColumn(f"_{side}own", F.col("_cell.t") == own)


def _meets() -> Column:
    return (F.col("x_max") >= F.col("qx0")) & (F.col("x_min") <= F.col("qx1")) & (F.col("y_max") >= F.col("qy0")) & (F.col("y_min") <= F.col("qy1"))


def meet(left: DataFrame, right: DataFrame, extent: Extent = WORLD, part: int = PART) -> DataFrame:
    """All columns of both sides for each pair of boxes (x_min, y_min, x_max, y_max) and (qx0, qy0, qx1, qy1) that meet, edges included.

    ``extent`` sets the grid; boxes outside it are kept in its border cells. Other column names must not clash.
    """
    a, b = _placed(left, LEFT, extent, "a"), _placed(right, RIGHT, extent, "b")
    # at most BITS + 1 rows a side
    used = lambda d, side: sorted(r[0] for r in d.select(f"_{side}shift").distinct().collect())
    a_shifts, b_shifts = used(a, "a"), used(b, "b")
    a, b = _entered(a, "a", b_shifts), _entered(b, "b", a_shifts)
    parts = a.groupBy("_cell").agg(F.count("*").alias("_n")).where(F.col("_n") > part).select("_cell", F.ceil(F.col("_n") / part).cast("int").alias("_parts"))
    a = a.join(parts, "_cell", "left").withColumn("_part", F.when(F.col("_parts") > 1, F.pmod(F.xxhash64(*left.columns), F.col("_parts"))).otherwise(0).cast("int")).drop("_parts")
    b = b.join(parts, "_cell", "left").withColumn("_part", F.explode(F.sequence(F.lit(0), F.coalesce("_parts", F.lit(1)) - 1))).drop("_parts")
    corner = lambda axis: F.call_function("shiftright", F.greatest(F.col(f"_a.{axis}0"), F.col(f"_b.{axis}0")), F.col("l._cell.t"))
    once = (corner("x") == F.col("l._cell.cx")) & (corner("y") == F.col("l._cell.cy"))
    same = (F.col("l._cell") == F.col("r._cell")) & (F.col("l._part") == F.col("r._part"))
    d = a.alias("l").join(b.alias("r"), same & (F.col("_aown") | F.col("_bown")) & _meets() & once)
    return d.select(*[F.col(f"l.`{c}`") for c in left.columns], *[F.col(f"r.`{c}`") for c in right.columns])
