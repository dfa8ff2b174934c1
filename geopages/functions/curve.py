"""Space-filling curve keys as Columns: Z by built-in bit functions, Hilbert by array work on Arrow batches."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


@dataclass(frozen=True)
class Extent:
    x_min: float
    y_min: float
    x_max: float
    y_max: float


WORLD = Extent(-180.0, -90.0, 180.0, 90.0)


def cell(v: Column, lo: float, hi: float, bits: int = 16) -> Column:
    """Number of the grid cell of a value along one axis; values outside go to the border cells."""
    side = 1 << bits
    return F.least(F.lit(side - 1), F.greatest(F.lit(0), F.floor((v - lo) / (hi - lo) * side))).cast("long")


def _spread(v: Column) -> Column:
    for shift, mask in ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555)):
        v = v.bitwiseOR(F.shiftleft(v, shift)).bitwiseAND(F.lit(mask))
    return v


def z_key(x: Column, y: Column, extent: Extent = WORLD, bits: int = 16) -> Column:
    """Bits of both cell numbers in turn, y's above x's."""
    return _spread(cell(x, extent.x_min, extent.x_max, bits)).bitwiseOR(F.shiftleft(_spread(cell(y, extent.y_min, extent.y_max, bits)), 1))


@F.arrow_udf(T.LongType())
def _hilbert(x: pa.Array, y: pa.Array, bits: pa.Array) -> pa.Array:
    """From the highest bit: a quadrant's digit, then its turn (x and y swap, first reflected in the whole grid)."""
    null = x.is_null().to_numpy(zero_copy_only=False)
    x, y = (v.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64) for v in (x, y))
    n = bits[0].as_py() if len(bits) else 0
    d = np.zeros(len(x), np.int64)
    for b in range(n - 1, -1, -1):
        bx, by = x >> b & 1, y >> b & 1
        d = d << 2 | (3 * bx ^ by)
        turn, flip = by == 0, (by == 0) & (bx == 1)
        u, v = np.where(flip, (1 << n) - 1 - y, y), np.where(flip, (1 << n) - 1 - x, x)
        x, y = np.where(turn, u, x), np.where(turn, v, y)
    return pa.array(d, mask=null)


def hilbert_key(x: Column, y: Column, extent: Extent = WORLD, bits: int = 16) -> Column:
    """Place along the Hilbert curve, for whole Arrow batches of cells."""
    return _hilbert(cell(x, extent.x_min, extent.x_max, bits), cell(y, extent.y_min, extent.y_max, bits), F.lit(bits))


def curve_key(curve: str, x: Column, y: Column, extent: Extent = WORLD, bits: int = 16) -> Column:
    return {"z": z_key, "hilbert": hilbert_key}[curve](x, y, extent, bits)
