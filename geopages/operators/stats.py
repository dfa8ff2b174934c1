"""Pages and deltas as rows: the relational model of what the codec does."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import cost, sorting


@F.arrow_udf(T.LongType())
def to_bits(v: pa.Array) -> pa.Array:
    """The 64 bits of a double as a signed integer."""
    import numpy as np

    return pa.array(np.ascontiguousarray(v.to_numpy(zero_copy_only=False)).view("i8"), mask=v.is_null().to_numpy(zero_copy_only=False))


@F.arrow_udf(T.IntegerType())
def to_bits32(v: pa.Array) -> pa.Array:
    import numpy as np

    return pa.array(np.ascontiguousarray(v.to_numpy(zero_copy_only=False)).view("i4"), mask=v.is_null().to_numpy(zero_copy_only=False))


def wrapped_difference(a: Column, b: Column) -> Column:
    """a - b modulo 2**64: by 32-bit halves, as ANSI arithmetic raises on overflow."""
    low = F.lit(0xFFFFFFFF)
    lo = a.bitwiseAND(low) - b.bitwiseAND(low)
    hi = F.shiftright(a, 32) - F.shiftright(b, 32) + F.shiftright(lo, 32)
    return F.shiftleft(hi, 32).bitwiseOR(lo.bitwiseAND(low))


def zigzag(d: Column) -> Column:
    return F.shiftright(d, 63).bitwiseXOR(F.shiftleft(d, 1))


def width(z: Column) -> Column:
    return F.when(z == 0, 0).otherwise(F.length(F.bin(z)))


def is_marker(z: Column) -> Column:
    """All ones up to its width."""
    return (z == 0) | (F.length(F.replace(F.bin(z), F.lit("1"), F.lit(""))) == 0)


def with_pages(points: DataFrame, order: list[Column], page_rows: int, group: Column | None = None) -> DataFrame:
    """``points`` with page and ord: page_rows neighbours in ``order``, which must leave no ties.

    Without ``group`` all rows are one sort group, numbered by ``sorting.numbered``. With it, each
    group is numbered in a window and must be a bounded share of the rows.
    """
    if group is None:
        d = sorting.numbered(points, order).withColumn("sort_group", F.lit(0))
    else:
        d = points.withColumn("sort_group", group)
        d = d.withColumn("pos", (F.row_number().over(W.partitionBy("sort_group").orderBy(*order)) - 1).cast("long"))
    return d.withColumn("page", F.floor(F.col("pos") / page_rows)).withColumn("ord", F.col("pos") % page_rows)


def deltas(paged: DataFrame, axes: tuple[str, ...] = ("x", "y"), restart: str | None = None) -> DataFrame:
    """(sort_group, page, ord, axis, delta, zigzag, width) of every value but a page's first."""
    d = paged.select("sort_group", "page", "ord", *([restart] if restart else []), *[to_bits(F.col(a)).alias(a) for a in axes])
    by = ["sort_group", "page", *([restart] if restart else [])]
    w = W.partitionBy(*by).orderBy("ord")
    for a in axes:
        d = d.withColumn(f"{a}_before", F.lag(a).over(w))
    d = d.select("sort_group", "page", "ord", F.explode(F.array(*[F.struct(F.lit(a).alias("axis"), F.col(a).alias("v"), F.col(f"{a}_before").alias("before")) for a in axes])).alias("s"))
    d = d.select("sort_group", "page", "ord", "s.axis", wrapped_difference(F.col("s.v"), F.col("s.before")).alias("delta")).where("delta is not null")
    return d.withColumn("zigzag", zigzag(F.col("delta"))).withColumn("width", width(F.col("zigzag")))


def width_histogram(delta: DataFrame, by: list[str]) -> DataFrame:
    """(by, width, cnt, markers)."""
    return delta.groupBy(*by, "width").agg(F.count("*").alias("cnt"), F.sum(F.when(is_marker(F.col("zigzag")), 1).otherwise(0)).alias("markers"))


def encode_runs(rows: DataFrame, value: str, order: str, by: list[str]) -> DataFrame:
    """Run-length coding of a column: (by, run_no, cnt, value)."""
    w = W.partitionBy(*by).orderBy(order)
    d = rows.withColumn("_new", F.when(F.lag(value).over(w).eqNullSafe(F.col(value)) & (F.row_number().over(w) > 1), 0).otherwise(1))
    d = d.withColumn("run_no", F.sum("_new").over(w) - 1)
    return d.groupBy(*by, "run_no").agg(F.count("*").alias("cnt"), F.first(value).alias(value))


def decode_runs(runs: Column) -> Column:
    return F.flatten(F.transform(runs, lambda r: F.array_repeat(r["type"], r["cnt"])))


def empirical_bits(paged: DataFrame, share: float = 0.01, seed: int = 7) -> DataFrame:
    """(axis, n, bits): one width for each axis that suits whole pages drawn with ``share``, for the fixed-width policy."""
    if share < 1:
        paged = paged.where(F.pmod(F.xxhash64(F.lit(seed), "sort_group", "page"), F.lit(1 << 20)) < int(share * (1 << 20)))
    h = width_histogram(deltas(paged), ["axis"])
    return cost.best_page_bits(h, ["axis"]).select("axis", "n", "bits")


_PAGE_SIZES = T.StructType([T.StructField(n, T.LongType()) for n in ("plain", "plain_gzip", "coded", "coded_gzip", "coded_bits")])


def encoded(values: Column, **options) -> Column:
    """Sizes of a page of an array of doubles: bytes plain and as the codec writes them, each also after gzip, and the bits that the model foretells."""

    @F.arrow_udf(_PAGE_SIZES)
    def sizes(v: pa.Array) -> pa.Array:
        import zlib

        import numpy as np

        from . import codec

        flat, at = v.values.to_numpy(zero_copy_only=False), v.offsets.to_numpy()
        rows = []
        for a, b in zip(at[:-1], at[1:], strict=True):
            own = np.ascontiguousarray(flat[a:b])
            p = codec.encode_page(own, **options)
            rows.append((own.nbytes, len(zlib.compress(own.tobytes(), 6, 31)), len(p.data), len(zlib.compress(p.data, 6, 31)), p.predicted_bits))
        return pa.StructArray.from_arrays([pa.array([r[i] for r in rows], pa.int64()) for i in range(5)], names=_PAGE_SIZES.names)

    return sizes(values)


def page_values(paged: DataFrame) -> DataFrame:
    """(page, x, y): each page's values in order, as arrays."""
    rows = F.array_sort(F.collect_list(F.struct("ord", "x", "y")))
    return paged.groupBy("page").agg(rows.alias("r")).select("page", F.col("r.x").alias("x"), F.col("r.y").alias("y"))
