"""Size of an encoded page for every delta width, from the histogram of needed widths."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def bit_width(z: np.ndarray) -> np.ndarray:
    """Bits needed by each unsigned code, 0 for 0; by shifts, as logarithms of large integers round."""
    z = z.astype(np.uint64)
    out = np.zeros(len(z), np.int64)
    for s in (32, 16, 8, 4, 2, 1):
        big = z >> np.uint64(s) != 0
        out[big] += s
        z = np.where(big, z >> np.uint64(s), z)
    return out + (z != 0)


def histogram(z: np.ndarray) -> np.ndarray:
    return np.bincount(bit_width(z), minlength=65)


def marker_histogram(z: np.ndarray) -> np.ndarray:
    """Codes that are all ones, by their width: they equal the marker of that width and are escaped."""
    z = z.astype(np.uint64)
    return np.bincount(bit_width(z[(z & (z + np.uint64(1))) == 0]), minlength=65)


def size_two_sums(h: np.ndarray, full: int = 64) -> np.ndarray:
    """S(n) as fitting codes plus overflowing ones with their values."""
    return np.array([n * h[: n + 1].sum() + (n + full) * h[n + 1 : full + 1].sum() for n in range(full + 1)])


def size_suffix(h: np.ndarray, full: int = 64) -> np.ndarray:
    """The same through one suffix sum."""
    over = h[: full + 1].sum() - np.cumsum(h[: full + 1])
    return np.arange(full + 1) * h[: full + 1].sum() + full * over


def best_bits(h: np.ndarray, markers: np.ndarray, policy: str = "exact", full: int = 64) -> tuple[int, int]:
    """(n, S(n)) of least size, the smaller n where sizes tie. ``exact`` counts escaped marker codes and has n = 0 only where all codes are 0."""
    s = size_suffix(h, full)
    if policy == "exact":
        s = s + full * markers[: full + 1]
        s[0] = 0 if h[0] == h[: full + 1].sum() else s.max() + 1
    n = int(s.argmin())
    return n, int(s[n])


# the same, over rows


def _sizes(h: Column, total: Column, full: int, exact: bool) -> Column:
    over = lambda n: F.aggregate(F.filter(h, lambda x: x["width"] > n), F.lit(0).cast("long"), lambda a, x: a + x["cnt"])
    marked = lambda n: F.aggregate(F.filter(h, lambda x: x["width"] == n), F.lit(0).cast("long"), lambda a, x: a + x["markers"])
    size = lambda n: n * total + full * over(n) + (full * marked(n) if exact else 0)
    ns = F.sequence(F.lit(0), F.lit(full))
    if exact:
        zero = F.aggregate(F.filter(h, lambda x: x["width"] == 0), F.lit(0).cast("long"), lambda a, x: a + x["cnt"]) == total
        ns = F.when(zero, F.array(F.lit(0))).otherwise(F.sequence(F.lit(1), F.lit(full)))
        size = lambda n: F.when(n == 0, F.lit(0).cast("long")).otherwise(n * total + full * over(n) + full * marked(n))
    return F.transform(ns, lambda n: F.struct(size(n).cast("long").alias("size"), n.alias("n")))


def page_sizes(hist: DataFrame, by: list[str], policy: str = "exact", full: int = 64) -> DataFrame:
    """``by`` columns and sizes array<struct<size,n>>, from rows (by, width, cnt, markers); one aggregate with 65 rows at most for each page."""
    h = hist.groupBy(*by).agg(F.collect_list(F.struct("width", "cnt", "markers")).alias("h"), F.sum("cnt").alias("total"))
    return h.select(*by, "total", "h", _sizes(F.col("h"), F.col("total"), full, policy == "exact").alias("sizes"))


def best_page_bits(hist: DataFrame, by: list[str], policy: str = "exact", full: int = 64) -> DataFrame:
    best = F.array_min("sizes")
    return page_sizes(hist, by, policy, full).select(*by, "total", best["n"].alias("n"), best["size"].alias("bits"))


def empirical_bits(hist: DataFrame, full: int = 64) -> int:
    """A fixed width for a dataset: the best one for the histogram of all its pages (or of a sample's) together."""
    one = hist.groupBy("width").agg(F.sum("cnt").alias("cnt"), F.sum("markers").alias("markers")).withColumn("all", F.lit(1))
    return best_page_bits(one, ["all"], "exact", full).first()["n"]
