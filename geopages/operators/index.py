"""The page index: boxes of pages, pruning by rectangles, and how good the boxes are."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.curve import WORLD, Extent
from . import box_join

Rect = tuple[float, float, float, float]


def page_boxes(paged: DataFrame, by: tuple[str, ...] = ("page",)) -> DataFrame:
    """Boxes of pages of points; NaN takes no part."""
    v = lambda c: F.when(~F.isnan(c), F.col(c))
    return paged.groupBy(*by).agg(F.min(v("x")).alias("x_min"), F.max(v("x")).alias("x_max"), F.min(v("y")).alias("y_min"), F.max(v("y")).alias("y_max"), F.count("*").alias("n"))


def meets(rect: Rect) -> Column:
    """A rectangle as two closed ranges over the four scalar bounds: this is what the scan can push down."""
    x0, y0, x1, y1 = rect
    return (F.col("x_max") >= x0) & (F.col("x_min") <= x1) & (F.col("y_max") >= y0) & (F.col("y_min") <= y1)


#: Windows that are sent to every task at most (32 bytes of bounds each, and their other columns); both ways give the same pairs.
MOST_WINDOWS = 100_000


def windows_meet(windows: DataFrame, boxes: DataFrame, most: int = MOST_WINDOWS) -> DataFrame:
    """Pairs of windows (qx0, qy0, qx1, qy1) and boxes that meet: up to ``most`` windows are broadcast, more are joined through a grid."""
    if windows.limit(most + 1).count() > most:
        return box_join.meet(boxes, windows)
    return boxes.join(F.broadcast(windows), (F.col("x_max") >= F.col("qx0")) & (F.col("x_min") <= F.col("qx1")) & (F.col("y_max") >= F.col("qy0")) & (F.col("y_min") <= F.col("qy1")))


def quality(boxes: DataFrame, extent: Extent = WORLD, page: str = "page") -> DataFrame:
    """Pages, their total area and margin, and the area that pairs of pages share, from a grid join of the boxes with themselves."""
    w, h = F.col("x_max") - F.col("x_min"), F.col("y_max") - F.col("y_min")
    one = boxes.agg(F.count("*").alias("pages"), F.sum(w * h).alias("area"), F.sum(w + h).alias("margin"))
    a = boxes.select(F.col(page).alias("_l"), *box_join.LEFT)
    b = boxes.select(F.col(page).alias("_r"), *[F.col(x).alias(y) for x, y in zip(box_join.LEFT, box_join.RIGHT, strict=True)])
    side = lambda axis: F.least(f"{axis}_max", f"q{axis}1") - F.greatest(f"{axis}_min", f"q{axis}0")
    shared = box_join.meet(a, b, extent).where("_l < _r").agg(F.coalesce(F.sum(side("x") * side("y")), F.lit(0.0)).alias("overlap"))
    return one.crossJoin(F.broadcast(shared))  # a row with a row


def cell_mask(paged: DataFrame, boxes: DataFrame, k: int = 8) -> DataFrame:
    """``boxes`` with a bit for each occupied cell of a k x k grid in the page's box (k * k up to 64)."""
    at = lambda v, lo, hi: F.when(F.col(hi) > F.col(lo), F.least(F.lit(k - 1), F.floor((F.col(v) - F.col(lo)) / (F.col(hi) - F.col(lo)) * k))).otherwise(0).cast("int")
    p = paged.select("page", "x", "y").join(boxes, "page")
    bit = F.expr("shiftleft(1L, cy * " + str(k) + " + cx)")
    masks = p.select("page", at("x", "x_min", "x_max").alias("cx"), at("y", "y_min", "y_max").alias("cy")).groupBy("page").agg(F.bit_or(bit).alias("mask"))
    return boxes.join(masks, "page")


def mask_meets(rect: Rect, k: int = 8) -> Column:
    """Does the rectangle meet an occupied cell? A cell's closed range in its page's box is compared with the rectangle."""
    x0, y0, x1, y1 = rect
    def hit(i):
        cx, cy = i % k, F.floor(i / k)
        lo = lambda a, b, c: F.col(a) + (F.col(b) - F.col(a)) * c / k
        inside = (lo("x_min", "x_max", cx) <= x1) & (lo("x_min", "x_max", cx + 1) >= x0) & (lo("y_min", "y_max", cy) <= y1) & (lo("y_min", "y_max", cy + 1) >= y0)
        return inside & (F.pmod(F.shiftright("mask", 0), F.lit(2)) >= 0) & (F.substring(F.lpad(F.bin("mask"), k * k, "0"), (k * k - i).cast("int"), F.lit(1)) == "1")

    return meets(rect) & F.exists(F.sequence(F.lit(0), F.lit(k * k - 1)), hit)
