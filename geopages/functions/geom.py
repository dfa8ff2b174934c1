"""Scalar functions over geometry columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .build import Kind, doubled_area

KIND_NAMES = ["EMPTY", "POINT", "LINESTRING", "POLYGON", "MULTIPOINT", "MULTILINESTRING", "MULTIPOLYGON"]


def _coords(g: Column) -> Column:
    return F.flatten(g["parts"])


def n_parts(g: Column) -> Column:
    return F.size(g["parts"])


def n_coords(g: Column) -> Column:
    return F.aggregate(g["parts"], F.lit(0), lambda a, p: a + F.size(p))


def kind_name(g: Column) -> Column:
    return F.get(F.array(*[F.lit(n) for n in KIND_NAMES]), g["type"])


def is_empty(g: Column) -> Column:
    return g["type"] == int(Kind.EMPTY)


def _lone(g: Column, axis: str) -> Column:
    """A value of a point's only vertex; null for NaN."""
    v = F.get(F.get(g["parts"], F.lit(0)), F.lit(0))[axis]
    return F.when(~F.isnan(v), v)


def box(g: Column) -> Column:
    """struct x_min, y_min, x_max, y_max; its fields are null without coordinates. NaN takes no part. A point's box needs no array work."""
    axis = lambda n: F.filter(F.transform(_coords(g), lambda c: c[n]), lambda v: ~F.isnan(v))
    bound = lambda f, n: F.when(g["type"] == int(Kind.POINT), _lone(g, n)).otherwise(f(axis(n)))
    return F.struct(bound(F.array_min, "x").alias("x_min"), bound(F.array_min, "y").alias("y_min"), bound(F.array_max, "x").alias("x_max"), bound(F.array_max, "y").alias("y_max"))


def intersects(a: Column, x0, y0, x1, y1) -> Column:
    """Does box ``a`` meet a closed rectangle?"""
    return (a["x_max"] >= x0) & (a["x_min"] <= x1) & (a["y_max"] >= y0) & (a["y_min"] <= y1)


def contains(a: Column, b: Column) -> Column:
    return (a["x_min"] <= b["x_min"]) & (a["y_min"] <= b["y_min"]) & (a["x_max"] >= b["x_max"]) & (a["y_max"] >= b["y_max"])


def length(coords: Column) -> Column:
    step = lambda i: F.hypot(coords[i + 1]["x"] - coords[i]["x"], coords[i + 1]["y"] - coords[i]["y"])
    return F.when(F.size(coords) > 1, F.aggregate(F.sequence(F.lit(0), F.size(coords) - 2), F.lit(0.0), lambda a, i: a + step(i))).otherwise(0.0)


def area(g: Column) -> Column:
    """Of polygons: shells less holes, whose signs differ."""
    return F.abs(F.aggregate(g["parts"], F.lit(0.0), lambda a, r: a + doubled_area(r))) / 2


def centre(g: Column, how: str = "box") -> Column:
    """Representative point: centre of the box, first vertex or vertex mean."""
    if how == "first":
        return F.get(F.get(g["parts"], F.lit(0)), F.lit(0))
    if how == "mean":
        c = _coords(g)
        mean = lambda n: F.aggregate(c, F.lit(0.0), lambda a, v: a + v[n]) / F.size(c)
        return F.struct(mean("x").alias("x"), mean("y").alias("y"))
    if how == "box":
        axis = lambda n: F.filter(F.transform(_coords(g), lambda c: c[n]), lambda v: ~F.isnan(v))
        middle = lambda n: F.when(g["type"] == int(Kind.POINT), _lone(g, n)).otherwise((F.array_min(axis(n)) + F.array_max(axis(n))) / 2)
        return F.struct(middle("x").alias("x"), middle("y").alias("y"))
    raise ValueError(f"no such point: {how}")


def contains_point(ring: Column, x, y) -> Column:
    """Even-odd rule along a closed ring."""
    def crosses(i):
        a, b = ring[i], ring[i + 1]
        return ((a["y"] > y) != (b["y"] > y)) & (x < (b["x"] - a["x"]) * (y - a["y"]) / (b["y"] - a["y"]) + a["x"])

    edges = F.sequence(F.lit(0), F.size(ring) - 2)
    return F.pmod(F.aggregate(edges, F.lit(0), lambda n, i: n + F.when(ring[i]["y"] == ring[i + 1]["y"], 0).when(crosses(i), 1).otherwise(0)), F.lit(2)) == 1


def _edges_meet(coords: Column, x0, y0, x1, y1) -> Column:
    """Does an edge of a chain of coordinates meet a closed rectangle? Its box does, and not all corners lie strictly on one side of it."""
    def meets(i):
        a, b = coords[i], coords[i + 1]
        near = (F.greatest(a["x"], b["x"]) >= x0) & (F.least(a["x"], b["x"]) <= x1) & (F.greatest(a["y"], b["y"]) >= y0) & (F.least(a["y"], b["y"]) <= y1)
        side = lambda x, y: (b["x"] - a["x"]) * (y - a["y"]) - (b["y"] - a["y"]) * (x - a["x"])
        corners = [side(x, y) for x in (x0, x1) for y in (y0, y1)]
        return near & (F.least(*corners) <= 0) & (F.greatest(*corners) >= 0)

    return F.when(F.size(coords) > 1, F.exists(F.sequence(F.lit(0), F.size(coords) - 2), meets)).otherwise(False)


def intersects_exactly(g: Column, x0: float, y0: float, x1: float, y1: float) -> Column:
    """Does the geometry itself, not only its box, meet a closed rectangle? Vertices within, edges across it or, for areas, its corner in the interior."""
    x0, y0, x1, y1 = (F.lit(float(v)) for v in (x0, y0, x1, y1))
    parts = g["parts"]
    inside = F.exists(parts, lambda p: F.exists(p, lambda c: (c["x"] >= x0) & (c["x"] <= x1) & (c["y"] >= y0) & (c["y"] <= y1)))
    across = g["type"].isin(2, 3, 5, 6) & F.exists(parts, lambda p: _edges_meet(p, x0, y0, x1, y1))
    around = F.aggregate(parts, F.lit(0), lambda a, r: a + F.when(F.size(r) > 1, contains_point(r, x0, y0)).otherwise(False).cast("int"))
    return inside | across | (g["type"].isin(3, 6) & (around % 2 == 1))


def translate(g: Column, dx, dy) -> Column:
    move = lambda c: F.struct((c["x"] + dx).alias("x"), (c["y"] + dy).alias("y"))
    return F.struct(g["type"].alias("type"), F.transform(g["parts"], lambda p: F.transform(p, move)).alias("parts"))


def validate(g: Column) -> Column:
    """Codes of what is wrong: unclosed or short rings, short lines, part counts against the kind, values that are not finite."""
    kind, parts = g["type"], g["parts"]
    areal, linear = kind.isin(3, 6), kind.isin(2, 5)
    ends = lambda r: (r[0]["x"] == F.element_at(r, -1)["x"]) & (r[0]["y"] == F.element_at(r, -1)["y"])
    odd = lambda v: F.isnan(v) | (F.abs(v) == float("inf"))
    checks = {
        "unclosed": areal & F.exists(parts, lambda r: (F.size(r) > 0) & ~ends(r)),
        "short_ring": areal & F.exists(parts, lambda r: F.size(r) < 4),
        "short_line": linear & F.exists(parts, lambda r: F.size(r) < 2),
        "parts": (kind.isin(1, 2) & (F.size(parts) != 1)) | ((kind == 0) & (F.size(parts) != 0)) | (kind.isin(3, 4, 5, 6) & (F.size(parts) == 0)),
        "points": kind.isin(1, 4) & F.exists(parts, lambda p: F.size(p) != 1),
        "not_finite": F.exists(parts, lambda p: F.exists(p, lambda c: odd(c["x"]) | odd(c["y"]))),
        "kind": (kind < 0) | (kind > 6),
    }
    return F.array_compact(F.array(*[F.when(c, F.lit(n)) for n, c in checks.items()]))


def as_wkt(g: Column, number=lambda v: v.cast("string")) -> Column:
    """Well-known text of the simple kinds; rings of a multipolygon are told apart by orientation."""
    from .build import split_polygons

    text = lambda cs: F.array_join(F.transform(cs, lambda c: F.concat(number(c["x"]), F.lit(" "), number(c["y"]))), ", ")
    wrap = lambda s: F.concat(F.lit("("), s, F.lit(")"))
    rings = lambda ps: wrap(F.array_join(F.transform(ps, lambda p: wrap(text(p))), ", "))
    parts = g["parts"]
    body = (
        F.when(g["type"] == 1, F.concat(F.lit("POINT "), wrap(text(F.get(parts, F.lit(0))))))
        .when(g["type"] == 2, F.concat(F.lit("LINESTRING "), wrap(text(F.get(parts, F.lit(0))))))
        .when(g["type"] == 3, F.concat(F.lit("POLYGON "), rings(parts)))
        .when(g["type"] == 4, F.concat(F.lit("MULTIPOINT "), rings(parts)))
        .when(g["type"] == 5, F.concat(F.lit("MULTILINESTRING "), rings(parts)))
        .when(g["type"] == 6, F.concat(F.lit("MULTIPOLYGON "), wrap(F.array_join(F.transform(split_polygons(parts), rings), ", "))))
    )
    return body.otherwise(F.lit("GEOMETRYCOLLECTION EMPTY"))


def from_wkt(text: Column) -> Column:
    """Geometry of well-known text, by built-in functions alone; EMPTY of any kind is kind 0.

    Null for other kinds, for coordinates that aren't two numbers and for unequal brackets.
    """
    t = F.trim(text)
    kind = F.array_position(F.array(*[F.lit(n) for n in KIND_NAMES]), F.upper(F.regexp_extract(t, r"^([A-Za-z]+)", 1))).cast("int") - 1
    body = F.regexp_extract(t, r"(?s)^[A-Za-z]+\s*(\(.*\))$", 1)

    def coordinate(c):
        words = F.split(F.trim(c), r"\s+")
        number = lambda i: F.when(F.size(words) == 2, F.get(words, F.lit(i)).try_cast("double"))
        return F.struct(number(0).alias("x"), number(1).alias("y"))

    # one part for each bracketed list, whatever its depth
    lists = F.split(F.regexp_replace(body, r"^[\s(]+|[\s)]+$", ""), r"\)[\s)]*,[\s(]*\(")
    parts = F.transform(lists, lambda p: F.transform(F.split(p, ","), coordinate))
    parts = F.when(kind == int(Kind.MULTIPOINT), F.transform(F.flatten(parts), lambda c: F.array(c))).otherwise(parts)
    sound = F.forall(F.flatten(parts), lambda c: c["x"].isNotNull() & c["y"].isNotNull())
    level = (F.length(F.replace(body, F.lit("("), F.lit(""))) == F.length(F.replace(body, F.lit(")"), F.lit("")))) & ~kind.isin(0, -1)
    nothing = F.struct(F.lit(0).alias("type"), F.array().cast("array<array<struct<x:double,y:double>>>").alias("parts"))
    empty = t.rlike(r"(?i)^[a-z]+\s+empty$")
    return F.when(empty, nothing).when(level & sound, F.struct(kind.alias("type"), parts.alias("parts")))
