"""The unified geometry type and its constructors, as Column expressions.

A geometry is ``struct<type:int, parts:array<array<struct<x,y>>>>``: a part is one
connected component (a ring, a line or a lone point). NULL is a missing geometry, kind
0 an empty one.
"""

from __future__ import annotations

from enum import IntEnum

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


class Kind(IntEnum):
    EMPTY, POINT, LINESTRING, POLYGON, MULTIPOINT, MULTILINESTRING, MULTIPOLYGON = range(7)


def geometry_type(dims: int = 2, coord: str = "double") -> T.StructType:
    leaf = {"double": T.DoubleType(), "float": T.FloatType(), "long": T.LongType()}[coord]
    point = T.StructType([T.StructField(n, leaf, False) for n in "xyzm"[:dims]])
    return T.StructType([T.StructField("type", T.IntegerType(), False), T.StructField("parts", T.ArrayType(T.ArrayType(point, False), False), False)])


def collection_type(**kw) -> T.ArrayType:
    return T.ArrayType(geometry_type(**kw), False)


def level_bits(kind: T.DataType, nullable: bool = False) -> dict[str, tuple[int, int]]:
    """Bits of repetition and definition levels of every leaf below a column of this type."""
    out: dict[str, tuple[int, int]] = {}

    def walk(t: T.DataType, name: str, rep: int, define: int) -> None:
        if isinstance(t, T.StructType):
            for f in t.fields:
                walk(f.dataType, f"{name}.{f.name}".lstrip("."), rep, define + f.nullable)
        elif isinstance(t, T.ArrayType):
            walk(t.elementType, name, rep + 1, define + 1 + t.containsNull)
        else:
            out[name] = rep.bit_length(), define.bit_length()

    walk(kind, "", 0, int(nullable))
    return out


def level_entries(column: Column, kind: T.DataType) -> dict[str, Column]:
    """Pairs of levels that a row has in every leaf below a column of this type: one for each value, null and empty list."""
    if isinstance(kind, T.StructType):
        return {f"{f.name}.{leaf}".rstrip("."): n for f in kind.fields for leaf, n in level_entries(column[f.name], f.dataType).items()}
    if isinstance(kind, T.ArrayType):
        inner = lambda leaf: F.aggregate(column, F.lit(0), lambda n, e: n + level_entries(e, kind.elementType)[leaf])
        return {leaf: F.greatest(F.lit(1), inner(leaf) if rep else F.size(column)) for leaf, (rep, _) in level_bits(kind.elementType).items()}
    return {"": F.lit(1)}


def _geometry(kind: int, parts: Column) -> Column:
    return F.struct(F.lit(int(kind)).alias("type"), parts.alias("parts"))


def coordinate(x, y) -> Column:
    return F.struct(F.col(x).alias("x") if isinstance(x, str) else x.alias("x"), F.col(y).alias("y") if isinstance(y, str) else y.alias("y"))


def empty() -> Column:
    return _geometry(Kind.EMPTY, F.array().cast("array<array<struct<x:double,y:double>>>"))


def point(x, y) -> Column:
    return _geometry(Kind.POINT, F.array(F.array(coordinate(x, y))))


def linestring(coords: Column) -> Column:
    return _geometry(Kind.LINESTRING, F.array(coords))


def doubled_area(ring: Column) -> Column:
    """Twice the signed area of a closed ring; below zero is clockwise. The ring starts at the origin of the sum."""
    n = F.size(ring)
    term = lambda i: (ring[i]["x"] - ring[0]["x"]) * (ring[i + 1]["y"] - ring[0]["y"]) - (ring[i + 1]["x"] - ring[0]["x"]) * (ring[i]["y"] - ring[0]["y"])
    return F.when(n > 2, F.aggregate(F.sequence(F.lit(0), n - 2), F.lit(0.0), lambda a, i: a + term(i))).otherwise(0.0)


def is_clockwise(ring: Column) -> Column:
    return doubled_area(ring) < 0


def closed(ring: Column) -> Column:
    ends = (F.element_at(ring, 1)["x"] == F.element_at(ring, -1)["x"]) & (F.element_at(ring, 1)["y"] == F.element_at(ring, -1)["y"])
    return F.when((F.size(ring) > 1) & ~ends, F.concat(ring, F.slice(ring, 1, 1))).otherwise(ring)


def oriented(ring: Column, clockwise: Column) -> Column:
    return F.when(is_clockwise(ring) == clockwise, ring).otherwise(F.reverse(ring))


def polygon(rings: Column, normalize: bool = True) -> Column:
    """First ring the shell, clockwise; the others holes, counter-clockwise; rings closed."""
    if normalize:
        rings = F.transform(F.transform(rings, closed), lambda r, i: oriented(r, i == 0))
    return _geometry(Kind.POLYGON, rings)


def multipoint(coords: Column, one_part: bool = False) -> Column:
    return _geometry(Kind.MULTIPOINT, F.array(coords) if one_part else F.transform(coords, lambda c: F.array(c)))


def multilinestring(lines: Column) -> Column:
    return _geometry(Kind.MULTILINESTRING, lines)


def multipolygon(polygons: Column) -> Column:
    """Polygons as arrays of rings, flattened in order."""
    rings = F.transform(polygons, lambda p: F.transform(F.transform(p, closed), lambda r, i: oriented(r, i == 0)))
    return _geometry(Kind.MULTIPOLYGON, F.flatten(rings))


# rings back to polygons


def shell(geometry: Column) -> Column:
    return F.get(geometry["parts"], F.lit(0))


def holes(geometry: Column) -> Column:
    return F.slice(geometry["parts"], 2, F.greatest(F.size(geometry["parts"]) - 1, F.lit(0)))


def split_polygons(parts: Column) -> Column:
    """Polygons of a stream of rings: a clockwise ring, or the first one, opens a polygon; the others join the open one."""
    opens = F.transform(parts, lambda r, i: (i == 0) | is_clockwise(r))
    starts = F.filter(F.sequence(F.lit(0), F.size(parts) - 1), lambda i: opens[i])
    cut = F.transform(starts, lambda s, k: F.slice(parts, s + 1, F.coalesce(F.get(starts, k + 1), F.size(parts)) - s))
    return F.when(F.size(parts) > 0, cut).otherwise(F.array().cast("array<array<array<struct<x:double,y:double>>>>"))


# leaves


def shred(df: DataFrame, geometry: str = "geometry", id: str = "id", nullable: bool = False) -> DataFrame:
    """Leaf rows as a column store sees them: kind, part and coordinate numbers, repetition and definition level, x, y.

    The repetition level is that of the list that goes on (0: a new record). The definition level
    counts what is there on the way to a coordinate: 0 without parts, 1 for a part without
    coordinates, 2 for a coordinate; one more each where the geometry itself may be null.
    """
    d = df.select(id, F.col(f"{geometry}.type").alias("kind"), F.posexplode_outer(f"{geometry}.parts").alias("part_no", "part"))
    d = d.select(id, "kind", "part_no", F.posexplode_outer("part").alias("coord_no", "c"))
    rep = F.when(F.col("coord_no") > 0, 2).when(F.col("part_no") > 0, 1).otherwise(0)
    define = F.when(F.col("coord_no").isNotNull(), 2).when(F.col("part_no").isNotNull(), 1).otherwise(0)
    define = define + F.when(F.col("kind").isNotNull(), 1).otherwise(0) if nullable else define
    return d.select(id, "kind", "part_no", "coord_no", rep.alias("rep_level"), define.alias("def_level"), F.col("c.x").alias("x"), F.col("c.y").alias("y"))


def assemble(leaves: DataFrame, id: str = "id", axes: tuple[str, ...] = ("x", "y")) -> DataFrame:
    """Geometries from leaf rows (id, kind, part_no, coord_no and the axes), in any order."""
    none = f"array<array<struct<{','.join(f'{a}:double' for a in axes)}>>>"
    c = F.array_sort(F.collect_list(F.struct("coord_no", F.struct(*axes).alias("c"))))
    parts = leaves.where("part_no is not null").groupBy(id, "kind", "part_no").agg(F.transform(c, lambda v: v["c"]).alias("part"))
    p = F.array_sort(F.collect_list(F.struct("part_no", "part")))
    whole = parts.groupBy(id, "kind").agg(F.transform(p, lambda v: v["part"]).alias("parts"))
    bare = leaves.where("part_no is null").select(id, "kind", F.array().cast(none).alias("parts"))
    g = F.when(F.col("kind").isNotNull(), F.struct(F.col("kind").cast("int").alias("type"), "parts"))
    return whole.unionByName(bare).select(id, g.alias("geometry"))


def flatten_collections(edges: DataFrame) -> DataFrame:
    """(root_id, pos, geometry) of an edge table (root_id, node_id, parent_id, ord, geometry or null for a nested collection), depth first.

    Levels are joined one by one until none is left; a node's path of ordinals sorts it.
    """
    edges = edges.withColumn("ord", F.lpad(F.col("ord").cast("string"), 10, "0"))
    level = edges.where("parent_id is null").withColumn("path", F.array("ord"))
    found = level.where("geometry is not null")
    while True:
        inner = level.where("geometry is null").select("root_id", F.col("node_id").alias("parent_id"), "path")
        level = edges.join(inner, ["root_id", "parent_id"]).select(*edges.columns, F.concat("path", F.array("ord")).alias("path"))
        found = found.unionByName(level.where("geometry is not null"))
        if not level.where("geometry is null").head(1):
            break
    rows = F.array_sort(F.collect_list(F.struct("path", "geometry")))
    return found.groupBy("root_id").agg(rows.alias("r")).select("root_id", F.posexplode("r").alias("pos", "r")).select("root_id", "pos", "r.geometry")
