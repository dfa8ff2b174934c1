"""GeoJSON as one rival format: a feature a line, in files as they come or all in one file and one compressed stream."""

from __future__ import annotations

import json

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions import build
from ..functions.build import Kind, collection_type, split_polygons

_EMPTY = '{"type":"GeometryCollection","geometries":[]}'
_MEMBERS = to_arrow_schema(T.StructType([T.StructField("g", collection_type())])).field(0).type


def geojson(g: Column) -> Column:
    """Text of the geometry member; an empty geometry is an empty collection, null stays null."""
    xy = lambda c: F.array(c["x"], c["y"])
    ring = lambda p: F.transform(p, xy)
    text = lambda kind, coords: F.concat(F.lit(f'{{"type":"{kind}","coordinates":'), F.to_json(coords), F.lit("}"))
    parts = g["parts"]
    return (
        F.when(g["type"] == 0, F.lit(_EMPTY))
        .when(g["type"] == 1, text("Point", xy(F.get(F.get(parts, F.lit(0)), F.lit(0))))).when(g["type"] == 2, text("LineString", ring(F.get(parts, F.lit(0)))))
        .when(g["type"] == 3, text("Polygon", F.transform(parts, ring))).when(g["type"] == 4, text("MultiPoint", F.transform(F.flatten(parts), xy)))
        .when(g["type"] == 5, text("MultiLineString", F.transform(parts, ring))).when(g["type"] == 6, text("MultiPolygon", F.transform(split_polygons(parts), lambda p: F.transform(p, ring))))
    )


def from_geojson(kind: Column, coordinates: Column) -> Column:
    """Geometry of a type name and its coordinates as JSON text; null for other types. Built-in functions alone."""
    point = lambda c: F.struct(F.get(c, F.lit(0)).alias("x"), F.get(c, F.lit(1)).alias("y"))
    ring = lambda r: F.transform(r, point)
    read = lambda depth: F.from_json(coordinates, "array<" * depth + "double" + ">" * depth)
    whole = lambda k, parts: F.struct(F.lit(int(k)).alias("type"), parts.alias("parts"))
    return (
        F.when(kind == "Point", whole(Kind.POINT, F.array(F.array(point(read(1)))))).when(kind == "LineString", whole(Kind.LINESTRING, F.array(ring(read(2)))))
        .when(kind == "Polygon", whole(Kind.POLYGON, F.transform(read(3), ring))).when(kind == "MultiPoint", whole(Kind.MULTIPOINT, F.transform(read(2), lambda c: F.array(point(c)))))
        .when(kind == "MultiLineString", whole(Kind.MULTILINESTRING, F.transform(read(3), ring))).when(kind == "MultiPolygon", whole(Kind.MULTIPOLYGON, F.transform(F.flatten(read(4)), ring)))
        .when(kind == "GeometryCollection", build.empty())
    )


def save_geojson(df: DataFrame, path: str, compression: str = "none", one_file: bool = False) -> None:
    """``one_file``: the whole dataset as one file (and one compressed stream), written by one task as the published comparison has it; not for large data."""
    line = F.concat(F.lit('{"type":"Feature","id":'), F.col("id").cast("string"), F.lit(',"geometry":'), F.coalesce(geojson(F.col("geometry")), F.lit("null")), F.lit("}"))
    d = df.select(line.alias("value"))
    (d.coalesce(1) if one_file else d).write.mode("overwrite").option("compression", compression).text(path)


def read_geojson(spark: SparkSession, path: str) -> DataFrame:
    """(id, geometry). A collection with members is no single geometry: use ``parse_geojson_collection``; here it raises."""
    t = spark.read.text(path)
    get = lambda p: F.get_json_object("value", p)
    d = t.select(get("$.id").cast("long").alias("id"), get("$.geometry.type").alias("kind"), get("$.geometry.coordinates").alias("coordinates"), get("$.geometry.geometries").alias("members"))
    kind = F.when(F.coalesce("members", F.lit("[]")) == "[]", F.col("kind")).otherwise(F.raise_error(F.lit("a collection with members is no single geometry")).cast("string"))
    return d.select("id", from_geojson(kind, F.col("coordinates")).alias("geometry"))


def _leaves(g: dict | None, out: list) -> list:
    if g is None:
        return out
    kind, c = g["type"], g.get("coordinates")
    vertex = lambda p: {"x": float(p[0]), "y": float(p[1])}
    ring = lambda r: [vertex(p) for p in r]
    if kind == "GeometryCollection":
        for m in g["geometries"]:
            _leaves(m, out)
    else:
        parts = {
            "Point": lambda: [[vertex(c)]], "LineString": lambda: [ring(c)], "Polygon": lambda: [ring(r) for r in c], "MultiPoint": lambda: [[vertex(p)] for p in c],
            "MultiLineString": lambda: [ring(r) for r in c], "MultiPolygon": lambda: [ring(r) for p in c for r in p],
        }[kind]()
        out.append({"type": int(Kind[kind.upper()]), "parts": parts})
    return out


@F.arrow_udf(collection_type())
def parse_geojson_collection(v: pa.Array) -> pa.Array:
    """Members of a geometry text, depth first, whatever their nesting; any other geometry is the only member of its own."""
    return pa.array([None if t is None else _leaves(json.loads(t), []) for t in v.to_pylist()], _MEMBERS)
