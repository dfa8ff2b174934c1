"""Geometry functions for SQL text: temporary SQL functions, which Catalyst expands in place."""

from __future__ import annotations

from pyspark.sql import SparkSession

_G = "STRUCT<type: INT, parts: ARRAY<ARRAY<STRUCT<x: DOUBLE, y: DOUBLE>>>>"
_BOX = "STRUCT<x_min: DOUBLE, y_min: DOUBLE, x_max: DOUBLE, y_max: DOUBLE>"
_AXIS = "filter(transform(flatten(g.parts), c -> c.{a}), v -> NOT isnan(v))"
_NAMES = ("EMPTY", "POINT", "LINESTRING", "POLYGON", "MULTIPOINT", "MULTILINESTRING", "MULTIPOLYGON")
_AREA = "aggregate(sequence(0, size(r) - 2), 0D, (a, i) -> a + (r[i].x - r[0].x) * (r[i + 1].y - r[0].y) - (r[i + 1].x - r[0].x) * (r[i].y - r[0].y))"
#: Name: (parameters, type, expression).
FUNCTIONS = {
    "geo_kind": (f"g {_G}", "STRING", f"element_at(array({', '.join(map(repr, _NAMES))}), g.type + 1)"),
    "geo_parts": (f"g {_G}", "INT", "size(g.parts)"),
    "geo_vertices": (f"g {_G}", "INT", "aggregate(g.parts, 0, (a, p) -> a + size(p))"),
    "geo_box": (f"g {_G}", _BOX, f"named_struct('x_min', array_min({_AXIS.format(a='x')}), 'y_min', array_min({_AXIS.format(a='y')}), 'x_max', array_max({_AXIS.format(a='x')}), 'y_max', array_max({_AXIS.format(a='y')}))"),
    "geo_meets": (f"g {_G}, x0 DOUBLE, y0 DOUBLE, x1 DOUBLE, y1 DOUBLE", "BOOLEAN", f"array_max({_AXIS.format(a='x')}) >= x0 AND array_min({_AXIS.format(a='x')}) <= x1 AND array_max({_AXIS.format(a='y')}) >= y0 AND array_min({_AXIS.format(a='y')}) <= y1"),
    "geo_area": (f"g {_G}", "DOUBLE", f"abs(aggregate(transform(filter(g.parts, r -> size(r) > 2), r -> {_AREA}), 0D, (a, v) -> a + v)) / 2"),
    "geo_point": ("x DOUBLE, y DOUBLE", _G, "named_struct('type', 1, 'parts', array(array(named_struct('x', x, 'y', y))))"),
}
#: Table functions: parameters, columns, query. ``FROM t, LATERAL geo_leaves(t.geometry)`` gives a row a vertex.
TABLES = {
    "geo_leaves": (f"g {_G}", "part_no INT, coord_no INT, x DOUBLE, y DOUBLE", "SELECT part_no, coord_no, c.x, c.y FROM (SELECT posexplode(g.parts) AS (part_no, part)) p LATERAL VIEW posexplode(part) v AS coord_no, c"),
}


def register(spark: SparkSession) -> None:
    """Make the functions known to the session's SQL; again is no harm."""
    for name, (parameters, columns, query) in TABLES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS TABLE({columns}) RETURN {query}")
    for name, (parameters, kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {kind} RETURN {body}")
