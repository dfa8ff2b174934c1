"""Well-known binary beside four box columns, as one rival format; encoding and decoding are array work over batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions import geom
from ..functions.build import Kind, collection_type, geometry_type, split_polygons
from ..operators.index import Rect, meets
from .flat import Bytes, Flat, flat, nested, raw, spread

COLLECTION = 7
_GEOMETRY = to_arrow_schema(T.StructType([T.StructField("g", geometry_type())])).field(0).type
_MEMBERS = to_arrow_schema(T.StructType([T.StructField("g", collection_type())])).field(0).type


def encode(f: Flat) -> pa.Array:
    """Little-endian binary of each geometry; a kind 0 is an empty collection, a null stays null."""
    kind = f.kind
    part_kind = kind[f.part_geometry]
    opens = f.opens() & (part_kind == Kind.MULTIPOLYGON)
    part_head = np.select([part_kind == 3, part_kind == 4, part_kind == 5, part_kind == 6], [4, 5, 9, 4 + 9 * opens], 0)
    head = np.where(kind < 0, 0, np.where(kind == Kind.POINT, 5, 9))
    part_size = part_head + 16 * f.n_coords
    sums = np.r_[0, np.cumsum(part_size)]
    size = head + sums[f.first_part[1:]] - sums[f.first_part[:-1]]
    start = np.cumsum(size) - size
    part_start = start[f.part_geometry] + head[f.part_geometry] + sums[:-1] - sums[f.first_part[:-1]][f.part_geometry]
    out = Bytes(int(size.sum()))
    real = kind >= 0
    out.put(start[real], 1, "u1")
    out.put(start[real] + 1, np.where(kind[real] == 0, COLLECTION, kind[real]), "<u4")
    polygons = np.bincount(f.part_geometry[opens], minlength=len(kind))
    first = f.first_part[:-1]
    lone = np.zeros(len(kind), np.int64)
    lone[f.n_parts > 0] = f.n_coords[first[f.n_parts > 0]]
    counts = np.select([kind == 2, kind == 6, kind == 0], [lone, polygons, 0], f.n_parts)
    counted = real & (kind != Kind.POINT)
    out.put(start[counted] + 5, counts[counted], "<u4")
    rings = np.zeros(0, np.int64)
    if opens.any():
        at = np.flatnonzero(opens)
        ends = np.minimum(np.r_[at[1:], len(opens)], f.first_part[1:][f.part_geometry[at]])
        rings = ends - at
    for k, code in ((4, 1), (5, 2)):
        at = part_start[part_kind == k]
        out.put(at, 1, "u1")
        out.put(at + 1, code, "<u4")
    out.put(part_start[opens], 1, "u1")
    out.put(part_start[opens] + 1, 3, "<u4")
    out.put(part_start[opens] + 5, rings, "<u4")
    counted = np.isin(part_kind, (3, 5, 6))
    out.put((part_start + part_head - 4)[counted], f.n_coords[counted], "<u4")
    at = spread(part_start + part_head, f.n_coords, 16)
    out.put(at, f.xy[:, 0], "<f8")
    out.put(at + 8, f.xy[:, 1], "<f8")
    return out.cut(size, kind < 0)


def _walk(data: memoryview, at: int, leaves: list) -> int:
    """Add (kind, parts as (place, coordinates, byte order)) of the geometry at ``at``, of a collection those of its members; returns where it ends."""
    order = "little" if data[at] == 1 else "big"
    number = lambda i: int.from_bytes(data[i : i + 4], order)
    kind = number(at + 1)
    at += 5
    if kind == Kind.POINT:
        leaves.append((1, [(at, 1, order)]))
        return at + 16
    n = number(at)
    at += 4
    if kind == Kind.LINESTRING:
        leaves.append((2, [(at, n, order)]))
        return at + 16 * n
    parts: list = []
    if kind == Kind.POLYGON:
        for _ in range(n):
            m = number(at)
            parts.append((at + 4, m, order))
            at += 4 + 16 * m
    elif kind in (Kind.MULTIPOINT, Kind.MULTILINESTRING, Kind.MULTIPOLYGON):
        own: list = []
        for _ in range(n):
            at = _walk(data, at, own)
        parts = [p for _, ps in own for p in ps]
    elif kind == COLLECTION:
        for _ in range(n):
            at = _walk(data, at, leaves)
        return at
    else:
        raise ValueError(f"well-known binary of kind {kind}")
    leaves.append((kind, parts))
    return at


def _gathered(data: np.ndarray, kinds: list[int], parts: list) -> Flat:
    place, count = (np.array([p[i] for ps in parts for p in ps], np.int64) for i in (0, 1))
    big = np.array([p[2] == "big" for ps in parts for p in ps], bool)
    at, source = spread(place, count, 16), Bytes(data)
    xy = np.stack([source.get(at, "<f8"), source.get(at + 8, "<f8")], 1)
    turned = np.repeat(big, count)
    xy[turned] = xy[turned].byteswap()
    return Flat(np.array(kinds, np.int64), np.array([len(p) for p in parts], np.int64), count, xy)


def decode(col: pa.Array) -> pa.Array:
    """Geometries of a binary column. A collection with members raises ValueError: it is an array of geometries (``parse_wkb_collection``)."""
    data, at = raw(col)
    missing = col.is_null().to_numpy(zero_copy_only=False)
    size = np.diff(at)
    starts = at[:-1]
    if len(col) and not missing.any() and (size == 21).all() and (data[starts] == 1).all() and (Bytes(data).get(starts + 1, "<u4") == 1).all():
        one = np.ones(len(col), np.int64)  # points alone
        return nested(Flat(one, one, one, np.stack([Bytes(data).get(starts + 5 + 8 * i, "<f8") for i in (0, 1)], 1)), _GEOMETRY)
    view = memoryview(data)
    kinds, parts = [], []
    for i in range(len(col)):
        if missing[i]:
            kinds.append(-1)
            parts.append([])
            continue
        leaves: list = []
        _walk(view, int(at[i]), leaves)
        collection = int.from_bytes(view[at[i] + 1 : at[i] + 5], "little" if view[at[i]] == 1 else "big") == COLLECTION
        if collection and leaves:
            raise ValueError("a collection with members is no single geometry: read it with parse_wkb_collection")
        kinds.append(0 if collection else leaves[0][0])
        parts.append([] if collection else leaves[0][1])
    return nested(_gathered(data, kinds, parts), _GEOMETRY)


@F.arrow_udf(geometry_type())
def parse_wkb(v: pa.Array) -> pa.Array:
    return decode(v)


@F.arrow_udf(collection_type())
def parse_wkb_collection(v: pa.Array) -> pa.Array:
    """Members of collections, depth first, whatever their nesting; any other geometry is the only member of its own."""
    data, at = raw(v)
    view, kinds, parts, ends = memoryview(data), [], [], [0]
    for i, missing in enumerate(v.is_null().to_pylist()):
        if not missing:
            leaves: list = []
            _walk(view, int(at[i]), leaves)
            kinds += [k for k, _ in leaves]
            parts += [p for _, p in leaves]
        ends.append(len(kinds))
    members = nested(_gathered(data, kinds, parts), _GEOMETRY)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), members, type=_MEMBERS, mask=v.is_null() if v.null_count else None)


@F.arrow_udf(T.BinaryType())
def as_wkb(v: pa.Array) -> pa.Array:
    return encode(flat(v))


@F.arrow_udf(T.BinaryType())
def as_wkb_collection(v: pa.Array) -> pa.Array:
    """Arrays of geometries as collections."""
    members = encode(flat(v.flatten()))
    counts = [len(x) if x.is_valid else None for x in v]
    ends = np.r_[0, np.cumsum([c or 0 for c in counts])]
    head = lambda n: b"\1" + COLLECTION.to_bytes(4, "little") + n.to_bytes(4, "little")
    return pa.array([None if c is None else head(c) + b"".join(m.as_py() for m in members[ends[i] : ends[i] + c]) for i, c in enumerate(counts)], pa.binary())


def _to_wkb(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield pa.record_batch([b.column(0), encode(flat(b.column(1))), *b.columns[2:]], names=["id", "wkb", "x_min", "y_min", "x_max", "y_max"])


def with_wkb(df: DataFrame) -> DataFrame:
    """(id, wkb, x_min, y_min, x_max, y_max)."""
    b = geom.box(F.col("geometry"))
    d = df.select(F.col("id").cast("long").alias("id"), "geometry", b.alias("b")).select("id", "geometry", "b.x_min", "b.y_min", "b.x_max", "b.y_max")
    return d.mapInArrow(_to_wkb, "id long, wkb binary, x_min double, y_min double, x_max double, y_max double")


def save_wkb(df: DataFrame, path: str, compression: str = "none") -> None:
    with_wkb(df).write.mode("overwrite").option("compression", compression).parquet(path)


def read_wkb(spark: SparkSession, path: str, rect: Rect | None = None) -> DataFrame:
    t = spark.read.parquet(path)
    return t.where(meets(rect)) if rect is not None else t


def wkb_size(g: Column) -> Column:
    """Bytes of the binary form, without making it."""
    parts = g["parts"]
    n = F.size(parts)
    each = lambda base, per: F.aggregate(parts, F.lit(base), lambda a, p: a + per + 16 * F.size(p))
    polygons = F.size(split_polygons(parts))
    return (
        F.when(g["type"] == 1, F.lit(21)).when(g["type"] == 2, 9 + 16 * F.size(F.get(parts, F.lit(0)))).when(g["type"] == 3, each(9, 4))
        .when(g["type"] == 4, 9 + 21 * n).when(g["type"] == 5, each(9, 9)).when(g["type"] == 6, each(9, 4) + 9 * polygons).otherwise(F.lit(9))
    )
