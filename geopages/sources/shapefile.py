"""Shapefiles as one rival format: main, index and attribute files of up to a million geometries of one shape type.

Spark has no sink for binary files, so a set of files is a row (part, shape_type, shp, shx,
dbf), each file on its own compressed where asked; ``export`` puts such rows into a folder and
``read_folder`` reads any folder of shapefiles. The attribute file holds a feature's id and the
kind that the shape type doesn't tell (a line from several, a polygon from several).
"""

from __future__ import annotations

import gzip
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions import geom
from ..functions.build import Kind, geometry_type
from .flat import Bytes, Flat, flat, nested, spread

SHAPE = {Kind.POINT: 1, Kind.LINESTRING: 3, Kind.POLYGON: 5, Kind.MULTIPOINT: 8, Kind.MULTILINESTRING: 3, Kind.MULTIPOLYGON: 5}
#: Geometries, and bytes of the main file, at which a set of files ends.
MOST_GEOMETRIES, MOST_BYTES = 1_000_000, 512 << 20
FILES = "part long, shape_type int, shp binary, shx binary, dbf binary"
_HEAD = 100
_ID, _KIND = 20, 2
_ROWS = T.StructType([T.StructField("id", T.LongType()), T.StructField("geometry", geometry_type())])


def shape_types(kind: np.ndarray) -> np.ndarray:
    """Shape type of each kind; 0 for empty and null."""
    table = np.zeros(8, np.int64)
    for k, v in SHAPE.items():
        table[int(k)] = v
    return table[np.maximum(kind, 0)]


def records(f: Flat, first_number: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Records of geometries end to end, their sizes, and the box around all (x_min, y_min, x_max, y_max)."""
    shape = shape_types(f.kind)
    first, m = f.first_coord[f.first_part[:-1]], np.diff(f.first_coord[f.first_part])
    shape = np.where(m == 0, 0, shape)
    lines = np.isin(shape, (3, 5))
    content = np.select([shape == 1, shape == 8, lines], [20, 40 + 16 * m, 44 + 4 * f.n_parts + 16 * m], 4)
    size = content + 8
    start = np.cumsum(size) - size
    out = Bytes(int(size.sum()))
    out.put(start, first_number + np.arange(len(shape)), ">i4")
    out.put(start + 4, content // 2, ">i4")
    body = start + 8
    out.put(body, shape, "<i4")
    xy_at = body + np.select([shape == 1, shape == 8, lines], [4, 40, 44 + 4 * f.n_parts], 4)
    real = np.flatnonzero(shape > 0)
    at = spread(xy_at[real], m[real], 16)
    xy = f.xy[spread(first[real], m[real])]
    out.put(at, xy[:, 0], "<f8")
    out.put(at + 8, xy[:, 1], "<f8")
    box = np.zeros(4)
    if len(real):
        cut = np.cumsum(m[real]) - m[real]
        bounds = [np.fmin.reduceat(xy[:, 0], cut), np.fmin.reduceat(xy[:, 1], cut), np.fmax.reduceat(xy[:, 0], cut), np.fmax.reduceat(xy[:, 1], cut)]
        boxed = shape[real] != 1
        for i, v in enumerate(bounds):
            out.put(body[real[boxed]] + 4 + 8 * i, v[boxed], "<f8")
        box = np.array([bounds[0].min(), bounds[1].min(), bounds[2].max(), bounds[3].max()])
    many = np.flatnonzero(shape == 8)
    out.put(body[many] + 36, m[many], "<i4")
    rows = np.flatnonzero(lines)
    out.put(body[rows] + 36, f.n_parts[rows], "<i4")
    out.put(body[rows] + 40, m[rows], "<i4")
    parts = spread(f.first_part[:-1][rows], f.n_parts[rows])
    out.put(spread(body[rows] + 44, f.n_parts[rows], 4), f.first_coord[:-1][parts] - np.repeat(first[rows], f.n_parts[rows]), "<i4")
    return out.data, size, box


def _header(length: int, shape: int, box: np.ndarray) -> bytes:
    out = Bytes(_HEAD)
    out.put([0, 24], [9994, length // 2], ">i4")
    out.put([28, 32], [1000, shape], "<i4")
    out.put(36 + 8 * np.arange(4), box, "<f8")
    return out.data.tobytes()


def _dbf(ids: np.ndarray, kind: np.ndarray) -> bytes:
    """Attribute file with the numeric fields ID and KIND."""
    fields = (("ID", _ID), ("KIND", _KIND))
    head = bytearray(32)
    head[0:4] = bytes([3, 100, 1, 1])
    head[4:8] = len(ids).to_bytes(4, "little")
    head[8:10] = (32 + 32 * len(fields) + 1).to_bytes(2, "little")
    head[10:12] = (1 + sum(n for _, n in fields)).to_bytes(2, "little")
    for name, n in fields:
        head += name.encode().ljust(11, b"\0") + b"N" + bytes(4) + bytes([n, 0]) + bytes(14)
    text = np.char.add(b" ", np.char.add(np.char.rjust(ids.astype(f"S{_ID}"), _ID), np.char.rjust(kind.astype(f"S{_KIND}"), _KIND))) if len(ids) else np.zeros(0, "S1")
    return bytes(head) + b"\r" + text.tobytes() + b"\x1a"


class _Set:
    """Files of one shape type that are being written."""

    def __init__(self, shape: int):
        self.shape, self.data, self.sizes, self.ids, self.kinds, self.n, self.bytes = shape, [], [], [], [], 0, 0
        self.box = np.array([np.inf, np.inf, -np.inf, -np.inf])

    def add(self, f: Flat, ids: np.ndarray) -> None:
        data, size, box = records(f, self.n + 1)
        self.data.append(data)
        self.sizes.append(size)
        self.ids.append(ids)
        self.kinds.append(f.kind)
        self.n += len(ids)
        self.bytes += len(data)
        if self.shape and len(f.xy):
            self.box = np.r_[np.minimum(self.box[:2], box[:2]), np.maximum(self.box[2:], box[2:])]

    def files(self) -> tuple[bytes, bytes, bytes]:
        size = np.concatenate(self.sizes)
        box = np.where(np.isfinite(self.box), self.box, 0)
        index = Bytes(8 * len(size))
        at = 8 * np.arange(len(size))
        index.put(at, (_HEAD + np.cumsum(size) - size) // 2, ">i4")
        index.put(at + 4, (size - 8) // 2, ">i4")
        shp = _header(_HEAD + self.bytes, self.shape, box) + b"".join(x.tobytes() for x in self.data)
        return shp, _header(_HEAD + len(index.data), self.shape, box) + index.data.tobytes(), _dbf(np.concatenate(self.ids), np.concatenate(self.kinds))


def shape_files(df: DataFrame, most: int = MOST_GEOMETRIES, compressed: bool = False) -> DataFrame:
    """(part, shape_type, shp, shx, dbf) of each run of up to ``most`` geometries of a partition and shape type; ``compressed``: each file by gzip."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, made = TaskContext.get().partitionId(), 0
        open_sets: dict[int, _Set] = {}

        def out(s: _Set) -> pa.RecordBatch:
            nonlocal made
            made += 1
            files = s.files()
            if compressed:
                files = tuple(gzip.compress(x, 6, mtime=0) for x in files)
            return pa.record_batch([pa.array([part * 1_000_000 + made - 1]), pa.array([s.shape], pa.int32()), *[pa.array([x], pa.binary()) for x in files]], names=["part", "shape_type", "shp", "shx", "dbf"])

        for b in batches:
            f, ids = flat(b.column(1)), b.column(0).to_numpy()
            shape = shape_types(f.kind)
            for k in np.unique(shape).tolist():
                rows = np.flatnonzero(shape == k)
                while len(rows):
                    s = open_sets.setdefault(k, _Set(k))
                    now, rows = rows[: most - s.n], rows[most - s.n :]
                    s.add(f.take(now), ids[now])
                    if s.n >= most or s.bytes >= MOST_BYTES:
                        yield out(open_sets.pop(k))
        for s in open_sets.values():
            yield out(s)

    return df.select(F.col("id").cast("long").alias("id"), "geometry").mapInArrow(run, FILES)


def save_shapefiles(df: DataFrame, path: str, compressed: bool = False, most: int = MOST_GEOMETRIES) -> None:
    shape_files(df, most, compressed).write.mode("overwrite").option("compression", "none").parquet(path)


def parse(shp: bytes, shx: bytes | None, dbf: bytes | None) -> tuple[np.ndarray, Flat]:
    """Ids and geometries of a set of files. Without an attribute file ids are record numbers and kinds the more general ones of a shape type; without an index records are walked."""
    data = Bytes(np.frombuffer(shp, np.uint8))
    if shx is not None:
        index = np.frombuffer(shx, ">i4", offset=_HEAD).reshape(-1, 2).astype(np.int64)
        start = 2 * index[:, 0]
    else:
        places, at = [], _HEAD
        while at < len(shp):
            places.append(at)
            at += 8 + 2 * int.from_bytes(shp[at + 4 : at + 8], "big")
        start = np.array(places, np.int64)
    body = start + 8
    shape = data.get(body, "<i4").astype(np.int64)
    if not np.isin(shape, (0, 1, 3, 5, 8)).all():
        raise ValueError(f"shape types {sorted(set(shape.tolist()) - {0, 1, 3, 5, 8})} are not read")
    lines, many = np.isin(shape, (3, 5)), shape == 8
    m, n = np.where(shape == 1, 1, 0), np.where(shape == 1, 1, 0)
    m[many] = data.get(body[many] + 36, "<i4")
    n[many] = m[many]
    n[lines] = data.get(body[lines] + 36, "<i4")
    m[lines] = data.get(body[lines] + 40, "<i4")
    xy_at = body + np.select([shape == 1, many, lines], [4, 40, 44 + 4 * n], 4)
    at = spread(xy_at, m, 16)
    xy = np.stack([data.get(at, "<f8"), data.get(at + 8, "<f8")], 1)
    # a part ends where the next one of its record starts, the last one where the record's points end
    n_coords = np.ones(int(n.sum()), np.int64)
    part_lines = np.repeat(lines, n)
    if part_lines.any():
        starts = data.get(spread(body[lines] + 44, n[lines], 4), "<i4").astype(np.int64)
        ends = np.r_[starts[1:], 0]
        ends[np.cumsum(n[lines])[n[lines] > 0] - 1] = m[lines][n[lines] > 0]
        n_coords[part_lines] = ends - starts
    if dbf is not None:
        rows, skip, width = (int.from_bytes(dbf[a:b], "little") for a, b in ((4, 8), (8, 10), (10, 12)))
        at, fields, i = 1, {}, 32
        while dbf[i] != 0x0D:
            fields[dbf[i : i + 11].rstrip(b"\0").decode()] = (at, dbf[i + 16])
            at += dbf[i + 16]
            i += 32
        table = np.frombuffer(dbf, np.uint8, rows * width, skip).reshape(rows, width)
        column = lambda name: np.ascontiguousarray(table[:, fields[name][0] : sum(fields[name])]).view(f"S{fields[name][1]}").ravel().astype(np.int64)
        if "ID" in fields and "KIND" in fields:
            return column("ID"), Flat(column("KIND"), n, n_coords, xy)
    general = np.array([0, 1, 0, 5, 0, 6, 0, 0, 4])[shape]
    return np.arange(1, len(shape) + 1), Flat(general, n, n_coords, xy)


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = to_arrow_schema(_ROWS)
    plain = lambda x: gzip.decompress(x) if x is not None and x[:2] == b"\x1f\x8b" else x
    for b in batches:
        for shp, shx, dbf in zip(*(c.to_pylist() for c in b.columns), strict=True):
            ids, f = parse(plain(shp), plain(shx), plain(dbf))
            for lo in range(0, len(ids), 100_000):
                rows = np.arange(lo, min(len(ids), lo + 100_000))
                yield pa.record_batch([pa.array(ids[rows]), nested(f.take(rows), schema.field("geometry").type)], schema=schema)


def read_shapefiles(spark: SparkSession, path: str) -> DataFrame:
    """(id, geometry) of what ``save_shapefiles`` wrote, compressed or not."""
    return spark.read.parquet(path).select("shp", "shx", "dbf").mapInArrow(_read, _ROWS)


def export(spark: SparkSession, path: str, folder: str) -> int:
    """Sets of ``save_shapefiles`` as files of a folder, one set at a time through the driver; returns their number."""
    jvm, n = spark._jvm, 0
    fs = jvm.org.apache.hadoop.fs.Path(folder).getFileSystem(spark._jsc.hadoopConfiguration())
    for r in spark.read.parquet(path).toLocalIterator():
        for ending in ("shp", "shx", "dbf"):
            out = fs.create(jvm.org.apache.hadoop.fs.Path(f"{folder}/{r.part:012d}.{ending}{'.gz' if r[ending][:2] == bytearray(b'\x1f\x8b') else ''}"), True)
            out.write(r[ending])
            out.close()
        n += 1
    return n


def read_folder(spark: SparkSession, folder: str) -> DataFrame:
    """(id, geometry) of a folder of shapefiles, ``.gz`` or plain; a set's index and attribute files may be missing."""
    f = spark.read.format("binaryFile").load(folder).select("content", F.regexp_extract("path", r"([^/]+?)\.(shp|shx|dbf)(?:\.gz)?$", 1).alias("stem"), F.regexp_extract("path", r"\.(shp|shx|dbf)(?:\.gz)?$", 1).alias("ending"))
    part = lambda e: f.where(F.col("ending") == e).select("stem", F.col("content").alias(e))
    return part("shp").join(part("shx"), "stem", "left").join(part("dbf"), "stem", "left").select("shp", "shx", "dbf").mapInArrow(_read, _ROWS)


def shapefile_size(g: Column) -> Column:
    """Bytes of a record, its header and its index entry."""
    n, m = geom.n_parts(g), geom.n_coords(g)
    body = F.when(g["type"] == 1, F.lit(20)).when(g["type"] == 4, 40 + 16 * m).when(g["type"].isin(2, 3, 5, 6), 44 + 4 * n + 16 * m).otherwise(F.lit(4))
    return body + 16
