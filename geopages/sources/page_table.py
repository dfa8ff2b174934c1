"""The page table: a Parquet dataset in which one row is one encoded page.

Page bounds are scalar columns, so a rectangle becomes range predicates that Spark
pushes to the scan, where row groups and column-index ranges are skipped undecoded.
Pages are cut from partitions as they stream by: no page crosses a partition, so the
cut needs no shuffle, and encoding runs in the same stage as the sort.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions import geom
from ..functions.build import geometry_type
from ..functions.curve import WORLD, Extent
from ..operators import codec, sorting
from ..operators.index import Rect, meets, windows_meet

#: Axes by the dimensions of coordinates.
AXES = "xyzm"
PAGE = "page_id long, n_geoms int, n_parts int, n_coords int, type_runs array<struct<cnt:int,type:int>>, ids array<long>, null_mask array<boolean>, geom_nparts array<int>, part_ncoords array<int>"
AXIS = "{a}_min {coord}, {a}_max {coord}, {a}_enc tinyint, {a}_nbits tinyint, {a}_bits long, {a}_bytes binary"
#: Name of the manifest inside a page table; Spark's readers pass over names that start so.
MANIFEST = "_manifest"
#: Files of which a scan takes those that a manifest names one by one; of more, each file's footer decides.
MOST_FILES = 10_000
#: Windows whose rectangles are pushed to the scan one by one; of more, the box around them.
MOST_PUSHED = 32


def page_schema(dims: int = 2, coord: str = "double") -> T.StructType:
    return T._parse_datatype_string(", ".join([PAGE, *[AXIS.format(a=a, coord=coord) for a in AXES[:dims]]]))


def coordinates(geometry: T.DataType) -> tuple[int, str]:
    """Dimensions and number type (double, float) of a geometry type; other types are refused."""
    point = geometry["parts"].dataType.elementType.elementType
    names, kinds = [f.name for f in point], {f.dataType.simpleString() for f in point}
    if names != list(AXES[: len(names)]) or len(names) < 2 or len(kinds) != 1 or not kinds <= {"double", "float"}:
        raise ValueError(f"coordinates must be x, y and at most z, m, all double or all float: {point.simpleString()}")
    return len(names), kinds.pop()


def geometry_of(page: T.StructType) -> T.StructType:
    """Type of the geometries that pages of this schema hold."""
    return geometry_type(sum(f"{a}_bytes" in page.names for a in AXES), page["x_min"].dataType.simpleString())


def _rows(g: pa.StructArray):
    """Kinds (-1 for null), parts of each geometry, coordinates of each part, and the values of each axis."""
    null = g.is_null().to_numpy(zero_copy_only=False)
    kind = g.field("type").fill_null(0).to_numpy(zero_copy_only=False).copy()
    parts = g.field("parts")
    outer = parts.offsets.to_numpy().astype(np.int64)
    n_parts = np.diff(outer)
    n_parts[null] = 0
    inner_list = parts.values
    inner = inner_list.offsets.to_numpy().astype(np.int64)
    ok = np.repeat(~null, np.diff(outer))
    span = slice(outer[0], outer[-1])
    n_coords = np.diff(inner)[span][ok]
    leaf = inner_list.values
    at = np.repeat(inner[:-1][span][ok], n_coords) + np.arange(n_coords.sum()) - np.repeat(np.cumsum(n_coords) - n_coords, n_coords)
    axes = [leaf.field(f.name) for f in leaf.type]
    if leaf.null_count or any(v.null_count for v in axes):
        raise ValueError("a coordinate is null; a page has no place for it")
    kind[null] = -1
    return kind, n_parts, n_coords, *[v.to_numpy(zero_copy_only=False)[at] for v in axes]


def _page(page_id, ids, kind, n_parts, n_coords, *axes, options) -> dict:
    at = np.flatnonzero(np.r_[True, kind[1:] != kind[:-1]]) if len(kind) else np.zeros(0, np.int64)
    row = {
        "page_id": page_id, "n_geoms": len(ids), "n_parts": len(n_coords), "n_coords": len(axes[0]),
        "type_runs": [{"cnt": int(c), "type": int(kind[i])} for i, c in zip(at, np.diff(np.r_[at, len(kind)]), strict=True)],
        "ids": ids, "null_mask": (kind < 0) if (kind < 0).any() else None, "geom_nparts": n_parts, "part_ncoords": n_coords,
    }
    for a, v in zip(AXES, axes, strict=False):
        real = v[~np.isnan(v)]
        p = codec.encode_page(v, **options) if options is not None else codec.Page(codec.RAW, v.dtype.itemsize * 8, v.tobytes(), v.nbytes * 8)
        row |= {f"{a}_min": float(real.min()) if len(real) else None, f"{a}_max": float(real.max()) if len(real) else None, f"{a}_enc": p.tag, f"{a}_nbits": p.n_bits, f"{a}_bits": p.predicted_bits, f"{a}_bytes": p.data}
    return row


def _batch(rows: list[dict], values: list[list[pa.Array]], schema: pa.Schema) -> pa.RecordBatch:
    """Page rows, with one list column for each attribute: its values as they came, end to end."""
    fields = list(schema)
    fixed = len(fields) - len(values[0])
    columns = pa.RecordBatch.from_pylist(rows, pa.schema(fields[:fixed])).columns
    ends = pa.array(np.cumsum([0, *(r["n_geoms"] for r in rows)]), pa.int32())
    for k, f in enumerate(fields[fixed:]):
        columns.append(pa.ListArray.from_arrays(ends, pa.concat_arrays([v[k] for v in values]).cast(f.type.value_type), type=f.type))
    return pa.RecordBatch.from_arrays(columns, schema=schema)


def _cut(schema: pa.Schema, budget: int, options: dict | None) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Pages of whole geometries of up to ``budget`` coordinates; the end of a sort group ends a page. Holds one page and one batch. Columns after the group are attributes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        base = TaskContext.get().partitionId() << 33
        held, made, last, attrs = None, 0, None, []
        for b in batches:
            geometry = b.column(1)
            group = b.column(2).to_numpy()
            kind, n_parts, n_coords, *axes = _rows(geometry)
            if b.column(0).null_count:
                raise ValueError("an id is null; every geometry of a page table needs one")
            ids = b.column(0).to_numpy()
            attrs = [pa.concat_arrays([a, v]) for a, v in zip(attrs, b.columns[3:], strict=True)] if held is not None else b.columns[3:]
            if held is not None:
                ids, group, kind, n_parts, n_coords, *axes = (np.concatenate(z) for z in zip(held, (ids, group, kind, n_parts, n_coords, *axes), strict=True))
            part_at = np.r_[0, np.cumsum(n_parts)]
            coord_at = np.r_[0, np.cumsum(n_coords)]
            ends = coord_at[part_at]  # coordinates up to each geometry
            i, pages = 0, []
            while i < len(ids):
                j = max(i + 1, int(np.searchsorted(ends, ends[i] + budget, "right")) - 1)
                j = min(j, i + budget, i + int(np.searchsorted(group[i:], group[i], "right")))
                if j == len(ids):
                    break
                pages.append((i, j))
                i = j
            cut = lambda i, j: (ids[i:j], kind[i:j], n_parts[i:j], n_coords[part_at[i] : part_at[j]], *[v[ends[i] : ends[j]] for v in axes])  # noqa: E731, B023
            rows, values = [], []
            for s, e in pages:
                rows.append(_page(base + made, *cut(s, e), options=options))
                values.append([a.slice(s, e - s) for a in attrs])
                made += 1
                if len(rows) == 16:
                    yield _batch(rows, values, schema)
                    rows, values = [], []
            if rows:
                yield _batch(rows, values, schema)
            own = cut(i, len(ids))
            attrs = [a.slice(i) for a in attrs]
            held = (own[0], group[i:], *own[1:])
            last = own
        if last is not None and len(last[0]):
            yield _batch([_page(base + made, *last, options=options)], [attrs], schema)

    return run


def pages(df: DataFrame, geometry: str = "geometry", id: str = "id", sort: str = "grouped", curve: str = "hilbert", extent: Extent = WORLD, curve_bits: int = 16, group_size: int = 1_000_000, page_bytes: int = 1 << 20, codec_name: str = "bitdelta", policy: str = "exact", fixed_bits: int | None = None, min_saving: float = 0.0, stream: str = "split", rle: bool = False, attributes: tuple[str, ...] = ()) -> DataFrame:
    """Rows of a page table, before they are written.

    ``sort``: ``grouped`` (bounded groups along the curve, no shuffle), ``total`` (one order along it),
    ``rectangles`` (R*-style rectangles from a sample, whose pages don't overlap for points) or ``none``.

    Coordinates may have up to four axes, of doubles or floats; the page columns tell which. A
    null geometry stays null; a null id or coordinate raises ValueError.
    Each of ``attributes`` becomes a list column ``attr_<name>`` in the order of ``ids``, so a
    scan reads those it asks for and no others.
    """
    d = df.select(F.col(id).cast("long").alias("id"), F.col(geometry).alias("geometry"), *[F.col(a).alias(f"attr_{a}") for a in attributes])
    if sort == "none":
        d = d.withColumn("_group", F.lit(0).cast("long"))
    elif sort == "rectangles":
        at = geom.centre(F.col("geometry"))
        d = d.withColumns({"x": at["x"], "y": at["y"]})
        d = sorting.assign(d, sorting.rectangles(d, max(1, page_bytes // 8)))
        d = d.repartitionByRange("cell", "id").sortWithinPartitions("cell", "id").withColumnRenamed("cell", "_group")
    else:
        d = sorting.with_key(d, curve, "geometry", extent, curve_bits)
        d = sorting.grouped(d, group_size) if sort == "grouped" else sorting.total(d)
    dims, coord = coordinates(d.schema["geometry"].dataType)
    lists = [T.StructField(f"attr_{a}", T.ArrayType(d.schema[f"attr_{a}"].dataType)) for a in attributes]
    kind = T.StructType([*page_schema(dims, coord), *lists])
    options = None if codec_name == "plain" else {"policy": policy, "fixed_bits": fixed_bits, "min_saving": min_saving, "stream": stream, "rle": rle}
    return d.select("id", "geometry", "_group", *[f.name for f in lists]).mapInArrow(_cut(to_arrow_schema(kind), page_bytes // (4 if coord == "float" else 8), options), kind)


def save(df: DataFrame, path: str, compression: str = "zstd", mode: str = "overwrite", index: bool = True, **options) -> None:
    """Write ``df`` (id, geometry) as a page table, or add it to one (``mode="append"``), with its manifest unless ``index`` is off.

    Few pages share a column-index entry, so that pages are skipped one by one. The writer's version is the
    first: Spark's vectorized reader gives wrong bytes for the delta byte arrays of the second one without compression.
    """
    (
        pages(df, **options).write.mode(mode).option("compression", compression).option("parquet.page.row.count.limit", "1")
        .option("parquet.enable.dictionary", "false").option("parquet.enable.dictionary#geom_nparts.list.element", "true").option("parquet.enable.dictionary#part_ncoords.list.element", "true").parquet(path)
    )
    if index:
        write_manifest(df.sparkSession, path)


def append(df: DataFrame, path: str, **options) -> None:
    """Add pages of ``df`` to a page table. Pages of different writes may share a page_id; the file and it together are a page's name."""
    save(df, path, mode="append", **options)


def compact(spark: SparkSession, path: str, to: str, stream: str = "split", **options) -> None:
    """Small pages (of streams, appends or many small partitions) rewritten as full ones along one curve, in a new place: readers keep the old table until they are pointed to ``to``."""
    attributes = tuple(c.removeprefix("attr_") for c in spark.read.parquet(path).columns if c.startswith("attr_"))
    save(scan(spark, path, stream=stream, attributes=attributes), to, **({"sort": "total", "stream": stream, "attributes": attributes} | options))


def manifest(spark: SparkSession, path: str) -> DataFrame:
    """A row for each file: its box and counts, from the scalar columns alone."""
    t = spark.read.parquet(path).select(F.col("_metadata.file_path").alias("file"), "x_min", "x_max", "y_min", "y_max", "n_geoms", "n_coords")
    return t.groupBy("file").agg(F.min("x_min").alias("x_min"), F.max("x_max").alias("x_max"), F.min("y_min").alias("y_min"), F.max("y_max").alias("y_max"), F.count("*").alias("pages"), F.sum("n_geoms").alias("n_geoms"), F.sum("n_coords").alias("n_coords"))


def write_manifest(spark: SparkSession, path: str) -> None:
    """Keep the manifest beside the files, for scans to choose files by."""
    manifest(spark, path).coalesce(1).write.mode("overwrite").parquet(f"{path.rstrip('/')}/{MANIFEST}")


def _name(file: str) -> str:
    """A file's name below its table, the same however the store is addressed."""
    return file.rsplit("/", 1)[-1]


def pruned(spark: SparkSession, path: str, rect: Rect | None, most: int = MOST_FILES) -> DataFrame:
    """The table's files that may hold pages in a rectangle: by the manifest, where there is one, files are left out before any footer is opened.

    Files that the manifest doesn't know (a later append without one) are read; one without a file of it names nothing.
    """
    t = spark.read.parquet(path)
    if rect is None or not _has_manifest(spark, path):
        return t
    m = spark.read.parquet(f"{path.rstrip('/')}/{MANIFEST}")
    away = m.where(~F.coalesce(meets(rect), F.lit(False))).select("file").limit(most + 1).collect()
    files = t.inputFiles()
    if not away or len(away) > most or len(files) > most:
        return t
    away = {_name(r.file) for r in away}
    near = [f for f in files if _name(f) not in away]
    return spark.read.schema(t.schema).parquet(*near) if near else t.where(F.lit(False))


def _has_manifest(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(f"{path.rstrip('/')}/{MANIFEST}/_SUCCESS")
    return "*" not in path and p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def extent_of(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).agg(F.min("x_min").alias("x_min"), F.max("x_max").alias("x_max"), F.min("y_min").alias("y_min"), F.max("y_max").alias("y_max"), F.sum("n_geoms").cast("long").alias("n"))


def _values(col: pa.Array):
    """Flat values of a list column and each list's bounds."""
    return col.values, col.offsets.to_numpy().astype(np.int64)


def _decode(rect: Rect | None, stream: str, schema: pa.Schema) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Pages back to geometries, from the columns' buffers; with a rectangle, only those whose box meets it leave Python."""
    whole = schema.field("geometry").type
    parts_type = whole.field("parts").type
    point = parts_type.value_type.value_type
    axes, dtype = [f.name for f in point], point[0].type.to_pandas_dtype()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            attrs = [b.column(f"attr_{f.name}") for f in list(schema)[2:]]
            counts = b.column("n_coords").to_numpy()
            ids, ids_at = _values(b.column("ids"))
            n_parts, parts_at = _values(b.column("geom_nparts"))
            n_coords, coords_at = _values(b.column("part_ncoords"))
            runs, runs_at = _values(b.column("type_runs"))
            n_parts, n_coords = n_parts.to_numpy(), n_coords.to_numpy()
            run_size, run_kind = (runs.field(n).to_numpy() for n in ("cnt", "type"))
            enc = [b.column(f"{a}_enc").to_numpy() for a in axes]
            for i in range(len(b)):
                v = [codec.decode_page(int(e[i]), b.column(f"{a}_bytes")[i].as_buffer(), int(counts[i]), dtype, stream) for a, e in zip(axes, enc, strict=True)]
                own = slice(runs_at[i], runs_at[i + 1])
                kind = np.repeat(run_kind[own], run_size[own]).astype(np.int32)
                part_at = np.r_[0, np.cumsum(n_parts[parts_at[i] : parts_at[i + 1]])]
                coord_at = np.r_[0, np.cumsum(n_coords[coords_at[i] : coords_at[i + 1]])]
                leaf = pa.StructArray.from_arrays([pa.array(x) for x in v], fields=list(point))
                inner = pa.ListArray.from_arrays(pa.array(coord_at.astype(np.int32)), leaf, type=parts_type.value_type)
                parts = pa.ListArray.from_arrays(pa.array(part_at.astype(np.int32)), inner, type=parts_type)
                g = pa.StructArray.from_arrays([pa.array(np.maximum(kind, 0)), parts], fields=list(whole), mask=pa.array(kind < 0))
                out = pa.record_batch([ids.slice(ids_at[i], ids_at[i + 1] - ids_at[i]), g, *(a[i].values.cast(f.type) for a, f in zip(attrs, list(schema)[2:], strict=True))], schema=schema)
                if rect is not None:
                    x, y = v[:2]
                    ends = coord_at[part_at]
                    has = np.flatnonzero(np.diff(ends) > 0)
                    hit = np.zeros(len(kind), bool)
                    if len(has):
                        at = ends[:-1][has]
                        lo, hi = np.fmin.reduceat, np.fmax.reduceat
                        hit[has] = (hi(x, at) >= rect[0]) & (lo(x, at) <= rect[2]) & (hi(y, at) >= rect[1]) & (lo(y, at) <= rect[3])
                    out = out.filter(pa.array(hit))
                if len(out):
                    yield out

    return run


def _decoded(t: DataFrame, rect: Rect | None = None, stream: str = "split", attributes: tuple[str, ...] = ()) -> DataFrame:
    """(id, geometry, attributes) of page rows."""
    own = [T.StructField(a, t.schema[f"attr_{a}"].dataType.elementType) for a in attributes]
    geometry = geometry_of(t.schema)
    axes = [f.name for f in geometry["parts"].dataType.elementType.elementType]
    kind = T.StructType([T.StructField("id", T.LongType()), T.StructField("geometry", geometry), *own])
    t = t.select("n_coords", "type_runs", "ids", "geom_nparts", "part_ncoords", *[f"{a}_{c}" for a in axes for c in ("enc", "bytes")], *[f"attr_{a}" for a in attributes])
    return t.mapInArrow(_decode(rect, stream, to_arrow_schema(kind)), kind)


def scan(spark: SparkSession, path: str, rect: Rect | None = None, stream: str = "split", kinds: tuple[int, ...] = (), attributes: tuple[str, ...] = (), exact: bool = False) -> DataFrame:
    """(id, geometry, attributes) of a page table. The rectangle and kinds must be given here: no filter gets below the decoder later.

    A rectangle works on two levels: files by the manifest, then pages by their bounds. Geometries
    come out whose boxes meet it; with ``exact``, those that meet it themselves.
    """
    t = pruned(spark, path, rect)
    if rect is not None:
        t = t.where(meets(rect))
    if kinds:
        t = t.where(F.exists("type_runs", lambda r: r["type"].isin(*kinds)))
    d = _decoded(t, rect, stream, attributes)
    if rect is not None and exact:
        d = d.where(geom.intersects_exactly(F.col("geometry"), *rect))
    return d.where(F.col("geometry.type").isin(*kinds)) if kinds else d


def scan_axis(spark: SparkSession, path: str, axis: str) -> DataFrame:
    """One axis alone: (page_id, ids, part counts, values); the other axis is never read."""
    t = spark.read.parquet(path)
    kind = t.schema[f"{axis}_min"].dataType.simpleString()
    t = t.select("page_id", "n_coords", "ids", "geom_nparts", "part_ncoords", F.col(f"{axis}_enc").alias("enc"), F.col(f"{axis}_bytes").alias("data"))
    leaf = pa.float32() if kind == "float" else pa.float64()

    @F.arrow_udf(f"array<{kind}>")
    def values(enc: pa.Array, data: pa.Array, count: pa.Array) -> pa.Array:
        own = [codec.decode_page(e, d.as_buffer(), c, leaf.to_pandas_dtype()) for e, d, c in zip(enc.to_pylist(), data, count.to_pylist(), strict=True)]
        return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, own)]), pa.int32()), pa.array(np.concatenate([np.zeros(0, leaf.to_pandas_dtype()), *own]), leaf))

    return t.select("page_id", "ids", "geom_nparts", "part_ncoords", values("enc", "data", "n_coords").alias(axis))


def scan_windows(spark: SparkSession, path: str, windows: DataFrame) -> DataFrame:
    """(window columns, id) of points and boxes that meet each window: every page that any window needs is decoded once.

    Few windows go to the scan as rectangles of their own, more as the box around all; pages
    that no window needs are then left out by a join on their names.
    """
    few = windows.where("qx0 is not null and qy0 is not null and qx1 is not null and qy1 is not null").select("qx0", "qy0", "qx1", "qy1")
    rects = [tuple(r) for r in few.limit(MOST_PUSHED + 1).collect()]
    around = tuple(few.agg(F.min("qx0"), F.min("qy0"), F.max("qx1"), F.max("qy1")).first())
    t = pruned(spark, path, around) if rects else spark.read.parquet(path)
    wanted = [meets(r) for r in (rects if len(rects) <= MOST_PUSHED else [around])]
    t = t.where(reduce(lambda a, b: a | b, wanted, F.lit(False))).withColumn("_file", F.col("_metadata.file_name"))
    asked = windows_meet(windows, t.select("_file", "page_id", "x_min", "x_max", "y_min", "y_max")).select("_file", "page_id").distinct()
    d = _decoded(t.join(asked, ["_file", "page_id"], "left_semi")).select("id", geom.box(F.col("geometry")).alias("b")).select("id", "b.*")
    return windows_meet(windows, d)


def nearest(spark: SparkSession, path: str, x: float, y: float, k: int) -> DataFrame:
    """The ``k`` geometries whose boxes are nearest to a place: (id, d2), squared distance, ties by id.

    The farthest corners of the pages' boxes, counted from the nearest page on, say how far the
    k-th can be at most; only pages within that distance are decoded.
    """
    away = lambda lo, hi, v: F.greatest(F.col(lo) - v, F.lit(v) - F.col(hi), F.lit(0.0))
    far = lambda lo, hi, v: F.greatest(F.abs(F.col(lo) - v), F.abs(F.col(hi) - v))
    square = lambda a, b: a * a + b * b
    least, most = (square(f("x_min", "x_max", x), f("y_min", "y_max", y)) for f in (away, far))
    t = spark.read.parquet(path)
    # with every page giving a geometry at least, the k pages of least farthest corners suffice
    bounds = t.where("x_min is not null and y_min is not null").select(most.alias("d2")).orderBy("d2").limit(k).collect()
    if not bounds:
        return spark.createDataFrame([], "id long, d2 double")
    t = t.where(least <= bounds[-1].d2) if len(bounds) == k else t
    d = _decoded(t).select("id", geom.box(F.col("geometry")).alias("b")).select("id", "b.*").where("x_min is not null and y_min is not null")
    return d.select("id", least.alias("d2")).orderBy("d2", "id").limit(k)


def prune_report(spark: SparkSession, path: str, rect: Rect) -> DataFrame:
    """Pages, geometries and encoded bytes that a rectangle needs, of all."""
    t = spark.read.parquet(path)
    hit = F.when(meets(rect), 1).otherwise(0)
    size = F.length("x_bytes") + F.length("y_bytes")
    return t.agg(F.sum(hit).cast("long").alias("pages_hit"), F.count("*").alias("pages_total"), F.sum(hit * F.col("n_geoms")).cast("long").alias("geoms_read"), F.sum(hit * size).cast("long").alias("bytes_read"), F.sum(size).cast("long").alias("bytes_total"))
