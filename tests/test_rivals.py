"""Rival formats against bytes made by hand, value by value."""

import json
import struct
from pathlib import Path

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geopages.functions import build
from geopages.plans import fixtures as X
from geopages.sources import geojson, shapefile, wkb
from geopages.sources.flat import flat, nested

SF = "/root/testdata/sf0.001"


def rows():
    out = [{"type": k, "parts": [[{"x": float(x), "y": float(y)} for x, y in p] for p in parts]} for k, parts in X.EXAMPLES.values()]
    return [*out, None, {"type": 0, "parts": []}, {"type": 2, "parts": [[]]}, *out]


def by_hand(g, order="<"):
    mark = b"\1" if order == "<" else b"\0"
    head = lambda k: mark + struct.pack(order + "I", k)
    xy = lambda p: b"".join(struct.pack(order + "2d", c["x"], c["y"]) for c in p)
    count = lambda n: struct.pack(order + "I", n)
    ring = lambda p: count(len(p)) + xy(p)
    k, parts = g["type"], g["parts"]
    if k == 0:
        return head(7) + count(0)
    if k == 1:
        return head(1) + xy(parts[0])
    if k == 2:
        return head(2) + ring(parts[0])
    if k == 3:
        return head(3) + count(len(parts)) + b"".join(map(ring, parts))
    if k in (4, 5):
        return head(k) + count(len(parts)) + b"".join(head(k - 3) + (xy(p) if k == 4 else ring(p)) for p in parts)
    polygons = []
    for p in parts:
        area = sum(a["x"] * b["y"] - b["x"] * a["y"] for a, b in zip(p, p[1:], strict=False))
        if not polygons or area < 0:
            polygons.append([])
        polygons[-1].append(p)
    return head(6) + count(len(polygons)) + b"".join(head(3) + count(len(q)) + b"".join(map(ring, q)) for q in polygons)


def test_binary_of_every_kind():
    a = pa.array(rows(), wkb._GEOMETRY)
    made = wkb.encode(flat(a)).to_pylist()
    assert made == [g and by_hand(g) for g in rows()]
    assert wkb.decode(pa.array(made, pa.binary())).to_pylist() == rows()
    big = [g and by_hand(g, ">") for g in rows()]
    assert wkb.decode(pa.array(big, pa.binary())).to_pylist() == rows()
    assert wkb.decode(pa.array(made, pa.binary()).slice(3, 4)).to_pylist() == rows()[3:7]
    assert wkb.encode(flat(a.slice(2, 5))).to_pylist() == made[2:7]
    points = [{"type": 1, "parts": [[{"x": i / 7, "y": -i / 3}]]} for i in range(50)]
    assert wkb.decode(pa.array([by_hand(p) for p in points], pa.binary())).to_pylist() == points
    assert wkb.decode(pa.array([], pa.binary())).to_pylist() == [] and wkb.encode(flat(a.slice(0, 0))).to_pylist() == []
    with pytest.raises(ValueError, match="collection"):
        wkb.decode(pa.array([b"\1" + struct.pack("<2I", 7, 1) + by_hand(rows()[0])], pa.binary()))


def test_collections(spark):
    c = rows()[:6]
    nested_text = json.dumps({"type": "GeometryCollection", "geometries": [{"type": "Point", "coordinates": [1, 2]}, {"type": "GeometryCollection", "geometries": [{"type": "MultiPoint", "coordinates": [[1, 2], [3, 4]]}, None]}]})
    d = spark.createDataFrame([(c, nested_text), (None, None), ([], '{"type":"LineString","coordinates":[[0,0],[1,1]]}')], T.StructType([T.StructField("c", build.collection_type()), T.StructField("t", T.StringType())]))
    got = d.select(wkb.parse_wkb_collection(wkb.as_wkb_collection(F.col("c"))).alias("w"), geojson.parse_geojson_collection("t").alias("j")).collect()
    assert [g.asDict(True) for g in got[0].w] == c and got[1].w is None and got[2].w == []
    assert [g.type for g in got[0].j] == [1, 4] and len(got[0].j[1].parts) == 2 and got[1].j is None and [g.type for g in got[2].j] == [2]
    deep = b"\1" + struct.pack("<2I", 7, 2) + by_hand(c[0]) + b"\0" + struct.pack(">2I", 7, 1) + by_hand(c[4], ">")
    leaf = spark.createDataFrame([(deep,)], "w binary").select(wkb.parse_wkb_collection("w").alias("g")).first().g
    assert [g.asDict(True) for g in leaf] == [c[0], c[4]]


def test_shapefiles(spark, tmp_path):
    g = [x for x in rows() if x is None or x["parts"] != [[]]]
    d = spark.createDataFrame([(10 * i, x) for i, x in enumerate(g)], T.StructType([T.StructField("id", T.LongType()), T.StructField("geometry", build.geometry_type())]))
    files = shapefile.shape_files(d.coalesce(1), most=2).collect()
    assert sorted(f.shape_type for f in files) == [0, 1, 3, 3, 5, 5, 8]
    for f in files:
        shp = bytes(f.shp)
        assert struct.unpack(">i", shp[:4])[0] == 9994 and 2 * struct.unpack(">i", shp[24:28])[0] == len(shp)
        assert 2 * struct.unpack(">i", bytes(f.shx)[24:28])[0] == len(f.shx) and struct.unpack("<2i", shp[28:36]) == (1000, f.shape_type)
        _, own = shapefile.parse(shp, bytes(f.shx), bytes(f.dbf))
        if f.shape_type:
            assert struct.unpack("<4d", shp[36:68]) == (*own.xy.min(0), *own.xy.max(0))
        walked = shapefile.parse(shp, None, None)
        assert (walked[1].xy == own.xy).all() and (walked[1].n_coords == own.n_coords).all() and list(walked[0]) == list(range(1, len(own.kind) + 1))
    key = lambda r: (r.id, str(r.geometry))
    # an empty and a null geometry are both null shapes; the attribute file tells them apart
    want = sorted(map(key, d.collect()))
    for compressed in (False, True):
        shapefile.save_shapefiles(d, f"{tmp_path}/s{compressed}", compressed, most=2)
        assert sorted(map(key, shapefile.read_shapefiles(spark, f"{tmp_path}/s{compressed}").collect())) == want
        n = shapefile.export(spark, f"{tmp_path}/s{compressed}", f"{tmp_path}/f{compressed}")
        assert len([p for p in Path(f"{tmp_path}/f{compressed}").iterdir() if not p.name.startswith(".")]) == 3 * n
        assert sorted(map(key, shapefile.read_folder(spark, f"{tmp_path}/f{compressed}").collect())) == want
    for p in Path(f"{tmp_path}/fFalse").glob("*.dbf"):
        p.unlink()
    assert shapefile.read_folder(spark, f"{tmp_path}/fFalse").count() == len(g)


def test_geojson(spark, tmp_path):
    g = [x for x in rows() if x is None or x["parts"] != [[]]]
    d = spark.createDataFrame(list(enumerate(g)), T.StructType([T.StructField("id", T.LongType()), T.StructField("geometry", build.geometry_type())]))
    key = lambda r: (r.id, str(r.geometry))
    for c, one in (("none", False), ("gzip", True)):
        geojson.save_geojson(d.repartition(3), f"{tmp_path}/{c}", c, one)
        assert sorted(map(key, geojson.read_geojson(spark, f"{tmp_path}/{c}").collect())) == sorted(map(key, d.collect()))
    assert len(list(Path(f"{tmp_path}/gzip").glob("*.gz"))) == 1
    lines = [json.loads(x) for p in Path(f"{tmp_path}/none").glob("part*") for x in p.read_text().splitlines()]
    assert {x["type"] for x in lines} == {"Feature"} and [x["geometry"]["coordinates"] for x in lines if x["id"] == 0] == [[3.0, 2.0]]


def test_flat_arrays_take_and_nest():
    a = pa.array(rows(), wkb._GEOMETRY)
    f = flat(a)
    r = np.random.default_rng(2)
    for _ in range(20):
        at = r.integers(0, len(a), r.integers(0, 8))
        assert nested(f.take(at), wkb._GEOMETRY).to_pylist() == [rows()[i] for i in at]
