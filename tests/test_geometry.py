import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geopages.functions import build, geom
from geopages.functions.curve import Extent, hilbert_key, z_key
from geopages.plans import fixtures as X


def test_examples_shred_to_their_leaves(spark):
    d = build.shred(X.literal_examples(spark), id="gid")
    assert {r.gid: r["count"] for r in d.groupBy("gid").count().collect()} == {"g1": 1, "g2": 3, "g3": 8, "g4": 3, "g5": 6, "g6": 13}
    back = build.assemble(d, id="gid").join(X.literal_examples(spark).withColumnRenamed("geometry", "want"), "gid")
    assert back.where(F.col("geometry") == F.col("want")).count() == 6


def test_orientation_and_reassembly(spark):
    d = X.literal_examples(spark).select("gid", "geometry", F.transform("geometry.parts", build.doubled_area).alias("a"), build.split_polygons(F.col("geometry.parts")).alias("p"))
    r = {x.gid: x for x in d.collect()}
    g3 = X.literal_examples(spark).where("gid = 'g3'").select(F.transform(F.transform("geometry.parts", build.closed), build.doubled_area).alias("a")).first().a
    assert g3 == [-24.0, 1.0] and r["g6"].a == [-13.0, 1.0, -2.0]
    assert [len(p) for p in r["g6"].p] == [2, 1]


def test_polygon_normalises(spark):
    ring = lambda *v: F.array(*[build.coordinate(F.lit(float(x)), F.lit(float(y))) for x, y in v])
    d = spark.range(1).select(build.polygon(F.array(ring((0, 0), (4, 0), (4, 4), (0, 4)), ring((1, 1), (1, 2), (2, 2)))).alias("g"))
    d = d.select("g", F.transform("g.parts", build.is_clockwise).alias("cw"), geom.validate(F.col("g")).alias("v"), geom.area(F.col("g")).alias("area"), geom.as_wkt(F.col("g"), lambda v: v.cast("int").cast("string")).alias("t")).first()
    assert d.cw == [True, False] and d.v == [] and d.area == 15.5 and d.t.startswith("POLYGON ((0 0, 0 4, 4 4, 4 0, 0 0), (")
    bad = X.literal_examples(spark).where("gid = 'g3'").select(geom.validate(F.col("geometry")).alias("v")).first().v
    assert bad == ["unclosed", "short_ring"]


def test_level_bits():
    assert build.level_bits(build.geometry_type()) == {"type": (0, 0), "parts.x": (2, 2), "parts.y": (2, 2)}
    assert build.level_bits(build.geometry_type(3), nullable=True)["parts.z"] == (2, 2)
    assert build.level_bits(build.collection_type())["parts.x"] == (2, 2)
    loose = T.ArrayType(T.ArrayType(T.DoubleType()))
    assert build.level_bits(T.StructType([T.StructField("p", loose)]), True)["p"] == (2, 3)


def test_level_entries_are_those_of_a_file(spark, tmp_path):
    import pyarrow.parquet as pq

    one = {"type": 1, "parts": [[{"x": 1.0, "y": 2.0}]]}
    many = {"type": 5, "parts": [[{"x": 1.0, "y": 2.0}, {"x": 3.0, "y": 4.0}], [], [{"x": 5.0, "y": 6.0}]]}
    kind = T.StructType([T.StructField("g", build.geometry_type()), T.StructField("c", build.collection_type())])
    d = spark.createDataFrame([(one, [one, many]), (many, []), (None, None), ({"type": 0, "parts": []}, [many])], kind).coalesce(1)
    d.write.parquet(f"{tmp_path}/t")
    columns = pq.ParquetFile(next(tmp_path.glob("t/*.parquet"))).metadata.row_group(0)
    columns = [columns.column(i) for i in range(columns.num_columns)]
    wanted = [(c.path_in_schema.split(".")[0], c.path_in_schema.split(".")[-1], c.num_values) for c in columns]
    entries = {(f.name, leaf.split(".")[-1]): n for f in kind.fields for leaf, n in build.level_entries(F.col(f.name), f.dataType).items()}
    got = d.agg(*[F.sum(entries[column, leaf]) for column, leaf, _ in wanted]).first()
    assert len(entries) == 6 and list(got) == [n for *_, n in wanted]


def own_events(spark, path, rows):
    spark.createDataFrame(rows, "event_id long, user_id long, event_type string, value double").write.parquet(f"{path}/events.parquet")
    return str(path)


def test_level_bits_of_a_table(spark, tmp_path):
    import __spark_entry__ as entry

    rows = [(i, 7 * i, t, i / 4) for i, t in enumerate(("click", "view", "view", None, "error", "view", "click", "signup", "view"))]
    got = {(r.variant, r.leaf): (r.rep_bits, r.def_bits, r.n_levels, r.level_bits) for r in entry.queries()["level_bits"](spark, own_events(spark, tmp_path / "some", rows)).collect()}
    coords = [sum(map(len, list(X.EXAMPLES.values())[i % 6][1])) for i, *_ in rows]
    view = [t == "view" for *_, t, _ in rows]
    assert coords == [1, 3, 8, 3, 6, 13, 1, 3, 8] and len(got) == 16
    assert got["required", "type"] == (0, 0, 9, 0) and got["optional", "type"] == (0, 1, 9, 9)
    assert got["collection", "type"] == (1, 1, 14, 28)
    assert got["floats", "parts.y"] == got["three_axes", "parts.z"] == got["required", "parts.x"] == (2, 2, sum(coords), 4 * sum(coords))
    assert got["optional", "parts.x"][2] == sum(1 if v else c for v, c in zip(view, coords, strict=True))
    assert got["collection", "parts.y"][2] == sum(1 if v else 1 + c for v, c in zip(view, coords, strict=True))
    none = entry.queries()["level_bits"](spark, own_events(spark, tmp_path / "none", [])).collect()
    assert len(none) == 16 and not any(r.n_levels or r.level_bits for r in none)


def test_worked_examples_of_a_table(spark, tmp_path):
    import __spark_entry__ as entry

    rows = [(i, 7 * i, "click", i / 4) for i in range(7)]
    got = {}
    for r in entry.queries()["worked_examples"](spark, own_events(spark, tmp_path, rows)).orderBy("id", "part_no", "coord_no").collect():
        got.setdefault((r.id, r.gid, r.kind), []).append((r.part_no, r.coord_no, r.rep_level, r.def_level, round(r.x * 10_000), round(r.y * 10_000)))
    assert len(got) == 7
    for i, user, _, value in rows:
        x0, y0 = user * 7919 % 3600 * 1000 - 1_800_000, user * 104_729 % 1800 * 1000 - 900_000
        w, h = 1 + i * 613 % 100, 1 + int(value * 100) * 31 % 100
        kind, parts = X.EXAMPLES[f"g{i % 6 + 1}"]
        assert got[i, f"g{kind}", kind] == [(p, c, 2 if c else 1 if p else 0, 2, x0 + x * w, y0 + y * h) for p, part in enumerate(parts) for c, (x, y) in enumerate(part)]


def test_collections_flatten(spark):
    p = {"type": 1, "parts": [[{"x": 1.0, "y": 2.0}]]}
    rows = [(1, 0, None, 0, None), (1, 1, 0, 1, p), (1, 2, 0, 0, None), (1, 3, 2, 0, None), (1, 4, 3, 10, p), (1, 5, 3, 2, {**p, "type": 2})]
    kind = T.StructType([T.StructField(n, T.LongType()) for n in ("root_id", "node_id", "parent_id", "ord")] + [T.StructField("geometry", build.geometry_type())])
    got = build.flatten_collections(spark.createDataFrame(rows, kind)).orderBy("pos").select("geometry.type").collect()
    assert [r.type for r in got] == [2, 1, 1]


@pytest.mark.parametrize("key, step", [(hilbert_key, True), (z_key, False)])
def test_curves_are_bijective(spark, key, step):
    d = spark.range(16).alias("a").selectExpr("id as i").join(spark.range(16).selectExpr("id as j"))
    e = Extent(0.0, 0.0, 16.0, 16.0)
    rows = d.select("i", "j", key(F.col("i").cast("double"), F.col("j").cast("double"), e, 4).alias("k")).orderBy("k").collect()
    assert [r.k for r in rows] == list(range(256))
    if step:
        assert all(abs(a.i - b.i) + abs(a.j - b.j) == 1 for a, b in zip(rows, rows[1:], strict=False))
    else:
        assert all(r.k == sum(((r.i >> b & 1) << 2 * b) | ((r.j >> b & 1) << 2 * b + 1) for b in range(4)) for r in rows)


def test_first_hilbert_keys(spark):
    d = X.dataset(spark, "/root/testdata/sf0.01", "obs").where("id < 4")
    from geopages.operators.sorting import with_key

    assert [r._key for r in with_key(d, "hilbert").orderBy("id").collect()] == [3565007210, 840253737, 606869207, 1532816575]


def test_rectangles_tile_the_plane(spark):
    from geopages.operators import sorting

    r = np.random.default_rng(3)
    p = r.normal(0, 1, (5000, 2))
    tree = sorting.split_points(p, 200, 0.3)
    boxes = tree.boxes()
    inside = [(p[:, 0] >= b[0]) & (p[:, 0] < b[2]) & (p[:, 1] >= b[1]) & (p[:, 1] < b[3]) for b in boxes]
    assert (np.sum(inside, 0) == 1).all() and max(x.sum() for x in inside) <= 200 and min(x.sum() for x in inside) >= 40
    assert (np.argmax(inside, 0) == tree.leaf_of(p[:, 0], p[:, 1])).all()
    assert sorting.split_points(np.ones((50, 2)), 10).boxes() == [(-np.inf, -np.inf, np.inf, np.inf)]
    d = spark.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(p)] + [(9000, float("nan"), 1.0), (9001, None, 1.0)], "id long, x double, y double")
    for sampled in (1_000_000, 100):
        cells = sorting.partitioned(d, 200, most_sampled=sampled)
        assert cells.count() == 5002 and cells.groupBy("cell").count().agg({"count": "max"}).first()[0] <= 202


def test_exact_meeting(spark):
    ring = lambda *p: [{"x": float(x), "y": float(y)} for x, y in p]
    square, hole = ring((0, 0), (0, 10), (10, 10), (10, 0), (0, 0)), ring((4, 4), (6, 4), (6, 6), (4, 6), (4, 4))
    cases = [
        ((3, [square]), (2, 2, 3, 3), True), ((3, [square, hole]), (4.5, 4.5, 5.5, 5.5), False), ((3, [square, hole]), (4.5, 4.5, 6.5, 5), True),
        ((3, [ring((0, 0), (0, 10), (1, 10), (1, 1), (10, 1), (10, 0), (0, 0))]), (3, 3, 9, 9), False), ((2, [ring((0, 0), (10, 10))]), (0, 5, 3, 9), False),
        ((2, [ring((0, 0), (10, 10))]), (4, 5, 6, 6), True), ((2, [ring((0, 0), (10, 0))]), (2, 0, 3, 1), True), ((1, [ring((1, 1))]), (1, 1, 1, 1), True), ((1, [ring((1, 2))]), (1, 1, 1, 1), False),
        ((5, [ring((0, 0), (1, 0)), ring((0, 9), (9, 0))]), (5, 5, 9, 9), False), ((4, [ring((0, 0)), ring((9, 9))]), (1, 1, 8, 8), False), ((3, [square]), (-5, -5, 20, 20), True), ((0, []), (0, 0, 1, 1), False),
    ]
    for (kind, parts), r, want in cases:
        d = spark.createDataFrame([({"type": kind, "parts": parts},)], T.StructType([T.StructField("g", build.geometry_type())]))
        assert d.select(geom.intersects_exactly(F.col("g"), *r).alias("v")).first().v is want, (kind, parts, r)
