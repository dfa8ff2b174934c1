import __spark_entry__ as entry
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geopages.functions import build, geom
from geopages.operators import index, sorting, stats
from geopages.plans import fixtures as X
from geopages.sources import page_table

SF = "/root/testdata/sf0.001"


def mixed_rows(spark):
    e = X.literal_examples(spark).collect()
    rows = [(i, r.geometry) for i, r in enumerate(e)] * 1
    rows = [(100 * k + i, g) for k in range(30) for i, g in rows] + [(9001, None), (9002, {"type": 0, "parts": []}), (9003, None), (9004, {"type": 1, "parts": [[{"x": float("nan"), "y": 1.0}]]})]
    return spark.createDataFrame(rows, T.StructType([T.StructField("id", T.LongType()), T.StructField("geometry", build.geometry_type())]))


def test_all_kinds_nulls_and_empties_round_trip(spark, tmp_path):
    d = mixed_rows(spark)
    for i, o in enumerate(({}, {"sort": "none"}, {"sort": "total"}, {"codec_name": "plain"}, {"rle": True}, {"stream": "interleaved"}, {"page_bytes": 80})):
        page_table.save(d.repartition(3), f"{tmp_path}/{i}", **({"page_bytes": 800, "group_size": 40} | o))
        back = page_table.scan(spark, f"{tmp_path}/{i}", stream=o.get("stream", "split"))
        key = lambda r: (r.id, str(r.geometry))
        assert sorted(map(key, back.collect())) == sorted(map(key, d.collect()))


def test_rectangles_lose_nothing_and_are_pushed(spark, tmp_path):
    d = X.dataset(spark, SF, "bldg").unionByName(mixed_rows(spark))
    page_table.save(d, f"{tmp_path}/p", page_bytes=2048, group_size=200, extent=X.DATASETS["bldg"].extent)
    b = geom.box(F.col("geometry"))
    for r in ((-100.0, 30.0, -90.0, 40.0), (1.0, 1.0, 1.0, 1.0), (5.0, 5.0, 6.0, 6.0), (2.5, 2.5, 2.6, 2.6), (900.0, 0.0, 901.0, 1.0)):
        want = {x.id for x in d.withColumn("b", b).where(geom.intersects(F.col("b"), *r)).collect()}
        assert {x.id for x in page_table.scan(spark, f"{tmp_path}/p", r).collect()} == want
    spark.conf.set("spark.sql.maxMetadataStringLength", "5000")
    plan = page_table.scan(spark, f"{tmp_path}/p", (0.0, 0.0, 1.0, 1.0))._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(x_max,0.0)" in plan and "LessThanOrEqual(y_min,1.0)" in plan
    axis = page_table.scan_axis(spark, f"{tmp_path}/p", "x")._jdf.queryExecution().executedPlan().toString()
    assert "x_bytes" in axis and "y_bytes" not in axis


def test_grouped_sort_needs_no_shuffle(spark):
    d = sorting.grouped(sorting.with_key(X.dataset(spark, SF, "obs"), "z"), 100)
    assert "Exchange" not in d._jdf.queryExecution().executedPlan().toString()
    p = d.withColumn("p", F.spark_partition_id()).collect()
    by = {}
    for r in p:
        by.setdefault((r.p, r._group), []).append(r._key)
    assert all(len(v) <= 100 and v == sorted(v) for v in by.values()) and len(p) == 1000


def test_sorting_tightens_pages(spark):
    area, bits = {}, {}
    for o in ("none", "z", "hilbert"):
        q = entry.queries()
        area[o] = q[f"index_quality_{o}"](spark, "/root/testdata/sf0.01").first().area_e4
    rows = q["codec_bits_unsorted"](spark, SF).unionByName(q["codec_bits_sorted"](spark, SF)).collect()
    for r in rows:
        bits[r.dataset, r["order"], r.axis] = r.total_bits
    assert area["hilbert"] < area["z"] < area["none"]
    assert all(bits["obs", o, a] < bits["obs", "none", a] for o in ("z", "hilbert") for a in "xy")


def test_cell_masks_lose_no_page(spark):
    d = X.leaves(spark, SF, "obs")
    p = stats.with_pages(d, [F.col("id")], 50)
    b = index.cell_mask(p, index.page_boxes(p))
    r = (18.0, -54.0, 36.0, -18.0)
    need = {x.page for x in p.where(f"x between {r[0]} and {r[2]} and y between {r[1]} and {r[3]}").collect()}
    got = {x.page for x in b.where(index.mask_meets(r)).collect()}
    assert need <= got and len(got) < b.where(index.meets(r)).count()


def test_wrapped_differences(spark):
    v = [0, 1, -1, 2**63 - 1, -(2**63), 2**32, -(2**32) - 5, 123456789012345678]
    d = spark.createDataFrame([(a, b) for a in v for b in v], "a long, b long").withColumn("d", stats.wrapped_difference(F.col("a"), F.col("b")))
    for r in d.select("a", "b", "d", stats.width(stats.zigzag(F.col("d"))).alias("w")).collect():
        want = (r.a - r.b + 2**63) % 2**64 - 2**63
        assert r.d == want and r.w == (2 * want if want >= 0 else -2 * want - 1).bit_length()


def test_entry_and_names(spark):
    assert entry.entry(spark).count() > 0
    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and len(q) > 120


def test_what_a_page_table_refuses(spark, tmp_path):
    import pytest

    d = X.literal_examples(spark).select(F.lit(None).cast("long").alias("id"), "geometry")
    with pytest.raises(Exception, match="id is null"):
        page_table.save(d, f"{tmp_path}/n")
    c = spark.range(1).select("id", F.expr("named_struct('type', 1, 'parts', array(array(named_struct('x', 1.0D, 'y', cast(null as double)))))").alias("geometry"))
    with pytest.raises(Exception, match="coordinate is null"):
        page_table.save(c, f"{tmp_path}/c")
    w = spark.range(1).select("id", F.expr("named_struct('type', 1, 'parts', array(array(named_struct('x', 1L, 'y', 2L))))").alias("geometry"))
    with pytest.raises(ValueError, match="double"):
        page_table.save(w, f"{tmp_path}/w")


def test_axes_and_widths_round_trip(spark, tmp_path):
    for coord in ("double", "float"):
        for dims in (2, 3, 4):
            axes = "xyzm"[:dims]
            rows = [(i, None if i % 7 == 0 else {"type": 2, "parts": [[{a: float((i * k + j) % 5) / 4 - k for k, a in enumerate(axes)} for j in range(i % 5 + 2)]]}) for i in range(300)]
            d = spark.createDataFrame(rows, T.StructType([T.StructField("id", T.LongType()), T.StructField("geometry", build.geometry_type(dims, coord))]))
            page_table.save(d, f"{tmp_path}/{coord}{dims}", page_bytes=512)
            back = page_table.scan(spark, f"{tmp_path}/{coord}{dims}")
            assert back.schema["geometry"].dataType == build.geometry_type(dims, coord)
            key = lambda r: (r.id, str(r.geometry))
            assert sorted(map(key, back.collect())) == sorted(map(key, d.collect()))


def test_manifest_leaves_out_files_and_knows_no_others(spark, tmp_path):
    path = f"{tmp_path}/m"
    d = X.dataset(spark, "/root/testdata/sf0.01", "obs")
    was = spark.conf.get("spark.sql.adaptive.coalescePartitions.enabled")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        page_table.save(d.where("id % 2 = 0"), path, sort="total", page_bytes=4096)
    finally:
        spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", was)
    r = X.RECTS["small"]
    all_files = len(spark.read.parquet(path).inputFiles())
    assert len(page_table.pruned(spark, path, r).inputFiles()) < all_files == 8
    assert len(page_table.pruned(spark, path, r, most=0).inputFiles()) == all_files
    far = page_table.scan(spark, path, (500.0, 500.0, 501.0, 501.0))
    assert far.count() == 0
    page_table.append(d.where("id % 2 = 1"), path, sort="none", page_bytes=4096, index=False)  # the manifest doesn't know these
    want = X.leaves(spark, "/root/testdata/sf0.01", "obs").where(f"x between {r[0]} and {r[2]} and y between {r[1]} and {r[3]}")
    assert {x.id for x in page_table.scan(spark, path, r).collect()} == {x.id for x in want.collect()}
    page_table.write_manifest(spark, path)
    assert {x.id for x in page_table.scan(spark, path, r).collect()} == {x.id for x in want.collect()}


def test_windows_one_by_one_and_around_all(spark, tmp_path, monkeypatch):
    d = X.dataset(spark, SF, "bldg")
    page_table.save(d, f"{tmp_path}/w", page_bytes=2048, extent=X.DATASETS["bldg"].extent)
    w = spark.createDataFrame([(k, -119.0 + 5 * k, 26.0 + k, -116.0 + 5 * k, 30.0 + k) for k in range(8)] + [(99, None, 1.0, 2.0, 3.0)], "k int, qx0 double, qy0 double, qx1 double, qy1 double")
    b = d.select("id", geom.box(F.col("geometry")).alias("b")).select("id", "b.*")
    want = sorted((r.k, r.id) for r in b.join(w, F.expr("x_max >= qx0 and x_min <= qx1 and y_max >= qy0 and y_min <= qy1")).collect())
    assert want
    for most in (32, 2):
        monkeypatch.setattr(page_table, "MOST_PUSHED", most)
        assert sorted((r.k, r.id) for r in page_table.scan_windows(spark, f"{tmp_path}/w", w).collect()) == want
    assert page_table.scan_windows(spark, f"{tmp_path}/w", w.where("k = 99")).count() == 0


def test_nearest(spark, tmp_path):
    d = X.dataset(spark, SF, "bldg").unionByName(mixed_rows(spark))
    page_table.save(d, f"{tmp_path}/k", page_bytes=1024, sort="total", extent=X.DATASETS["bldg"].extent)
    x, y = -97.3, 38.1
    boxes = d.select("id", geom.box(F.col("geometry")).alias("b")).where("b.x_min is not null").collect()
    away = lambda r: max(r.b.x_min - x, x - r.b.x_max, 0.0) ** 2 + max(r.b.y_min - y, y - r.b.y_max, 0.0) ** 2
    for k in (1, 7, 5000):
        want = sorted((away(r), r.id) for r in boxes)[:k]
        got = page_table.nearest(spark, f"{tmp_path}/k", x, y, k).collect()
        assert [r.id for r in got] == [i for _, i in want]


def test_every_compression_round_trips(spark, tmp_path):
    d = X.dataset(spark, SF, "bldg")
    key = lambda r: (r.id, str(r.geometry))
    want = sorted(map(key, d.collect()))
    for c in ("none", "gzip", "zstd", "snappy"):
        for size in (1 << 20, 2048):
            page_table.save(d, f"{tmp_path}/{c}{size}", c, sort="total", page_bytes=size, extent=X.DATASETS["bldg"].extent)
            assert sorted(map(key, page_table.scan(spark, f"{tmp_path}/{c}{size}").collect())) == want
