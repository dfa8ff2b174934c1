import random

from pyspark.sql import functions as F

from geopages.functions import geom
from geopages.operators import box_join, index
from geopages.sources import baselines, page_table
from tests.test_pages import mixed_rows

LEFT = "id long, x_min double, y_min double, x_max double, y_max double"
RIGHT = "w long, qx0 double, qy0 double, qx1 double, qy1 double"


def boxes(n, seed):
    r = random.Random(seed)
    out = []
    for i in range(n):
        size = r.choice((0.0, 0.0, 0.001, 0.1, 5.0, 300.0))
        x, y = r.choice(((r.uniform(-200, 200), r.uniform(-100, 100)), (7.0, 7.0)))
        out.append((i, x, y, x + size * r.random(), y + size))
    return out


def brute(a, b):
    return sorted((p[0], q[0]) for p in a for q in b if p[3] >= q[1] and p[1] <= q[3] and p[4] >= q[2] and p[2] <= q[4])


def test_pairs_come_out_once_whatever_their_size(spark):
    a, b = boxes(300, 1), boxes(80, 2)
    left, right = spark.createDataFrame(a, LEFT), spark.createDataFrame(b, RIGHT)
    want = brute(a, b)
    for part in (box_join.PART, 10):
        assert sorted((r.id, r.w) for r in box_join.meet(left, right, part=part).collect()) == want
    for most in (0, 1000):
        assert sorted((r.id, r.w) for r in index.windows_meet(right, left, most=most).select("id", "w").collect()) == want


def test_unusable_boxes_meet_nothing(spark):
    nan = float("nan")
    a = [(1, None, 0.0, 1.0, 1.0), (2, nan, 0.0, nan, 1.0), (3, 2.0, 0.0, 1.0, 1.0), (4, 0.0, 0.0, 1.0, 1.0), (4, 0.0, 0.0, 1.0, 1.0)]
    right = spark.createDataFrame([(9, 1.0, 1.0, 1.0, 1.0)], RIGHT)
    assert [r.id for r in box_join.meet(spark.createDataFrame(a, LEFT), right).collect()] == [4, 4]
    assert box_join.meet(spark.createDataFrame([], LEFT), right).count() == 0


def test_ordered_bits_keep_values_and_order(spark, tmp_path):
    d = mixed_rows(spark)
    baselines.save_ordered_bits(d, f"{tmp_path}/b")
    key = lambda r: (r.id, str(r.geometry))
    assert sorted(map(key, baselines.read_ordered_bits(spark, f"{tmp_path}/b").collect())) == sorted(map(key, d.collect()))
    v = [-1e300, -2.5, -1e-320, -0.0, 0.0, 1e-320, 1.0, float("inf")]
    p = spark.createDataFrame([(i, {"type": 1, "parts": [[{"x": x, "y": -x}]]}) for i, x in enumerate(v)], d.schema)
    baselines.save_ordered_bits(p, f"{tmp_path}/o")
    got = [r.x for r in spark.read.parquet(f"{tmp_path}/o").orderBy("id").select(F.expr("geometry.parts[0][0].x").alias("x")).collect()]
    assert got == sorted(got) and len(set(got)) == len(v)


def test_compaction_keeps_rows_and_narrows_pages(spark, tmp_path):
    d = mixed_rows(spark)
    page_table.save(d.repartition(9), f"{tmp_path}/s", sort="none", page_bytes=80)
    page_table.compact(spark, f"{tmp_path}/s", f"{tmp_path}/t")
    key = lambda r: (r.id, str(r.geometry))
    assert sorted(map(key, page_table.scan(spark, f"{tmp_path}/t").collect())) == sorted(map(key, d.collect()))
    assert spark.read.parquet(f"{tmp_path}/t").count() < spark.read.parquet(f"{tmp_path}/s").count()
    assert page_table.scan(spark, f"{tmp_path}/t").where(geom.is_empty(F.col("geometry"))).count() == 1
