from pyspark.sql import functions as F
from pyspark.sql import types as T

from geopages.functions import build
from geopages.operators import sorting, stats
from geopages.sources import page_table


def test_places_are_those_of_a_full_sort(spark):
    rows = [(i, i * 7919 % 13, float(i % 5)) for i in range(500)]
    d = spark.createDataFrame(rows, "id long, k long, v double").repartition(7)
    got = {r.id: r.pos for r in sorting.numbered(d, [F.col("k"), F.col("id")]).collect()}
    assert got == {r[0]: n for n, r in enumerate(sorted(rows, key=lambda r: (r[1], r[0])))}
    assert sorting.numbered(d.where("id < 0"), [F.col("id")]).count() == 0


def test_one_key_may_hold_all_rows(spark):
    d = spark.range(300).withColumn("k", F.lit(1))
    assert [r.pos for r in sorting.numbered(d, [F.col("k"), F.col("id")]).orderBy("id").collect()] == list(range(300))


def test_values_before_cross_blocks(spark):
    rows = [(i, None if i % 11 == 3 else i * i) for i in range(100)]
    d = spark.createDataFrame(rows, "pos long, v long").repartition(5)
    got = {r.pos: r._before for r in sorting.before(d, "v", block=8).collect()}
    assert got == {i: rows[i - 1][1] if i else None for i in range(100)}


def test_shares_are_those_of_ntile(spark):
    for n, k in ((0, 3), (2, 5), (10, 3), (12, 4), (17, 5)):
        parts = [j for j in range(k) for _ in range(n // k + (j < n % k))]
        d = spark.range(n).select("id", sorting.share(F.col("id"), F.lit(n), k).alias("s")).orderBy("id")
        d = d.withColumn("start", sorting.share_start(F.col("s"), F.lit(n), k))
        assert [(r.s, r.start) for r in d.collect()] == [(p, parts.index(p)) for p in parts]


def test_sampled_widths_come_near_the_best(spark):
    d = spark.range(20_000).select("id", (F.lit(10.0) + F.col("id") / 1e6).alias("x"), (F.lit(5.0) - F.col("id") / 1e6).alias("y"))
    p = stats.with_pages(d, [F.col("id")], 100)
    best = {r.axis: r.n for r in stats.empirical_bits(p, 1.0).collect()}
    some = {r.axis: r.n for r in stats.empirical_bits(p, 0.2).collect()}
    assert set(best) == set(some) == {"x", "y"} and all(abs(best[a] - some[a]) <= 2 for a in best)


def test_pages_without_the_kinds_are_left_out(spark, tmp_path):
    rows = [(i, {"type": 1 if i < 50 else 2, "parts": [[{"x": float(i), "y": 0.0}] * (1 if i < 50 else 2)]}) for i in range(100)]
    d = spark.createDataFrame(rows, T.StructType([T.StructField("id", T.LongType()), T.StructField("geometry", build.geometry_type())]))
    page_table.save(d.coalesce(1), f"{tmp_path}/k", sort="none", page_bytes=160)
    for k in ((1,), (2,), (1, 2), (3,)):
        assert sorted(r.id for r in page_table.scan(spark, f"{tmp_path}/k", kinds=k).collect()) == [i for i, g in rows if g["type"] in k]
