import __spark_entry__ as entry
from pyspark.sql import functions as F

from geopages.functions import geom
from geopages.plans import fixtures as X
from geopages.sources import page_table

SF = "/root/testdata/sf0.001"


def test_well_known_text(spark):
    cases = {
        "POINT (1 2)": (1, [[(1, 2)]]),
        " point(1.5e3 -.5) ": (1, [[(1500, -0.5)]]),
        "POLYGON ((0 0, 0 1, 1 1, 0 0), (1 1, 2 2, 3 3, 1 1))": (3, [[(0, 0), (0, 1), (1, 1), (0, 0)], [(1, 1), (2, 2), (3, 3), (1, 1)]]),
        "MULTIPOINT (1 2, 3 4)": (4, [[(1, 2)], [(3, 4)]]),
        "MULTIPOINT ((1 2), (3 4))": (4, [[(1, 2)], [(3, 4)]]),
        "MULTIPOLYGON (((0 0, 0 1, 1 1, 0 0)), ((5 5, 5 6, 6 6, 5 5)))": (6, [[(0, 0), (0, 1), (1, 1), (0, 0)], [(5, 5), (5, 6), (6, 6), (5, 5)]]),
        "LINESTRING EMPTY": (0, []), "GEOMETRYCOLLECTION EMPTY": (0, []),
        "POINT (1 2 3)": None, "POINT (a b)": None, "CIRCLE (1 2)": None, "POINT (1 2": None, "POLYGON ((0 0, 1 1)": None, "": None, None: None,
    }
    rows = spark.createDataFrame([(t,) for t in cases], "t string").select("t", geom.from_wkt(F.col("t")).alias("g")).collect()
    for r in rows:
        assert (r.g and (r.g.type, [[(c.x, c.y) for c in p] for p in r.g.parts])) == cases[r.t], r.t


def test_text_round_trip(spark):
    for n in ("traj", "bldg", "lots"):
        d = X.dataset(spark, SF, n)
        back = d.select("id", geom.from_wkt(geom.as_wkt(F.col("geometry"))).alias("geometry"))
        assert back.exceptAll(d).count() == 0 == d.exceptAll(back).count()


def test_attributes_stay_with_their_geometry(spark, tmp_path):
    e = X.DATASETS["bldg"].extent
    d = X.dataset(spark, SF, "bldg").select("*", F.concat(F.lit("n"), "id").alias("name"), F.when(F.col("id") % 3 > 0, F.array("id")).alias("tags"), F.when(F.col("id") % 5 > 0, F.timestamp_seconds("id")).alias("t"))
    for sort in ("none", "grouped", "total"):
        page_table.save(d, f"{tmp_path}/{sort}", page_bytes=2048, group_size=300, sort=sort, extent=e, attributes=("name", "tags", "t"))
        back = page_table.scan(spark, f"{tmp_path}/{sort}", attributes=("t", "name", "tags")).select(d.columns)
        assert back.exceptAll(d).count() == 0 == d.exceptAll(back).count()
    hit = page_table.scan(spark, f"{tmp_path}/total", (-100.0, 30.0, -90.0, 40.0), attributes=("name",))
    assert hit.where("name != concat('n', id)").count() == 0 < hit.count()
    plan = hit._jdf.queryExecution().executedPlan().toString()
    assert "attr_name" in plan and "attr_tags" not in plan
    page_table.compact(spark, f"{tmp_path}/total", f"{tmp_path}/compacted")
    back = page_table.scan(spark, f"{tmp_path}/compacted", attributes=("name", "tags", "t"))
    assert d.exceptAll(back).count() == 0
    assert page_table.scan(spark, f"{tmp_path}/compacted").columns == ["id", "geometry"]
    page_table.save(d.limit(0), f"{tmp_path}/empty", attributes=("name",))
    assert page_table.scan(spark, f"{tmp_path}/empty", attributes=("name",)).count() == 0


def test_trips_of_a_stream_are_those_of_the_table(spark):
    e = spark.read.parquet(f"{SF}/events.parquet").toPandas().sort_values(["user_id", "ts", "event_id"])
    mark = e.ts.max().floor("ms").timestamp() - 600
    want = []
    for user, g in e.groupby("user_id"):
        new = g.ts.diff().dt.total_seconds().fillna(1e9) >= 1800
        for _, t in g.groupby(new.cumsum()):
            if t.ts.max().floor("ms").timestamp() + 1800 < mark:
                want.append((user, len(t)))
    got = [(r.user_id, r.n) for r in entry.queries()["stream_trips"](spark, SF).collect()]
    assert sorted(got) == sorted(want)
