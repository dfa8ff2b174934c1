"""Stand-in datasets, derived from the base tables by integer arithmetic and one division.

Each is a SQL text that Spark and DuckDB both run: leaf rows (id, kind, part_no,
coord_no, xi, yi) with whole-number coordinates. Table names stand in braces.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import build
from ..functions.curve import WORLD, Extent
from ..sources.scratch import scratch_path

CENTS = "CAST(ROUND({v} * 100) AS BIGINT)"
_value, _price, _extended = (CENTS.format(v=v) for v in ("value", "o_totalprice", "l_extendedprice"))


def _steps(n: int) -> str:
    return f"(VALUES {', '.join(f'({i})' for i in range(n))}) AS steps(k)"


def _choose(values: list[str]) -> str:
    return "CASE k " + " ".join(f"WHEN {i} THEN {v}" for i, v in enumerate(values)) + " END"


_CORNER = f"""SELECT o_orderkey, o_custkey, o_orderstatus, c_nationkey,
  -12000000 + c_nationkey * 220000 + (o_custkey * 631 % 200) * 1000 + o_orderkey * 17 % 900 AS cx,
  2600000 + (c_nationkey * 7 % 25) * 80000 + (o_custkey * 389 % 70) * 1000 + o_orderkey * 29 % 900 AS cy,
  10 + {_price} % 40 AS w, 8 + o_orderkey % 30 AS h,
  CAST((10 + {_price} % 40 - (10 + {_price} % 40) % 2) / 2 AS BIGINT) AS w2, CAST((8 + o_orderkey % 30 - (8 + o_orderkey % 30) % 2) / 2 AS BIGINT) AS h2
  FROM {{orders}} JOIN {{customer}} ON o_custkey = c_custkey"""
_EVEN = _choose(["0", "0", "w", "w", "0"]), _choose(["0", "h", "h", "0", "0"])
_ODD = _choose(["0", "0", "w2", "w2", "w", "w", "0"]), _choose(["0", "h", "h", "h2", "h2", "0", "0"])
_HOLE = _choose(["2", "w - 2", "w - 2", "2", "2"]), _choose(["2", "2", "h - 2", "h - 2", "2"])
RINGS = f"""SELECT o_orderkey, o_custkey, o_orderstatus, c_nationkey, 0 AS ring, k AS coord_no,
  cx + CASE WHEN o_orderkey % 2 = 0 THEN {_EVEN[0]} ELSE {_ODD[0]} END AS xi, cy + CASE WHEN o_orderkey % 2 = 0 THEN {_EVEN[1]} ELSE {_ODD[1]} END AS yi
  FROM ({_CORNER}) b JOIN {_steps(7)} ON k < CASE WHEN o_orderkey % 2 = 0 THEN 5 ELSE 7 END
  UNION ALL
  SELECT o_orderkey, o_custkey, o_orderstatus, c_nationkey, 1 AS ring, k AS coord_no, cx + {_HOLE[0]} AS xi, cy + {_HOLE[1]} AS yi
  FROM ({_CORNER}) b JOIN {_steps(5)} ON k < 5 WHERE o_orderkey % 10 = 0"""


@dataclass(frozen=True)
class Dataset:
    sql: str
    scale: int
    extent: Extent
    tables: tuple[str, ...]


DATASETS = {
    "obs": Dataset(
        f"""SELECT event_id AS id, 1 AS kind, 0 AS part_no, 0 AS coord_no,
        (user_id * 7919 % 3600) * 1000 - 1800000 + CASE WHEN event_type = 'view' THEN 0 ELSE event_id * 613 % 1000 END AS xi,
        (user_id * 104729 % 1800) * 1000 - 900000 + CASE WHEN event_type = 'view' THEN 0 ELSE {_value} * 31 % 1000 END AS yi FROM {{events}}""",
        10_000, WORLD, ("events",),
    ),
    "traj": Dataset(
        f"""SELECT user_id AS id, 4 AS kind, CAST(row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS INT) AS part_no, 0 AS coord_no,
        CAST(-861000 + user_id * 37 % 400 + SUM({_value} % 201 - 100) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS xi,
        CAST(4115000 + user_id * 53 % 400 + SUM(({_value} * 7 + event_id) % 201 - 100) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS yi FROM {{events}}""",
        100_000, Extent(-8.75, 41.0, -8.5, 41.25), ("events",),
    ),
    "roads": Dataset(
        f"""SELECT l_orderkey AS id, 5 AS kind, part_no, k AS coord_no,
        -12500000 + (l_orderkey * 7919 % 5800) * 1000 + (l_partkey % 100) * 7 + k * (11 + l_suppkey % 17) AS xi,
        2500000 + (l_orderkey * 104729 % 2400) * 1000 + (l_partkey * 3 % 100) * 7 + k * (l_suppkey % 29 - 14) AS yi
        FROM (SELECT *, CAST(row_number() OVER (PARTITION BY l_orderkey ORDER BY l_shipdate, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_quantity) - 1 AS INT) AS part_no FROM {{lineitem}}) l
        JOIN {_steps(6)} ON k < 2 + CAST(l_quantity AS BIGINT) % 5""",
        100_000, Extent(-125.0, 24.0, -61.0, 56.0), ("lineitem",),
    ),
    "bldg": Dataset(f"SELECT o_orderkey AS id, 3 AS kind, ring AS part_no, coord_no, xi, yi FROM ({RINGS}) r", 100_000, Extent(-120.0, 20.0, -56.0, 52.0), ("orders", "customer")),
    "lots": Dataset(
        f"""SELECT o_custkey AS id, 6 AS kind, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderkey, ring) - 1 AS INT) AS part_no, coord_no, xi, yi
        FROM ({RINGS}) r WHERE o_orderstatus = 'F'
        UNION ALL SELECT c_custkey, 0, NULL, NULL, NULL, NULL FROM {{customer}} c LEFT JOIN (SELECT DISTINCT o_custkey AS k FROM {{orders}} WHERE o_orderstatus = 'F') f ON f.k = c.c_custkey WHERE f.k IS NULL""",
        100_000, Extent(-120.0, 20.0, -56.0, 52.0), ("orders", "customer"),
    ),
    "obs_li": Dataset(
        f"""SELECT (((l_orderkey * 8 + l_linenumber) * 32768 + l_partkey % 32768) * 1024 + l_suppkey % 1024) * 1024 + {_extended} % 1024 AS id,
        1 AS kind, 0 AS part_no, 0 AS coord_no,
        ((l_suppkey * 7919 + l_partkey * 13) % 3600) * 1000 - 1800000 + {_extended} % 1000 AS xi, (l_partkey * 104729 % 1800) * 1000 - 900000 + l_orderkey * 31 % 1000 AS yi FROM {{lineitem}}""",
        10_000, WORLD, ("lineitem",),
    ),
}

#: Kinds by customer for run-length coding; -1 is a null geometry.
MIX = """SELECT c_custkey AS id, CASE WHEN c_custkey % 8 = 7 THEN -1 WHEN o.k IS NULL THEN 0 ELSE c_custkey % 8 END AS kind
FROM {customer} LEFT JOIN (SELECT DISTINCT o_custkey AS k FROM {orders}) o ON o.k = c_custkey"""
WINDOWS = """SELECT s_suppkey, CAST((s_suppkey * 7919 % 3600) * 1000 - 1800000 AS DOUBLE) / 10000 - (5 + s_nationkey) AS qx0, CAST((s_suppkey * 104729 % 1800) * 1000 - 900000 AS DOUBLE) / 10000 - (3 + s_nationkey) AS qy0,
CAST((s_suppkey * 7919 % 3600) * 1000 - 1800000 AS DOUBLE) / 10000 + (5 + s_nationkey) AS qx1, CAST((s_suppkey * 104729 % 1800) * 1000 - 900000 AS DOUBLE) / 10000 + (3 + s_nationkey) AS qy1 FROM {supplier}"""
RECTS = {"small": (91.8, -48.0, 93.6, -45.0), "medium": (18.0, -54.0, 36.0, -18.0), "far": (500.0, 500.0, 501.0, 501.0)}
# Six geometries with their leaf coordinates, part by part.
EXAMPLES = {
    "g1": (1, [[(3, 2)]]),
    "g2": (2, [[(1, 1), (2, 3), (1, 4)]]),
    "g3": (3, [[(1, 1), (2, 4), (5, 5), (5, 1), (1, 1)], [(3, 2), (4, 2), (4, 3)]]),
    "g4": (4, [[(1, 3)], [(2, 4)], [(4, 3)]]),
    "g5": (5, [[(1, 1), (4, 1), (3, 2)], [(3, 3), (2, 4), (1, 3)]]),
    "g6": (6, [[(2, 4), (5, 5), (5, 2), (3, 2), (2, 4)], [(3, 3), (4, 3), (4, 4), (3, 3)], [(1, 1), (1, 2), (3, 1), (1, 1)]]),
}
#: Place, stretch of both axes and example of every event; a view has no geometry of its own where nulls and empty collections are asked for.
PLACES = f"""SELECT event_id AS id, event_type = 'view' AS is_view, CAST(event_id % 6 + 1 AS INT) AS kind,
(user_id * 7919 % 3600) * 1000 - 1800000 AS x0, (user_id * 104729 % 1800) * 1000 - 900000 AS y0, 1 + event_id * 613 % 100 AS w, 1 + {_value} * 31 % 100 AS h FROM {{events}}"""


def run_sql(spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
    names = [t for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "embeddings") if "{" + t + "}" in sql]
    return spark.sql(sql, **{t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in names})


def duck(sql: str) -> str:
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "embeddings"):
        sql = sql.replace("{" + t + "}", t)
    return sql


def points_sql(name: str) -> str:
    d = DATASETS[name]
    return f"SELECT id, kind, part_no, coord_no, CAST(xi AS DOUBLE) / {d.scale} AS x, CAST(yi AS DOUBLE) / {d.scale} AS y FROM ({d.sql}) leaf"


def leaves(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return run_sql(spark, sf_dir, points_sql(name))


def dataset(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(id, geometry)."""
    d = leaves(spark, sf_dir, name)
    return d.select("id", build.point("x", "y").alias("geometry")) if name.startswith("obs") else build.assemble(d)


def literal_examples(spark: SparkSession) -> DataFrame:
    rows = [(g, {"type": k, "parts": [[{"x": float(x), "y": float(y)} for x, y in p] for p in parts]}) for g, (k, parts) in EXAMPLES.items()]
    from pyspark.sql import types as T

    return spark.createDataFrame(rows, T.StructType([T.StructField("gid", T.StringType()), T.StructField("geometry", build.geometry_type())]))


def examples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, is_view, geometry, place): the six examples, one at the place of each event, stretched by its numbers."""
    shapes = F.array(*[F.array(*[F.array(*[build.coordinate(F.lit(x), F.lit(y)) for x, y in p]) for p in parts]) for _, parts in EXAMPLES.values()])
    at = lambda x, y: build.coordinate((F.col("x0") + x * F.col("w")).cast("double") / 10_000, (F.col("y0") + y * F.col("h")).cast("double") / 10_000)
    parts = F.transform(F.element_at(shapes, F.col("kind")), lambda p: F.transform(p, lambda c: at(c["x"], c["y"])))
    return run_sql(spark, sf_dir, PLACES).select("id", "is_view", F.struct(F.col("kind").alias("type"), parts.alias("parts")).alias("geometry"), at(F.lit(0), F.lit(0)).alias("place"))


__all__ = ["DATASETS", "EXAMPLES", "F", "MIX", "PLACES", "RECTS", "RINGS", "WINDOWS", "dataset", "duck", "examples", "leaves", "literal_examples", "points_sql", "run_sql", "scratch_path"]
