"""The registered queries, each with DuckDB SQL for the same rows where SQL can express them.

Page sizes are those of small inputs (1,024 rows); the writer's own default is 1 MiB.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .functions import build, geom
from .functions.curve import curve_key
from .operators import box_join, cost, index, sorting, stats
from .plans import fixtures as X
from .plans import oracles as O
from .sources import baselines, geojson, page_table, shapefile, wkb
from .sources import sql as sql_functions
from .streaming import events as streams

PAGE = 1024
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
SETS = ("obs", "traj", "roads", "bldg", "lots")
ORDERS = ("none", "z", "hilbert")


def add(name: str, query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle is not None:
        ORACLES[name] = X.duck(oracle)


def _read(spark, sf_dir, name):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


# geometry layout


def _worked(spark, sf_dir):
    d = build.shred(X.examples(spark, sf_dir))
    return d.select("id", F.concat(F.lit("g"), "kind").alias("gid"), "kind", "part_no", "coord_no", "rep_level", "def_level", "x", "y")


_rows = [(k, i, j, 2 if j else 1 if i else 0, 2, x, y) for k, parts in X.EXAMPLES.values() for i, p in enumerate(parts) for j, (x, y) in enumerate(p)]
add("worked_examples", _worked, f"""SELECT id, concat('g', v.kind) AS gid, v.kind, part_no, coord_no, rep_level, def_level, CAST(x0 + i * w AS DOUBLE) / 10000 AS x, CAST(y0 + j * h AS DOUBLE) / 10000 AS y
    FROM ({X.PLACES}) p JOIN (VALUES {', '.join(map(str, _rows))}) v(kind, part_no, coord_no, rep_level, def_level, i, j) ON v.kind = p.kind""")


def _shred(name, spark, sf_dir):
    return build.shred(X.dataset(spark, sf_dir, name))


def _roundtrip(name, spark, sf_dir):
    g = build.assemble(build.shred(X.dataset(spark, sf_dir, name)))
    return g.select("id", F.col("geometry.type").alias("kind"), geom.n_parts(F.col("geometry")).alias("n_parts"), geom.n_coords(F.col("geometry")).alias("n_coords"))


for _n in SETS:
    add(f"shred_{_n}", partial(_shred, _n), f"SELECT id, kind, part_no, coord_no, CASE WHEN coord_no > 0 THEN 2 WHEN part_no > 0 THEN 1 ELSE 0 END AS rep_level, CASE WHEN part_no IS NULL THEN 0 ELSE 2 END AS def_level, x, y FROM ({X.points_sql(_n)}) p")
    add(f"roundtrip_shred_{_n}", partial(_roundtrip, _n), f"SELECT id, kind, count(DISTINCT part_no)::INT AS n_parts, count(x)::INT AS n_coords FROM ({X.points_sql(_n)}) p GROUP BY ALL")


def _summary(spark, sf_dir):
    out = []
    for n in (*SETS, "obs_li"):
        g = X.leaves(spark, sf_dir, n).groupBy("id").agg(F.max("kind").alias("kind"), F.count_distinct("part_no").alias("parts"), F.count("x").alias("coords"))
        out.append(g.agg(F.lit(n).alias("dataset"), F.count("*").alias("n_geoms"), F.sum("parts").alias("n_parts"), F.sum("coords").alias("n_coords"), F.max("kind").alias("kind")).select("dataset", "n_geoms", "n_parts", "n_coords", "kind"))
    first, *rest = out
    for r in rest:
        first = first.unionByName(r)
    return first


add("dataset_summary", _summary, " UNION ALL ".join(f"SELECT '{n}' AS dataset, count(*) AS n_geoms, sum(parts)::BIGINT AS n_parts, sum(coords)::BIGINT AS n_coords, max(kind) AS kind FROM (SELECT id, max(kind) AS kind, count(DISTINCT part_no) AS parts, count(x) AS coords FROM ({X.points_sql(n)}) p GROUP BY id) g" for n in (*SETS, "obs_li")))


def _orientation(spark, sf_dir):
    """On whole-number coordinates, so that areas are exact."""
    d = X.run_sql(spark, sf_dir, X.DATASETS["bldg"].sql).select("id", "kind", "part_no", "coord_no", F.col("xi").cast("double").alias("x"), F.col("yi").cast("double").alias("y"))
    r = build.assemble(d).select("id", F.posexplode("geometry.parts").alias("ring_no", "ring"))
    return r.select("id", "ring_no", build.doubled_area(F.col("ring")).cast("long").alias("doubled_area"), build.is_clockwise(F.col("ring")).alias("is_cw"))


_area = "(SELECT id, part_no AS ring_no, sum(xi * ny - nx * yi)::BIGINT AS doubled_area FROM (SELECT *, lead(xi) OVER r AS nx, lead(yi) OVER r AS ny FROM ({sql}) l WINDOW r AS (PARTITION BY id, part_no ORDER BY coord_no)) GROUP BY ALL)"
add("ring_orientation", _orientation, "SELECT *, doubled_area < 0 AS is_cw FROM " + _area.replace("{sql}", X.DATASETS["bldg"].sql) + " a")


def _split(spark, sf_dir):
    g = X.dataset(spark, sf_dir, "lots").where("geometry.type = 6")
    p = build.split_polygons(F.col("geometry.parts"))
    return g.select(F.col("id").alias("c_custkey"), F.size(p).alias("n_polygons"), F.aggregate(p, F.lit(0), lambda a, q: a + F.size(q) - 1).alias("n_holes"))


add("multipolygon_split", _split, "SELECT o_custkey AS c_custkey, count(*)::INT AS n_polygons, count(*) FILTER (o_orderkey % 10 = 0)::INT AS n_holes FROM {orders} WHERE o_orderstatus = 'F' AND o_custkey IN (SELECT c_custkey FROM {customer}) GROUP BY o_custkey")


def _states(spark, sf_dir):
    d = X.run_sql(spark, sf_dir, X.MIX)
    g = F.when(F.col("kind") == 0, build.empty()).when(F.col("kind") > 0, build.point(F.lit(1.0), F.lit(2.0)))
    g = d.withColumn("geometry", g)
    return g.groupBy(F.when(F.col("geometry").isNull(), "null").when(geom.is_empty(F.col("geometry")), "empty").otherwise("present").alias("state")).agg(F.count("*").alias("cnt"))


add("empty_null_counts", _states, f"SELECT CASE kind WHEN -1 THEN 'null' WHEN 0 THEN 'empty' ELSE 'present' END AS state, count(*) AS cnt FROM ({X.MIX}) m GROUP BY ALL")


def _collections(spark, sf_dir, whole=False):
    c = _read(spark, sf_dir, "customer").join(_read(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey")).distinct(), "c_custkey", "left_semi")
    p, line = build.point(F.lit(1.0), F.lit(2.0)), build.linestring(F.array(build.coordinate(F.lit(0.0), F.lit(0.0)), build.coordinate(F.lit(1.0), F.lit(1.0))))
    ring = F.array(*[build.coordinate(F.lit(float(x)), F.lit(float(y))) for x, y in ((0, 0), (0, 1), (1, 1), (1, 0))])
    poly, none = build.polygon(F.array(ring)), F.lit(None).cast(build.geometry_type())
    deep = F.col("c_custkey") % 10 == 0
    node = lambda i, parent, o, g: F.struct(F.lit(i).alias("node_id"), (F.lit(parent) if not hasattr(parent, "cast") else parent).cast("int").alias("parent_id"), F.lit(o).alias("ord"), g.alias("geometry"))
    rows = F.array(node(0, F.lit(None), 0, none), node(1, 0, 0, p), node(2, 0, 1, poly), node(3, 0, 2, none), node(5, F.when(deep, 4).otherwise(3), 0, line), node(6, F.when(deep, 4).otherwise(3), 1, p))
    rows = F.when(deep, F.concat(rows, F.array(node(4, 3, 0, none)))).otherwise(rows)
    edges = c.select(F.col("c_custkey").alias("root_id"), F.explode(rows).alias("r")).select("root_id", "r.*")
    flat = build.flatten_collections(edges)
    if whole:
        return flat.groupBy("root_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "geometry"))), lambda v: v["geometry"]).alias("members"))
    return flat.select("root_id", "pos", F.col("geometry.type").alias("kind"))


add("collection_flatten", _collections, "SELECT o_custkey AS root_id, pos, kind FROM (SELECT DISTINCT o_custkey FROM {orders} WHERE o_custkey IN (SELECT c_custkey FROM {customer})) o CROSS JOIN (VALUES (0, 1), (1, 3), (2, 2), (3, 1)) v(pos, kind)")


def _levels(spark, sf_dir):
    """Bits of levels that each leaf costs, by variant of the type: those of one value, and how many they are in the examples of all events."""
    g, view, place = F.col("geometry"), F.col("is_view"), F.col("place")
    lifted = F.transform(g["parts"], lambda p: F.transform(p, lambda c: F.struct(c["x"], c["y"], (c["x"] + c["y"]).alias("z"))))
    required, floats, collection = build.geometry_type(), build.geometry_type(coord="float"), build.collection_type()
    variants = {
        "required": (g, required, False),
        "three_axes": (F.struct(g["type"].alias("type"), lifted.alias("parts")), build.geometry_type(3), False),
        "floats": (g.cast(floats.simpleString()), floats, False),
        "collection": (F.when(view, F.array().cast(collection.simpleString())).otherwise(F.array(build.point(place["x"], place["y"]), g)), collection, False),
        "optional": (F.when(view, None).otherwise(g), required, True),
    }
    d = X.examples(spark, sf_dir).select(*[c.alias(v) for v, (c, _, _) in variants.items()])
    leaves = [(v, leaf, *build.level_bits(t, null)[leaf], n) for v, (_, t, null) in variants.items() for leaf, n in build.level_entries(F.col(v), t).items()]
    d = d.agg(*[F.coalesce(F.sum(n), F.lit(0)).alias(f"n{i}") for i, (*_, n) in enumerate(leaves)])
    rows = [F.struct(*[F.lit(c).alias(a) for a, c in zip(("variant", "leaf", "rep_bits", "def_bits"), r, strict=False)], F.col(f"n{i}").alias("n_levels")) for i, r in enumerate(leaves)]
    d = d.select(F.explode(F.array(*rows)).alias("r")).select("r.*")
    return d.withColumn("level_bits", F.col("n_levels") * (F.col("rep_bits") + F.col("def_bits")))


# Two bits of repetition and two of definition level for each coordinate value
_levels_rows = [(v, leaf, *((0, 0) if leaf == "type" else (2, 2))) for v, axes in (("required", "xy"), ("three_axes", "xyz"), ("floats", "xy")) for leaf in ("type", *(f"parts.{a}" for a in axes))]
_levels_rows += [("collection", "type", 1, 1), ("collection", "parts.x", 2, 2), ("collection", "parts.y", 2, 2), ("optional", "type", 0, 1), ("optional", "parts.x", 2, 2), ("optional", "parts.y", 2, 2)]
_coords = ", ".join(f"({k}, {sum(map(len, parts))})" for k, parts in X.EXAMPLES.values())
add("level_bits", _levels, f"""WITH e AS (SELECT p.is_view, v.coords FROM ({X.PLACES}) p JOIN (VALUES {_coords}) v(kind, coords) ON v.kind = p.kind),
    t AS (SELECT count(*) AS geometries, coalesce(sum(coords), 0) AS vertices, coalesce(sum(CASE WHEN is_view THEN 1 ELSE 2 END), 0) AS members,
    coalesce(sum(CASE WHEN is_view THEN 1 ELSE 1 + coords END), 0) AS member_vertices, coalesce(sum(CASE WHEN is_view THEN 1 ELSE coords END), 0) AS some_vertices FROM e),
    n AS (SELECT v.*, CAST(CASE WHEN variant = 'collection' THEN CASE WHEN leaf = 'type' THEN members ELSE member_vertices END WHEN leaf = 'type' THEN geometries
    WHEN variant = 'optional' THEN some_vertices ELSE vertices END AS BIGINT) AS n_levels FROM (VALUES {', '.join(map(str, _levels_rows))}) v(variant, leaf, rep_bits, def_bits) CROSS JOIN t)
    SELECT *, n_levels * (rep_bits + def_bits) AS level_bits FROM n""")


def _multipoints(spark, sf_dir):
    """Points in parts of their own, and all in one part: the same leaves."""
    g = X.dataset(spark, sf_dir, "traj").select("id", F.flatten("geometry.parts").alias("c"))
    own, one = build.multipoint(F.col("c")), build.multipoint(F.col("c"), one_part=True)
    return g.select("id", geom.n_parts(own).alias("parts_each"), geom.n_parts(one).alias("parts_one"), geom.n_coords(own).alias("coords_each"), geom.n_coords(one).alias("coords_one"))


add("multipoint_variants", _multipoints, f"SELECT id, count(x)::INT AS parts_each, 1 AS parts_one, count(x)::INT AS coords_each, count(x)::INT AS coords_one FROM ({X.points_sql('traj')}) p GROUP BY id")


def _representatives(spark, sf_dir):
    """Places by which lines are sorted: centre of the box, first vertex, mean of vertices (on whole numbers, so that sums are exact)."""
    d = X.run_sql(spark, sf_dir, X.DATASETS["roads"].sql).select("id", "kind", "part_no", "coord_no", F.col("xi").cast("double").alias("x"), F.col("yi").cast("double").alias("y"))
    g = build.assemble(d)
    at = {how: geom.centre(F.col("geometry"), how) for how in ("box", "first", "mean")}
    return g.select("id", *[c[a].alias(f"{how}_{a}") for how, c in at.items() for a in "xy"])


add("representative_points", _representatives, "SELECT id, " + ", ".join(f"(min({a}i) + max({a}i))::DOUBLE / 2 AS box_{a}, arg_min({a}i, part_no * 1000 + coord_no)::DOUBLE AS first_{a}, sum({a}i)::DOUBLE / count(*) AS mean_{a}" for a in "xy") + f" FROM ({X.DATASETS['roads'].sql}) l GROUP BY id")


def _validate(spark, sf_dir):
    d = X.dataset(spark, sf_dir, "bldg").select("geometry").unionByName(X.literal_examples(spark).select("geometry"))
    v = d.select(geom.validate(F.col("geometry")).alias("v"))
    return v.select(F.explode(F.when(F.size("v") > 0, F.col("v")).otherwise(F.array(F.lit("valid")))).alias("code")).groupBy("code").agg(F.count("*").alias("cnt"))


add("validate_rings", _validate, "SELECT 'valid' AS code, count(*) + 5 AS cnt FROM {orders} JOIN {customer} ON o_custkey = c_custkey UNION ALL SELECT 'unclosed', 1 UNION ALL SELECT 'short_ring', 1")


# kinds


def _runs(by_kind, spark, sf_dir):
    d = X.run_sql(spark, sf_dir, X.MIX)
    d = sorting.numbered(d, [F.col(c) for c in (("kind", "id") if by_kind else ("id",))]).withColumn("page", F.floor(F.col("pos") / PAGE))
    return stats.encode_runs(d, "kind", "pos", ["page"]).selectExpr("page", "cast(run_no as long) as run_no", "cnt", "cast(kind as int) as kind")


for _n, _o in (("kind_runs", "id"), ("kind_runs_sorted", "kind, id")):
    add(_n, partial(_runs, _n.endswith("sorted")), f"""WITH m AS ({X.MIX}), p AS (SELECT kind, row_number() OVER (ORDER BY {_o}) - 1 AS pos FROM m), q AS (SELECT *, pos // {PAGE} AS page FROM p),
    r AS (SELECT *, CASE WHEN lag(kind) OVER (PARTITION BY page ORDER BY pos) = kind THEN 0 ELSE 1 END AS nw FROM q), s AS (SELECT *, sum(nw) OVER (PARTITION BY page ORDER BY pos) - 1 AS run_no FROM r)
    SELECT page, run_no::BIGINT AS run_no, count(*) AS cnt, any_value(kind)::INT AS kind FROM s GROUP BY page, run_no""")

# codec


def _int_delta(spark, sf_dir):
    d = _read(spark, sf_dir, "events").select("event_id", F.round(F.col("value") * 100).cast("long").alias("c"))
    d = sorting.before(sorting.numbered(d, [F.col("event_id")]), "c")
    return d.select("event_id", (F.col("c") - F.coalesce("_before", F.lit(0))).alias("delta"))


add("int_delta", _int_delta,
    "SELECT event_id, c - coalesce(lag(c) OVER (ORDER BY event_id), 0) AS delta FROM (SELECT event_id, CAST(round(value * 100) AS BIGINT) AS c FROM {events})")
add("bit_view", lambda s, d: X.leaves(s, d, "obs").select("id", stats.to_bits(F.col("x")).alias("bits")), f"SELECT id, x::BIT::BIGINT AS bits FROM ({X.points_sql('obs')}) p")
add("bit_view_f32", lambda s, d: _read(s, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "v")).select("vec_id", "i", stats.to_bits32(F.col("v")).alias("bits")),
    "SELECT vec_id, generate_subscripts(embedding, 1)::INT - 1 AS i, unnest(embedding)::BIT::INTEGER AS bits FROM {embeddings}")


def _paged(spark, sf_dir, name, order, rows=PAGE):
    e = X.DATASETS[name].extent
    d = X.leaves(spark, sf_dir, name).where("x is not null")
    if order in ("none", "shuffled"):
        key = F.col("id") if order == "none" else F.col("id") * 2654435761 % 2147483648
        d = d.withColumn("key", key)
    else:
        c = d.groupBy("id").agg(((F.min("x") + F.max("x")) / 2).alias("cx"), ((F.min("y") + F.max("y")) / 2).alias("cy"))
        d = d.join(c.select("id", curve_key(order, F.col("cx"), F.col("cy"), e).alias("key")), "id")
    return stats.with_pages(d, [F.col(c) for c in ("key", "id", "part_no", "coord_no")], rows)


def _deltas(spark, sf_dir, name, order, restart=None):
    return stats.deltas(_paged(spark, sf_dir, name, order), restart=restart)


def _hist(spark, sf_dir, name, order, restart=None):
    return stats.width_histogram(_deltas(spark, sf_dir, name, order, restart), ["page", "axis"])


add("bit_delta_zigzag", lambda s, d: _deltas(s, d, "obs", "none").select("page", "ord", "axis", F.when(F.col("zigzag") < 0, F.col("zigzag").cast("decimal(20,0)") + F.lit("18446744073709551616").cast("decimal(20,0)")).otherwise(F.col("zigzag")).cast("decimal(20,0)").cast("string").alias("zigzag"), "width"),
    f"WITH {O.deltas('obs', 'none', PAGE)} SELECT page, ord, axis, z::VARCHAR AS zigzag, width FROM d")
for _n in ("obs", "bldg"):
    for _o in ORDERS:
        add(f"width_hist_{_o}_{_n}", lambda s, d, n=_n, o=_o: _hist(s, d, n, o).groupBy("axis", "width").agg(F.sum("cnt").alias("cnt")), f"WITH {O.deltas(_n, _o, PAGE)} SELECT axis, width, sum(cnt)::BIGINT AS cnt FROM hist GROUP BY ALL")


def _size_curve(spark, sf_dir):
    h = _hist(spark, sf_dir, "obs", "none")
    s = cost.page_sizes(h, ["page", "axis"], "paper")
    n, fit = F.col("s.n"), lambda n: F.aggregate(F.filter("h", lambda x: x["width"] <= n), F.lit(0).cast("long"), lambda a, x: a + x["cnt"])
    s = s.select("page", "axis", "total", "h", F.explode("sizes").alias("s"))
    return s.select("page", "axis", n.alias("n"), (n * fit(n) + (n + 64) * (F.col("total") - fit(n))).alias("size_long"), F.col("s.size").alias("size_short"))


add("size_curve", _size_curve, f"WITH {O.deltas('obs', 'none', PAGE)}, {O.sizes(False)} SELECT page, axis, n, (SELECT sum(CASE WHEN width <= n THEN n ELSE n + 64 END * cnt) FROM hist h WHERE h.page = s.page AND h.axis = s.axis)::BIGINT AS size_long, size AS size_short FROM s")


def _best(name, order, policy, spark, sf_dir):
    return cost.best_page_bits(_hist(spark, sf_dir, name, order), ["page", "axis"], policy).select("page", "axis", "n", "bits")


for _n in ("obs", "traj", "roads", "bldg"):
    for _o in ("none", "hilbert"):
        for _p in ("paper", "exact"):
            add(f"best_bits_{_p}_{_n}_{_o}", partial(_best, _n, _o, _p), f"WITH {O.deltas(_n, _o, PAGE)}, {O.sizes(_p == 'exact')}, {O.BEST} SELECT page, axis, n, bits FROM best")


def _codec_bits(orders, spark, sf_dir):
    """Bits of the coded pages (header and raw fall-back included) and of raw doubles."""
    out = None
    for n in ("obs", "traj", "roads", "bldg"):
        for o in orders:
            b = cost.best_page_bits(_hist(spark, sf_dir, n, o), ["page", "axis"])
            raw = 64 * (F.col("total") + 1)
            b = b.groupBy("axis").agg(F.sum(F.least(F.col("bits") + 72, raw)).alias("total_bits"), F.sum(raw).alias("raw_bits")).select(F.lit(n).alias("dataset"), F.lit(o).alias("order"), "axis", "total_bits", "raw_bits")
            out = b if out is None else out.unionByName(b)
    return out


def _codec_bits_sql(orders):
    return " UNION ALL ".join(f"SELECT * FROM (WITH {O.deltas(n, o, PAGE)}, {O.sizes(True)}, {O.BEST} SELECT '{n}' AS dataset, '{o}' AS \"order\", axis, sum(least(bits + 72, 64 * (total + 1)))::BIGINT AS total_bits, sum(64 * (total + 1))::BIGINT AS raw_bits FROM best GROUP BY axis)" for n in ("obs", "traj", "roads", "bldg") for o in orders)


for _n, _o in (("unsorted", ("none",)), ("sorted", ("z", "hilbert")), ("shuffled", ("shuffled",))):
    add(f"codec_bits_{_n}", partial(_codec_bits, _o), _codec_bits_sql(_o))


def _payload(orders, spark, sf_dir):
    """Bytes that the encoder writes for the pages of the relational model."""
    out = None
    for n in ("obs", "traj", "roads", "bldg"):
        for o in orders:
            v = stats.page_values(_paged(spark, sf_dir, n, o))
            b = v.agg(F.lit(n).alias("dataset"), F.lit(o).alias("order"), *[F.sum(stats.encoded(F.col(a))["coded"]).alias(f"{a}_bytes") for a in "xy"])
            out = b if out is None else out.unionByName(b)
    return out


def _payload_sql(orders):
    one = "sum((least(bits + 72, 64 * (total + 1)) + 7) // 8) FILTER (axis = '{a}')::BIGINT AS {a}_bytes"
    return " UNION ALL ".join(f"SELECT * FROM (WITH {O.deltas(n, o, PAGE)}, {O.sizes(True)}, {O.BEST} SELECT '{n}' AS dataset, '{o}' AS \"order\", {', '.join(one.format(a=a) for a in 'xy')} FROM best)" for n in ("obs", "traj", "roads", "bldg") for o in orders)


for _o in ORDERS:
    add(f"payload_bytes_{_o}", partial(_payload, (_o,)), _payload_sql((_o,)))


def _ablation(spark, sf_dir):
    """Bytes of all pages by set and order: plain or coded, with and without gzip for each page."""
    out = None
    for n in ("obs", "traj", "roads", "bldg"):
        for o in ORDERS:
            v = stats.page_values(_paged(spark, sf_dir, n, o)).select(F.explode(F.array(*[stats.encoded(F.col(a)) for a in "xy"])).alias("s")).select("s.*")
            b = v.agg(F.lit(n).alias("dataset"), F.lit(o).alias("order"), *[F.sum(c).alias(c) for c in ("plain", "plain_gzip", "coded", "coded_gzip")])
            out = b if out is None else out.unionByName(b)
    return out


def _ablation_wins(spark, sf_dir):
    """The codec makes every set smaller, with gzip and without, but points in no order."""
    return _ablation(spark, sf_dir).select("dataset", "order", "plain", (F.col("coded") < F.col("plain")).alias("codec_wins"), (F.col("coded_gzip") < F.col("plain_gzip")).alias("codec_wins_gzip"))


add("size_ablation", _ablation)
add("size_ablation_wins", _ablation_wins, " UNION ALL ".join(f"SELECT '{n}' AS dataset, '{o}' AS \"order\", (SELECT 16 * count(x) FROM ({X.points_sql(n)}) p)::BIGINT AS plain, {str((n, o) != ('obs', 'none')).lower()} AS codec_wins, {str((n, o) != ('obs', 'none')).lower()} AS codec_wins_gzip" for n in ("obs", "traj", "roads", "bldg") for o in ORDERS))


def _rle_gain(spark, sf_dir):
    """Bits of the coded pages of points without and with run-length coding of the codes."""
    out = None
    for o in ORDERS:
        v = stats.page_values(_paged(spark, sf_dir, "obs", o)).select(F.explode(F.array(*[F.struct(F.lit(a).alias("axis"), stats.encoded(F.col(a))["coded_bits"].alias("p"), stats.encoded(F.col(a), rle=True)["coded_bits"].alias("r")) for a in "xy"])).alias("s"))
        b = v.groupBy("s.axis").agg(F.sum("s.p").alias("plain_bits"), F.sum("s.r").alias("rle_bits")).select(F.lit(o).alias("order"), "axis", "plain_bits", "rle_bits")
        out = b if out is None else out.unionByName(b)
    return out


def _rle_gain_sql(o):
    return f"""SELECT * FROM (WITH {O.deltas('obs', o, PAGE)}, {O.sizes(True)}, {O.BEST},
    c AS (SELECT page, axis, ord, z, n, total, bits, n > 0 AND z >= CAST(power(2, n) AS HUGEINT) - 1 AS esc FROM d JOIN best USING (page, axis)),
    r AS (SELECT *, CASE WHEN esc OR coalesce(lag(esc) OVER w, true) OR z <> lag(z) OVER w THEN 1 ELSE 0 END AS nw FROM c WINDOW w AS (PARTITION BY page, axis ORDER BY ord)),
    g AS (SELECT page, axis, least(any_value(bits) + 72, 64 * (any_value(total) + 1)) AS p, CASE WHEN any_value(n) = 0 THEN 72 ELSE 104 + (any_value(n) + 32) * sum(nw) + 64 * count(*) FILTER (esc) END AS r FROM r GROUP BY page, axis)
    SELECT '{o}' AS "order", axis, sum(p)::BIGINT AS plain_bits, sum(least(p, r))::BIGINT AS rle_bits FROM g GROUP BY axis)"""


add("rle_gain", _rle_gain, " UNION ALL ".join(map(_rle_gain_sql, ORDERS)))


def _raw_repeats(spark, sf_dir):
    """What a store can do with uncoded doubles: bytes plain, by a dictionary and by runs of equal values, page by page."""
    out = None
    for n in ("obs", "traj", "roads", "bldg"):
        p = _paged(spark, sf_dir, n, "none").select("page", "ord", F.explode(F.array(*[F.struct(F.lit(a).alias("axis"), stats.to_bits(F.col(a)).alias("v")) for a in "xy"])).alias("s")).select("page", "ord", "s.*")
        p = p.withColumn("new", F.when(F.lag("v").over(W.partitionBy("page", "axis").orderBy("ord")) == F.col("v"), 0).otherwise(1))
        g = p.groupBy("page", "axis").agg(F.count("*").alias("n"), F.count_distinct("v").alias("d"), F.sum("new").alias("r"))
        bits = F.when(F.col("d") > 1, F.length(F.bin(F.col("d") - 1))).otherwise(0)
        b = g.groupBy("axis").agg(F.sum(8 * F.col("n")).alias("plain"), F.sum(8 * F.col("d") + F.floor((F.col("n") * bits + 7) / 8)).alias("by_dictionary"), F.sum(12 * F.col("r")).alias("by_runs")).select(F.lit(n).alias("dataset"), "*")
        out = b if out is None else out.unionByName(b)
    return out


def _raw_repeats_sql(n):
    return f"""SELECT * FROM (WITH {O.deltas(n, 'none', PAGE)}, v2 AS (SELECT page, axis, v, CASE WHEN lag(v) OVER (PARTITION BY page, axis ORDER BY ord) = v THEN 0 ELSE 1 END AS nw FROM bv),
    g AS (SELECT page, axis, count(*) AS n, count(DISTINCT v) AS d, sum(nw) AS r FROM v2 GROUP BY ALL)
    SELECT '{n}' AS dataset, axis, sum(8 * n)::BIGINT AS plain, sum(8 * d + (n * CASE WHEN d > 1 THEN length(ltrim((d - 1)::UBIGINT::BIT::VARCHAR, '0')) ELSE 0 END + 7) // 8)::BIGINT AS by_dictionary, sum(12 * r)::BIGINT AS by_runs FROM g GROUP BY axis)"""


add("raw_repeats", _raw_repeats, " UNION ALL ".join(_raw_repeats_sql(n) for n in ("obs", "traj", "roads", "bldg")))


def _measures(spark, sf_dir):
    """Hundredths of a bit for each coordinate value, and sizes of rivals in thousandths of the coded pages."""
    own = _payload(("hilbert",), spark, sf_dir).select("dataset", (F.col("x_bytes") + F.col("y_bytes")).alias("own"))
    d = own.join(_sizes(spark, sf_dir), "dataset")
    ratio = lambda c: F.floor(F.col(c) * 1000 / F.col("own"))
    return d.select("dataset", F.floor(F.col("own") * 6400 / F.col("raw_bytes")).alias("bits_e2"), ratio("wkbbox_bytes").alias("wkbbox_e3"), ratio("shp_bytes").alias("shp_e3"), ratio("raw_bytes").alias("raw_e3"))


def _sort_bound(spark, sf_dir):
    """Rows of the largest sort group: never more than asked for."""
    d = sorting.grouped(sorting.with_key(X.dataset(spark, sf_dir, "obs").repartition(3), "hilbert"), 500)
    g = d.groupBy(F.spark_partition_id().alias("p"), "_group").agg(F.count("*").alias("n"))
    return g.agg(F.sum("n").alias("n"), F.max("n").alias("most"))


#: Page tables that this session has written already.
_TABLES: dict[tuple, str] = {}


def _written(spark, sf_dir, name, **options):
    """Path of a page table of a stand-in, written once a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name, *sorted(options.items()))
    if key not in _TABLES:
        path = X.scratch_path(spark, f"pages_{name}")
        page_table.save(X.dataset(spark, sf_dir, name), path, extent=X.DATASETS[name].extent, **({"page_bytes": 16 << 10, "group_size": 5000} | options))
        _TABLES[key] = path
    return _TABLES[key]


def _same(got, want, axes="xy", bits=stats.to_bits):
    """Leaves of ``want`` (id, part_no, coord_no, axes) that the geometries ``got`` have lost, and those they have made up, bit by bit."""
    key = ["id", "part_no", "coord_no"]
    g = got.select("id", F.posexplode("geometry.parts").alias("part_no", "part")).select("id", "part_no", F.posexplode("part").alias("coord_no", "c"))
    g = g.select(*key, F.struct(*[bits(F.col(f"c.{a}")).alias(a) for a in axes]).alias("got"))
    w = want.where("x is not null").select(*key, F.struct(*[bits(F.col(a)).alias(a) for a in axes]).alias("want"))
    d = g.join(w, key, "full_outer")
    other = ~F.col("got").eqNullSafe(F.col("want"))
    return d.agg(F.count("got").alias("n_coords"), F.count_if(other & F.col("want").isNotNull()).alias("lost"), F.count_if(other & F.col("got").isNotNull()).alias("made"))


def _codec_roundtrip(name, options, spark, sf_dir):
    path = _written(spark, sf_dir, name, **options)
    return _same(page_table.scan(spark, path, stream=options.get("stream", "split")), X.leaves(spark, sf_dir, name))


for _n in SETS:
    add(f"codec_roundtrip_{_n}", partial(_codec_roundtrip, _n, {}), f"SELECT count(x) AS n_coords, 0::BIGINT AS lost, 0::BIGINT AS made FROM ({X.points_sql(_n)}) p")
for _k, _v in {"interleaved": {"stream": "interleaved"}, "rle": {"rle": True}, "fixed": {"policy": "fixed", "fixed_bits": 40}, "plain": {"codec_name": "plain"}, "total": {"sort": "total"}, "rectangles": {"sort": "rectangles"}, "z": {"curve": "z"}, "unsorted": {"sort": "none"}}.items():
    add(f"codec_roundtrip_obs_{_k}", partial(_codec_roundtrip, "obs", _v), f"SELECT count(x) AS n_coords, 0::BIGINT AS lost, 0::BIGINT AS made FROM ({X.points_sql('obs')}) p")


def _ordered_bits(name, spark, sf_dir):
    path = X.scratch_path(spark, f"bits_{name}")
    baselines.save_ordered_bits(X.dataset(spark, sf_dir, name), path)
    return _same(baselines.read_ordered_bits(spark, path), X.leaves(spark, sf_dir, name))


def _emb32(spark, sf_dir):
    """Geometries of 32-bit numbers, a vertex from each two elements."""
    e = F.col("embedding").cast("array<float>")
    vertex = lambda j: F.array(F.struct(F.get(e, 2 * j).alias("x"), F.get(e, 2 * j + 1).alias("y")))
    return _read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.struct(F.lit(4).alias("type"), F.transform(F.sequence(F.lit(0), F.floor(F.size(e) / 2).cast("int") - 1), vertex).alias("parts")).alias("geometry"))


def _roundtrip_32(spark, sf_dir):
    d, path = _emb32(spark, sf_dir), X.scratch_path(spark, "emb32")
    page_table.save(d, path, sort="none", page_bytes=4 << 10)
    g = page_table.scan(spark, path)
    leaf = d.select("id", F.posexplode("geometry.parts").alias("part_no", "part")).select("id", "part_no", F.lit(0).alias("coord_no"), "part.x", "part.y").withColumns({a: F.get(a, F.lit(0)) for a in "xy"})
    return _same(g, leaf, bits=stats.to_bits32)


add("codec_roundtrip_emb32", _roundtrip_32, "SELECT sum(len(embedding) // 2)::BIGINT AS n_coords, 0::BIGINT AS lost, 0::BIGINT AS made FROM {embeddings}")


def _roundtrip_xyz(spark, sf_dir):
    leaf, path = X.leaves(spark, sf_dir, "bldg").withColumn("z", F.col("x") * F.col("coord_no") - F.col("y")), X.scratch_path(spark, "xyz")
    page_table.save(build.assemble(leaf, axes=("x", "y", "z")), path, extent=X.DATASETS["bldg"].extent, page_bytes=16 << 10)
    return _same(page_table.scan(spark, path), leaf, "xyz")


add("codec_roundtrip_xyz", _roundtrip_xyz, ORACLES["codec_roundtrip_bldg"])


def _appended(spark, sf_dir):
    """Half of a set, then the other half added."""
    d, path = X.dataset(spark, sf_dir, "bldg"), X.scratch_path(spark, "appended")
    page_table.save(d.where("id % 2 = 0"), path, page_bytes=16 << 10, extent=X.DATASETS["bldg"].extent)
    page_table.append(d.where("id % 2 = 1"), path, page_bytes=16 << 10, extent=X.DATASETS["bldg"].extent)
    return _same(page_table.scan(spark, path), X.leaves(spark, sf_dir, "bldg"))


add("append_pages", _appended, ORACLES["codec_roundtrip_bldg"])


def _compact(spark, sf_dir):
    """Small unsorted pages of sixteen partitions made into full ones."""
    d, path = X.dataset(spark, sf_dir, "bldg"), X.scratch_path(spark, "compacted")
    small = X.scratch_path(spark, "small_pages")
    page_table.save(d.repartition(16), small, sort="none", page_bytes=1 << 10)
    page_table.compact(spark, small, path, extent=X.DATASETS["bldg"].extent)
    pages = lambda p, n: spark.read.parquet(p).agg(F.count("*").alias(n))
    fewer = pages(path, "after").join(pages(small, "before")).select((F.col("after") < F.col("before")).alias("fewer_pages"))
    return _same(page_table.scan(spark, path), X.leaves(spark, sf_dir, "bldg")).join(fewer)


for _n in SETS:
    add(f"ordered_bits_{_n}", partial(_ordered_bits, _n), ORACLES[f"codec_roundtrip_{_n}"])
add("compact_pages", _compact, f"SELECT count(x) AS n_coords, 0::BIGINT AS lost, 0::BIGINT AS made, true AS fewer_pages FROM ({X.points_sql('bldg')}) p")


def _fixed(spark, sf_dir):
    """Bits at every fixed width, marker codes escaped."""
    h = _hist(spark, sf_dir, "obs", "hilbert").groupBy("width").agg(F.sum("cnt").alias("cnt"), F.sum("markers").alias("markers")).withColumn("all", F.lit(1))
    s = cost.page_sizes(h, ["all"], "exact").select(F.explode("sizes").alias("s"))
    return s.select("s.n", F.col("s.size").alias("total_bits"))


add("fixed_bits_sweep", _fixed, f"WITH {O.deltas('obs', 'hilbert', PAGE)}, {O.sizes(True)} SELECT n, (n * (SELECT sum(cnt) FROM hist) + 64 * coalesce((SELECT sum(cnt) FROM hist WHERE width > n), 0) + 64 * coalesce((SELECT sum(markers) FROM hist WHERE width = n), 0))::BIGINT AS total_bits FROM range(1, 65) r(n)")


add("empirical_bits", lambda s, d: stats.empirical_bits(_paged(s, d, "obs", "hilbert"), 1.0),
    f"WITH {O.deltas('obs', 'hilbert', PAGE)}, w AS (SELECT axis, n, (n * sum(cnt) + 64 * coalesce(sum(cnt) FILTER (width > n), 0) + 64 * coalesce(sum(markers) FILTER (width = n), 0))::BIGINT AS bits FROM hist, range(1, 65) r(n) GROUP BY axis, n) SELECT axis, arg_min(n, bits * 100 + n) AS n, min(bits) AS bits FROM w GROUP BY axis")


def _restart(spark, sf_dir):
    out = None
    for n in ("traj", "roads"):
        h = _hist(spark, sf_dir, n, "none", "id")
        b = cost.best_page_bits(h, ["page", "axis"]).groupBy("axis").agg(F.sum("bits").alias("total_bits")).select(F.lit(n).alias("dataset"), "axis", "total_bits")
        out = b if out is None else out.unionByName(b)
    return out


add("restart_geometry_bits", _restart, " UNION ALL ".join(f"SELECT * FROM (WITH {O.deltas(n, 'none', PAGE, 'id')}, {O.sizes(True)}, {O.BEST} SELECT '{n}' AS dataset, axis, sum(bits)::BIGINT AS total_bits FROM best GROUP BY axis)" for n in ("traj", "roads")))


def _zero(spark, sf_dir):
    out = None
    for o in ORDERS:
        d = _deltas(spark, sf_dir, "obs", o)
        w = W.partitionBy("page", "axis").orderBy("ord")
        d = d.withColumn("new", F.when((F.lag("zigzag").over(w) == F.col("zigzag")), 0).otherwise(1))
        b = d.groupBy("axis").agg(F.sum(F.when(F.col("width") == 0, 1).otherwise(0)).alias("n_zero"), F.sum(F.when(F.col("width") == 64, 1).otherwise(0)).alias("n_full"), F.sum("new").alias("n_runs"), F.count("*").alias("cnt"))
        b = b.select(F.lit(o).alias("order"), "axis", "n_zero", "n_full", "n_runs", "cnt")
        out = b if out is None else out.unionByName(b)
    return out


add("zero_delta_share", _zero, " UNION ALL ".join(f"SELECT * FROM (WITH {O.deltas('obs', o, PAGE)} SELECT '{o}' AS \"order\", axis, count(*) FILTER (width = 0) AS n_zero, count(*) FILTER (width = 64) AS n_full, sum(CASE WHEN pz = z THEN 0 ELSE 1 END)::BIGINT AS n_runs, count(*) AS cnt FROM (SELECT *, lag(z) OVER (PARTITION BY page, axis ORDER BY ord) AS pz FROM d) GROUP BY axis)" for o in ORDERS))


def _raw_pages(spark, sf_dir):
    b = cost.best_page_bits(_hist(spark, sf_dir, "obs", "none"), ["page", "axis"])
    return b.select("page", "axis", (F.col("bits") + 72 > 64 * (F.col("total") + 1)).alias("is_raw"))


add("raw_fallback_pages", _raw_pages, f"WITH {O.deltas('obs', 'none', PAGE)}, {O.sizes(True)}, {O.BEST} SELECT page, axis, bits + 72 > 64 * (total + 1) AS is_raw FROM best")

# curves, sorting, partitions


for _n in ("obs", "bldg"):
    for _o in ("z", "hilbert"):
        def _keys(spark, sf_dir, n=_n, o=_o):
            d = sorting.with_key(X.dataset(spark, sf_dir, n), o, extent=X.DATASETS[n].extent)
            return d.select("id", F.col("_key").alias("key"))

        add(f"{_o}_key_{_n}", _keys, f"WITH {O.keyed(_n, _o)} SELECT id, key FROM k")


def _grouped(spark, sf_dir):
    """Bounded groups by an explicit ordinal, sorted within."""
    d = sorting.with_key(X.dataset(spark, sf_dir, "obs"), "hilbert").withColumn("group", F.floor(F.col("id") / 5000))
    return d.select("id", "group", (F.row_number().over(W.partitionBy("group").orderBy("_key", "id")) - 1).cast("long").alias("pos"))


add("grouped_sort", _grouped, f"WITH {O.keyed('obs', 'hilbert')} SELECT id, id // 5000 AS \"group\", row_number() OVER (PARTITION BY id // 5000 ORDER BY key, id) - 1 AS pos FROM k")


def _total(spark, sf_dir):
    """Places in the range-partitioned order, counted partition by partition."""
    d = sorting.with_key(X.dataset(spark, sf_dir, "obs"), "hilbert").select("id", "_key")
    return sorting.numbered(d, [F.col("_key"), F.col("id")]).select("id", "pos")


add("total_sort", _total, f"WITH {O.keyed('obs', 'hilbert')} SELECT id, row_number() OVER (ORDER BY key, id) - 1 AS pos FROM k")
add("grid_partition", lambda s, d: sorting.grid(X.leaves(s, d, "obs_li"), X.DATASETS["obs_li"].extent, 16).groupBy("cell").agg(F.count("*").alias("cnt")),
    f"SELECT CAST(least(15, floor((y + 90) / 180 * 16)) * 16 + least(15, floor((x + 180) / 360 * 16)) AS BIGINT) AS cell, count(*) AS cnt FROM ({X.points_sql('obs_li')}) p GROUP BY ALL")
add("tile_partition", lambda s, d: sorting.tiles(X.leaves(s, d, "obs_li"), 8, 8).groupBy(F.col("cell").cast("int")).agg(F.count("*").alias("cnt"), F.min("x").alias("x_min"), F.max("y").alias("y_max")),
    f"SELECT slab * 8 + tile AS cell, count(*) AS cnt, min(x) AS x_min, max(y) AS y_max FROM (SELECT *, (ntile(8) OVER (PARTITION BY slab ORDER BY y, x, id) - 1)::INT AS tile FROM (SELECT *, (ntile(8) OVER (ORDER BY x, y, id) - 1)::INT AS slab FROM ({X.points_sql('obs_li')}) p)) GROUP BY ALL")


def _rstar_boxes(points, capacity, most_sampled=sorting.MOST_SAMPLED):
    d = sorting.partitioned(points, capacity, most_sampled=most_sampled)
    return d, index.page_boxes(d, ("cell",)).withColumnRenamed("cell", "page")


def _rstar(most_sampled, spark, sf_dir):
    """Rectangles keep to their capacity, hold every point once and their tight boxes share no area."""
    d, b = _rstar_boxes(X.leaves(spark, sf_dir, "obs_li").select("id", "x", "y"), 2000, most_sampled)
    q = index.quality(b).select(F.col("overlap").alias("shared_area"))
    return b.agg(F.sum("n").alias("n"), F.count_if(F.col("n") > 2000).alias("too_full")).join(q)


for _n, _k in (("rstar_partition", sorting.MOST_SAMPLED), ("rstar_partition_small_sample", 2_000)):
    add(_n, partial(_rstar, _k), "SELECT count(*) AS n, 0::BIGINT AS too_full, 0.0::DOUBLE AS shared_area FROM {lineitem}")

# index


for _n in ("obs", "obs_li"):
    for _o in ORDERS:
        add(f"page_boxes_{_o}_{_n}", lambda s, d, n=_n, o=_o: index.page_boxes(_paged(s, d, n, o)), f"WITH {O.paged(_n, _o, PAGE)} SELECT page, min(x) AS x_min, max(x) AS x_max, min(y) AS y_min, max(y) AS y_max, count(*) AS n FROM paged GROUP BY page")

for _o in ORDERS:
    def _prune(spark, sf_dir, o=_o):
        b = index.page_boxes(_paged(spark, sf_dir, "obs", o))
        w = X.run_sql(spark, sf_dir, X.WINDOWS)
        hit = index.windows_meet(w, b).groupBy("s_suppkey").agg(F.count("*").alias("pages_hit"))
        return w.select("s_suppkey").join(hit, "s_suppkey", "left").select("s_suppkey", F.coalesce("pages_hit", F.lit(0)).alias("pages_hit"))

    _b = f"b AS (SELECT page, min(x) AS x_min, max(x) AS x_max, min(y) AS y_min, max(y) AS y_max FROM paged GROUP BY page), w AS ({X.WINDOWS})"
    add(f"prune_{_o}", _prune, f"WITH {O.paged('obs', _o, PAGE)}, {_b} SELECT s_suppkey, count(page) AS pages_hit FROM w LEFT JOIN b ON x_max >= qx0 AND x_min <= qx1 AND y_max >= qy0 AND y_min <= qy1 GROUP BY s_suppkey")

    def _mask(spark, sf_dir, o=_o):
        p = _paged(spark, sf_dir, "obs", o)
        b = index.cell_mask(p, index.page_boxes(p))
        r = X.RECTS["medium"]
        return b.agg(F.sum(F.when(index.meets(r), 1).otherwise(0)).alias("by_box"), F.sum(F.when(index.mask_meets(r), 1).otherwise(0)).alias("by_mask"))

    _x0, _y0, _x1, _y1 = X.RECTS["medium"]
    _side = lambda a, c: f"b.{a}_min + (b.{a}_max - b.{a}_min) * {c} / 8"
    _cell = lambda a: f"CASE WHEN b.{a}_max > b.{a}_min THEN least(7, floor((p.{a} - b.{a}_min) / (b.{a}_max - b.{a}_min) * 8))::INT ELSE 0 END"
    add(f"cell_mask_{_o}", _mask, f"""WITH {O.paged('obs', _o, PAGE)}, b AS (SELECT page, min(x) AS x_min, max(x) AS x_max, min(y) AS y_min, max(y) AS y_max FROM paged GROUP BY page),
    c AS (SELECT DISTINCT page, {_cell('x')} AS cx, {_cell('y')} AS cy FROM paged p JOIN b USING (page)),
    m AS (SELECT page, x_max >= {_x0}::DOUBLE AND x_min <= {_x1}::DOUBLE AND y_max >= {_y0}::DOUBLE AND y_min <= {_y1}::DOUBLE AS whole,
      bool_or({_side('x', 'cx')} <= {_x1}::DOUBLE AND {_side('x', '(cx + 1)')} >= {_x0}::DOUBLE AND {_side('y', 'cy')} <= {_y1}::DOUBLE AND {_side('y', '(cy + 1)')} >= {_y0}::DOUBLE) AS part FROM c JOIN b USING (page) GROUP BY ALL)
    SELECT (count(*) FILTER (whole))::BIGINT AS by_box, (count(*) FILTER (whole AND part))::BIGINT AS by_mask FROM m""")

    def _quality(spark, sf_dir, o=_o):
        """Area of boxes and of what pairs of them share, in ten-thousandths of the domain, rounded down."""
        q = index.quality(index.page_boxes(_paged(spark, sf_dir, "obs", o)))
        part = lambda c: F.floor(F.round(F.col(c) / (360.0 * 180.0) * 10000, 6))
        return q.select("pages", part("area").alias("area_e4"), part("overlap").alias("overlap_e4"))

    _part = lambda v: f"floor(round({v} / (360.0 * 180.0) * 10000, 6))::BIGINT"
    add(f"index_quality_{_o}", _quality, f"""WITH {O.paged('obs', _o, PAGE)}, {_b},
    s AS (SELECT coalesce(sum((least(l.x_max, r.x_max) - greatest(l.x_min, r.x_min)) * (least(l.y_max, r.y_max) - greatest(l.y_min, r.y_min))), 0) AS shared FROM b l JOIN b r ON l.page < r.page AND l.x_min <= r.x_max AND l.x_max >= r.x_min AND l.y_min <= r.y_max AND l.y_max >= r.y_min)
    SELECT count(*) AS pages, {_part("sum((x_max - x_min) * (y_max - y_min))")} AS area_e4, {_part("(SELECT shared FROM s)")} AS overlap_e4 FROM b""")


def _rstar_quality(spark, sf_dir):
    """The arm without overlap beside the best curve: no shared area, and less area in all."""
    _, b = _rstar_boxes(X.leaves(spark, sf_dir, "obs").select("id", "x", "y"), PAGE)
    q = index.quality(b).select(F.col("area").alias("own"), F.col("overlap").alias("shared_area"))
    h = index.quality(index.page_boxes(_paged(spark, sf_dir, "obs", "hilbert"))).select("area")
    return q.join(h).select("shared_area", (F.col("own") < F.col("area")).alias("less_than_hilbert"))


def _rstar_windows(spark, sf_dir):
    """Points of each window through the rectangles' boxes."""
    d, b = _rstar_boxes(X.leaves(spark, sf_dir, "obs").select("id", "x", "y"), PAGE)
    w = X.run_sql(spark, sf_dir, X.WINDOWS)
    hit = index.windows_meet(w, b).select("s_suppkey", "qx0", "qy0", "qx1", "qy1", F.col("page").alias("cell"))
    return d.join(hit, "cell").where("x >= qx0 and x <= qx1 and y >= qy0 and y <= qy1").groupBy("s_suppkey").agg(F.count("*").alias("cnt"))


add("index_quality_rstar", _rstar_quality, "SELECT 0.0::DOUBLE AS shared_area, true AS less_than_hilbert")
add("prune_rstar", _rstar_windows, f"SELECT s_suppkey, count(*) AS cnt FROM ({X.WINDOWS}) w JOIN ({X.points_sql('obs')}) p ON x >= qx0 AND x <= qx1 AND y >= qy0 AND y <= qy1 GROUP BY s_suppkey")


def _range(name, rect, spark, sf_dir):
    path = _written(spark, sf_dir, name)
    g = page_table.scan(spark, path, rect)
    return g.select("id", geom.n_coords(F.col("geometry")).alias("n_coords"))


def _rel_rect(name):
    """A window of about a hundredth of the area that a dataset really covers."""
    return {"traj": (-8.612, 41.15, -8.608, 41.153), "roads": (-95.0, 35.0, -90.0, 38.0)}.get(name, (-99.0, 36.0, -92.0, 43.0))


def _range_sql(name, rect):
    where = f"HAVING max(x) >= {rect[0]!r}::DOUBLE AND min(x) <= {rect[2]!r}::DOUBLE AND max(y) >= {rect[1]!r}::DOUBLE AND min(y) <= {rect[3]!r}::DOUBLE" if rect else ""
    return f"SELECT id, count(x)::INT AS n_coords FROM ({X.points_sql(name)}) p GROUP BY id {where}"


def _small_rect(name):
    """A window below a ten-thousandth of that area."""
    return {"traj": (-8.6105, 41.151, -8.61025, 41.1512), "roads": (-125.038, 24.881, -124.545, 25.084)}.get(name, (-82.6, 41.712, -82.139, 41.879))


def _window(name, size):
    return X.RECTS[size] if name == "obs" else _small_rect(name) if size == "small" else _rel_rect(name)


for _n in SETS:
    add(f"range_none_{_n}", partial(_range, _n, None), _range_sql(_n, None))
    for _k in ("small", "medium"):
        add(f"range_{_k}_{_n}", partial(_range, _n, _window(_n, _k)), _range_sql(_n, _window(_n, _k)))
add("range_far_obs", partial(_range, "obs", X.RECTS["far"]), _range_sql("obs", X.RECTS["far"]))


def _exact(name, spark, sf_dir):
    return page_table.scan(spark, _written(spark, sf_dir, name), _exact_rect(name), exact=True).select("id")


def _exact_rect(name):
    """Windows that some boxes meet and their geometries don't."""
    return _window(name, "medium")


def _exact_sql(name):
    x0, y0, x1, y1 = (f"{v!r}::DOUBLE" for v in _exact_rect(name))
    side = lambda x, y: f"((nx - x) * ({y} - y) - (ny - y) * ({x} - x))"
    corners = ", ".join(side(x, y) for x in (x0, x1) for y in (y0, y1))
    crosses = f"CASE WHEN nx IS NOT NULL AND ny <> y AND (y > {y0}) <> (ny > {y0}) AND {x0} < (nx - x) * ({y0} - y) / (ny - y) + x THEN 1 ELSE 0 END"
    areal = "kind IN (3, 6)"
    return f"""SELECT id FROM (SELECT *, lead(x) OVER r AS nx, lead(y) OVER r AS ny FROM ({X.points_sql(name)}) p WINDOW r AS (PARTITION BY id, part_no ORDER BY coord_no)) e GROUP BY id, kind
    HAVING bool_or(x >= {x0} AND x <= {x1} AND y >= {y0} AND y <= {y1})
      OR bool_or(nx IS NOT NULL AND greatest(x, nx) >= {x0} AND least(x, nx) <= {x1} AND greatest(y, ny) >= {y0} AND least(y, ny) <= {y1} AND least({corners}) <= 0 AND greatest({corners}) >= 0)
      OR ({areal} AND sum({crosses}) % 2 = 1)"""


for _n in ("roads", "bldg"):
    add(f"range_exact_{_n}", partial(_exact, _n), _exact_sql(_n))


def _selectivity(spark, sf_dir):
    """Share of each window in the extent that a set covers, in millionths, and the geometries that meet it."""
    out = None
    for n in SETS:
        path = _written(spark, sf_dir, n)
        e = page_table.extent_of(spark, path)
        for k in ("small", "medium"):
            r = _window(n, k)
            hit = page_table.scan(spark, path, r).agg(F.count("*").alias("n_hit"))
            part = F.floor((r[2] - r[0]) * (r[3] - r[1]) / ((F.col("x_max") - F.col("x_min")) * (F.col("y_max") - F.col("y_min"))) * 1e6)
            b = e.select(F.lit(n).alias("dataset"), F.lit(k).alias("size"), part.alias("area_ppm"), F.col("n").alias("n_total")).join(hit)
            out = b if out is None else out.unionByName(b)
    return out


def _selectivity_sql(n, k):
    r = _window(n, k)
    area = (r[2] - r[0]) * (r[3] - r[1])
    return f"SELECT '{n}' AS dataset, '{k}' AS size, (SELECT floor({area!r}::DOUBLE / ((max(x) - min(x)) * (max(y) - min(y))) * 1000000.0::DOUBLE)::BIGINT FROM ({X.points_sql(n)}) p) AS area_ppm, (SELECT count(DISTINCT id) FROM ({X.points_sql(n)}) p) AS n_total, (SELECT count(*) FROM ({_range_sql(n, r)}) h) AS n_hit"


add("window_selectivity", _selectivity, " UNION ALL ".join(_selectivity_sql(n, k) for n in SETS for k in ("small", "medium")))


def _pruning(spark, sf_dir):
    """The medium window on a table in one order along the curve: files left out by the manifest, pages and bytes by their bounds.

    Most trips (traj) meet their window, so there is little to leave out.
    """
    out = None
    for n in SETS:
        path, r = _written(spark, sf_dir, n, sort="total", page_bytes=2 << 10), _window(n, "medium")
        files = len(page_table.pruned(spark, path, r).inputFiles()), len(spark.read.parquet(path).inputFiles())
        b = page_table.prune_report(spark, path, r).select(F.lit(n).alias("dataset"), (2 * F.col("pages_hit") < F.col("pages_total")).alias("half_the_pages"), (2 * F.col("bytes_read") < F.col("bytes_total")).alias("half_the_bytes"), F.lit(files[0] <= files[1]).alias("no_more_files"))
        b = b.join(page_table.scan(spark, path, r).agg(F.count("*").alias("n_hit")))
        out = b if out is None else out.unionByName(b)
    return out


add("pruned_reads", _pruning, " UNION ALL ".join(f"SELECT '{n}' AS dataset, {str(n != 'traj').lower()} AS half_the_pages, {str(n != 'traj').lower()} AS half_the_bytes, true AS no_more_files, (SELECT count(*) FROM ({_range_sql(n, _window(n, 'medium'))}) h) AS n_hit" for n in SETS))


def _wkb_range(name, rect, spark, sf_dir):
    path = X.scratch_path(spark, f"wkb_{name}")
    wkb.save_wkb(X.dataset(spark, sf_dir, name), path)
    d = wkb.read_wkb(spark, path, rect)
    return d.select("id", geom.n_coords(wkb.parse_wkb(F.col("wkb"))).alias("n_coords"))


for _n in SETS:
    for _k in ("small", "medium"):
        add(f"range_wkbbox_{_k}_{_n}", partial(_wkb_range, _n, _window(_n, _k)), _range_sql(_n, _window(_n, _k)))


def _windows(spark, sf_dir):
    path = _written(spark, sf_dir, "obs")
    w = X.run_sql(spark, sf_dir, X.WINDOWS)
    return page_table.scan_windows(spark, path, w).groupBy("s_suppkey").agg(F.count("*").alias("cnt"))


add("windows_batch", _windows, f"SELECT s_suppkey, count(*) AS cnt FROM ({X.WINDOWS}) w JOIN ({X.points_sql('obs')}) p ON x >= qx0 AND x <= qx1 AND y >= qy0 AND y <= qy1 GROUP BY s_suppkey")


def _windows_grid(spark, sf_dir):
    """The same through the grid, as for more windows than are broadcast."""
    p = X.leaves(spark, sf_dir, "obs").selectExpr("id", "x as x_min", "y as y_min", "x as x_max", "y as y_max")
    return index.windows_meet(X.run_sql(spark, sf_dir, X.WINDOWS), p, most=0).groupBy("s_suppkey").agg(F.count("*").alias("cnt"))


add("windows_grid", _windows_grid, ORACLES["windows_batch"])


def _join_boxes(spark, sf_dir):
    """Pairs of buildings whose boxes meet."""
    b = X.dataset(spark, sf_dir, "bldg").select("id", geom.box(F.col("geometry")).alias("b")).select("id", "b.*")
    other = b.select(F.col("id").alias("other"), *[F.col(a).alias(n) for a, n in zip(box_join.LEFT, box_join.RIGHT, strict=True)])
    return box_join.meet(b, other, X.DATASETS["bldg"].extent).where("id < other").select("id", "other")


_box = f"(SELECT id, min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1 FROM ({X.points_sql('bldg')}) p GROUP BY id)"
add("join_boxes", _join_boxes, f"WITH b AS {_box} SELECT l.id, r.id AS other FROM b l JOIN b r ON l.id < r.id AND l.x0 <= r.x1 AND l.x1 >= r.x0 AND l.y0 <= r.y1 AND l.y1 >= r.y0")


def _extent(spark, sf_dir):
    out = None
    for n in SETS:
        b = page_table.extent_of(spark, _written(spark, sf_dir, n)).select(F.lit(n).alias("dataset"), "*")
        out = b if out is None else out.unionByName(b)
    return out


add("extent_meta", _extent, " UNION ALL ".join(f"SELECT '{n}' AS dataset, min(x) AS x_min, max(x) AS x_max, min(y) AS y_min, max(y) AS y_max, count(DISTINCT id) AS n FROM ({X.points_sql(n)}) p" for n in SETS))


def _axis(spark, sf_dir):
    d = page_table.scan_axis(spark, _written(spark, sf_dir, "traj"), "x")
    # trajectories have a vertex in each part, so the counts of parts cut the values
    ends = F.aggregate("geom_nparts", F.array(F.lit(0)), lambda a, n: F.concat(a, F.array(F.element_at(a, -1) + n)))
    d = d.withColumn("ends", ends).select("x", "ends", F.posexplode("ids").alias("i", "id"))
    at = lambda k: F.element_at("x", k)
    return d.select("id", (F.get("ends", F.col("i") + 1) - F.get("ends", F.col("i"))).alias("n"), at(F.get("ends", F.col("i")) + 1).alias("x_first"), at(F.get("ends", F.col("i") + 1)).alias("x_last"))


add("project_axis", _axis, f"SELECT id, count(*)::INT AS n, arg_min(x, part_no) AS x_first, arg_max(x, part_no) AS x_last FROM ({X.points_sql('traj')}) p GROUP BY id")


def _manifest(spark, sf_dir):
    m = page_table.manifest(spark, _written(spark, sf_dir, "bldg"))
    return m.agg(F.sum("n_geoms").alias("n_geoms"), F.sum("n_coords").alias("n_coords"), F.min("x_min").alias("x_min"), F.max("y_max").alias("y_max"))


add("manifest_totals", _manifest, f"SELECT count(DISTINCT id) AS n_geoms, count(x) AS n_coords, min(x) AS x_min, max(y) AS y_max FROM ({X.points_sql('bldg')}) p")

# other formats


def _sizes(spark, sf_dir):
    out = None
    for n in SETS:
        d = X.dataset(spark, sf_dir, n)
        g = F.col("geometry")
        b = d.agg(F.lit(n).alias("dataset"), F.sum(wkb.wkb_size(g)).alias("wkb_bytes"), F.sum(wkb.wkb_size(g) + 32).alias("wkbbox_bytes"), F.sum(shapefile.shapefile_size(g)).alias("shp_bytes"), F.sum(16 * geom.n_coords(g)).alias("raw_bytes"))
        out = b if out is None else out.unionByName(b)
    return out


def _sizes_sql(n):
    polygons = "(SELECT o_custkey AS id, count(*) AS polys FROM {orders} WHERE o_orderstatus = 'F' GROUP BY ALL)" if n == "lots" else "(SELECT -1 AS id, 0 AS polys)"
    return f"""SELECT '{n}' AS dataset, sum(w)::BIGINT AS wkb_bytes, sum(w + 32)::BIGINT AS wkbbox_bytes, sum(s + 16)::BIGINT AS shp_bytes, sum(16 * c)::BIGINT AS raw_bytes FROM (
      SELECT CASE kind WHEN 1 THEN 21 WHEN 3 THEN 9 + 4 * p + 16 * c WHEN 4 THEN 9 + 21 * p WHEN 5 THEN 9 + 9 * p + 16 * c WHEN 6 THEN 9 + 9 * polys + 4 * p + 16 * c ELSE 9 END AS w,
      CASE kind WHEN 1 THEN 20 WHEN 4 THEN 40 + 16 * c WHEN 0 THEN 4 ELSE 44 + 4 * p + 16 * c END AS s, c
      FROM (SELECT id, kind, count(DISTINCT part_no) AS p, count(x) AS c FROM ({X.points_sql(n)}) l GROUP BY id, kind) g LEFT JOIN {polygons} q USING (id)) t"""


add("size_analytic", _sizes, " UNION ALL ".join(_sizes_sql(n) for n in SETS))
add("size_measures", _measures, f"""SELECT dataset, own * 6400 // raw_bytes AS bits_e2, wkbbox_bytes * 1000 // own AS wkbbox_e3, shp_bytes * 1000 // own AS shp_e3, raw_bytes * 1000 // own AS raw_e3
  FROM (SELECT dataset, x_bytes + y_bytes AS own FROM ({ORACLES['payload_bytes_hilbert']}) p) o JOIN ({ORACLES['size_analytic']}) s USING (dataset)""")
add("sort_bound", _sort_bound, "SELECT count(*) AS n, 500::BIGINT AS most FROM {events}")


def _wkb_made(spark, sf_dir):
    """Bytes really made, against the formula."""
    d = wkb.with_wkb(X.dataset(spark, sf_dir, "lots")).select("id", F.length("wkb").alias("made"))
    return d.join(X.dataset(spark, sf_dir, "lots").select("id", wkb.wkb_size(F.col("geometry")).alias("size")), "id").agg(F.count("*").alias("n"), F.sum(F.abs(F.col("made") - F.col("size"))).alias("off"))


add("wkb_bytes_made", _wkb_made, f"SELECT count(DISTINCT id) AS n, 0::BIGINT AS off FROM ({X.points_sql('lots')}) p")


def _rival(arm, name, spark, sf_dir):
    """A set through a rival format and back."""
    d, path = X.dataset(spark, sf_dir, name), X.scratch_path(spark, f"{arm}_{name}")
    if arm == "wkb":
        wkb.save_wkb(d, path)
        back = wkb.read_wkb(spark, path).select("id", wkb.parse_wkb(F.col("wkb")).alias("geometry"))
    elif arm == "shapefile":
        shapefile.save_shapefiles(d, path, compressed=name == "lots")
        back = shapefile.read_shapefiles(spark, path)
    else:
        geojson.save_geojson(d, path, "gzip" if name == "lots" else "none", one_file=name == "traj")
        back = geojson.read_geojson(spark, path)
    kinds = back.agg(F.count_distinct("id").alias("n_geoms"), F.sum(F.col("geometry.type") * (F.col("id") % 7 + 1)).alias("kinds"))
    return _same(back, X.leaves(spark, sf_dir, name)).join(kinds)


for _n in SETS:
    for _k in ("wkb", "shapefile", "geojson"):
        add(f"{_k}_roundtrip_{_n}", partial(_rival, _k, _n), f"SELECT count(x) AS n_coords, 0::BIGINT AS lost, 0::BIGINT AS made, count(DISTINCT id) AS n_geoms, (SELECT sum(kind * (id % 7 + 1))::BIGINT FROM (SELECT DISTINCT id, kind FROM ({X.points_sql(_n)}) q) k) AS kinds FROM ({X.points_sql(_n)}) p")


def _members(text, spark, sf_dir):
    """Flattened collections as one collection each, through its binary or text form and back."""
    edges = _collections(spark, sf_dir, whole=True)
    if text:
        path = X.scratch_path(spark, "collections")
        inner = lambda m: F.concat(F.lit('{"type":"GeometryCollection","geometries":['), F.array_join(m, ","), F.lit("]}"))
        m = F.transform("members", lambda x: geojson.geojson(x))
        # the last two members stand in a collection of their own
        edges.select("root_id", inner(F.concat(F.slice(m, 1, 2), F.array(inner(F.slice(m, 3, 2))))).alias("text")).write.parquet(path)
        edges, back = spark.read.parquet(path), geojson.parse_geojson_collection("text")
    else:
        back = wkb.parse_wkb_collection(wkb.as_wkb_collection(F.col("members")))
    back = edges.select("root_id", back.alias("m"))
    return back.select("root_id", F.posexplode("m").alias("pos", "g")).select("root_id", "pos", F.col("g.type").alias("kind"))


add("collection_wkb", partial(_members, False), ORACLES["collection_flatten"])
add("collection_geojson", partial(_members, True), ORACLES["collection_flatten"])


def _csv(spark, sf_dir):
    path, p = X.scratch_path(spark, "csv"), X.leaves(spark, sf_dir, "obs")
    baselines.save_csv_points(p, path)
    same = (stats.to_bits(F.col("x")) == stats.to_bits(F.col("x2"))) & (stats.to_bits(F.col("y")) == stats.to_bits(F.col("y2")))
    d = baselines.read_csv_points(spark, path).toDF("id", "x2", "y2").join(p.select("id", "x", "y"), "id")
    return d.withColumn("same", same).agg(F.count("*").alias("n"), F.count_if(~F.col("same")).alias("off"))


add("csv_points", _csv, f"SELECT count(*) AS n, 0::BIGINT AS off FROM ({X.points_sql('obs')}) p")


def _wkt(spark, sf_dir):
    d = X.run_sql(spark, sf_dir, X.DATASETS["bldg"].sql).select("id", "kind", "part_no", "coord_no", F.col("xi").cast("double").alias("x"), F.col("yi").cast("double").alias("y"))
    return build.assemble(d).select("id", geom.as_wkt(F.col("geometry"), lambda v: v.cast("long").cast("string")).alias("text"))


add("wkt_text", _wkt, f"SELECT id, 'POLYGON (' || string_agg(ring, ', ' ORDER BY part_no) || ')' AS text FROM (SELECT id, part_no, '(' || string_agg(xi || ' ' || yi, ', ' ORDER BY coord_no) || ')' AS ring FROM ({X.DATASETS['bldg'].sql}) l GROUP BY id, part_no) r GROUP BY id")


def _json(spark, sf_dir):
    path, p = X.scratch_path(spark, "json"), X.leaves(spark, sf_dir, "obs")
    baselines.save_json_points(p, path)
    d = baselines.read_json_points(spark, path).select("id", build.point("x", "y").alias("geometry"))
    return _same(d, p)


add("json_points", _json, ORACLES["codec_roundtrip_obs"])


def _shp(spark, sf_dir):
    out = None
    for n in ("obs", "bldg"):
        b = shapefile.shape_files(X.dataset(spark, sf_dir, n)).agg(F.lit(n).alias("dataset"), F.sum(F.length("shp") - 100 + F.length("shx") - 100).alias("record_bytes"))
        out = b if out is None else out.unionByName(b)
    return out


add("shapefile_lengths", _shp, f"SELECT dataset, shp_bytes AS record_bytes FROM ({ORACLES['size_analytic']}) s WHERE dataset IN ('obs', 'bldg')")

# relational surface


def _bldg_attrs(s, d):
    return X.dataset(s, d, "bldg").join(_read(s, d, "orders").select(F.col("o_orderkey").alias("id"), "o_custkey", "o_orderstatus"), "id")


_bc = f"(SELECT id, count(x) AS c FROM ({X.points_sql('bldg')}) p GROUP BY id)"
add("join_attrs", lambda s, d: _bldg_attrs(s, d).join(_read(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum(geom.n_coords(F.col("geometry"))).alias("coords")),
    f"SELECT c_mktsegment, count(*) AS n, sum(c)::BIGINT AS coords FROM {_bc} b JOIN {{orders}} ON id = o_orderkey JOIN {{customer}} ON o_custkey = c_custkey GROUP BY ALL")
for _k, _sql in (("semi", "IN"), ("anti", "NOT IN")):
    add(f"join_{_k}", lambda s, d, k=_k: _read(s, d, "customer").join(_read(s, d, "orders").where("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), f"left_{k}").select("c_custkey"), f"SELECT c_custkey FROM {{customer}} WHERE c_custkey {_sql} (SELECT o_custkey FROM {{orders}} WHERE o_orderstatus = 'F')")


def _rollup(spark, sf_dir):
    d = _bldg_attrs(spark, sf_dir).join(_read(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(_read(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return d.rollup("n_name", "o_orderstatus").agg(F.count("*").alias("n"), F.sum(geom.n_parts(F.col("geometry"))).alias("rings"))


add("rollup_nation_status", _rollup, "SELECT n_name, o_orderstatus, count(*) AS n, sum(CASE WHEN o_orderkey % 10 = 0 THEN 2 ELSE 1 END)::BIGINT AS rings FROM {orders} JOIN {customer} ON o_custkey = c_custkey JOIN {nation} ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_name, o_orderstatus)")
add("filter_kind", lambda s, d: page_table.scan(s, _written(s, d, "lots"), kinds=(6,)).select("id", geom.n_coords(F.col("geometry")).alias("n_coords")), f"SELECT id, count(x)::INT AS n_coords FROM ({X.points_sql('lots')}) p WHERE kind = 6 GROUP BY id")


def _cube(spark, sf_dir):
    d = X.dataset(spark, sf_dir, "lots").join(_read(spark, sf_dir, "customer"), F.col("id") == F.col("c_custkey"))
    d = d.select("c_mktsegment", F.col("geometry.type").alias("kind"), geom.n_coords(F.col("geometry")).alias("c"))
    return d.cube("c_mktsegment", "kind").agg(F.count("*").alias("n"), F.sum("c").alias("coords"))


add("cube_segment_kind", _cube, f"SELECT c_mktsegment, kind, count(*) AS n, sum(c)::BIGINT AS coords FROM (SELECT id, kind, count(x) AS c FROM ({X.points_sql('lots')}) p GROUP BY id, kind) g JOIN {{customer}} ON id = c_custkey GROUP BY CUBE (c_mktsegment, kind)")
add("join_outer", lambda s, d: _read(s, d, "customer").select("c_custkey").join(X.dataset(s, d, "bldg").select("id", geom.n_parts(F.col("geometry")).alias("p")).join(_read(s, d, "orders").select(F.col("o_orderkey").alias("id"), "o_custkey"), "id"), F.col("c_custkey") == F.col("o_custkey"), "full_outer").groupBy("c_custkey").agg(F.count("id").alias("n"), F.sum("p").alias("rings")),
    "SELECT c_custkey, count(o_orderkey) AS n, sum(CASE WHEN o_orderkey IS NULL THEN NULL WHEN o_orderkey % 10 = 0 THEN 2 ELSE 1 END)::BIGINT AS rings FROM {customer} LEFT JOIN {orders} ON o_custkey = c_custkey GROUP BY c_custkey")


def _ranks(spark, sf_dir):
    """Ranks, neighbours and running sums of vertices among a customer's buildings."""
    d = _bldg_attrs(spark, sf_dir).select("id", "o_custkey", geom.n_coords(F.col("geometry")).alias("c"))
    w, by_id = W.partitionBy("o_custkey").orderBy(F.desc("c")), W.partitionBy("o_custkey").orderBy("id")
    return d.select("id", F.rank().over(w).alias("rnk"), F.dense_rank().over(w).alias("dense"), F.lag("id").over(by_id).alias("prev"), F.sum("c").over(by_id.rowsBetween(W.unboundedPreceding, 0)).alias("running"))


add("win_ranks", _ranks, f"SELECT id, rank() OVER w AS rnk, dense_rank() OVER w AS dense, lag(id) OVER v AS prev, (sum(c) OVER (v ROWS UNBOUNDED PRECEDING))::BIGINT AS running FROM {_bc} b JOIN {{orders}} ON id = o_orderkey WINDOW w AS (PARTITION BY o_custkey ORDER BY c DESC), v AS (PARTITION BY o_custkey ORDER BY id)")
add("agg_vertices", lambda s, d: X.dataset(s, d, "roads").select("id", geom.n_coords(F.col("geometry")).alias("c")).agg(F.min("c").alias("least"), F.max("c").alias("most"), F.percentile("c", 0.5).alias("median"), F.max_by("id", F.struct("c", "id")).alias("largest")),
    f"SELECT min(c)::INT AS least, max(c)::INT AS most, quantile_cont(c, 0.5)::DOUBLE AS median, arg_max(id, c * 100000000 + id) AS largest FROM (SELECT id, count(x) AS c FROM ({X.points_sql('roads')}) p GROUP BY id) g")
add("fn_props", lambda s, d: _read(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k")), "SELECT event_type, sum((props->>'$.k')::BIGINT)::BIGINT AS k FROM {events} GROUP BY event_type")
add("filter_attr_rect", lambda s, d: _bldg_attrs(s, d).where(F.col("o_orderstatus") == "F").withColumn("b", geom.box(F.col("geometry"))).where(geom.intersects(F.col("b"), *_rel_rect("bldg"))).select("id"),
    f"SELECT id FROM ({_range_sql('bldg', _rel_rect('bldg'))}) r JOIN {{orders}} ON id = o_orderkey WHERE o_orderstatus = 'F'")
add("topk_vertices", lambda s, d: X.dataset(s, d, "roads").select("id", geom.n_coords(F.col("geometry")).alias("n")).orderBy(F.desc("n"), "id").limit(20), f"SELECT id, count(x)::INT AS n FROM ({X.points_sql('roads')}) p GROUP BY id ORDER BY n DESC, id LIMIT 20")
_d2 = "(x - 20.0) * (x - 20.0) + (y + 30.0) * (y + 30.0)"
add("knn_points", lambda s, d: page_table.nearest(s, _written(s, d, "obs", sort="total", page_bytes=2 << 10), 20.0, -30.0, 10).select("id"), f"SELECT id FROM ({X.points_sql('obs')}) p ORDER BY {_d2}, id LIMIT 10")
add("agg_distinct_coords", lambda s, d: X.leaves(s, d, "obs").agg(F.count_distinct("x", "y").alias("n")), f"SELECT count(*) AS n FROM (SELECT DISTINCT x, y FROM ({X.points_sql('obs')}) p) q")
_two = (X.RECTS["medium"], (10.0, -60.0, 30.0, -20.0))
for _k, _sql in (("intersect", "INTERSECT"), ("subtract", "EXCEPT"), ("union", "UNION")):
    def _set(spark, sf_dir, k=_k):
        p = X.leaves(spark, sf_dir, "obs")
        a, b = (p.where(f"x between {r[0]} and {r[2]} and y between {r[1]} and {r[3]}").select("id") for r in _two)
        return getattr(a, k)(b).distinct()

    _a, _b2 = (f"SELECT id FROM ({X.points_sql('obs')}) p WHERE x BETWEEN {r[0]} AND {r[2]} AND y BETWEEN {r[1]} AND {r[3]}" for r in _two)
    add(f"set_{_k}", _set, f"{_a} {_sql} {_b2}")


def _scalars(spark, sf_dir):
    d = X.run_sql(spark, sf_dir, X.DATASETS["bldg"].sql).select("id", "kind", "part_no", "coord_no", F.col("xi").cast("double").alias("x"), F.col("yi").cast("double").alias("y"))
    g, b = F.col("geometry"), geom.box(F.col("geometry"))
    return build.assemble(d).select("id", geom.kind_name(g).alias("name"), geom.n_parts(g).alias("n_parts"), (2 * geom.area(g)).cast("long").alias("area2"), (b["x_max"] - b["x_min"]).cast("long").alias("w"), geom.contains_point(build.shell(g), b["x_min"] + 1.5, b["y_min"] + 1.5).alias("corner_in"))


add("fn_scalars", _scalars, f"""SELECT id, 'POLYGON' AS name, count(*)::INT AS n_parts, abs(sum(a))::BIGINT AS area2, max(w) AS w, true AS corner_in FROM (
  SELECT id, part_no, sum(xi * ny - nx * yi) AS a, max(xi) - min(xi) AS w FROM (SELECT *, lead(xi) OVER r AS nx, lead(yi) OVER r AS ny FROM ({X.DATASETS['bldg'].sql}) l WINDOW r AS (PARTITION BY id, part_no ORDER BY coord_no)) GROUP BY ALL) GROUP BY id""")
add("traj_duration", lambda s, d: _read(s, d, "events").groupBy("user_id").agg(F.count("*").alias("n"), (F.unix_micros(F.max(F.col("ts").cast("timestamp"))) - F.unix_micros(F.min(F.col("ts").cast("timestamp")))).alias("micros")), "SELECT user_id, count(*) AS n, epoch_us(max(ts)) - epoch_us(min(ts)) AS micros FROM {events} GROUP BY user_id")


def _asof(spark, sf_dir):
    e = _read(spark, sf_dir, "events")
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    return e.select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("last_purchase"))


add("asof_traj", _asof, "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS last_purchase FROM {events}")


def _functions(spark, sf_dir):
    """Registered functions over a view of a page table."""
    sql_functions.register(spark)
    page_table.scan(spark, _written(spark, sf_dir, "bldg")).createOrReplaceTempView("geopages_bldg")
    return spark.sql("SELECT geo_kind(geometry) AS kind, count(*) AS n, sum(geo_parts(geometry)) AS rings, sum(geo_vertices(geometry)) AS vertices, max(geo_box(geometry).x_max) AS x_max FROM geopages_bldg WHERE geo_meets(geometry, -99, 36, -92, 43) GROUP BY 1")


add("sql_functions", _functions, f"SELECT 'POLYGON' AS kind, count(*) AS n, sum(p)::BIGINT AS rings, sum(c)::BIGINT AS vertices, max(x1) AS x_max FROM (SELECT id, count(DISTINCT part_no) AS p, count(x) AS c, min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1 FROM ({X.points_sql('bldg')}) p GROUP BY id) g WHERE x1 >= -99 AND x0 <= -92 AND y1 >= 36 AND y0 <= 43")


def _table_function(spark, sf_dir):
    """Vertices of a page table by a table function."""
    sql_functions.register(spark)
    page_table.scan(spark, _written(spark, sf_dir, "lots")).createOrReplaceTempView("geopages_lots")
    return spark.sql("SELECT id, part_no, coord_no, x, y FROM geopages_lots t, LATERAL geo_leaves(t.geometry)")


add("sql_table_function", _table_function, f"SELECT id, part_no, coord_no, x, y FROM ({X.points_sql('lots')}) p WHERE x IS NOT NULL")


def _sql(spark, sf_dir):
    X.dataset(spark, sf_dir, "obs").createOrReplaceTempView("geopages_obs")
    return spark.sql("SELECT geometry.type AS kind, count(*) AS n, max(geometry.parts[0][0].x) AS x_max FROM geopages_obs GROUP BY 1")


add("sql_surface", _sql, f"SELECT 1 AS kind, count(*) AS n, max(x) AS x_max FROM ({X.points_sql('obs')}) p")


def _wkt_back(name, spark, sf_dir):
    text = X.dataset(spark, sf_dir, name).select("id", geom.as_wkt(F.col("geometry")).alias("text"))
    g = F.col("g")
    return text.select("id", geom.from_wkt(F.col("text")).alias("g")).select("id", g["type"].alias("kind"), geom.n_parts(g).alias("n_parts"), geom.n_coords(g).alias("n_coords"), F.aggregate(F.flatten(g["parts"]), F.lit(0).cast("long"), lambda a, c: a + F.round(c["x"] * X.DATASETS[name].scale).cast("long")).alias("xs"))


for _n in ("traj", "roads", "bldg", "lots"):
    add(f"wkt_parse_back_{_n}", partial(_wkt_back, _n), f"SELECT id, max(kind)::INT AS kind, count(DISTINCT part_no)::INT AS n_parts, count(xi)::INT AS n_coords, coalesce(sum(xi), 0)::BIGINT AS xs FROM ({X.DATASETS[_n].sql}) l GROUP BY id")


def _attributes(spark, sf_dir):
    o = _read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), "o_orderstatus", "o_orderdate", "o_totalprice")
    path = X.scratch_path(spark, "attributes")
    page_table.save(X.dataset(spark, sf_dir, "bldg").join(o, "id"), path, attributes=("o_orderstatus", "o_orderdate", "o_totalprice"), extent=X.DATASETS["bldg"].extent, page_bytes=16 << 10)
    d = page_table.scan(spark, path, attributes=("o_orderstatus", "o_orderdate"))
    return d.groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum(geom.n_coords(F.col("geometry"))).alias("n_coords"), F.max(F.year("o_orderdate")).alias("last_year"))


add("page_attributes", _attributes, f"SELECT o_orderstatus, count(*) AS n, sum(n)::BIGINT AS n_coords, max(year(o_orderdate))::INT AS last_year FROM (SELECT id, count(*) AS n FROM ({X.DATASETS['bldg'].sql}) l GROUP BY id) g JOIN {{orders}} ON id = o_orderkey GROUP BY o_orderstatus")

# streams


_ev = lambda s, d: streams.event_stream(s, d)
_us = lambda c: F.unix_micros(c)
add("stream_tumbling", lambda s, d: streams.drained(streams.tumbling(_ev(s, d)), "complete").select(_us(F.col("window.start")).alias("start_us"), "event_type", "cnt"), "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start_us, event_type, count(*) AS cnt FROM {events} GROUP BY ALL")
add("stream_sliding", lambda s, d: streams.drained(streams.sliding(_ev(s, d)), "complete").select(_us(F.col("window.start")).alias("start_us"), "cnt"), "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) - k * 3600000000 AS start_us, count(*) AS cnt FROM {events} CROSS JOIN (VALUES (0), (1)) v(k) GROUP BY ALL")
add("stream_session", lambda s, d: streams.drained(streams.sessions(_ev(s, d)), "complete").select("user_id", _us(F.col("w.start")).alias("start_us"), "cnt"),
    "SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS cnt FROM (SELECT *, sum(nw) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS nw FROM {events})) GROUP BY user_id, s")
add("stream_dedupe", lambda s, d: streams.drained(streams.without_repeats(_ev(s, d)), "append").agg(F.count("*").alias("n")), "SELECT count(DISTINCT event_id) AS n FROM {events}")


def _stream_pages(spark, sf_dir):
    d = streams.event_stream(spark, sf_dir)
    x = F.pmod(F.col("user_id") * 7919, F.lit(3600)).cast("double") / 10 - 180
    y = F.pmod(F.col("user_id") * 104729, F.lit(1800)).cast("double") / 10 - 90
    path = X.scratch_path(spark, "stream_pages")
    streams.pages_of_stream(d.select(F.col("event_id").alias("id"), build.point(x, y).alias("geometry")), path, page_bytes=16 << 10)
    return page_table.scan(spark, f"{path}/batch=*").agg(F.count("*").alias("n"), F.sum("id").alias("ids"))


add("stream_pages", _stream_pages, "SELECT count(*) AS n, sum(event_id)::BIGINT AS ids FROM {events}")


def _stream_trips(spark, sf_dir):
    cents = F.round(F.col("value") * 100).cast("long")
    d = streams.event_stream(spark, sf_dir).select("user_id", "event_id", "ts", (cents % 2001).cast("double").alias("x"), ((cents * 7 + F.col("event_id")) % 2001).cast("double").alias("y"))
    c = F.flatten("geometry.parts")
    return streams.drained(streams.trips(d), "append").select("user_id", "start_us", "end_us", F.size(c).alias("n"), F.get(c, F.lit(0))["x"].alias("x_first"), F.element_at(c, -1)["y"].alias("y_last"))


add("stream_trips", _stream_trips, f"""SELECT user_id, min(us) AS start_us, max(us) AS end_us, count(*)::INT AS n, arg_min(x, (us, event_id)) AS x_first, arg_max(y, (us, event_id)) AS y_last FROM (
  SELECT *, sum(nw) OVER (PARTITION BY user_id ORDER BY us, event_id) AS s FROM (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY user_id ORDER BY us, event_id) < 1800000000 THEN 0 ELSE 1 END AS nw FROM (
    SELECT user_id, event_id, epoch_us(ts) AS us, CAST({X._value} % 2001 AS DOUBLE) AS x, CAST(({X._value} * 7 + event_id) % 2001 AS DOUBLE) AS y FROM {{events}}))) GROUP BY user_id, s
  HAVING max(us) // 1000 + 1800000 < (SELECT epoch_us(max(ts)) // 1000 - 600000 FROM {{events}})""")


def _stream_late(spark, sf_dir):
    e, path = _read(spark, sf_dir, "events"), X.scratch_path(spark, "late")
    n = e.count()
    # quarters by event_id, each a batch, in an order with late ones
    for i, k in enumerate(LATE_ORDER):
        e.where(F.floor(F.col("event_id") * 4 / n) == k).coalesce(1).write.parquet(f"{path}/{i}")
    d = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/*").withColumn("ts", F.col("ts").cast("timestamp"))
    return spark.createDataFrame([streams.late_rows(d)], "n long, late long")


LATE_ORDER = (2, 0, 1, 3)
# Spark holds rows of a batch against the watermark that the batch before it began with
add("stream_late", _stream_late, f"""SELECT count(*) AS n, count(*) FILTER (us <= mark) AS late FROM (
  SELECT epoch_us(e.ts) AS us, (epoch_us(p.most) // 1000 - 600000) * 1000 AS mark FROM (SELECT ts, CASE event_id * 4 // (SELECT count(*) FROM {{events}}) {' '.join(f'WHEN {k} THEN {i}' for i, k in enumerate(LATE_ORDER))} END AS batch FROM {{events}}) e
  LEFT JOIN (SELECT batch + 2 AS batch, max(most) OVER (ORDER BY batch) AS most FROM (SELECT CASE event_id * 4 // (SELECT count(*) FROM {{events}}) {' '.join(f'WHEN {k} THEN {i}' for i, k in enumerate(LATE_ORDER))} END AS batch, max(ts) AS most FROM {{events}} GROUP BY 1)) p ON p.batch = e.batch)""")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _range("obs", X.RECTS["medium"], spark, sf_dir)
