"""Connected components of an edge table, by star contraction.

Every pass re-hangs each node's neighbours on the smallest label in sight: first
the larger ones, then the smaller ones. Passes grow with the logarithm of the
longest chain; the edges never leave the executors.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import Scratch


def connected_components(edges: DataFrame, scratch: Scratch, most_passes: int = 60) -> DataFrame:
    """(node, component) of every node in ``edges`` (u, v longs); component is its smallest node.

    Nulls and loops are left out, repeated edges count once; no edges give no rows.
    """
    e = edges.where("u is not null and v is not null and u <> v")
    e = scratch.put(e.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    before = None
    for _ in range(most_passes):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("x")).select("x.*").where("u <> v").distinct()
        after = scratch.put(small, "edges")
        scratch.drop(e)
        e = after
        now = e.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))")).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {most_passes} passes")
    nodes = e.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return nodes.unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
