"""Other layouts to compare with: plain doubles, ordered bits, CSV and JSON rows. Rival formats have modules of their own (``wkb``, ``shapefile``, ``geojson``)."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions.build import geometry_type


def save_plain(df: DataFrame, path: str, compression: str = "none", dictionary: bool = True) -> None:
    """The nested column itself, doubles uncoded; ``dictionary``: repeated values by dictionary and runs of its numbers, where Parquet finds that smaller."""
    df.select("id", "geometry").write.mode("overwrite").option("compression", compression).option("parquet.enable.dictionary", str(dictionary).lower()).parquet(path)


def _recoded(to_bits: bool, schema: pa.Schema) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Coordinates to ordered bits or back: integers that sort as the doubles do, so that min and max of a page mean the same."""
    kind = schema.field("geometry").type
    parts_kind = kind.field("parts").type
    low = np.int64(2**63 - 1)

    def leaf(v: pa.Array) -> pa.Array:
        x = v.to_numpy(zero_copy_only=False)
        bits = np.ascontiguousarray(x).view(np.int64)
        bits = bits ^ ((bits >> np.int64(63)) & low)
        return pa.array(bits if to_bits else bits.view(np.float64))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            g = pa.concat_arrays([b.column(1)])
            parts = g.field("parts")
            inner = parts.values
            c = inner.values
            fields = parts_kind.value_type.value_type
            coords = pa.StructArray.from_arrays([leaf(c.field(a)) for a in "xy"], fields=list(fields))
            inner = pa.ListArray.from_arrays(inner.offsets, coords, type=parts_kind.value_type)
            parts = pa.ListArray.from_arrays(parts.offsets, inner, type=parts_kind)
            yield pa.record_batch([b.column(0), pa.StructArray.from_arrays([g.field("type"), parts], fields=list(kind), mask=g.is_null())], schema=schema)

    return run


def _recode(df: DataFrame, to_bits: bool) -> DataFrame:
    kind = T.StructType([T.StructField("id", T.LongType()), T.StructField("geometry", geometry_type(coord="long" if to_bits else "double"))])
    return df.select(F.col("id").cast("long").alias("id"), "geometry").mapInArrow(_recoded(to_bits, to_arrow_schema(kind)), kind)


def save_ordered_bits(df: DataFrame, path: str, compression: str = "none") -> None:
    """The nested column with coordinates as ordered integers, for Parquet's own integer delta encoding."""
    _recode(df, True).write.mode("overwrite").option("compression", compression).option("parquet.writer.version", "PARQUET_2_0").option("parquet.enable.dictionary", "false").parquet(path)


def read_ordered_bits(spark: SparkSession, path: str) -> DataFrame:
    return _recode(spark.read.parquet(path), False)


def save_csv_points(points: DataFrame, path: str, compression: str = "none") -> None:
    """(id, x, y) as text; the shortest digits that give the same doubles again."""
    points.select("id", "x", "y").write.mode("overwrite").option("compression", compression).csv(path)


def read_csv_points(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("id long, x double, y double").csv(path)


def save_json_points(points: DataFrame, path: str, compression: str = "none") -> None:
    """(id, x, y) as one JSON object a line."""
    points.select("id", "x", "y").write.mode("overwrite").option("compression", compression).json(path)


def read_json_points(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("id long, x double, y double").json(path)
