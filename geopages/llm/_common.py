"""What the document operators share: input rows, scratch tables, row keys."""

from __future__ import annotations

import shutil
import tempfile
import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.sorting import numbered
from ..sources.scratch import delete_at_exit

#: Stands for a null doc_id inside an operator: later than every real one.
NO_ID = 2**63 - 1
#: Shared doc_ids are broadcast up to this many, else joined by a shuffle; the result is the same.
BROADCAST_ROWS = 200_000

#: Settings while a scratch table is written: shuffle files go with it, and Python gets Arrow batches
#: of so many bytes, not rows, however long the texts are.
_WRITING = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.execution.arrow.maxBytesPerBatch": str(6 << 20)}
_local_dir: str | None = None


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """The shared folder that the cluster names; a temporary one only for a local session that names none."""
    global _local_dir
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        return spark.conf.get("spark.sql.warehouse.dir").rstrip("/")
    if _local_dir is None:
        _local_dir = tempfile.mkdtemp(prefix="documents_")
        import atexit

        atexit.register(shutil.rmtree, _local_dir, True)
    return f"file://{_local_dir}"


class Scratch:
    """Tables that one run of an operator writes to the shared folder to cut its lineage.

    A written table outlives the executors that made it, and the shuffle files
    behind it are removed as soon as it is written. Results are read from such tables
    lazily, so they stay until the driver ends, and go then.
    """

    def __init__(self, spark: SparkSession, what: str):
        self.spark = spark
        self.root = f"{scratch_root(spark)}/{what}-{uuid.uuid4().hex[:12]}"
        delete_at_exit(spark, self.root)
        self._n = 0

    def put(self, df: DataFrame, name: str = "t") -> DataFrame:
        self._n += 1
        path = f"{self.root}/{self._n:03d}_{name}"
        was = {k: self.spark.conf.get(k, None) for k in _WRITING}
        for k, v in _WRITING.items():
            self.spark.conf.set(k, v)
        try:
            df.write.mode("overwrite").parquet(path)
        finally:
            for k, v in was.items():
                self.spark.conf.unset(k) if v is None else self.spark.conf.set(k, v)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, *tables: DataFrame) -> None:
        for t in tables:
            if path := getattr(t, "_scratch_path", None):
                hdfs_delete(self.spark, path)


def column_of(df: DataFrame, name: str) -> Column:
    """A top-level column of ``df``, whatever stands in its name."""
    return df["`" + name.replace("`", "``") + "`"]


def unused(df: DataFrame, name: str) -> str:
    """``name``, with underscores before it until ``df`` has no such column."""
    have = {c.lower() for c in df.columns}
    while name.lower() in have:
        name = f"_{name}"
    return name


def hdfs_delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def _order() -> Column:
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID))


def _digest() -> Column:
    return F.sha2(F.col("text").cast("string").cast("binary"), 256)


@dataclass
class Keyed:
    """The distinct (doc_id, text) of a table as ``rows`` (doc long, text string), and the way back.

    ``doc >> shift`` orders rows as their doc_ids do, a null one last; rows of one doc_id
    differ in the lower bits. Where no two rows share a doc_id, ``doc`` is the doc_id itself
    and nothing is shuffled; ``names`` (doc, doc_id, digest, copies) is there for other tables only.
    """

    rows: DataFrame
    shift: int = 0
    names: DataFrame | None = None

    def again(self, df: DataFrame) -> DataFrame:
        """``df`` with doc_id in place of doc: a row for each row that was read, equal ones included."""
        rest = [c for c in df.columns if c != "doc"]
        if self.names is None:
            return df.select(_id_of("doc").alias("doc_id"), *rest)
        out = df.join(self.names.select("doc", "doc_id", "copies"), "doc")
        return out.withColumn("_copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select("doc_id", *rest)

    def ids(self, df: DataFrame, column: str) -> DataFrame:
        """``df`` with the doc_id of the key in ``column`` in its place."""
        if self.names is None:
            return df.withColumn(column, _id_of(column))
        n = self.names.select(F.col("doc").alias("_doc"), F.col("doc_id").alias("_id"))
        return df.join(n, F.col(column) == n["_doc"]).withColumn(column, F.col("_id")).drop("_doc", "_id")

    def matched(self, docs: DataFrame, chosen: DataFrame, how: str) -> DataFrame:
        """``docs`` joined (``left_semi``, ``left_anti``) with the keys ``chosen`` (doc); columns stay as they are."""
        if self.names is None:
            c = chosen.select(F.col("doc").alias("_doc"))
            return docs.join(c, F.coalesce(docs["doc_id"].cast("long"), F.lit(NO_ID)) == c["_doc"], how)
        c = chosen.join(self.names, "doc").select(F.coalesce("doc_id", F.lit(NO_ID)).alias("_id"), F.col("doc_id").isNull().alias("_none"), F.col("digest").alias("_digest"))
        same = (F.coalesce(docs["doc_id"].cast("long"), F.lit(NO_ID)) == c["_id"]) & (docs["doc_id"].cast("long").isNull() == c["_none"])
        return docs.join(c, same & F.sha2(docs["text"].cast("string").cast("binary"), 256).eqNullSafe(c["_digest"]), how)

    def one_of_equal(self, docs: DataFrame) -> DataFrame:
        """One row for each (doc_id, text) of ``docs``; columns stay as they are."""
        if self.names is None:
            return docs
        a, b = unused(docs, "_id"), unused(docs, "_digest")
        return docs.withColumns({a: F.col("doc_id").cast("long"), b: _digest()}).dropDuplicates([a, b]).drop(a, b)


def _id_of(doc: str) -> Column:
    return F.when(F.col(doc) != NO_ID, F.col(doc))


def keyed(docs: DataFrame, scratch: Scratch) -> Keyed:
    """Rows with a key of their own for each distinct (doc_id, text).

    Only tables in which rows share a doc_id, null included, pay for the keys: they are told
    apart by a count over the doc_id column alone. There, distinct rows are numbered along
    doc_id and a digest of the text by one range shuffle.
    """
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    most = docs.select(_order().alias("_o")).groupBy("_o").count().agg(F.max("count")).first()[0]
    if (most or 0) <= 1:
        return Keyed(d.select(_order().alias("doc"), "text"))
    one = d.groupBy("doc_id", _digest().alias("digest")).agg(F.first("text").alias("text"), F.count("*").alias("copies"))
    place = numbered(one, [F.col("doc_id").asc_nulls_last(), F.col("digest")], "_n")
    sizes = scratch.put(place.groupBy("doc_id").agg(F.min("_n").alias("_first"), F.count("*").alias("_size")), "ids")
    n, most = sizes.agg(F.sum("_size"), F.max("_size")).first()
    shift = (most - 1).bit_length()
    if (n - 1).bit_length() + shift > 62:
        raise ValueError("too many rows share a doc_id for keys of 64 bits")
    # an id of one row needs no look-up: its first row is itself
    shared = sizes.where("_size > 1").select(F.col("doc_id").alias("_id"), "_first")
    shared = F.broadcast(shared) if shared.count() <= BROADCAST_ROWS else shared
    place = place.join(shared, F.col("doc_id").eqNullSafe(F.col("_id")), "left").withColumn("_first", F.coalesce("_first", "_n"))
    key = F.shiftleft("_first", shift) + F.col("_n") - F.col("_first")
    place = scratch.put(place.select(key.alias("doc"), "doc_id", "digest", "copies", "text"), "keyed")
    return Keyed(place.select("doc", "text"), shift, place.select("doc", "doc_id", "digest", "copies"))


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
