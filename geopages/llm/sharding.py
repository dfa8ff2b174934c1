"""Sharding by size-tiered compaction.

Arrivals are appended in the order of their rows (of files: by name and place in the file,
however Spark would pack them into tasks), each task's rows as one small immutable shard.
Compaction merges shards that follow one another, those of one size tier (sizes within a
factor of ``fan_in``) first, until they reach the target size; a merge reads its shards in
order and writes one new file, without a shuffle. So the shards, one after another, hold the
rows in the order of arrival. What the store holds is said by a manifest: each version
is a new file, written aside and renamed into place, which fails if another writer
has taken the number; the loser applies its change to the newer version and tries again.
Readers see a whole version or the one before. A task or a driver lost in between leaves
files that no manifest names; ``vacuum`` removes them, but nothing that one of the last
versions names (an older reader may still hold it) and nothing young enough to belong
to an arrival that is not committed yet.

Results by case: rows, nulls and columns pass through unchanged; an empty table makes a
version with no shards; equal rows are all kept; arrivals with other columns add them, null in rows without, and
one in which a column has another type is refused.
"""

from __future__ import annotations

import json
import random
import time
import uuid
from collections.abc import Callable
from dataclasses import asdict, dataclass
from functools import reduce
from itertools import accumulate, groupby
from math import floor, log

from py4j.protocol import Py4JJavaError
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

from ._common import column_of, scratch_root, table, unused

TARGET_BYTES, FAN_IN = 128 << 20, 8
#: ``vacuum`` keeps the files of this many newest versions, and files younger than this many seconds.
KEEP_VERSIONS, GRACE_SECONDS = 10, 24 * 3600
#: Times that a change is tried against versions of other writers.
ATTEMPTS = 50
#: Merges that one Spark job runs side by side.
MERGES_PER_JOB = 64
#: Else the merges of one job, each of a single partition, would end up in one file.
_UNION = "spark.sql.unionOutputPartitioning"


@dataclass(frozen=True)
class Shard:
    path: str
    bytes: int
    rows: int
    level: int
    #: Place of its first arrival, for the order of neighbours.
    seq: int


def _all_columns(a: StructType | None, b: StructType) -> StructType:
    """Columns of both, those of ``a`` first, all nullable; raises where a name has two types."""
    out = [StructField(f.name, f.dataType) for f in (a or StructType())]
    types = {f.name.lower(): f.dataType for f in out}
    for f in b:
        have = types.get(f.name.lower())
        if have is None:
            out.append(StructField(f.name, f.dataType))
        elif have.simpleString() != f.dataType.simpleString():
            raise ValueError(f"column {f.name} is {have.simpleString()} in the store, {f.dataType.simpleString()} in the arrival")
    return StructType(out)


class VersionTaken(RuntimeError):
    """Another writer has committed the version."""


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, target_bytes: int = TARGET_BYTES, fan_in: int = FAN_IN):
        self.spark, self.root, self.target, self.fan_in = spark, root.rstrip("/"), target_bytes, fan_in
        self._jvm = spark._jvm
        self._fs = self._path(root).getFileSystem(spark._jsc.hadoopConfiguration())

    def _path(self, p: str):
        return self._jvm.org.apache.hadoop.fs.Path(p)

    def _list(self, directory: str):
        p = self._path(directory)
        return sorted(self._fs.listStatus(p), key=lambda s: s.getPath().getName()) if self._fs.exists(p) else []

    # versions

    def version(self) -> int:
        names = [s.getPath().getName() for s in self._list(f"{self.root}/_versions")]
        return max([0, *(int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json"))])

    def _manifest(self, version: int | None) -> dict:
        version = self.version() if version is None else version
        if not version:
            return {"shards": []}
        f = self._fs.open(self._path(f"{self.root}/_versions/v{version:010d}.json"))
        try:
            text = self._jvm.org.apache.commons.io.IOUtils.toString(f, "UTF-8")
        finally:
            f.close()
        return json.loads(text)

    def shards(self, version: int | None = None) -> list[Shard]:
        return [Shard(**x) for x in self._manifest(version)["shards"]]

    def schema(self, version: int | None = None) -> StructType | None:
        """Columns of all arrivals up to a version; None before the first."""
        manifest = self._manifest(version)
        if said := manifest.get("schema"):
            return StructType.fromJson(said)
        # a manifest without a schema: the columns of its shards
        return reduce(_all_columns, (self.spark.read.parquet(s["path"]).schema for s in manifest["shards"]), None)

    def commit(self, shards: list[Shard], after: int, schema: StructType | None = None) -> int:
        """Make ``shards`` the version that follows ``after``; raises VersionTaken if another writer has done so. ``schema`` is that of ``after`` unless given."""
        schema = schema or self.schema(after)
        target = f"{self.root}/_versions/v{after + 1:010d}.json"
        aside = f"{self.root}/_versions/_{uuid.uuid4().hex}"
        out = self._fs.create(self._path(aside), False)
        try:
            out.write(bytearray(json.dumps({"version": after + 1, "schema": schema and schema.jsonValue(), "shards": [asdict(s) for s in sorted(shards, key=lambda s: s.seq)]}).encode()))
        finally:
            out.close()
        context = self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(self._path(aside).toUri() if "://" in aside else self._fs.getUri(), self.spark._jsc.hadoopConfiguration())
        options = self.spark.sparkContext._gateway.new_array(getattr(self._jvm, "org.apache.hadoop.fs.Options$Rename"), 0)
        try:
            context.rename(self._path(aside), self._path(target), options)  # never over a file that is there
        except Py4JJavaError as e:
            self._fs.delete(self._path(aside), False)
            if self._fs.exists(self._path(target)):
                raise VersionTaken(f"version {after + 1} exists") from e
            raise
        return after + 1

    def _change(self, change: Callable[[int, list[Shard]], tuple[list[Shard], StructType | None]]) -> int:
        """Commit what ``change`` makes of the newest version and its shards, again and again if other writers come first."""
        for _ in range(ATTEMPTS):
            now = self.version()
            shards, schema = change(now, self.shards(now))
            try:
                return self.commit(shards, now, schema)
            except VersionTaken:
                time.sleep(random.random() / 10)
        raise VersionTaken(f"{ATTEMPTS} attempts lost against other writers")

    # data

    def _written(self, df: DataFrame, level: int) -> list[tuple[str, int, int]]:
        """Write ``df``, a file for each partition that has rows: (path, bytes, rows) in the order of the partitions."""
        directory = f"{self.root}/data/{level}-{uuid.uuid4().hex[:12]}"
        was = self.spark.conf.get(_UNION, "true")
        self.spark.conf.set(_UNION, "false")
        try:
            df.write.parquet(directory)
        finally:
            self.spark.conf.set(_UNION, was)
        files = {s.getPath().getName(): (s.getPath().toString(), s.getLen()) for s in self._list(directory) if s.getPath().getName().endswith(".parquet")}
        read = self.spark.read.schema(df.schema).parquet(directory)
        rows = {r.name: r["count"] for r in read.select(F.col("_metadata.file_name").alias("name")).groupBy("name").count().collect()}
        return [(*files[n], rows[n]) for n in sorted(files) if rows.get(n)]

    def append(self, df: DataFrame) -> int:
        """Add ``df``'s rows behind all others; a version is made even of an empty table."""
        _all_columns(self.schema(), df.schema)  # refuses before anything is written
        parts = in_file_order(df)
        written = [w for lo in range(0, len(parts), MERGES_PER_JOB) for w in self._written(reduce(DataFrame.union, parts[lo : lo + MERGES_PER_JOB]), 0)]

        def change(now: int, have: list[Shard]):
            seq = max([-1, *(s.seq for s in have)]) + 1
            new = [Shard(p, b, r, 0, seq + i) for i, (p, b, r) in enumerate(written)]
            return [*have, *new], _all_columns(self.schema(now), df.schema)

        return self._change(change)

    def tier(self, size: int) -> int:
        return floor(log(max(size, 1), self.fan_in))

    def plan(self, shards: list[Shard]) -> list[list[Shard]]:
        """Runs of shards that follow one another, to merge: those of one tier first; when nowhere enough of a tier stand together, whatever small neighbours are left."""
        ordered = sorted(shards, key=lambda s: s.seq)
        small = lambda s: 2 * s.bytes <= self.target
        tiers = [list(v) for k, v in groupby(ordered, lambda s: self.tier(s.bytes) if small(s) else None) if k is not None]
        full = [v for v in tiers if len(v) >= self.fan_in]
        out = []
        for same in full or [list(v) for k, v in groupby(ordered, small) if k]:
            run: list[Shard] = []
            for s in same:
                if run and (sum(x.bytes for x in run) + s.bytes > self.target * 5 // 4 or len(run) >= self.fan_in):
                    out.append(run)
                    run = []
                run.append(s)
            out.append(run)
        return [r for r in out if len(r) > 1]

    def compact(self, sole: bool = False) -> int:
        """Merge until no run is left to merge; each round is one version. ``sole``: nobody else reads or writes the store, so merged files go at once."""
        now = self.version()
        while runs := self.plan(self.shards(now)):
            schema = self.schema(now)
            read = lambda s: self.spark.read.schema(schema).parquet(s.path)  # noqa: B023, E731
            done: list[tuple[list[Shard], Shard]] = []
            for lo in range(0, len(runs), MERGES_PER_JOB):
                part = runs[lo : lo + MERGES_PER_JOB]
                merged = [reduce(DataFrame.union, map(read, run)).coalesce(1) for run in part]
                level = max(s.level for run in part for s in run) + 1
                for run, (p, b, r) in zip(part, self._written(reduce(DataFrame.union, merged), level), strict=True):
                    assert r == sum(s.rows for s in run), "a merge must keep all rows"
                    done.append((run, Shard(p, b, r, level, run[0].seq)))

            def change(now: int, have: list[Shard], done=done):
                shards = {s.path: s for s in have}
                for run, new in done:
                    if all(s.path in shards for s in run):  # else another compaction has taken one of them
                        for s in run:
                            del shards[s.path]
                        shards[new.path] = new
                return list(shards.values()), None

            now = self._change(change)
            if sole:
                self.vacuum(1, 0)
        return now

    def vacuum(self, keep_versions: int = KEEP_VERSIONS, grace_seconds: float = GRACE_SECONDS) -> None:
        """Remove data that none of the last ``keep_versions`` versions names and that is older than ``grace_seconds``.

        An arrival that takes longer than that from its first file to its commit needs a longer grace.
        """
        newest = self.version()
        kept = range(max(1, newest - keep_versions + 1), newest + 1)
        live = {self._path(s.path).getName() for v in kept for s in self.shards(v)}
        before = time.time() * 1000 - grace_seconds * 1000
        for d in self._list(f"{self.root}/data"):
            files = self._list(d.getPath().toString())
            # what isn't a shard (a job's own marks) goes with the last shard of its directory
            shards = [f for f in files if f.getPath().getName().endswith(".parquet")]
            dead = [f for f in shards if f.getPath().getName() not in live and f.getModificationTime() <= before]
            if len(dead) == len(shards) and all(f.getModificationTime() <= before for f in [d, *files]):
                self._fs.delete(d.getPath(), True)
            else:
                for f in dead:
                    self._fs.delete(f.getPath(), False)

    def read(self, version: int | None = None) -> DataFrame | None:
        """Rows of a version, the newest unless given, with ``_shard`` (with more underscores if that is taken): struct of id (place in the manifest), rows, bytes, level and position (place among all rows, shard after shard); None if it has no shards."""
        version = self.version() if version is None else version
        shards = self.shards(version)
        if not shards:
            return None
        starts = accumulate((s.rows for s in shards), initial=0)
        names = self.spark.createDataFrame([(s.path.rsplit("/", 1)[-1], i, s.rows, s.bytes, s.level, n) for i, (s, n) in enumerate(zip(shards, starts, strict=False))], "__shard_file string, id long, rows long, bytes long, level int, __start long")
        files = self.spark.read.schema(self.schema(version)).parquet(*[s.path for s in shards])
        rows = files.select(F.struct(*[column_of(files, c) for c in files.columns]).alias("__row"), F.col("_metadata.file_name").alias("__shard_file"), F.col("_metadata.row_index").alias("__place"))
        about = F.struct("id", "rows", "bytes", "level", (F.col("__start") + F.col("__place")).alias("position"))
        return rows.join(names, "__shard_file").select("__row.*", about.alias(unused(files, "_shard")))


def in_file_order(df: DataFrame) -> list[DataFrame]:
    """``df`` in parts that hold its rows in order: partitions as they are, but of a scan of files, which Spark packs by size, by file and place in it.

    Small files that follow one another are one part of one partition, sorted by file and place; a
    large file is a part of its own, split in order. No shuffle.
    """
    plan = df._jdf.queryExecution().analyzed()
    while plan.nodeName() in ("Project", "Filter", "SubqueryAlias"):
        plan = plan.children().head()
    if plan.getClass().getSimpleName() not in ("LogicalRelation", "DataSourceV2Relation"):
        return [df]
    spark = df.sparkSession
    try:
        # a row for each file
        files = df.select("_metadata.file_path", "_metadata.file_size").distinct().collect()
        df.select("_metadata.row_index")
    except AnalysisException:
        return [df]
    size = {r.file_path: r.file_size for r in files}
    if len(size) < 2:
        return [df]
    # a longer number of a part stands later
    order = sorted(size, key=lambda p: (len(p), p))
    default = spark._jsparkSession.sessionState().conf()
    most = min(default.filesMaxPartitionBytes(), max(default.filesOpenCostInBytes(), sum(size.values()) // spark.sparkContext.defaultParallelism))
    groups: list[list[str]] = []
    for p in order:
        if groups and sum(size[x] for x in groups[-1]) + size[p] <= most:
            groups[-1].append(p)
        else:
            groups.append([p])
    columns = [column_of(df, c) for c in df.columns]
    file, place = unused(df, "__file"), unused(df, "__place")
    path, row = F.col("_metadata.file_path"), F.col("_metadata.row_index")
    out = []
    for g in groups:
        part = df.where(path.isin(g))
        if len(g) > 1:
            part = part.select(*columns, path.alias(file), row.alias(place)).coalesce(1).sortWithinPartitions(F.length(file), file, place).drop(file, place)
        out.append(part)
    return out


def shard(docs: DataFrame, target_bytes: int = TARGET_BYTES, fan_in: int = FAN_IN, root: str | None = None, position: bool = False) -> DataFrame:
    """Append ``docs`` to a store, compact it and give each document's shard: (doc_id, shard_id, shard_rows, shard_level), on request with its position among all rows."""
    spark = docs.sparkSession
    store = ShardStore(spark, root or f"{scratch_root(spark)}/shards-{uuid.uuid4().hex[:12]}", target_bytes, fan_in)
    store.append(docs)
    store.compact(sole=root is None)
    rows = store.read()
    if rows is None:
        return docs.limit(0).selectExpr("doc_id", "0L as shard_id", "0L as shard_rows", "0 as shard_level", *["0L as position"] * position)
    at = unused(docs, "_shard")
    return rows.selectExpr("doc_id", f"{at}.id as shard_id", f"{at}.rows as shard_rows", f"{at}.level as shard_level", *[f"{at}.position as position"] * position)


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard(table(spark, sf_dir, "documents"))
