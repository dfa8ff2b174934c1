"""Where tables that cut lineage are written."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import SparkSession

#: Folder of each session below its root.
_FOLDERS: dict[tuple[str, str], str] = {}


def scratch_path(spark: SparkSession, what: str) -> str:
    """A new path under the shared folder that the session names; a temporary folder only where driver and tasks are one process.

    All such paths of a session are in one folder, which goes when its driver ends.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root is None:
        local = spark.sparkContext.master.startswith("local")
        root = f"file://{tempfile.gettempdir()}/geopages" if local else spark.conf.get("spark.sql.warehouse.dir")
    key = (root, spark.sparkContext.applicationId)
    if key not in _FOLDERS:
        _FOLDERS[key] = f"{root.rstrip('/')}/session-{uuid.uuid4().hex[:12]}"
        delete_at_exit(spark, _FOLDERS[key])
    return f"{_FOLDERS[key]}/{what}-{uuid.uuid4().hex[:12]}"


def delete_at_exit(spark: SparkSession, folder: str) -> None:
    """Make a folder that is removed, with all in it, when the driver's JVM ends."""
    p = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = p.getFileSystem(spark._jsc.hadoopConfiguration())
    fs.mkdirs(p)
    fs.deleteOnExit(p)
