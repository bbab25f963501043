"""Where iterative operators keep their state."""

from __future__ import annotations

import os
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


_made: set[str] = set()


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path in the folder that driver and executors share (spark.checkpoint.dir).

    Where the setting is missing, a session on one machine uses its warehouse; a cluster has to name a folder.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        root = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"
    path = f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    _made.add(path)
    return path


def stored(df: DataFrame, name: str) -> DataFrame:
    """Written and read back: plans of the next round begin at a table, and survive lost executors."""
    path = shared_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def forget(spark: SparkSession) -> None:
    """Remove everything that this process has stored: for when no result is read any more."""
    for path in list(_made):
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
        _made.discard(path)


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package to workers that would not find it: neither their folder nor PYTHONPATH leads here."""
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    here = {os.path.realpath(p) for p in [os.getcwd(), *os.environ.get("PYTHONPATH", "").split(os.pathsep)] if p}
    app = spark.sparkContext.applicationId
    if root in here or app in _shipped:
        return
    _shipped.add(app)
    made = shutil.make_archive(os.path.join(tempfile.mkdtemp(), "tplforge"), "zip", root, "tplforge")
    spark.sparkContext.addPyFile(made)
