"""Intermediate tables that survive the loss of executors.

Lineage is cut by writing Parquet into the folder that all executors share, the one the cluster
names in ``spark.checkpoint.dir``.  Only where that is unset in local mode, as in tests, a folder of
our own is made, and removed when Python ends; a result must be read before.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN: dict[str, str] = {}


def shared_root(spark: SparkSession) -> str:
    """The folder that all executors share; on a cluster without one this is an error."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        folder = tempfile.mkdtemp(prefix="sigres-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        _OWN[app] = "file://" + folder
    return _OWN[app]


class Scratch:
    """Named tables of one run, each in a folder that no other run uses."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.base = f"{shared_root(spark)}/sigres-{label}-{uuid.uuid4().hex}"
        self._n = 0

    def save(self, df: DataFrame, name: str) -> DataFrame:
        """Write the frame and return a scan of what was written."""
        self._n += 1
        path = f"{self.base}/{self._n:03d}-{name}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out.scratch_path = path
        return out

    def drop(self, *frames: DataFrame) -> None:
        """Delete tables that nothing reads any more."""
        jvm = self.spark.sparkContext._jvm
        conf = self.spark.sparkContext._jsc.hadoopConfiguration()
        for df in frames:
            path = jvm.org.apache.hadoop.fs.Path(df.scratch_path)
            path.getFileSystem(conf).delete(path, True)


def small_side(df: DataFrame, rows: int) -> DataFrame:
    """Mark a frame for broadcast if it has at most ``rows`` rows; else leave it to a shuffle join.

    ``df`` should be a scratch table, so that counting it reads only Parquet footers.
    """
    return F.broadcast(df) if df.count() <= rows else df
