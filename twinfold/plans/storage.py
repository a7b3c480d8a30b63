"""Lineage cuts in storage that every executor sees.

A lost executor takes its cached blocks and shuffle files with it. Whatever an iteration or a
second pass needs again is therefore written as Parquet below the folder that the session names
in ``spark.checkpoint.dir``. Only where that is unset and driver and executors are one process (tests, notebooks) a folder of our own is made; on a cluster
an unset folder is an error, since executors would write to disks of their own.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder for intermediate tables; the session's own setting wins."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    master = spark.sparkContext.master
    if not (master == "local" or master.startswith("local[")):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        _OWN[app] = "file://" + tempfile.mkdtemp(prefix="twinfold-")
    return _OWN[app]


def materialise(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write once, read back: the result's lineage is a file scan. Deterministic rows from here on."""
    spark = df.sparkSession
    path = fresh(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._twinfold_path = path
    return out


def fresh(spark: SparkSession, name: str) -> str:
    """A path of its own below the shared folder."""
    return f"{shared_dir(spark)}/twinfold/{name}-{uuid.uuid4().hex}"


def discard(*frames: DataFrame) -> None:
    """Delete intermediate tables that nothing reads any more (through Spark's file system)."""
    for df in frames:
        path = getattr(df, "_twinfold_path", None)
        if path:
            sc = df.sparkSession.sparkContext
            p = sc._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(sc._jsc.hadoopConfiguration()).delete(p, True)


def width(spark: SparkSession) -> int:
    """Number of shuffle partitions of the session, the unit for salts and blocks."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
