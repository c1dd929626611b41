"""Scratch tables and files in the one folder that driver and executors share.

The folder is ``spark.checkpoint.dir`` of the session.  Only where it is unset
and the master is local do we make a temporary folder of our own.  Tables
written here cut lineage: a lost executor costs a re-read, not a recompute.
"""

from __future__ import annotations

import atexit
import ctypes
import gc
import shutil
import tempfile
import uuid

import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_local_dirs: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """URI of the shared folder; raises on a cluster that names none."""
    conf = spark.sparkContext.getConf()
    found = conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return _qualified(spark, found).rstrip("/")
    if not conf.get("spark.master", "local").startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _local_dirs:
        folder = tempfile.mkdtemp(prefix="entlink-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        _local_dirs[app] = "file://" + folder
        spark.sparkContext.setCheckpointDir(_local_dirs[app])
    return _local_dirs[app]


def _qualified(spark: SparkSession, uri: str) -> str:
    """The folder with its scheme, so that Spark and Arrow mean the same store."""
    if "://" in uri:
        return uri
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(uri)
    full = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).makeQualified(path).toString()
    return full if "://" in full else full.replace(":", "://", 1)


def scratch_path(spark: SparkSession, tag: str) -> str:
    """A fresh path in this application's part of the shared folder."""
    return f"{shared_dir(spark)}/entlink-{spark.sparkContext.applicationId}/{tag}-{uuid.uuid4().hex}"


def clear_scratch(spark: SparkSession) -> None:
    """Delete all that this application wrote to the shared folder; frames read from it are void then."""
    remove(spark, f"{shared_dir(spark)}/entlink-{spark.sparkContext.applicationId}")


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` once as Parquet in the shared folder and return its reread."""
    spark = df.sparkSession
    path = scratch_path(spark, tag)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def discard(df: DataFrame) -> None:
    """Delete the files behind a frame made by :func:`materialize`."""
    path = getattr(df, "_scratch", None)
    if path:
        remove(df.sparkSession, path)


def remove(spark: SparkSession, uri: str) -> None:
    """Delete a file or folder on whatever store it is."""
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(uri)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def bounded_batches(spark: SparkSession, rows: int = 1024) -> None:
    """Let Arrow batches of long texts hold ``rows`` rows at most; a runtime setting of the session."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= rows:
        spark.conf.set(name, rows)


def locate(uri: str) -> tuple[pafs.FileSystem, str]:
    """Arrow's file system and path of a file or folder in the shared folder."""
    return pafs.FileSystem.from_uri(uri)


BROADCAST = "spark.sql.autoBroadcastJoinThreshold"


def measured_broadcasts(spark: SparkSession) -> None:
    """Let joins broadcast by sizes that were measured; a runtime setting of the session.

    Before a run Spark takes exploded words and vectors for hardly larger than the files they come from, and the driver
    fails to gather them.  The threshold stays as it was, but holds for what shuffles have written.
    """
    before = spark.conf.get(BROADCAST)
    if before != "-1":
        name = "spark.sql.adaptive.autoBroadcastJoinThreshold"
        if spark.conf.get(name, None) is None:
            spark.conf.set(name, before)
        spark.conf.set(BROADCAST, "-1")


HELD = 1 << 18  # keys that every task may hold


def held(df: DataFrame, tag: str) -> DataFrame:
    """A table of keys written once; joins send it to the tasks, so that what it meets stays put, if it has ``HELD`` rows at most."""
    stored = materialize(df, tag)
    return F.broadcast(stored) if stored.count() <= HELD else stored


def release_memory() -> None:
    """Give freed memory back to the system at the end of a task: Python workers live on, and many share a machine."""
    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # where the C library has it
    if trim:
        trim(0)


def spread(df: DataFrame) -> DataFrame:
    """Rows of a file with few splits dealt out to all cores, where the work on a row costs far more than its way."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(4 * cores) if df.rdd.getNumPartitions() < cores else df


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
