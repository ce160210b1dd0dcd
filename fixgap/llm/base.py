"""What the corpus operators share: reading tables, shared storage, and shipping Python code to workers."""

from __future__ import annotations

import atexit
import ctypes
import os
import tempfile
import uuid
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

REPO = str(Path(__file__).resolve().parents[2])


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package: the repository goes on their PYTHONPATH (clusters may use --py-files)."""
    env = spark.sparkContext.environment
    have = env.get("PYTHONPATH", "")
    if REPO not in have.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (REPO, have) if x)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The shared folder the session names. Where it names none, a local session (as in tests) gets a folder of our own as
    checkpoint folder; on a cluster that is an error, since executors would each write to a disk of their own."""
    root = spark.conf.get("spark.checkpoint.dir", None) or os.environ.get("FIXGAP_SHARED")
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = os.environ["FIXGAP_SHARED"] = "file://" + tempfile.mkdtemp(prefix="fixgap-shared-")
        atexit.register(__import__("shutil").rmtree, root.removeprefix("file://"), True)
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def shared_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder, deleted when the driver program ends."""
    path = f"{shared_root(spark)}/fixgap-{name}-{uuid.uuid4().hex}"
    atexit.register(_delete, spark, path)
    return path


def _delete(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session has already ended; the folder's owner cleans up
        pass


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write df as a table in the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = shared_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def crc_text(col: str):
    """crc32 of the column as text, unsigned."""
    return F.crc32(F.col(col).cast("string").cast("binary"))


def is_empty(df: DataFrame) -> bool:
    return not df.take(1)


def give_back() -> None:
    """Return freed memory of this Python worker to the system: workers are kept, and a later stage's need comes on top."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass
