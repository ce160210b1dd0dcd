"""Tables in the session's shared folder: lineage is cut there, and lost executors cost no more than a rerun of lost tasks."""

from __future__ import annotations

import atexit
import itertools
import os
import shutil
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

REPO = str(Path(__file__).resolve().parents[2])


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package where the repository's path reaches them."""
    env = spark.sparkContext.environment
    have = env.get("PYTHONPATH", "")
    if REPO not in have.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (REPO, have) if x)


def folder(spark: SparkSession) -> str:
    root = spark.conf.get("spark.checkpoint.dir", None) or os.environ.get("FIXGAP_TABLES")
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = os.environ["FIXGAP_TABLES"] = "file://" + tempfile.mkdtemp(prefix="fixgap-tables-")
        atexit.register(shutil.rmtree, root.removeprefix("file://"), True)
    return root.rstrip("/")


class Scratch:
    """Tables of one computation, deleted when the program ends."""

    def __init__(self, spark: SparkSession):
        self.spark, self.path, self.n = spark, f"{folder(spark)}/fixgap-run-{uuid.uuid4().hex}", itertools.count(1)  # tables may be written from several threads
        atexit.register(self.close)

    def write(self, df: DataFrame) -> DataFrame:
        at = f"{self.path}/{next(self.n)}"
        df.write.parquet(at)
        return self.spark.read.schema(df.schema).parquet(at)

    def close(self) -> None:
        try:
            p = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
            p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # the session has ended; the folder's owner cleans up
            pass
