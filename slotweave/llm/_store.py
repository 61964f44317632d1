"""Where intermediate tables go.

A written Parquet table cuts lineage as checkpoint() does, survives a lost executor, and can be read
with column pruning. Tables go below ``spark.checkpoint.dir``, which the cluster shares; only where the
session of one machine names none (tests) is a temporary folder set.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    sc = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not found:
        if sc.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="slotweave-")
        sc.setCheckpointDir(found)
    return found


def _delete(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session may have ended; the folder is the cluster's to clean
        pass


#: Tables saved between two collections of the driver's garbage.
COLLECT_EVERY = 3


class Scratch:
    """Tables of one operator run; drop() frees one early, the rest go when the process ends. Every few tables the garbage of the driver's JVM is
    collected: the plans and compiled classes of the jobs before would else fill its heap, which is given back afterwards."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"
        self.saved = 0
        atexit.register(_delete, spark, self.root)

    def save(self, df: DataFrame, name: str) -> DataFrame:
        path = f"{self.root}/{name}"
        df.write.mode("overwrite").option("compression", "zstd").parquet(path)
        self.saved += 1
        if self.saved % COLLECT_EVERY == 0:
            self.spark.sparkContext._jvm.System.gc()
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *names: str) -> None:
        for name in names:
            _delete(self.spark, f"{self.root}/{name}")
