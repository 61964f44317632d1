"""Corpora and results in Spark's file formats, always with an explicit schema."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DOCUMENTS = "doc_id long, text string, lang string, source string, n_chars long"


def read(spark: SparkSession, path: str, kind: str, schema: str = DOCUMENTS) -> DataFrame:
    """kind: parquet, json, csv or orc; csv with header, quoted line ends kept."""
    reader = spark.read.schema(schema)
    if kind == "csv":
        reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    return reader.format(kind).load(path)


def over_all_cores(df: DataFrame) -> DataFrame:
    """Rows of fewer splits than cores, such as one small file, dealt over all cores; larger inputs stay as they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def write(df: DataFrame, path: str, kind: str, by: str | None = None) -> None:
    writer = df.write.mode("overwrite").format(kind)
    if kind == "csv":
        writer = writer.option("header", True).option("escape", '"')
    (writer.partitionBy(by) if by else writer).save(path)


def read_texts(spark: SparkSession, path: str, whole: bool = False) -> DataFrame:
    """A row per line, or per file."""
    return spark.read.text(path, wholetext=whole).select(F.col("value").alias("text"))


def read_binary(spark: SparkSession, path: str) -> DataFrame:
    """Files byte by byte, as symbol strings."""
    return spark.read.format("binaryFile").load(path).select("path", F.decode("content", "ISO-8859-1").alias("sym"))


def write_ids(encoded: DataFrame, path: str, by: str = "corpus") -> None:
    encoded.write.mode("overwrite").partitionBy(by).parquet(path)


def shared_folder(spark: SparkSession) -> tuple[str, str | None]:
    """The folder that driver and executors share, as the session names it; a local session without one gets a temporary one, which comes second as well."""
    sc = spark.sparkContext
    folder = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not folder and sc.master.split("[")[0] != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    own = None if folder else tempfile.mkdtemp(prefix="slotweave-")
    return (folder or own).rstrip("/"), own


def delete(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def free_driver(spark: SparkSession) -> None:
    """Collects the garbage of the driver's JVM: many jobs in a row leave plans and compiled classes behind, and its heap grows to all it may have before it is
    collected in full; afterwards it is given back."""
    spark.sparkContext._jvm.System.gc()
