"""Final exposure: how often a token stands in the corpus after all merges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slotweave.functions.symbols import token_column

from .train import MergeLog, merged


def exposures(log: MergeLog, m: int | None = None) -> list[int]:
    """By token, in closed form: what its merge made, less what later merges took."""
    own = log.merges[: len(log) if m is None else m]
    out = [*log.byte_counts, *[0] * len(own)]
    for x in own:
        out[x.token] += x.repl
        out[x.left] -= x.repl
        out[x.right] -= x.repl
    return out


def exposure_by_count(chunks: DataFrame, log: MergeLog) -> DataFrame:
    """The same by counting symbols of the merged corpus."""
    spark = chunks.sparkSession
    seen = merged(chunks, log).select(F.explode(F.split("sym", "")).alias("s"), "n").filter("s != ''").groupBy("s").agg(F.sum("n").alias("e"))
    seen = seen.select(token_column(F.col("s")).cast("int").alias("token"), "e")
    return spark.range(256 + len(log)).select(F.col("id").cast("int").alias("token")).join(seen, "token", "left").select("token", F.coalesce("e", F.lit(0)).alias("exposure"))


def exposure_from_log(log: MergeLog, spark, m: int | None = None) -> DataFrame:
    return spark.createDataFrame(list(enumerate(exposures(log, m))), "token int, exposure long")


def absorption(log: MergeLog, spark) -> DataFrame:
    e = exposures(log)
    return spark.createDataFrame([(x.token, x.freq, e[x.token]) for x in log.merges], "token int, freq long, exposure long").withColumn("absorbed", F.round((F.col("freq") - F.col("exposure")) / F.col("freq"), 4))
