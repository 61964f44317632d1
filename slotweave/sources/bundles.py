"""Tokenizers and training checkpoints as files."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slotweave.functions.pretok import JAVA
from slotweave.operators.train import Merge, MergeLog
from slotweave.operators.visibility import Tokenizer


def _write_log(spark: SparkSession, log: MergeLog, path: str, meta: dict, pretok: bool) -> None:
    log.frame(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/merges")
    spark.createDataFrame([(json.dumps(meta | {"byte_counts": log.byte_counts, "pretokenizer": JAVA if pretok else None}),)], "meta string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")


def _read_log(spark: SparkSession, path: str) -> tuple[MergeLog, dict]:
    meta = json.loads(spark.read.text(f"{path}/meta", wholetext=True).first()[0])
    if meta["pretokenizer"] not in (JAVA, None):
        raise ValueError("made with another pretokenizer")
    rows = spark.read.parquet(f"{path}/merges").orderBy("rank").collect()
    return MergeLog(tuple(Merge(r["rank"], r["left"], r["right"], r["token"], r["freq"], r["repl"], bytes(r["bytes"])) for r in rows), tuple(meta["byte_counts"])), meta


def save_tokenizer(tok: Tokenizer, path: str, spark: SparkSession, pretok: bool = True) -> None:
    """A lossless bundle, which records whether the texts were pretokenized and how, and the visible and internal vocabularies as text, a token per line in hex."""
    _write_log(spark, tok.log, path, {"internal": sorted(tok.internal), "n_reserved": tok.n_reserved, "trained": tok.trained, "tau": tok.tau}, pretok)
    for name, visible in (("visible", True), ("internal", False)):
        lines = tok.frame(spark).filter(F.col("visible") == visible).orderBy("export_id").select(F.lower(F.hex("bytes")))
        lines.coalesce(1).write.mode("overwrite").text(f"{path}/{name}")


def load_tokenizer(spark: SparkSession, path: str) -> Tokenizer:
    log, meta = _read_log(spark, path)
    return Tokenizer(log, frozenset(meta["internal"]), meta["n_reserved"], meta["trained"], meta["tau"])


def uses_pretokenizer(spark: SparkSession, path: str) -> bool:
    return _read_log(spark, path)[1]["pretokenizer"] is not None


def save_checkpoint(chunks: DataFrame, log: MergeLog, path: str, pretok: bool = True) -> None:
    chunks.write.mode("overwrite").parquet(f"{path}/chunks")
    _write_log(chunks.sparkSession, log, path, {}, pretok)


def load_checkpoint(spark: SparkSession, path: str) -> tuple[DataFrame, MergeLog]:
    return spark.read.parquet(f"{path}/chunks"), _read_log(spark, path)[0]
