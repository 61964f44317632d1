"""The corpus pipeline: language ID, exact dedup, near-dedup, pseudonyms, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slotweave.llm import exact_dedup, langid, minhash, packing, pii
from slotweave.llm._store import Scratch


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language that the labelled ones show; those without a letter and those far from every language go."""
    own = {c: f"c{i}" for i, c in enumerate(docs.columns)}  # so that no column clashes with the operator's
    tagged = docs.toDF(*own.values())
    found = langid.identify(tagged, id_col=own["doc_id"], text_col=own["text"], lang_col=own["lang"], keep=tagged.columns)
    return found.filter("accepted").select(*tagged.columns).toDF(*docs.columns)


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents with the same text the one with the largest doc_id stays."""
    return exact_dedup.drop_exact(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: the one with the smallest doc_id. Shingles of five words, similarity 0.8."""
    gone = minhash.near_duplicates(docs).filter("not kept").select("doc_id").distinct()
    gone = Scratch(spark, "near").save(gone, "gone")
    few = gone.count() <= minhash.BROADCAST_IDS
    return docs.join(F.broadcast(gone) if few else gone, "doc_id", "left_anti").select(*docs.columns)


def private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data replaced by pseudonyms under the session's key; n_chars follows the text."""
    out = pii.pseudonymise(docs, pii.session_key(spark))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, 1024)


STAGES = [("language_id", language), ("exact_dedup", exact), ("near_dedup", near), ("pseudonyms", private), ("packing", packed)]

#: Language models, components and token ids have no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
