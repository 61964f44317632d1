"""Exact duplicates with a two-pass Bloom filter, in DataFrame functions alone.

First pass: each task counts its texts' 64-bit hashes, and the sums of those counts name the hashes met more than once: 16 bytes move for each
distinct hash of a task, never a text. (Dense filters of bits, one from each task, would move tasks x filter instead: at 30 billion texts in 100,000
tasks 6 PB, against 0.5 TB.) Each repeated hash sets three of 64 bits in a word of the filter. It has at
most MOST_WORDS words, about 100 MB as a broadcast. Second pass: every row probes it where it stands.
Rows that miss are surely single and pass straight through; only possible repeats shuffle, by the SHA-256 of
their text. A filter that is too full for the data sends more rows through the shuffle, never a wrong one.

Groups with at least a thousandth of the possible repeats (a thousand at most) are joined back by broadcast,
so a group with a third of all rows stays spread over the tasks that read it.

Edge cases: a null text counts as empty, and all empty texts are one group. A null doc_id never wins over
another. Repeated rows of one doc_id are counted as rows and decided alike. An empty table
gives an empty result; extra columns pass through ``drop_exact`` and are ignored by ``exact_groups``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._store import Scratch

#: Words of the filter: a power of two near a quarter of the rows, between these two.
LEAST_WORDS, MOST_WORDS = 1 << 16, 1 << 21


def _slots(h: Column, words: int) -> tuple[Column, Column]:
    one = F.expr("1L")
    bits = [F.call_function("shiftleft", one, F.shiftrightunsigned(h, at).bitwiseAND(F.lit(63)).cast("int")) for at in (40, 46, 52)]
    return F.pmod(h, F.lit(words)).alias("slot"), bits[0].bitwiseOR(bits[1]).bitwiseOR(bits[2]).alias("bits")


def filter_words(rows: int) -> int:
    words = LEAST_WORDS
    while words < min(rows // 4, MOST_WORDS):
        words *= 2
    return words


def _probed(docs: DataFrame, text: Column) -> DataFrame:
    """docs with its text's SHA-256 and whether that may be repeated."""
    words = filter_words(docs.count())
    seen = docs.select(F.xxhash64(text).alias("h")).groupBy("h").agg(F.count("*").alias("n"))
    repeats = seen.filter("n > 1").select(*_slots(F.col("h"), words)).groupBy("slot").agg(F.bit_or("bits").alias("__filled")).withColumnRenamed("slot", "__slot")
    slot, bits = _slots(F.xxhash64(text), words)
    own = docs.withColumns({"__slot": slot, "__bits": bits, "__sha": F.sha2(text, 256)}).join(F.broadcast(repeats), "__slot", "left")
    own = own.withColumn("__maybe", F.coalesce(F.col("__filled").bitwiseAND(F.col("__bits")) == F.col("__bits"), F.lit(False)))
    return own.drop("__slot", "__bits", "__filled")


def _text(docs: DataFrame, text_col: str) -> Column:
    return F.coalesce(docs[text_col].cast("string"), F.lit(""))


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row per document: doc_id, keep_id, group_size, kept, text_sha256; the largest doc_id of a group is kept."""
    scratch = Scratch(docs.sparkSession, "exact")
    rows = _probed(docs, _text(docs, text_col)).select(F.col(id_col).alias("doc_id"), "__sha", "__maybe")
    rows = scratch.save(rows, "rows")
    single = rows.filter(~F.col("__maybe")).select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), "__sha")
    maybe = rows.filter("__maybe").select("doc_id", "__sha")
    groups = scratch.save(maybe.groupBy("__sha").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size")), "groups")
    large = max(1000, maybe.count() // 1000)
    hot = groups.filter(F.col("group_size") >= large)
    cold = groups.filter(F.col("group_size") < large).toDF("__sha", "k", "g")
    met = maybe.join(F.broadcast(hot), "__sha", "left")
    done = met.filter("group_size is not null").select(*single.columns)
    rest = met.filter("group_size is null").select("doc_id", "__sha").join(cold, "__sha").select("doc_id", F.col("k").alias("keep_id"), F.col("g").alias("group_size"), "__sha")
    out = single.unionByName(done).unionByName(rest)
    return out.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.col("__sha").alias("text_sha256"))


def drop_exact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows that stay, with all their columns."""
    probed = _probed(docs, _text(docs, text_col))
    maybe = probed.filter("__maybe")
    winners = maybe.groupBy("__sha").agg(F.max(id_col).alias("__keep"))
    same = (maybe["__sha"] == winners["__sha"]) & maybe[id_col].eqNullSafe(winners["__keep"])
    kept = maybe.join(winners, same, "left_semi")
    return probed.filter(~F.col("__maybe")).unionByName(kept).select(*docs.columns)
