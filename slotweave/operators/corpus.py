"""Building and checking the training corpora."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def distinct_texts(docs: DataFrame) -> DataFrame:
    """One row per text, that of the smallest doc_id. Only checksums of 32 bytes move, and of repeated texts the ids that go."""
    docs = docs.filter("text is not null")
    sums = docs.select("doc_id", F.unhex(F.sha2("text", 256)).alias("sum"))
    repeated = sums.groupBy("sum").agg(F.min("doc_id").alias("first"), F.count("*").alias("n")).filter("n > 1")
    gone = sums.join(repeated, "sum").filter("doc_id <> first").select("doc_id")
    return docs.join(gone, "doc_id", "left_anti")


def build_corpora(docs: DataFrame) -> DataFrame:
    """Exact-deduplicated documents in two disjoint corpora: A leans to English, B is larger and more balanced."""
    docs = distinct_texts(docs.select("doc_id", "text", "lang", "source"))
    english = F.col("lang") == "en"
    a = (english & (F.col("doc_id") % 2 == 0)) | (~english & (F.col("doc_id") % 4 == 0))
    return docs.withColumn("corpus", F.when(a, "A").otherwise("B"))


def assert_disjoint(a: DataFrame, b: DataFrame, key: str = "text") -> DataFrame:
    """The rows of a whose key is in b as well: none, for disjoint corpora."""
    return a.join(b.select(key), key, "left_semi")


def cap_by_category(df: DataFrame, category: str, max_bytes: int, seed: str = "0") -> DataFrame:
    """Documents in random order up to the same bytes of each category. The order's first three digits deal a category over 4096 cells: sums of the
    cells before, and an order inside each cell, give every row its place."""
    order = F.md5(F.concat(F.col("doc_id").cast("string"), F.lit(seed)).cast("binary"))
    sized = df.withColumns({"__order": order, "__cell": F.substring(order, 1, 3), "__bytes": F.octet_length("text").cast("long")})
    cells = sized.groupBy(category, "__cell").agg(F.sum("__bytes").alias("__held"))
    w = Window.partitionBy(category).orderBy("__cell").rowsBetween(Window.unboundedPreceding, -1)
    before = cells.select(F.col(category).alias("__category"), F.col("__cell").alias("__at"), F.coalesce(F.sum("__held").over(w), F.lit(0)).alias("__before")).filter(F.col("__before") <= max_bytes)
    inside = Window.partitionBy(category, "__cell").orderBy("__order", "doc_id").rowsBetween(Window.unboundedPreceding, 0)
    placed = sized.join(before, F.col(category).eqNullSafe(F.col("__category")) & (F.col("__cell") == F.col("__at"))).withColumn("so_far", F.col("__before") + F.sum("__bytes").over(inside))
    return placed.filter(F.col("so_far") <= max_bytes).drop("__order", "__cell", "__bytes", "__before", "__category", "__at")


def shuffled_sample(df: DataFrame, share: float, seed: str = "0") -> DataFrame:
    """A random share of the documents by a threshold on a hash: no sort, so it holds at any size."""
    draw = F.conv(F.substring(F.md5(F.concat(F.col("doc_id").cast("string"), F.lit(seed)).cast("binary")), 1, 8), 16, 10).cast("long")
    return df.filter(draw < int(share * 2**32))


def drop_boilerplate(df: DataFrame, source: str = "source", min_documents: int = 5) -> DataFrame:
    """doc_id and text without the lines that stand in many documents of one source."""
    lines = df.select("doc_id", source, F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
    common = lines.filter("line != ''").groupBy(source, "line").agg(F.count_distinct("doc_id").alias("docs")).filter(F.col("docs") >= min_documents)
    # the empty line, a hot key that no rule drops, stays out of the join
    kept = lines.filter("line != ''").join(common, [source, "line"], "left_anti").unionByName(lines.filter("line = ''")).groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("pos", "line"))).alias("l"))
    return df.select("doc_id").join(kept, "doc_id", "left").select("doc_id", F.coalesce(F.array_join(F.transform("l", lambda x: x["line"]), "\n"), F.lit("")).alias("text"))


def corpus_profile(df: DataFrame) -> DataFrame:
    sized = df.select("corpus", "lang", F.octet_length("text").cast("long").alias("b"))
    return sized.rollup("corpus", "lang").agg(F.sum("b").alias("bytes"), F.count("*").alias("docs"))


def read_shards(spark: SparkSession, paths: list[str]) -> DataFrame:
    return spark.read.parquet(*paths)
