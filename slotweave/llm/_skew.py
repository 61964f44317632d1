"""Joins on keys of which one may hold a third of all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of one key that stay together; and the share of all rows above which a key counts as hot, so at most its inverse are.
TOGETHER, SHARE = 128, 1e-5


def hot_keys(rows: DataFrame, keys: list[str], total: int | None = None) -> DataFrame:
    """The keys with many rows and the number of parts to cut them in: at most 1 / SHARE rows, so they may be broadcast."""
    return too_many(rows.groupBy(*keys).agg(F.count("*").alias("__n")), keys, "__n", rows.count() if total is None else total)


def too_many(counts: DataFrame, keys: list[str], count: str, total: int) -> DataFrame:
    """The same from known counts of the keys."""
    bound = max(TOGETHER, int(total * SHARE))
    return counts.filter(F.col(count) > bound).select(*keys, F.ceil(F.col(count) / bound).cast("int").alias("__parts"))


def spread_join(rows: DataFrame, unique: DataFrame, keys: list[str], how: str = "inner", hot: DataFrame | None = None, merge: bool = False) -> DataFrame:
    """rows joined with unique, which has each key once. A hot key's rows are dealt over parts by their own hash, and its
    row of unique is repeated for each part, so no task gets more than a bounded number of them. hot: the keys with __parts, if known.
    merge: sort and merge whatever the sizes, so that what moves grows as the input does."""
    hot = hot_keys(rows, keys) if hot is None else hot
    parts = F.coalesce("__parts", F.lit(1))
    salted = rows.join(F.broadcast(hot), keys, "left").withColumn("__part", F.pmod(F.xxhash64(*rows.columns), parts).cast("int")).drop("__parts")
    copies = unique.join(F.broadcast(hot), keys, "left").withColumn("__part", F.explode(F.sequence(F.lit(0), parts - 1))).drop("__parts")
    return salted.join(copies.hint("merge") if merge else copies, [*keys, "__part"], how).drop("__part")


#: Parts over which fanned_join deals every key.
FANS = 8


def fanned_join(rows: DataFrame, unique: DataFrame, keys: list[str]) -> DataFrame:
    """The same for narrow rows, without counting: every key's rows are dealt over a few parts, and every row of unique is repeated for each."""
    salted = rows.withColumn("__part", F.pmod(F.xxhash64(*rows.columns), F.lit(FANS)).cast("int"))
    copies = unique.withColumn("__part", F.explode(F.sequence(F.lit(0), F.lit(FANS - 1))))
    return salted.join(copies, [*keys, "__part"]).drop("__part")
