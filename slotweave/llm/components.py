"""Connected components of a table of links, without gathering it.

Two alternating contractions: every node sends its larger neighbours, and then its smaller ones, to the smallest
node it knows. Links that each partition finds redundant by itself are left out first, so each contraction
shuffles no more than the forest. A node with many links is dealt over several tasks. The round stops when the links no longer change.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._skew import fanned_join
from ._store import Scratch

LINK = "a long, b long"


def _forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each batch's links as stars around its own smallest nodes."""
    for batch in batches:
        up: dict[int, int] = {}

        def root(x: int, up: dict[int, int] = up) -> int:
            top = x
            while (over := up.get(top, top)) != top:
                top = over
            while (over := up.get(x, x)) != top:
                up[x], x = top, over
            return top

        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            x, y = root(a), root(b)
            if x != y:
                up[max(x, y)] = min(x, y)
        nodes = list(up)
        yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([root(x) for x in nodes], pa.int64())], names=["a", "b"])


def connected(links: DataFrame, scratch: Scratch, name: str) -> DataFrame:
    """(node, root) of every node with a link to a smaller one; root, which has no row itself, is the smallest node of its component."""
    links = links.select("a", "b").filter("a != b").mapInArrow(_forest, LINK).distinct()
    links = scratch.save(links, f"{name}-0")
    before = None
    for step in range(1, 60):
        ways = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = ways.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = fanned_join(ways.filter("b > a"), least, ["a"]).select(F.col("b").alias("a"), F.col("m").alias("b"))
        # large holds links (node, smaller node); the same again among each node's smaller ones
        large = large.distinct()
        lower = large.groupBy("a").agg(F.min("b").alias("m"))
        small = fanned_join(large, lower, ["a"]).filter("b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        links = scratch.save(small.unionByName(lower.select("a", F.col("m").alias("b"))).distinct(), f"{name}-{step}")
        scratch.drop(f"{name}-{step - 1}")
        now = links.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h"), F.count_distinct("a").alias("d")).first()
        if now == before:
            break
        before = now
    return links.select(F.col("a").alias("node"), F.col("b").alias("root"))
