"""Fewest tokens of a vocabulary that spell each chunk: an exact program over positions that sees byte strings alone."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .visibility import Tokenizer


def vocabulary(tok: Tokenizer) -> list[bytes]:
    return [tok.log.token_bytes(t) for t in tok.visible]


class Trie:
    def __init__(self, words: list[bytes]):
        self.root: dict = {}
        for i, w in enumerate(words):
            node = self.root
            for b in w:
                node = node.setdefault(b, {})
            node[-1] = i

    def ends(self, data: bytes, start: int) -> Iterator[tuple[int, int]]:
        """(end, word) of the words that start here, shortest first."""
        node = self.root
        for i in range(start, len(data)):
            if (node := node.get(data[i])) is None:
                return
            if -1 in node:
                yield i + 1, node[-1]


def segment(trie: Trie, data: bytes) -> list[int]:
    """The words of a shortest segmentation; of several, at each place the longest first word."""
    n = len(data)
    cost, step = [0] * (n + 1), [(0, 0)] * n
    for i in range(n - 1, -1, -1):
        cost[i] = 1 << 60
        for end, word in trie.ends(data, i):
            if 1 + cost[end] <= cost[i]:
                cost[i], step[i] = 1 + cost[end], (end, word)
    out, i = [], 0
    while i < n:
        out.append(step[i][1])
        i = step[i][0]
    return out


def fewest(trie: Trie, data: bytes) -> int:
    """How many words a shortest segmentation has."""
    n = len(data)
    cost, root = [0] * (n + 1), trie.root
    for i in range(n - 1, -1, -1):
        node, best, at = root, 1 << 60, i
        while at < n and (node := node.get(data[at])) is not None:
            at += 1
            if -1 in node and cost[at] < best:
                best = cost[at]
        cost[i] = best + 1
    return cost[0]


def min_tokens(chunks: DataFrame, words: list[bytes]) -> DataFrame:
    """sym, n, tokens."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie = Trie(words)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([len(segment(trie, bytes(map(ord, s)))) for s in batch.column(0).to_pylist()], pa.int64())], names=["sym", "n", "tokens"])

    return chunks.select("sym", F.col("n").cast("long").alias("n")).mapInArrow(run, "sym string, n long, tokens long")


def min_tokens_relational(chunks: DataFrame, words: list[bytes]) -> DataFrame:
    """The same as joins: places x lengths against the vocabulary give edges, folded from the right. For small corpora."""
    spark = chunks.sparkSession
    longest = max(map(len, words))
    known = spark.createDataFrame([(w.decode("latin-1"),) for w in words], "w string")
    places = chunks.select("sym", "n", F.explode(F.sequence(F.lit(1), F.char_length("sym"))).alias("i"))
    spans = places.select("sym", "n", "i", F.explode(F.sequence(F.lit(1), F.least(F.lit(longest), F.char_length("sym") - F.col("i") + 1))).alias("len"))
    edges = spans.withColumn("w", F.substr("sym", "i", "len")).join(F.broadcast(known), "w", "left_semi")
    lists = edges.groupBy("sym", "n", "i").agg(F.collect_list("len").alias("lens")).groupBy("sym", "n").agg(F.reverse(F.array_sort(F.collect_list(F.struct("i", "lens")))).alias("p"))
    # the fold's state lists the costs from the current place on, so a word of length l leads to element l - 1
    fold = F.aggregate("p", F.array(F.lit(0)), lambda costs, p: F.concat(F.array(F.array_min(F.transform(p["lens"], lambda n: F.get(costs, n - 1))) + 1), costs))
    return lists.select("sym", F.col("n").cast("long").alias("n"), F.get(fold, F.lit(0)).cast("long").alias("tokens"))


def min_lengths(chunks: DataFrame, vocabularies: dict) -> dict:
    """Fewest tokens of the whole corpus under each vocabulary, in one pass."""
    keys = list(vocabularies)
    shared = chunks.sparkSession.sparkContext.broadcast(list(vocabularies.values()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tries = [Trie(words) for words in shared.value]
        totals = [0] * len(tries)
        for batch in batches:
            for sym, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                data = bytes(map(ord, sym))
                for i, trie in enumerate(tries):
                    totals[i] += n * fewest(trie, data)
        yield pa.RecordBatch.from_arrays([pa.array(range(len(tries)), pa.int32()), pa.array(totals, pa.int64())], names=["i", "tokens"])

    got = {r.i: r.tokens for r in chunks.select("sym", F.col("n").cast("long")).mapInArrow(run, "i int, tokens long").groupBy("i").agg(F.sum("tokens").alias("tokens")).collect()}
    return {k: got.get(i, 0) for i, k in enumerate(keys)}


def min_length(chunks: DataFrame, words: list[bytes]) -> int:
    return min_lengths(chunks, {0: words})[0]
