"""Encoding by merges in rank order, then expansion of internal tokens; decoding; lengths without encoding."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import replace

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slotweave.functions.pretok import chunks_of
from slotweave.functions.symbols import symbol, token_of

from .exposure import exposures
from .train import MergeLog, Replacer, byte_counts, merged
from .visibility import Tokenizer

#: Chunks of the cache; chunks that a task turns into Python's at once, a longer text aside.
CACHE, HELD = 300_000, 100_000


class ChunkEncoder:
    """bytes of a chunk -> exported ids; cached, and the cache is bounded."""

    def __init__(self, tok: Tokenizer):
        self.after = Replacer({(m.left, m.right): m.token for m in tok.log.merges})
        ids = tok.export_ids()
        self.emit = [[ids[t] for t in e] for e in tok.expansions()]
        self.known: dict[str, list[int]] = {}

    def tokens(self, data: bytes) -> list[int]:
        return list(map(token_of, self.after(data.decode("latin-1"))))

    def __call__(self, chunk: str) -> list[int]:
        if (found := self.known.get(chunk)) is None:
            if len(self.known) >= CACHE:
                self.known.clear()
            found = self.known[chunk] = [i for t in self.tokens(chunk.encode("utf-8", "surrogatepass")) for i in self.emit[t]]
        return found


def in_parts(batch: pa.RecordBatch, most: int) -> Iterator[pa.RecordBatch]:
    """The batch's rows in order, so many at once as hold most elements in their second column's lists, one row at least: a batch of long texts has millions."""
    sizes, start, held = pc.fill_null(pc.list_value_length(batch.column(1)), 0).to_pylist(), 0, 0
    for i, n in enumerate(sizes):
        if i > start and held + n > most:
            yield batch.slice(start, i - start)
            start, held = i, 0
        held += n
    yield batch.slice(start)


def encode(docs: DataFrame, tok: Tokenizer, text: str = "text", id_col: str = "doc_id", pretok: bool = True) -> DataFrame:
    """id and ids of each text, where its row stands: no shuffle, so it also serves streams and skewed text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one = ChunkEncoder(tok)
        for batch in (part for whole in batches for part in in_parts(whole, HELD)):
            ids = [[i for c in chunks for i in one(c)] for chunks in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.list_(pa.int32()))], names=[id_col, "ids"])

    return docs.select(F.col(id_col).cast("long").alias(id_col), chunks_of(F.col(text), pretok).alias("c")).mapInArrow(run, f"{id_col} long, ids array<int>")


def encode_chunks_native(chunks: DataFrame, tok: Tokenizer) -> DataFrame:
    """sym, n and the number of visible tokens: the merged chunk's symbols, and for each internal one how many more it becomes."""
    after = merged(chunks.select("sym", "n", F.col("sym").alias("whole")), tok.log)
    fan = {symbol(t): len(e) - 1 for t, e in enumerate(tok.expansions()) if len(e) > 1}
    out = F.col("sym")
    extra = F.lit(0)
    if fan:
        table = F.create_map(*[F.lit(x) for pair in fan.items() for x in pair])
        inner = F.filter(F.split(out, ""), lambda c: F.contains(F.lit("".join(fan)), c) & (c != ""))
        extra = F.aggregate(inner, F.lit(0), lambda s, c: s + F.coalesce(table[c], F.lit(0)))
    return after.select(F.col("whole").alias("sym"), "n", (F.char_length(out) + extra).cast("long").alias("tokens"))


def decode_ids(encoded: DataFrame, tok: Tokenizer, id_col: str = "doc_id", ids: str = "ids") -> DataFrame:
    """id and text: the bytes of the ids end to end; reserved tokens spell nothing."""
    table = [tok.log.token_bytes(t) for t in tok.visible] + [b""] * tok.n_reserved

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spelled = [None if i is None else b"".join(map(table.__getitem__, i)).decode("utf-8", "replace") for i in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(spelled, pa.string())], names=[id_col, "text"])

    return encoded.select(F.col(id_col).cast("long").alias(id_col), ids).mapInArrow(run, f"{id_col} long, text string")


def with_specials(ids: Column, tok: Tokenizer, end: bool = True, start: bool = False, pad_to: int | None = None) -> Column:
    """ids with reserved tokens around them; the reserved ones are end, start, separator and padding."""
    first = len(tok.visible)
    out = F.concat(F.array(F.lit(first + 1)), ids) if start else ids
    out = F.concat(out, F.array(F.lit(first))) if end else out
    return F.concat(out, F.array_repeat(F.lit(first + 3), F.greatest(F.lit(0), F.lit(pad_to) - F.size(out)))) if pad_to else out


def encoded_length(chunks: DataFrame, tok: Tokenizer) -> int:
    """Tokens of a whole corpus, by encoding its distinct chunks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one = ChunkEncoder(tok)
        fan = [len(e) for e in one.emit]
        for batch in batches:
            total = sum(n * sum(fan[t] for t in one.tokens(bytes(map(ord, s)))) for s, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True))
            yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], names=["tokens"])

    return chunks.select("sym", F.col("n").cast("long")).mapInArrow(run, "tokens long").agg(F.coalesce(F.sum("tokens"), F.lit(0))).first()[0]


def length_from_log(log: MergeLog, m: int | None = None) -> int:
    return sum(log.byte_counts) - sum(x.repl for x in log.merges[:m])


def vp_length_from_log(tok: Tokenizer, log: MergeLog) -> int:
    """Length under tok of the corpus whose replacements log holds; log's merges begin with tok's."""
    own = log.prefix(len(tok.log))
    e, fans = exposures(own), tok.expansions()
    return length_from_log(own) + sum(e[t] * (len(fans[t]) - 1) for t in tok.internal)


def replay(log: MergeLog, chunks: DataFrame) -> MergeLog:
    """The log with the replacements that its merges make on another corpus: one encoding with counters gives every length."""
    ranks = {(m.left, m.right): m.token for m in log.merges}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made, after = Counter(), Replacer(ranks)
        for batch in batches:
            for s, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                own: Counter[int] = Counter()
                after(s, own)
                for token, times in own.items():
                    made[token - 256] += n * times
        yield pa.RecordBatch.from_arrays([pa.array(list(made), pa.int64()), pa.array(list(made.values()), pa.int64())], names=["rank", "repl"])

    got = {r["rank"]: r["repl"] for r in chunks.select("sym", F.col("n").cast("long")).mapInArrow(run, "rank long, repl long").groupBy("rank").agg(F.sum("repl").alias("repl")).collect()}
    return MergeLog(tuple(replace(m, repl=got.get(m.rank, 0)) for m in log.merges), byte_counts(chunks))
