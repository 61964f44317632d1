"""Packing documents into fixed-length training sequences: first-fit decreasing in randomised groups.

Each document's ids are cut at every ``length`` ids. The pieces fall by a hash of document and place into groups
of about GROUP, so no key or source decides a group; in each the pieces go, longest first, into the first bin with
room, found by a tournament tree of the bins' room in log time. Groups are independent, so the work grows with the rows.

Edge cases: a null or empty text is the closing id alone; a long text gives as many full pieces as it needs; repeated rows of a doc_id
are packed each; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._store import Scratch
from .bytebpe import vocabulary_path

GROUP = 8192
PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


@cache
def _tokenizer(name: str):
    """Ids of a text by the tokenizers library's file; the rank file of the same vocabulary encodes alike and faster."""
    import base64
    import os

    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    import public_tokenizers
    import tiktoken
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(vocabulary_path(f"{name}.json"))
    special = [t.content for t in whole.get_added_tokens_decoder().values()]
    with open(vocabulary_path(f"{name}.tiktoken"), "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    plain = tiktoken.Encoding(name, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def ids(text: str) -> list[int]:
        if any(s in text for s in special):
            return whole.encode(text, add_special_tokens=False).ids
        return plain.encode_ordinary(text)

    return ids


def pieces(docs: DataFrame, length: int, tokenizer: str, closing_id: int, id_col: str, text_col: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = _tokenizer(tokenizer)
        for batch in batches:
            rows: list[tuple] = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                packed = np.array([*encode(text or ""), closing_id], "<u4")
                for start in range(0, len(packed), length):
                    part = packed[start : start + length]
                    rows.append((doc, start, len(part), zlib.crc32(part.tobytes()), len(packed)))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)] if rows else [pa.array([], pa.int64())] * 5, names=["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return docs.selectExpr(f"cast(`{id_col}` as long) doc_id", f"cast(`{text_col}` as string) text").mapInArrow(run, PIECE)


def first_fit_decreasing(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """(bin, offset in it) of each item."""
    order = np.argsort(-sizes, kind="stable")
    leaves = 1 << max(0, int(len(sizes) - 1).bit_length())
    room = [capacity] * (2 * leaves)  # a node holds the greater room of its two children
    where, offset = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64)
    for item in order.tolist():
        size, node = int(sizes[item]), 1
        while node < leaves:
            node *= 2
            if room[node] < size:
                node += 1
        where[item], offset[item] = node - leaves, capacity - room[node]
        room[node] -= size
        while node > 1:
            node //= 2
            best = room[2 * node] if room[2 * node] >= room[2 * node + 1] else room[2 * node + 1]
            if room[node] == best:
                break
            room[node] = best
    return where, offset


def pack(docs: DataFrame, length: int = 1024, tokenizer: str = "byte_bpe_50k", closing_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row per piece with its sequence and offset; a sequence's rest up to ``length`` is padding."""
    scratch = Scratch(docs.sparkSession, "packing")
    cut = scratch.save(pieces(docs, length, tokenizer, closing_id, id_col, text_col), "pieces")
    groups = max(1, -(-cut.count() // GROUP))

    def fill(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["doc_id", "start", "ids_crc32"], kind="stable")
        where, offset = first_fit_decreasing(rows["length"].to_numpy(), length)
        return rows.drop(columns="grp").assign(sequence_id=(int(key[0]) << 32) + where, offset=offset)

    grouped = cut.withColumn("grp", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(groups)))
    return grouped.groupBy("grp").applyInPandas(fill, f"{PIECE}, sequence_id long, offset long")
