"""SQL names for a tokenizer: tok_encode, tok_decode, tok_min_count, tok_min_segment, tok_pretokenize, tok_exposure (aggregate), the table functions tok_chunks and tok_expand, and views of its vocabulary."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pandas as pd
import regex
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from slotweave.functions.pretok import JAVA, PYTHON
from slotweave.operators.encode import ChunkEncoder
from slotweave.operators.mintoken import Trie, fewest, segment, vocabulary
from slotweave.operators.visibility import Tokenizer


def register(spark: SparkSession, tok: Tokenizer) -> None:
    @F.pandas_udf("array<int>")
    def tok_encode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        one = ChunkEncoder(tok)
        for chunk in batches:
            yield chunk.map(lambda c: one(c or ""))

    words = vocabulary(tok)
    grammar = regex.compile(PYTHON)

    @F.pandas_udf("int")
    def tok_min_count(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        trie = Trie(words)
        for chunk in batches:
            yield chunk.map(lambda c: fewest(trie, (c or "").encode()))

    @F.pandas_udf("array<int>")
    def tok_min_segment(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        trie = Trie(words)
        for chunk in batches:
            yield chunk.map(lambda c: segment(trie, (c or "").encode()))

    @F.pandas_udf("string")
    def tok_decode(ids: pd.Series) -> pd.Series:
        return ids.map(lambda i: b"".join(words[x] for x in i if x < len(words)).decode("utf-8", "replace") if i is not None else None)

    @F.pandas_udf("map<int,bigint>")
    def tok_exposure(chunk: pd.Series) -> dict:
        one = ChunkEncoder(tok)
        return dict(Counter(i for c in chunk for i in one(c or "")))

    @F.udtf(returnType="pos int, chunk string")
    class tok_chunks:
        def eval(self, text: str):
            yield from enumerate(m.group() for m in grammar.finditer(text or ""))

    @F.udtf(returnType="token int")
    class tok_expand:
        def eval(self, token: int):
            for t in tok.expansions()[token]:
                yield (t,)

    spark.udf.register("tok_encode", tok_encode)
    for name, f in (("tok_min_count", tok_min_count), ("tok_min_segment", tok_min_segment), ("tok_decode", tok_decode), ("tok_exposure", tok_exposure)):
        spark.udf.register(name, f)
    spark.udtf.register("tok_chunks", tok_chunks)
    spark.udtf.register("tok_expand", tok_expand)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION tok_pretokenize(t STRING) RETURNS ARRAY<STRING> RETURN regexp_extract_all(t, '{JAVA.replace(chr(92), chr(92) * 2).replace(chr(39), chr(92) + chr(39))}', 0)")
    tok.frame(spark).createOrReplaceTempView("tok_vocab")
    tok.log.frame(spark).createOrReplaceTempView("tok_merges")
