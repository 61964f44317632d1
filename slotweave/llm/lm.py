"""Scoring texts with a log-bilinear word model trained by noise-contrastive estimation.

Symbols are the most frequent words, the end, and classes of all other words by their last bytes. A symbol's
probability after another is the softmax of r(next) . C q(previous) + b(next); the vectors are trained in numpy on
the pair counts of all training texts against noise from the unigram counts, and batched matrix products then normalise every row of
the table. Inside a class a word has its smoothed share of the class, with room for one unknown word, so the whole is a
normalised distribution.

Words with few counts are too many to broadcast: at most HEAD words travel to the tasks, and the rest meet their counts
in a shuffle of (text, word) rows. All counts are exact and over all training texts.

Edge cases: null text is empty: one end token. Without any training text all counts are 0 and the model equals the base.
Repeated rows are scored each (and learnt from each); extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from math import log10

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._store import Scratch

WORDS, CLASSES, HEAD = 767, 256, 150_000
K = WORDS + 1 + CLASSES  # the end stands between words and classes
END, START = WORDS, WORDS  # the end of one text is the start of the next
DIM, STEPS, RATE, NOISE, PRIOR = 48, 300, 0.05, 12, 100
FLUSH = 200_000


def word_class(word: bytes) -> int:
    return WORDS + 1 + zlib.crc32(word[-3:]) % CLASSES


def _split(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def _count_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    counts: Counter = Counter()

    def flush() -> pa.RecordBatch:
        words = list(counts)
        out = pa.RecordBatch.from_arrays([pa.array([w.decode("utf-8", "surrogatepass") for w in words], pa.string()), pa.array([word_class(w) for w in words], pa.int32()), pa.array(list(counts.values()), pa.int64())], names=["word", "cls", "c"])
        counts.clear()
        return out

    for batch in batches:
        for text in batch.column(0).to_pylist():
            counts.update(_split(text))
            if len(counts) > FLUSH:
                yield flush()
    yield flush()


def train(pairs: np.ndarray, seed: int = 7) -> np.ndarray:
    """Natural-log probabilities [previous, next] from counts of pairs, by noise-contrastive estimation.

    The counts say how often each pair is real and how often noise would make it, so each step takes the expectation over
    all pairs and all noise, by matrix products, instead of a sample. A Gaussian prior holds vectors at zero, and with them
    a symbol at its unigram share, where few texts were seen.
    """
    n = pairs.shape[0]
    total = pairs.sum()
    unigram = (pairs.sum(axis=0) + 0.5) / (total + 0.5 * n)
    if total == 0:
        return np.tile(np.log(unigram), (n, 1))
    rng = np.random.default_rng(seed)
    start = np.log(unigram).astype(np.float32)
    target, context = (rng.normal(0, 0.1, (n, DIM)).astype(np.float32) for _ in range(2))
    bilinear, bias = np.eye(DIM, dtype=np.float32), start.copy()
    real = (pairs / total).astype(np.float32)
    noise = (NOISE * pairs.sum(axis=1, keepdims=True) * unigram / total).astype(np.float32)
    log_noise = np.log(NOISE * unigram).astype(np.float32)
    prior = np.float32(PRIOR / total)
    values = (target, context, bilinear, bias)
    means, squares = [np.zeros_like(x) for x in values], [np.zeros_like(x) for x in values]
    for i in range(STEPS):
        predicted = context @ bilinear
        is_real = 1 / (1 + np.exp(np.clip(log_noise - bias - predicted @ target.T, -30, 30)))
        g = is_real * (real + noise) - real
        g_predicted = g @ target
        slopes = (g.T @ predicted + prior * target, g_predicted @ bilinear.T + prior * context, context.T @ g_predicted, g.sum(axis=0) + prior * (bias - start))
        rate = RATE * (1 - i / STEPS)
        for x, mean, square, slope in zip(values, means, squares, slopes, strict=True):
            mean += 0.1 * (slope - mean)
            square += 0.01 * (slope * slope - square)
            x -= rate * (mean / (1 - 0.9 ** (i + 1))) / (np.sqrt(square / (1 - 0.99 ** (i + 1))) + 1e-10)
    out = np.empty((n, n))
    for at in range(0, n, 256):
        score = (context[at : at + 256] @ bilinear @ target.T + bias).astype(np.float64)
        top = score.max(axis=1, keepdims=True)
        out[at : at + 256] = score - top - np.log(np.exp(score - top).sum(axis=1, keepdims=True))
    return out


def score_documents(docs: DataFrame, held_out: Column, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score; learns from the rows that aren't held out."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "lm")
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.coalesce(held_out, F.lit(False)).alias("held_out"))
    training = docs.filter(~F.col("held_out")).select("text")

    counted = training.mapInArrow(_count_rows, "word string, cls int, c long").groupBy("word", "cls").agg(F.sum("c").alias("c"))
    counts = scratch.save(counted, "counts")
    ends = training.count()
    histogram = sorted(((r.c, r["n"]) for r in counts.groupBy("c").agg(F.count("*").alias("n")).collect()), reverse=True)
    total, kinds = sum(c * n for c, n in histogram) + ends, sum(n for _, n in histogram) + (ends > 0)
    taken, least = 0, 1 << 62
    for c, n in histogram:
        if taken + n > HEAD:
            break
        taken, least = taken + n, c
    head = sorted(((r.c, r.word, r.cls) for r in counts.filter(F.col("c") >= least).collect()), key=lambda r: (-r[0], r[1]))
    known = {w.encode("utf-8", "surrogatepass"): (i if i < WORDS else cls, c) for i, (c, w, cls) in enumerate(head)}
    single = {w for _, w, _ in head[:WORDS]}

    inside = counts.filter(~F.col("word").isin(list(single))) if single else counts
    classes = {r.cls: (r.c, r["n"]) for r in inside.groupBy("cls").agg(F.sum("c").alias("c"), F.count("*").alias("n")).collect()}
    class_total = np.zeros(K)
    class_kinds = np.zeros(K)
    for cls, (c, n) in classes.items():
        class_total[cls], class_kinds[cls] = c, n
    # log10 of (total + 0.5 (kinds + 1)) of each class; 0 where the symbol is one word
    room = np.where(np.arange(K) > WORDS, np.log10(class_total + 0.5 * (class_kinds + 1)), 0.0)
    base_room = log10(total + 0.5 * (kinds + 1))
    given = spark.sparkContext.broadcast((known, room))

    def symbols(words: list[bytes], table: dict) -> list[int]:
        return [found[0] if (found := table.get(w)) else word_class(w) for w in words]

    def pair_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = given.value[0]
        cells = np.zeros(K * K, np.int64)
        for batch in batches:
            for text in batch.column(0).to_pylist():
                s = np.array([START, *symbols(_split(text), table), END], np.int64)
                cells += np.bincount(s[:-1] * K + s[1:], minlength=K * K) if len(s) > 50_000 else 0
                if len(s) <= 50_000:
                    np.add.at(cells, s[:-1] * K + s[1:], 1)
        at = np.flatnonzero(cells)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(cells[at], pa.int64())], names=["cell", "c"])

    pairs = np.zeros(K * K)
    for r in training.mapInArrow(pair_rows, "cell long, c long").groupBy("cell").agg(F.sum("c").alias("c")).toLocalIterator():
        pairs[r.cell] = r.c
    table = spark.sparkContext.broadcast((train(pairs.reshape(K, K)) / np.log(10)).astype(np.float32))

    def score_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        (words, room_), logs = given.value, table.value
        number = TaskContext.get().partitionId() << 40
        empty_end = log10(0.5 + ends) - base_room
        value = {w: (s, log10(c + 0.5) - room_[s] if s > WORDS else 0.0, log10(c + 0.5)) for w, (s, c) in words.items()}
        for batch in batches:
            rows = []
            for text in batch.column(1).to_pylist():
                own = _split(text)
                s, gain, base, tail = [START], 0.0, 0.0, []
                for w in own:
                    found = value.get(w)
                    if found is None:
                        cls = word_class(w)
                        s.append(cls)
                        gain -= room_[cls]
                        tail.append(w.decode("utf-8", "surrogatepass"))
                    else:
                        s.append(found[0])
                        gain += found[1]
                        base += found[2]
                s.append(END)
                at = np.array(s)
                rows.append((number, len(own) + 1, len(own) - len(tail) + (ends > 0), base - base_room * len(own) + empty_end, gain + float(logs[at[:-1], at[1:]].sum(dtype=np.float64)), tail))
                number += 1
            kinds_ = (pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.list_(pa.string()))
            columns = [pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds_, strict=True)] if rows else [pa.array([], t) for t in kinds_]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), *columns], names=["doc_id", "held_out", "row", "n_tokens", "n_known", "base", "gain", "tail"])

    schema = "doc_id long, held_out boolean, row long, n_tokens long, n_known long, base double, gain double, tail array<string>"
    scored = scratch.save(docs.select("doc_id", "text", "held_out").mapInArrow(score_rows, schema), "scored")
    rare = scored.select("row", F.explode("tail").alias("word")).groupBy("row", "word").agg(F.count("*").alias("times"))
    met = rare.join(counts.filter(F.col("c") < least).select("word", "c"), "word", "left")
    log = F.log10(F.coalesce("c", F.lit(0)) + 0.5) * F.col("times")
    sums = met.groupBy("row").agg(F.sum(log).alias("more"), F.sum(F.when(F.col("c") > 0, F.col("times")).otherwise(0)).alias("hit"), F.sum("times").alias("n"))
    out = scored.drop("tail").join(sums, "row", "left")
    # each rare word adds log10(c + 0.5) to both sums; the class room is in gain, the base room in base
    more = F.coalesce("more", F.lit(0.0))
    return out.select("doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("hit", F.lit(0))).alias("n_known"), F.lit(total).cast("long").alias("train_tokens"), (F.col("base") + more).alias("base_score"), (F.col("gain") + more).alias("score"))
