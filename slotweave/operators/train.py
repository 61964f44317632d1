"""Standard byte-pair training: distinct chunks, pair counts, merges.

Five strategies give one and the same log: ``stepwise`` runs a job per merge in DataFrame functions alone; ``batch`` takes from
each pass all leading merges that provably come next; ``delta`` counts pairs once and then only the changes in chunks that hold
the merged pair; ``compact`` gathers the distinct chunks, when they are few, into one task that keeps counts incrementally;
``runs`` gathers the distinct runs of frequent pairs alone, and so takes from each pass all merges down to a frequency.
``auto`` takes compact below COMPACT rows and COMPACT_SYMBOLS symbols, else runs. All resume: one pass brings the chunks to the
state after the merges that are done.

Ties go to the smallest (left, right). A pair's frequency counts adjacent places, overlapping ones too; replacement is
left to right, and ``repl`` logs what was really replaced.
"""

from __future__ import annotations

import heapq
import itertools
import operator
import shutil
import uuid
from collections import Counter, defaultdict
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slotweave.functions.pretok import chunks_of
from slotweave.functions.symbols import symbol, to_symbols, token_of
from slotweave.sources.tables import delete, free_driver, shared_folder

COMPACT, COMPACT_SYMBOLS = 1_000_000, 4_000_000
#: Frequent pairs of the first pass of runs, and the most of any pass; distinct runs that a task holds before it passes them on.
PAIRS, MOST_PAIRS, HELD = 64, 100_000, 100_000
#: Merges after which the strategies of many passes cut the lineage.
CUT_EVERY = 8
#: Merges up to which they are spelled as nested native replaces; longer logs go through one pass of Arrow batches.
NESTED = 32
#: Symbols of a chunk above which its merges go through a heap.
LONG = 100
LOG_SCHEMA = "rank int, left int, right int, token int, freq long, repl long, bytes binary, n_bytes int"


class TrainingExhausted(ValueError):
    """No pair is left to merge."""


@dataclass(frozen=True)
class Merge:
    rank: int
    left: int
    right: int
    token: int
    freq: int
    repl: int
    bytes: bytes


@dataclass(frozen=True)
class MergeLog:
    """The merges in order, with the corpus' byte counts; every prefix is the log of a smaller vocabulary."""

    merges: tuple[Merge, ...]
    byte_counts: tuple[int, ...]

    def __len__(self) -> int:
        return len(self.merges)

    def prefix(self, m: int) -> MergeLog:
        return MergeLog(self.merges[:m], self.byte_counts)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(m.rank, m.left, m.right, m.token, m.freq, m.repl, bytearray(m.bytes), len(m.bytes)) for m in self.merges], LOG_SCHEMA)

    def token_bytes(self, token: int) -> bytes:
        return bytes([token]) if token < 256 else self.merges[token - 256].bytes


def chunk_table(docs: DataFrame, text: str = "text", pretok: bool = True) -> DataFrame:
    """Distinct chunks as symbol strings with their counts: the one shuffle of the whole corpus."""
    return docs.select(F.explode(chunks_of(F.col(text), pretok)).alias("chunk")).groupBy("chunk").agg(F.count("*").alias("n")).select(to_symbols("chunk").alias("sym"), "n")


def pair_counts(chunks: DataFrame) -> DataFrame:
    sym = F.col("sym")
    at = F.sequence(F.lit(1), F.char_length(sym) - 1)
    pairs = F.transform(at, lambda i: F.substr(sym, i, F.lit(2)))
    return chunks.filter(F.char_length(sym) > 1).select(F.explode(pairs).alias("pair"), "n").groupBy("pair").agg(F.sum("n").alias("f"))


def top_pairs(pairs: DataFrame, k: int = 1) -> DataFrame:
    return pairs.orderBy(F.desc("f"), "pair").limit(k)


def frequent(pairs: DataFrame, width: int) -> tuple[list[tuple[int, str]], list[tuple[int, int]]]:
    """The pairs of the highest frequencies, as (-frequency, pair) in order, so many whole frequencies as give at most width pairs; and the
    (frequency, number of its pairs) down to the first one that is left out. Frequencies are counted first, so the driver gets no more pairs than these:
    a limit after a sort would send it the best of every partition, up to width from each."""
    counted = [(r.f, r.n) for r in pairs.groupBy("f").agg(F.count("*").alias("n")).orderBy(F.desc("f")).limit(width + 1).collect()]
    least = _least(counted, width)
    return sorted((-r.f, r.pair) for r in pairs.filter(F.col("f") >= least).collect()) if counted and counted[0][0] >= least else [], counted


def _least(counted: list[tuple[int, int]], width: int) -> int:
    """The frequency above the first one with which the pairs are more than width; 1 if there is none."""
    held = 0
    for f, n in counted:
        held += n
        if held > width:
            return f + 1
    return 1


def apply_merge(chunks: DataFrame, pair: str, token: int) -> DataFrame:
    return chunks.select(F.replace(F.col("sym"), F.lit(pair), F.lit(symbol(token))).alias("sym"), "n")


def byte_counts(chunks: DataFrame) -> tuple[int, ...]:
    got = chunks.select(F.explode(F.split("sym", "")).alias("s"), "n").filter("s != ''").groupBy("s").agg(F.sum("n").alias("n")).collect()
    counts = {ord(r.s): r.n for r in got}
    return tuple(counts.get(b, 0) for b in range(256))


def _merge(log: list[Merge], left: int, right: int, freq: int, repl: int) -> Merge:
    part = lambda t: bytes([t]) if t < 256 else log[t - 256].bytes
    return Merge(len(log), left, right, 256 + len(log), freq, repl, part(left) + part(right))


def _length(chunks: DataFrame) -> int:
    return chunks.agg(F.coalesce(F.sum(F.col("n") * F.char_length("sym")), F.lit(0))).first()[0]


class _Cuts:
    """Lineage cut by written tables in the shared folder that the session names; each replaces the one before, so one copy is left, and close() frees that.
    A local session without a folder gets one of its own; a cluster has to name a shared one."""

    def __init__(self, spark: SparkSession):
        self.spark, (folder, self.own) = spark, shared_folder(spark)
        self.root, self.last, self.count = f"{folder}/training-{uuid.uuid4().hex[:12]}", None, 0

    def __call__(self, chunks: DataFrame) -> DataFrame:
        path, self.count = f"{self.root}/{self.count}", self.count + 1
        chunks.write.mode("overwrite").parquet(path)
        before, self.last = self.last, path
        if before:
            delete(self.spark, before)
        free_driver(self.spark)
        return self.spark.read.schema(chunks.schema).parquet(path)

    def close(self) -> None:
        delete(self.spark, self.root)
        if self.own:
            shutil.rmtree(self.own, ignore_errors=True)


def merge_word(word: list[int], ranks: dict[tuple[int, int], int], made: Counter | None = None) -> list[int]:
    """All merges in rank order; the lowest pair present is always next, for a merge only makes pairs of later rank. Counts them in made."""
    if len(word) > LONG:
        return _merge_long(list(word), ranks, made)
    while len(word) > 1:
        found = [ranks.get(p, 1 << 40) for p in zip(word, word[1:], strict=False)]
        best = min(found)
        if best == 1 << 40:
            break
        out, i = [], 0
        while i < len(word):
            here = i < len(found) and found[i] == best
            out.append(best if here else word[i])
            i += 1 + here
        if made is not None:
            made[best] += len(word) - len(out)
        word = out
    return word


def _merge_long(word: list, ranks: dict[tuple[int, int], int], made: Counter | None) -> list[int]:
    """The same in n log n steps: a heap of (token, place) over a linked list of the symbols left."""
    n = len(word)
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = [(t, i) for i, p in enumerate(zip(word, word[1:], strict=False)) if (t := ranks.get(p))]
    heapq.heapify(heap)
    while heap:
        token, i = heapq.heappop(heap)
        j = after[i]
        if word[i] is None or j >= n or ranks.get((word[i], word[j])) != token:
            continue
        word[i], word[j], after[i] = token, None, after[j]
        if made is not None:
            made[token] += 1
        if after[i] < n:
            before[after[i]] = i
            if t := ranks.get((token, word[after[i]])):
                heapq.heappush(heap, (t, i))
        if before[i] >= 0 and (t := ranks.get((word[before[i]], token))):
            heapq.heappush(heap, (t, before[i]))
    return [w for w in word if w is not None]


class Replacer:
    """merge_word on symbol strings, a string replace for each merge: several times as fast for chunks of common length, most of which hold few of the pairs."""

    def __init__(self, ranks: dict[tuple[int, int], int]):
        self.ranks = ranks
        self.known = {symbol(a) + symbol(b): token for (a, b), token in ranks.items()}
        self.swap = {token: (pair, symbol(token)) for pair, token in self.known.items()}

    def __call__(self, s: str, made: Counter | None = None) -> str:
        if len(s) > LONG:
            return "".join(map(symbol, merge_word(list(map(token_of, s)), self.ranks, made)))
        while best := min(filter(None, map(self.known.get, map(operator.concat, s, s[1:]))), default=0):
            after = s.replace(*self.swap[best])
            if made is not None:
                made[best] += len(s) - len(after)
            s = after
        return s


def advance(chunks: DataFrame, done: list[Merge]) -> DataFrame:
    """The chunks after the merges of a log, in one pass whatever their number."""
    if not done:
        return chunks
    shared = chunks.sparkSession.sparkContext.broadcast({(m.left, m.right): m.token for m in done})
    rest = [c for c in chunks.columns if c != "sym"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        after = Replacer(shared.value)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(list(map(after, batch.column(0).to_pylist())), pa.string()), *batch.columns[1:]], names=["sym", *rest])

    return chunks.select("sym", *rest).mapInArrow(run, ", ".join(f"{c} {dict(chunks.dtypes)[c]}" for c in ["sym", *rest]))


def _stepwise(chunks: DataFrame, n: int, log: list[Merge], cut: Callable[[DataFrame], DataFrame]) -> list[Merge]:
    before = _length(chunks)
    while len(log) < n:
        top = top_pairs(pair_counts(chunks)).first()
        if top is None:
            break
        chunks = apply_merge(chunks, top.pair, 256 + len(log))
        if len(log) % CUT_EVERY == CUT_EVERY - 1:
            chunks = cut(chunks)
        after = _length(chunks)
        log.append(_merge(log, token_of(top.pair[0]), token_of(top.pair[1]), top.f, before - after))
        before = after
    return log


def _delta(chunks: DataFrame, n: int, log: list[Merge], cut: Callable[[DataFrame], DataFrame]) -> list[Merge]:
    """Pair counts on the driver, bounded by the pairs of the alphabet; a merge is one narrow scan that returns count changes."""
    counts = {r.pair: r.f for r in pair_counts(chunks).collect()}
    heap = [(-f, p) for p, f in counts.items()]
    heapq.heapify(heap)
    while len(log) < n:
        while heap and counts.get(heap[0][1], 0) != -heap[0][0]:
            heapq.heappop(heap)
        if not heap:
            break
        f, pair = heapq.heappop(heap)
        holders = chunks.filter(F.contains("sym", F.lit(pair)))
        after = apply_merge(holders, pair, 256 + len(log))
        both = holders.select("sym", (-F.col("n")).alias("n")).unionByName(after)
        changes = {r.pair: r.f for r in pair_counts(both).filter("f != 0").collect()}
        # a chunk has one pair fewer than symbols, so the pairs lost are the replacements made
        log.append(_merge(log, token_of(pair[0]), token_of(pair[1]), -f, -sum(changes.values())))
        for p, change in changes.items():
            counts[p] = counts.get(p, 0) + change
            if counts[p]:
                heapq.heappush(heap, (-counts[p], p))
            else:
                del counts[p]
        chunks = apply_merge(chunks, pair, 255 + len(log))
        if len(log) % CUT_EVERY == 0:
            chunks = cut(chunks)
    return log


def _batch(chunks: DataFrame, n: int, log: list[Merge], cut: Callable[[DataFrame], DataFrame], width: int = 48) -> list[Merge]:
    """Merges taken together while they don't touch and no pair born of them can be as frequent as the next."""
    spark = chunks.sparkSession
    while len(log) < n:
        top = top_pairs(pair_counts(chunks), width).collect()
        if not top:
            break
        named = spark.createDataFrame([(r.pair,) for r in top], "pair string")
        sym = F.col("sym")
        triples = chunks.filter(F.char_length(sym) > 2).select(F.explode(F.transform(F.sequence(F.lit(1), F.char_length(sym) - 2), lambda i: F.substr(sym, i, F.lit(3)))).alias("t"), "n").groupBy("t").agg(F.sum("n").alias("f"))
        sides = triples.select(F.substr("t", F.lit(1), F.lit(2)).alias("pair"), "f").unionByName(triples.select(F.substr("t", F.lit(2), F.lit(2)).alias("pair"), "f"))
        born = {r.pair: r.f for r in sides.join(F.broadcast(named), "pair", "left_semi").groupBy("pair").agg(F.max("f").alias("f")).collect()}
        taken: list[tuple[str, int]] = []
        bound = -1
        for r in top:
            a, b = r.pair
            if len(log) + len(taken) >= n or (taken and (r.f <= bound or a == b or any(a == q[1] or b == q[0] for q, _ in taken))):
                break
            taken.append((r.pair, r.f))
            bound = max(bound, born.get(r.pair, 0))
            if a == b:
                break
        sums, step = [], F.col("sym")
        for i, (pair, _) in enumerate(taken):
            new = F.replace(step, F.lit(pair), F.lit(symbol(256 + len(log) + i)))
            sums.append(F.sum(F.col("n") * (F.char_length(step) - F.char_length(new))).alias(f"r{i}"))
            step = new
        repl = chunks.agg(*sums).first()
        chunks = cut(chunks.select(step.alias("sym"), "n"))
        for (pair, f), replaced in zip(taken, repl, strict=True):
            log.append(_merge(log, token_of(pair[0]), token_of(pair[1]), f, replaced))
    return log


def _replaced(word: list[int], a: int, b: int, t: int) -> list[int]:
    out, i = [], 0
    while i < len(word):
        if i + 1 < len(word) and word[i] == a and word[i + 1] == b:
            out.append(t)
            i += 2
        else:
            out.append(word[i])
            i += 1
    return out


def incremental(words: list[list[int]], counts: list[int], n: int, token: int = 256) -> Iterator[tuple[int, int, int, int]]:
    """(left, right, freq, repl) of n more merges, the first of which makes ``token``, keeping pair counts up to date."""
    pairs: dict[tuple[int, int], int] = defaultdict(int)
    where: dict[tuple[int, int], set[int]] = defaultdict(set)
    for i, w in enumerate(words):
        for p in zip(w, w[1:], strict=False):
            pairs[p] += counts[i]
            where[p].add(i)
    heap = [(-f, *p) for p, f in pairs.items()]
    heapq.heapify(heap)
    for _ in range(n):
        while heap and pairs.get(heap[0][1:], 0) != -heap[0][0]:
            heapq.heappop(heap)
        if not heap or heap[0][0] == 0:
            return
        f, a, b = heapq.heappop(heap)
        repl, changed = 0, set()
        for i in where.pop((a, b)):
            old = words[i]
            new = _replaced(old, a, b, token)
            if len(new) == len(old):
                continue
            repl += counts[i] * (len(old) - len(new))
            for p in zip(old, old[1:], strict=False):
                pairs[p] -= counts[i]
                changed.add(p)
            for p in zip(new, new[1:], strict=False):
                pairs[p] += counts[i]
                where[p].add(i)
                changed.add(p)
            words[i] = new
        for p in changed:
            if pairs[p] > 0:
                heapq.heappush(heap, (-pairs[p], *p))
            else:
                del pairs[p]
        yield a, b, -f, repl
        token += 1


def _in_one_task(chunks: DataFrame, n: int, log: list[Merge], least: int = 1) -> list[Merge]:
    """Adds the merges up to n that are as frequent as least. A worker holds the symbols as Python numbers and the places of each pair, about 150 bytes a
    symbol, so 0.6 GB at the bound."""
    more, first = n - len(log), 256 + len(log)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, counts = [], []
        for batch in batches:
            words += [[token_of(c) for c in s] for s in batch.column(0).to_pylist()]
            counts += batch.column(1).to_pylist()
        rows = list(itertools.takewhile(lambda r: r[2] >= least, incremental(words, counts, more, first)))
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.int64()) for i in range(4)], names=["a", "b", "f", "r"])

    for a, b, f, r in chunks.select("sym", F.col("n").cast("long")).repartition(1).mapInArrow(run, "a long, b long, f long, r long").collect():
        log.append(_merge(log, a, b, f, r))
    return log


def _compact(chunks: DataFrame, n: int, log: list[Merge], cut: Callable[[DataFrame], DataFrame]) -> list[Merge]:
    return _in_one_task(chunks, n, log)


def runs_of(chunks: DataFrame, pairs: list[str]) -> DataFrame:
    """The chunks cut between every two symbols that are none of the pairs: distinct runs of two symbols or more, with their counts."""
    shared = chunks.sparkSession.sparkContext.broadcast(set(pairs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, held = shared.value, Counter()

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(list(held), pa.string()), pa.array(list(held.values()), pa.int64())], names=["sym", "n"])

        for batch in batches:
            for s, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                start, held_by = 0, list(map(known.__contains__, map(operator.concat, s, s[1:])))
                if not any(held_by):
                    continue
                for i, inside in enumerate(held_by, 1):
                    if not inside:
                        if i - start > 1:
                            held[s[start:i]] += n
                        start = i
                if len(s) - start > 1:
                    held[s[start:]] += n
            if len(held) >= HELD:
                yield out()
                held.clear()
        yield out()

    return chunks.select("sym", F.col("n").cast("long")).mapInArrow(run, "sym string, n long").groupBy("sym").agg(F.sum("n").alias("n"))


def _runs(chunks: DataFrame, n: int, log: list[Merge], cut: Callable[[DataFrame], DataFrame]) -> list[Merge]:
    """A pass takes all merges down to a frequency. A pair born in it is no more frequent than the pair of symbols that stood at its middle when the pass
    began, so chunks may be cut wherever that pair is rarer: no merge of the pass crosses such a place, and the runs between hold all places of the others.
    Equal runs are counted as one, and few enough pairs are taken that one task holds the runs."""
    width = PAIRS
    while len(log) < n:
        width = min(width, MOST_PAIRS)
        pairs_of = pair_counts(chunks).persist()
        top, counted = frequent(pairs_of, width)
        pairs_of.unpersist()
        if not counted:
            break
        while True:
            least = _least(counted, width)
            pairs = [p for f, p in top if -f >= least]
            if not pairs:
                break
            pieces = runs_of(chunks, pairs).persist()
            rows, symbols = pieces.agg(F.count("*"), F.coalesce(F.sum(F.char_length("sym")), F.lit(0))).first()
            share = max(rows / max(1, COMPACT), symbols / max(1, COMPACT_SYMBOLS))
            if share <= 1 or len(pairs) == 1:
                break
            pieces.unpersist()
            width = max(1, min(width, len(pairs)) // 4)
        if not pairs:  # all are equally frequent
            if width == MOST_PAIRS:
                return _batch(chunks, n, log, cut)
            width *= 4
            continue
        before = len(log)
        _in_one_task(pieces, n, log, least)
        pieces.unpersist()
        if len(log) < n:
            chunks = cut(advance(chunks, log[before:]).filter(F.char_length("sym") > 1))
        width *= 8 if share < 0.1 else 3 if share < 0.5 else 2
    return log


STRATEGIES = {"stepwise": _stepwise, "batch": _batch, "delta": _delta, "compact": _compact}
#: Above the bounds of compact; like the others it may be named.
LARGE = {"runs": _runs}


def train_bpe(chunks: DataFrame, n_merges: int, strategy: str = "auto", resume: MergeLog | None = None) -> MergeLog:
    """The log of up to n_merges merges in all; resume continues a log of the same chunks, with any strategy."""
    done = list(resume.merges) if resume else []
    if len(done) >= n_merges > 0:
        return resume.prefix(n_merges)
    if strategy == "auto":
        rows, symbols = chunks.agg(F.count("*"), F.coalesce(F.sum(F.char_length("sym")), F.lit(0))).first()
        strategy = "compact" if rows <= COMPACT and symbols <= COMPACT_SYMBOLS else "runs"
    counts = resume.byte_counts if resume else byte_counts(chunks)
    chunks = advance(chunks, done)
    cut = _Cuts(chunks.sparkSession)
    try:
        if done and strategy != "compact":
            chunks = cut(chunks)
        return MergeLog(tuple((STRATEGIES | LARGE)[strategy](chunks, n_merges, done, cut)), counts)
    finally:
        cut.close()


def merged(chunks: DataFrame, log: MergeLog) -> DataFrame:
    """The chunks after all merges of the log: short ones by native replaces, others in one pass."""
    if len(log) > NESTED:
        return advance(chunks, list(log.merges))
    step = F.col("sym")
    for m in log.merges:
        step = F.replace(step, F.lit(symbol(m.left) + symbol(m.right)), F.lit(symbol(m.token)))
    return chunks.withColumn("sym", step)
