"""Shards of nearly equal bytes by histogram sort, in DataFrame functions alone.

Rows get the 64-bit hash of their text as key, so equal texts stay together. Probes start as 4096 even key
boundaries; every round counts the exact bytes between them in all partitions, keeps those cells in which a
splitter must lie, and refines these alone, until each splitter is within the tolerance. Groups too large for a cell are found by like rounds, which
refine the cells that hold enough bytes. Only sums of cells leave a task until the rows move, once, and are numbered where they arrive.

A group of equal texts (or one long text) too large to be rounded away is placed first, on the emptiest shard, and the
splitters fill up what is left; a group that does not fit into a shard's share is spread by doc_id, since no law of
equal bytes could hold otherwise. By the tolerance at most 8000 cells or groups, and in each of at most 6 rounds at most 15 x 4096
counts, reach the driver.

Edge cases: a null text has no bytes, size 1, and counts as the empty text; ties and repeated rows are separate
rows; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import bisect

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ._store import Scratch

STEP_BITS, HEAVY_BITS = 12, 16
#: Rows of one slot-numbering cell.
CELL_ROWS = 100_000


def _splitters(rows: DataFrame, targets: list[float], tolerance: float) -> list[int]:
    """Keys below which the rows' bytes come within the tolerance of each target."""
    low = -(1 << 63)
    found: dict[int, int] = {}
    open_: dict[int, list[int]] = {low: list(range(len(targets)))}  # start of a cell -> its targets
    below = {low: 0}
    width = 64
    while open_ and width > 0:
        width = max(0, width - STEP_BITS)
        cell = F.shiftright("key", width)
        counted = rows
        if len(open_) != 1 or low not in open_ or width < 64 - STEP_BITS:
            counted = rows.filter(F.shiftright("key", width + STEP_BITS if width else STEP_BITS - 8).isin([start >> (width + STEP_BITS if width else STEP_BITS - 8) for start in open_]))
        got = sorted((int(r.c), int(r.b)) for r in counted.groupBy(cell.alias("c")).agg(F.sum("size").alias("b")).collect())
        parents = sorted(open_)
        inner: dict[int, list[tuple[int, int]]] = {p: [] for p in parents}
        for c, b in got:
            start = c << width
            inner[parents[bisect.bisect_right(parents, start) - 1]].append((start, b))
        following: dict[int, list[int]] = {}
        for p in parents:
            for t in open_[p]:
                before, chosen = below[p], None
                for start, b in inner[p]:
                    if before + b >= targets[t]:
                        left, right = targets[t] - before, before + b - targets[t]
                        if min(left, right) <= tolerance or not width:
                            chosen = start if left <= right else start + (1 << width)
                        else:
                            following.setdefault(start, []).append(t)
                            below[start] = before
                            chosen = None
                        break
                    before += b
                else:
                    chosen = (1 << 63) - 1
                if chosen is not None:
                    found[t] = min(chosen, (1 << 63) - 1)
        open_ = following
    return [found[t] for t in range(len(targets))]


def _placed(heavy: list[tuple[int, int]], share: float, shards: int) -> tuple[dict[int, int], list[float]]:
    """Largest group first on the emptiest shard; those that don't fit are left to be spread."""
    load = [0.0] * shards
    at: dict[int, int] = {}
    for size, key in sorted(((s, k) for k, s in heavy), reverse=True):
        shard = min(range(shards), key=lambda i: (load[i], i))
        if load[shard] + size <= share * 1.01:
            at[key] = shard
            load[shard] += size
    return at, load


def _heavy(rows: DataFrame, bound: float) -> list[tuple[int, int]]:
    """(hash, bytes) of the groups of more than bound bytes: at every round the cells with as much are refined, so at most total / bound are left."""
    found: list[tuple[int, int]] = []
    for width in range(64 - HEAVY_BITS, -1, -HEAVY_BITS):
        inside = rows if width == 64 - HEAVY_BITS else rows.filter(F.shiftright("h", width + HEAVY_BITS).isin([c for c, _ in found]))
        cells = inside.groupBy((F.shiftright("h", width) if width else F.col("h")).alias("c")).agg(F.sum("size").alias("b"))
        found = [(int(r.c), int(r.b)) for r in cells.filter(F.col("b") > bound).collect()]
        if not found:
            break
    return found


def _measured(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = docs[text_col].cast("string")
    full = F.coalesce(text, F.lit(""))
    return docs.select(F.col(id_col).alias("doc_id"), (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long").alias("size"), F.crc32(full).alias("text_crc32"), F.xxhash64(full).alias("h"))


def _slotted(rows: DataFrame, measured: DataFrame, shards: int, tolerance: float) -> DataFrame:
    """rows, which hold the measured columns among others, with shard and slot."""
    n, total = measured.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    share = total / shards
    heavy = _heavy(measured, max(1.0, share * tolerance * 4))
    at, load = _placed(heavy, share, shards)
    spread = [k for k, _ in heavy if k not in at]
    kinds = rows.sparkSession.createDataFrame([(k, s) for k, s in at.items()] + [(k, -1) for k in spread], "h long, fixed int")

    def keyed(df: DataFrame) -> DataFrame:
        return df.join(F.broadcast(kinds), "h", "left").withColumn("key", F.when(F.col("fixed") == -1, F.xxhash64("h", "doc_id")).otherwise(F.col("h")))

    room, targets = 0.0, []
    for i in range(shards - 1):
        room += max(0.0, share - load[i])
        targets.append(room)
    free = keyed(measured).filter("fixed is null or fixed < 0").select("key", "size")
    bounds = _splitters(free, targets, share * tolerance) if n else [0] * (shards - 1)
    by_key: Column = sum((F.when(F.col("key") >= F.lit(b), 1).otherwise(0) for b in bounds), F.lit(0))
    shard = F.when(F.col("fixed") >= 0, F.col("fixed")).otherwise(by_key).cast("int").alias("shard")
    cells = max(1, n // (shards * CELL_ROWS) + 1)
    cell = F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(cells)).cast("int").alias("cell")
    counts = keyed(measured).select(shard, cell).groupBy("shard", "cell").agg(F.count("*").alias("held"))
    before = F.coalesce(F.sum("held").over(Window.partitionBy("shard").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = counts.select("shard", "cell", before.alias("first"))
    moved = keyed(rows).select(*[c for c in rows.columns if c != "h"], shard, cell)
    numbered = moved.withColumn("r", F.row_number().over(Window.partitionBy("shard", "cell").orderBy("doc_id", "text_crc32")))
    out = numbered.join(F.broadcast(starts), ["shard", "cell"])
    return out.withColumn("slot", (F.col("first") + F.col("r") - 1).cast("long")).drop("first", "r", "cell")


def assign_shards(docs: DataFrame, shards: int = 16, tolerance: float = 0.0005, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row per document: doc_id, size, text_crc32, shard, slot (gapless from 0 in its shard)."""
    rows = Scratch(docs.sparkSession, "shards").save(_measured(docs, id_col, text_col), "rows")
    return _slotted(rows, rows, shards, tolerance).select("doc_id", "size", "text_crc32", "shard", "slot")


def write_shards(docs: DataFrame, path: str, shards: int = 16, tolerance: float = 0.0005, id_col: str = "doc_id", text_col: str = "text") -> None:
    """docs with shard and slot (which replace columns of these names), one folder for each shard: every row once, also where ids repeat."""
    own = {c: f"own_{i}" for i, c in enumerate(docs.columns)}
    renamed = docs.toDF(*own.values())
    measured = Scratch(docs.sparkSession, "shards").save(_measured(renamed, own[id_col], own[text_col]), "rows")
    text = F.coalesce(F.col(own[text_col]).cast("string"), F.lit(""))
    rows = renamed.withColumns({"doc_id": F.col(own[id_col]), "text_crc32": F.crc32(text), "h": F.xxhash64(text)})
    out = _slotted(rows, measured, shards, tolerance)
    kept = [F.col(o).alias(c) for c, o in own.items() if c not in ("shard", "slot")]
    out.select(*kept, "shard", "slot").write.mode("overwrite").partitionBy("shard").parquet(path)
