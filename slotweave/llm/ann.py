"""Nearest neighbours by inner product: a block matrix join with 8-bit tiles and exact finish.

1. Every vector is rounded once to 8 bits with a scale of its own. Queries and candidates are dealt into blocks; every pair of blocks is one
   tile and one task, and only the 8-bit codes travel to it.
2. In a tile the integer products bound every inner product from both sides. A pair stays if its upper bound reaches the query's
   k-th best lower bound in the tile, and then the k-th best of all its tiles.
3. The pairs left, about k of a query, meet the original vectors, are computed in double precision, and each query's are merged by a heap.

The bounds are strict, so no neighbour is lost and the result is exact. Of equal vectors only the k + 1 with the smallest ids can be among anyone's k
nearest, so of a group of copies no more are candidates. A tile's product is O(queries x candidates); codes are sent once for each block of
the other side, so with blocks of a fixed size the traffic is linear in rows times the number of blocks.

Edge cases: vectors that are null, empty, all zero, or hold null or non-finite components take no part, nor do rows with a null id; vectors of another
dimension are not compared; ties go to the smaller vec_id; fewer candidates than k give fewer rows. Rows of a repeated vec_id are rows
of their own: each query row has its own ranks, from which the row itself, but not its namesakes, is left out. An empty table gives an empty result.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ._skew import spread_join
from ._store import Scratch

QUERIES, CANDIDATES = 4096, 16384
#: Queries that are finished in one task's group.
FINISH = 256
LEAST_SCALE = 1e-307


def rounded(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """8-bit codes and scales; every component differs by at most half its row's scale."""
    scale = np.maximum(np.abs(x).max(axis=1) / 127, LEAST_SCALE)
    return np.rint(x / scale[:, None]).astype(np.int8), scale


def products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """a @ b.T of 8-bit matrices; float32 holds the sums of 1040 products exactly."""
    out = np.zeros((len(a), len(b)))
    for at in range(0, a.shape[1], 1024):
        out += a[:, at : at + 1024].astype(np.float32) @ b[:, at : at + 1024].astype(np.float32).T
    return out


def _matrix(column) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1)


def _code_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        dims = batch.column("dim").to_numpy()
        for dim in np.unique(dims):
            part = batch.filter(pa.array(dims == dim))
            x = _matrix(part.column("v"))
            codes, scale = rounded(x)
            size, code_size = np.abs(x).sum(axis=1), np.abs(codes.astype(np.float64)).sum(axis=1) * scale
            columns = [part.column("row"), part.column("dim"), part.column("q"), pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(scale), pa.array(size), pa.array(code_size)]
            yield pa.RecordBatch.from_arrays(columns, names=["row", "dim", "q", "code", "scale", "size", "code_size"])


CODES = "row long, dim int, q boolean, code binary, scale double, size double, code_size double"
PAIRS = "q_row long, c_row long, low double, high double"


def tile(q_rows: np.ndarray, q: tuple[np.ndarray, ...], c_rows: np.ndarray, c: tuple[np.ndarray, ...], k: int, rows: int = 256) -> Iterator[tuple[np.ndarray, ...]]:
    """(query, candidate, low, high) of the pairs that may be among the query's k best of the tile; q and c hold codes, scales, sizes of the
    vectors, and sizes of the rounded ones."""
    qi, qs, _, q_size = q
    ci, cs, c_size, _ = c
    for at in range(0, len(qi), rows):
        part = slice(at, at + rows)
        with np.errstate(over="ignore", invalid="ignore"):
            near = products(qi[part], ci) * qs[part, None] * cs
            # q.c = q8.c8 + (q - q8).c + q8.(c - c8), each difference within half a step
            slack = (qs[part, None] * c_size + q_size[part, None] * cs) * 0.5 * (1 + 1e-9) + 1e-300
            low, high = near - slack, near + slack
        low[~np.isfinite(low)], high[~np.isfinite(high)] = -np.inf, np.inf
        own = q_rows[part, None] == c_rows
        low[own] = -np.inf
        edge = np.partition(low, len(ci) - k, axis=1)[:, len(ci) - k] if len(ci) > k else np.full(len(low), -np.inf)
        r, j = np.nonzero(~own & (high >= edge[:, None]))
        yield q_rows[part][r], c_rows[j], low[r, j], high[r, j]


def _unmatched(rows: DataFrame, k: int) -> DataFrame:
    """The rows that may be among someone's k nearest: of equal vectors those with the k + 1 smallest ids."""
    same = ["h1", "h2"]
    hashed = rows.select("row", "vec_id", F.xxhash64(F.lit(1), "v").alias("h1"), F.xxhash64(F.lit(2), "v").alias("h2"))
    many = hashed.groupBy(*same).agg(F.count("*").alias("n")).filter(F.col("n") > k + 1).select(*same)
    if many.isEmpty():
        return rows
    copies = hashed.join(many, same, "left_semi") if many.count() > 1_000_000 else hashed.join(F.broadcast(many), same, "left_semi")
    best = copies.withColumn("r", F.row_number().over(Window.partitionBy(*same).orderBy("vec_id", "row"))).filter(F.col("r") <= k + 1)
    gone = copies.select("row").join(best.select("row"), "row", "left_anti")
    return rows.join(gone, "row", "left_anti")


def nearest(vectors: DataFrame, is_query: Column, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: each query's k nearest other rows, nearest first."""
    scratch = Scratch(vectors.sparkSession, "nearest")
    kind = dict(vectors.dtypes)[vector_col]
    kind = kind if kind in ("array<float>", "array<double>") else "array<double>"
    v = F.col("v")
    good = v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast(kind).alias("v"), F.coalesce(is_query, F.lit(False)).alias("q")).filter(good & F.col("vec_id").isNotNull())
    rows = scratch.save(rows.withColumns({"dim": F.size("v"), "row": F.monotonically_increasing_id()}), "rows")
    n, m = rows.agg(F.count("*"), F.coalesce(F.sum(F.col("q").cast("long")), F.lit(0))).first()
    across, down = max(1, -(-n // CANDIDATES)), max(1, -(-m // QUERIES))

    codes = lambda of: of.select("row", "dim", "q", "v").mapInArrow(_code_rows, CODES)
    block = lambda parts, salt: F.pmod(F.xxhash64("row", F.lit(salt)), F.lit(parts)).cast("int")
    every = lambda parts: F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    asked = codes(rows.filter("q")).withColumns({"qb": block(down, 1), "cb": every(across)})
    given = codes(_unmatched(rows, k)).withColumns({"q": F.lit(False), "qb": every(down), "cb": block(across, 2)})

    def search(part: pd.DataFrame) -> pd.DataFrame:
        sides = []
        for side in (part[part["q"]], part[~part["q"]]):
            table = np.frombuffer(b"".join(side["code"]), np.int8).reshape(len(side), int(part["dim"].iloc[0]))
            sides += [side["row"].to_numpy(), (table, *(side[c].to_numpy() for c in ("scale", "size", "code_size")))]
        got = list(tile(*sides, k)) if len(sides[0]) and len(sides[2]) else []
        return pd.DataFrame({c: np.concatenate([g[i] for g in got]) if got else np.zeros(0, t) for i, (c, t) in enumerate((("q_row", np.int64), ("c_row", np.int64), ("low", np.float64), ("high", np.float64)))})

    near = scratch.save(asked.unionByName(given).groupBy("dim", "qb", "cb").applyInPandas(search, PAIRS), "near")
    if across > 1:
        edge = near.groupBy("q_row").agg(F.coalesce(F.get(F.sort_array(F.collect_list("low"), False), F.lit(k - 1)), F.lit(float("-inf"))).alias("edge"))
        near = scratch.save(near.join(edge, "q_row").filter("high >= edge").select("q_row", "c_row"), "left")
    found = spread_join(near.select("q_row", F.col("c_row").alias("row")), rows.select("row", F.col("vec_id").alias("c_id"), F.col("v").alias("c")), ["row"])
    groups = max(1, m // FINISH)
    group = lambda column: F.pmod(F.xxhash64(column), F.lit(groups))
    left = rows.filter("q").select(F.col("row").alias("own"), F.col("vec_id").alias("own_id"), F.col("v").alias("own_v")).withColumn("g", group("own"))

    def finish(queries: pd.DataFrame, pairs: pd.DataFrame) -> pd.DataFrame:
        of = {row: (i, np.asarray(x, np.float64)) for row, i, x in zip(queries["own"], queries["own_id"], queries["own_v"], strict=True)}
        out: list[tuple] = []
        for row, own in pairs.groupby("q_row", sort=False):
            query_id, x = of[row]
            c = np.stack(own["c"].to_list()).astype(np.float64)
            score = np.zeros(len(c))
            with np.errstate(over="ignore", invalid="ignore"):
                for d in range(len(x)):  # component after component, so equal vectors get equal sums
                    score += x[d] * c[:, d]
            best = heapq.nsmallest(k, zip(-np.nan_to_num(score, nan=-np.inf, posinf=np.inf, neginf=-np.inf), own["c_id"].to_numpy(), strict=True))
            out += [(query_id, rank, int(i), -float(s)) for rank, (s, i) in enumerate(best, 1)]
        return pd.DataFrame(out, columns=["query_id", "rank", "vec_id", "score"]).astype({"query_id": "int64", "rank": "int32", "vec_id": "int64", "score": "float64"})

    return left.groupBy("g").cogroup(found.withColumn("g", group("q_row")).groupBy("g")).applyInPandas(finish, "query_id long, rank int, vec_id long, score double")
