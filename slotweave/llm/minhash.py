"""Near-duplicate groups of documents from set sketches.

Method: a sketch has M registers. Each element of a shingle set throws one value into every interval of an
exponential spacing, at a register of its own order, and a register keeps its smallest value, truncated to
a 16-bit scale of logarithms. Sketches merge by the larger register and two registers are equal with about
the Jaccard similarity J of the sets. The steps:

1. Sketch every row; rows with the same shingle set are one class, shown by one of its rows with the smallest doc_id.
2. Registers in bands: the classes that share a band's values share a bucket. Each bucket's members are paired
   with its smallest member only, so the pairs grow with the members, not with their square.
3. Pairs pass a likelihood estimate of J from all registers (and both set sizes), set 4.5 standard errors below
   the threshold, and then an exact comparison of both full sets.
4. Components of the links so far. In buckets that still hold several components, the members outside the largest one
   are compared with all members of other components, sketch against sketch in tiles of 1024 x 1024, so a large bucket is many
   tasks and only likely pairs leave them: first each member's most likely partner in each component, then, for those still
   apart, all. These pass the exact comparison too. So every pair that shares a bucket is
   either compared or known to be connected.

With independent registers a pair at J = 0.8 misses all 63 bands of 8 registers with probability 9e-6, and fails the estimate
with 3e-6. Of 320,000 simulated pairs each of 4 and 5, 9 and 9, 8 and 10, 16 and 20 elements at this J, none missed all bands.

A bucket, a head, a class or a component may hold a third of all rows: what shares a key is counted first, and a hot key's rows are dealt over many
tasks, each of which gets a copy of the one row that they meet (``_skew``).

Edge cases: null or empty text, or text without a word, has an empty set: n_shingles 0, component its own
doc_id, linked with nothing. Each row is a document of its own, also where rows share a doc_id, with equal texts or others: each
gives one row, and a component is named by the smallest doc_id of its rows, of which a null one counts as the smallest. Extra columns are ignored;
an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ._skew import spread_join, too_many
from ._store import Scratch
from ._words import STEP, U, in_slices, mix, shingle_sets
from .components import connected

REGISTERS, BAND, RATE, SCALE, TOP = 509, 8, 20.0, 1.001, 65_534  # a prime number of registers
BANDS = REGISTERS // BAND
#: A fixed permutation of the registers.
with np.errstate(over="ignore"):
    TURN = np.argsort(mix((np.arange(REGISTERS, dtype=U) + U(1)) * STEP), kind="stable").astype(np.int64)
#: Members of a bucket that are compared with as many others at once.
TILE = 1024
#: Standard errors below the threshold at which the estimate gives a pair up.
ERRORS = 4.5
#: Broadcast a list of ids up to this many rows (16 MB), and of classes up to this many (about 50 MB); beyond it the join shuffles.
BROADCAST_IDS, BROADCAST_CLASSES = 2_000_000, 500_000
#: What makes a class: the number of shingles and two sums of their hashes. And the number that stands for a null doc_id.
SAME, NO_ID = ["n", "print1", "print2"], -(1 << 63)


def sketches(elements: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Registers (texts x REGISTERS, uint16) of sets given one after another; sets of no element stay 0.

    An element's order of the registers is two keyed affine maps around TURN: an affine map alone would spread a small
    set's elements so evenly over the bands that sets with few differences miss all of them too often.
    """
    n, m = len(sizes), REGISTERS
    low = np.full(n * m, 2.0)
    owner = np.repeat(np.arange(n), sizes)
    with np.errstate(over="ignore"):
        seed = mix(elements ^ STEP)
        first = (seed % U(m)).astype(np.int64)
        stride = ((seed >> U(20)) % U(m - 1)).astype(np.int64) + 1
        seed = mix(seed + STEP)
        start = (seed % U(m)).astype(np.int64)
        step = ((seed >> U(20)) % U(m - 1)).astype(np.int64) + 1
        for level in range(m):
            if not len(elements):
                break
            draw = (mix(elements + U(level + 1) * STEP) >> U(11)).astype(np.float64) * 2.0**-53
            register = (start + step * TURN[(first + level * stride) % m]) % m
            np.minimum.at(low, owner * m + register, (level + draw) / m)
            if level % 4 == 0 or level < 8:
                open_ = (low.reshape(n, m).max(axis=1) > 1.5)[owner]
                if not open_.all():
                    elements, owner, first, stride, start, step = (x[open_] for x in (elements, owner, first, stride, start, step))
    value = -np.log1p(-np.minimum(low, 1 - 2.0**-53)) / RATE
    register = np.floor(1 - np.log(np.maximum(value, 1e-300)) / np.log(SCALE))
    out = np.clip(register, 0, TOP + 1).astype(np.uint16).reshape(n, m)
    out[sizes == 0] = 0
    return out


def band_keys(registers: np.ndarray) -> np.ndarray:
    """One 64-bit key for each band of each sketch."""
    cells = registers[:, : BANDS * BAND].reshape(-1, BANDS, BAND).astype(U)
    with np.errstate(over="ignore"):
        key = np.broadcast_to(np.arange(1, BANDS + 1, dtype=U) * STEP, cells.shape[:2]).copy()
        for i in range(BAND):
            key = mix(key * STEP + cells[:, :, i])
    return key


def estimate(a: np.ndarray, b: np.ndarray, na: np.ndarray, nb: np.ndarray) -> np.ndarray:
    """Maximum-likelihood J from registers a, b (along the last axis) of sets with na, nb elements.

    With d0 equal registers, d1 where a's is larger and d2 where b's is, u and v the shares of na and nb, the
    likelihood (u-vJ)^d1 (v-uJ)^d2 J^d0 is greatest at a root of
    uv m J^2 - (u^2 (d0+d2) + v^2 (d0+d1)) J + uv d0.
    """
    d1, d2 = (a > b).sum(axis=-1), (a < b).sum(axis=-1)
    d0 = a.shape[-1] - d1 - d2
    u = na / (na + nb)
    v = 1 - u
    half = u * u * (d0 + d2) + v * v * (d0 + d1)
    square = u * v * a.shape[-1]
    return (half - np.sqrt(np.maximum(half * half - 4 * square * u * v * d0, 0))) / (2 * square)


def merge(*registers: np.ndarray) -> np.ndarray:
    """The sketch of the union of the sketched sets."""
    return np.maximum.reduce(registers)


def _prints(elements: np.ndarray, edges: np.ndarray) -> list[np.ndarray]:
    with np.errstate(over="ignore"):
        one, two = (np.concatenate([[U(0)], np.cumsum(mix(elements ^ U(c)))]) for c in (0x51, 0xA7))
        return [(s[edges[1:]] - s[edges[:-1]]).view(np.int64) for s in (one, two)]


def _sketch_rows(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, raws in in_slices(batch.column(1)):
                elements, sizes = shingle_sets(raws, k)
                registers = sketches(elements, sizes)
                print_ = _prints(elements, np.concatenate([[0], np.cumsum(sizes)]))
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(start, len(raws)),
                        pa.array(sizes),
                        pa.array(print_[0]),
                        pa.array(print_[1]),
                        pa.array([r.tobytes() for r in registers], pa.binary()),
                    ],
                    names=["doc_id", "n", "print1", "print2", "sketch"],
                )

    return run


def _band_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The band keys of (id, n, sketch): made from the registers where needed, as kept ones would be half as large again as these."""
    for batch in batches:
        registers = np.frombuffer(b"".join(batch.column(2).to_pylist()), np.uint16).reshape(-1, REGISTERS)
        keys = pa.array(band_keys(registers).view(np.int64).ravel(), pa.int64())
        edges = pa.array(np.arange(batch.num_rows + 1, dtype=np.int32) * BANDS)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.ListArray.from_arrays(edges, keys)], names=["id", "n", "keys"])


def _set_rows(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, raws in in_slices(batch.column(1)):
                elements, sizes = shingle_sets(raws, k)
                edges = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
                held = [batch.column(0).slice(start, len(raws)), pa.array(sizes), *map(pa.array, _prints(elements, edges)), pa.ListArray.from_arrays(pa.array(edges), pa.array(elements.view(np.int64)))]
                yield pa.RecordBatch.from_arrays(held, names=["doc_id", *SAME, "elements"])

    return run


def _likely(least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            a, b = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint16).reshape(-1, REGISTERS) for c in (2, 3))
            na, nb = (batch.column(c).to_numpy().astype(float) for c in (4, 5))
            keep = pa.array(estimate(a, b, na, nb) >= least)
            yield batch.select([0, 1]).filter(keep)

    return run


def _tile_pairs(percent: int, least: float, best: bool):
    """Who has likely partners in the tiles of one spot, side 0 against side 1: a row per tile and member, with at most a tile's
    side of partners; or of each member only the most likely of each component."""

    def run(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["key", "u", "r", "side"], kind="stable")
        cells = part[["key", "u", "r"]].to_numpy()
        edges = [0, *(np.flatnonzero((cells[1:] != cells[:-1]).any(axis=1)) + 1).tolist(), len(part)]
        registers = np.frombuffer(b"".join(part["sketch"]), np.uint16).reshape(-1, REGISTERS)
        side, ids, roots, mains = (part[c].to_numpy() for c in ("side", "id", "root", "main"))
        n = part["n"].to_numpy().astype(float)
        keys = part["key"].to_numpy()
        tiles, rows = part["tile"].to_numpy(), []
        for start, end in zip(edges, edges[1:], strict=False):
            got = []
            middle = start + int((side[start:end] == 0).sum())
            for at in range(start, middle, 32):
                x, y = slice(at, min(at + 32, middle)), slice(middle, end)
                nx, ny = n[x][:, None], n[y][None]
                fit = (roots[x][:, None] != roots[y]) & (100 * np.minimum(nx, ny) >= percent * np.maximum(nx, ny)) & ((roots[y] == mains[y]) | (ids[x][:, None] < ids[y]))
                i, j = np.nonzero(fit)
                for cut in range(0, len(i), 20_000):
                    p, q = i[cut : cut + 20_000], j[cut : cut + 20_000]
                    likely = estimate(registers[x][p], registers[y][q], n[x][p], n[y][q])
                    good = np.flatnonzero(likely >= least)
                    if best:
                        good = good[np.lexsort((-likely[good], roots[y][q[good]], p[good]))]
                        last = np.stack([p[good], roots[y][q[good]]])
                        good = good[np.concatenate([[True], (last[:, 1:] != last[:, :-1]).any(axis=0)])] if len(good) else good
                    elif len(good):  # a pair leaves the first of its common buckets alone
                        a, b = registers[x][p[good]], registers[y][q[good]]
                        first = (a == b)[:, : BANDS * BAND].reshape(-1, BANDS, BAND).all(axis=2).argmax(axis=1)
                        good = good[band_keys(a)[np.arange(len(a)), first].view(np.int64) == keys[start]]
                    got.append(np.stack([ids[x][p[good]], ids[y][q[good]]]))
            pairs = np.unique(np.concatenate(got, axis=1), axis=1) if got else np.zeros((2, 0), np.int64)
            if pairs.size:
                u, first = np.unique(pairs[0], return_index=True)
                partners = np.split(pairs[1], first[1:])
                alone = np.setdiff1d(pairs[1], u)
                tile = int(tiles[start])
                rows += zip([tile] * (len(u) + len(alone)), [*u.tolist(), *alone.tolist()], [*partners, *[[]] * len(alone)], strict=True)
        return pd.DataFrame(rows, columns=["tile", "id", "partners"])

    return run


def _stragglers(open_: DataFrame, percent: int, least: float, best: bool) -> DataFrame:
    """Likely pairs of members outside their bucket's largest component with members of others, from tiles of the buckets."""
    spots = max(1, open_.count() // (4 * TILE))
    own = lambda parts, salt: F.pmod(F.xxhash64("id", F.lit(salt)), F.col(parts))
    every = lambda parts: F.explode(F.sequence(F.lit(0).cast("long"), F.col(parts) - 1))
    carried = ["key", "id", "n", "root", "main", "sketch"]
    out = open_.filter("root != main").select(*carried, F.lit(0).alias("side"), own("us", 1).alias("u"), every("rs").alias("r"))
    rest = open_.select(*carried, F.lit(1).alias("side"), own("rs", 2).alias("r"), every("us").alias("u"))
    tiles = out.unionByName(rest).withColumn("tile", F.xxhash64("key", "u", "r")).withColumn("spot", F.pmod("tile", F.lit(spots)))
    return tiles.groupBy("spot").applyInPandas(_tile_pairs(percent, least, best), "tile long, id long, partners array<bigint>")


def _exact_tiles(percent: int):
    def run(part: pd.DataFrame) -> pd.DataFrame:
        a, b = [], []
        for _, tile in part.groupby("tile", sort=False):
            sets = dict(zip(tile["id"], tile["elements"], strict=True))
            for u, partners in zip(tile["id"], tile["partners"], strict=True):
                for t in partners:
                    meet = len(np.intersect1d(sets[u], sets[t], assume_unique=True))
                    if 100 * meet >= percent * (len(sets[u]) + len(sets[t]) - meet):
                        a.append(max(u, t))
                        b.append(min(u, t))
        return pd.DataFrame({"a": np.array(a, np.int64), "b": np.array(b, np.int64)})

    return run


def _exact_likely(docs: DataFrame, classes: DataFrame, likely: DataFrame, k: int, percent: int) -> DataFrame:
    """The links among likely partners; every set goes once to each tile that needs it."""
    spots = max(1, likely.count() // TILE)
    met = likely.join(_sets(docs, classes, likely.select("id").distinct(), k), "id").withColumn("spot", F.pmod("tile", F.lit(spots)))
    return met.groupBy("spot").applyInPandas(_exact_tiles(percent), "a long, b long").distinct()


def _sets(docs: DataFrame, classes: DataFrame, ids: DataFrame, k: int) -> DataFrame:
    """The shingle sets of classes, made again from the texts with the classes' doc_ids."""
    wanted = classes.join(ids, "id", "left_semi").select("id", "doc_id", *SAME)
    n = wanted.count()
    named = wanted.select("doc_id").distinct()
    chosen = docs.join(F.broadcast(named) if n <= BROADCAST_IDS else named, "doc_id", "left_semi")
    rows = chosen.mapInArrow(_set_rows(k), "doc_id long, n long, print1 long, print2 long, elements array<bigint>")
    return rows.join(F.broadcast(wanted) if n <= BROADCAST_CLASSES else wanted, ["doc_id", *SAME]).select("id", "elements").dropDuplicates(["id"])


def _exact(docs: DataFrame, classes: DataFrame, pairs: DataFrame, k: int, percent: int) -> DataFrame:
    """Of the pairs (a, b) of class ids, those whose full shingle sets reach the similarity."""
    sets = _sets(docs, classes, pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct(), k)
    both = spread_join(pairs, sets.toDF("b", "eb"), ["b"]).join(sets.toDF("a", "ea"), "a")
    meet = F.size(F.array_intersect("ea", "eb"))
    return both.filter(100 * meet >= percent * (F.size("ea") + F.size("eb") - meet)).select("a", "b")


def near_duplicates(docs: DataFrame, shingle: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row per document: doc_id, n_shingles, component_id, kept, class_id (a number of its class; null without a shingle)."""
    scratch = Scratch(docs.sparkSession, "minhash")
    docs = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    schema = "doc_id long, n long, print1 long, print2 long, sketch binary"
    sketched = scratch.save(docs.mapInArrow(_sketch_rows(shingle), schema).withColumn("row", F.monotonically_increasing_id()), "sketched")
    rows = scratch.save(sketched.drop("sketch"), "rows")
    classes = rows.filter("n > 0").groupBy(*SAME).agg(F.min(F.struct("doc_id", "row")).alias("first"), F.count("*").alias("held"))
    classes = scratch.save(classes.select(*SAME, F.col("first.row").alias("id"), F.col("first.doc_id").alias("doc_id"), "held"), "classes")
    shown = classes.select(F.col("id").alias("row"))
    heads = sketched.join(F.broadcast(shown) if classes.count() <= BROADCAST_IDS else shown, "row", "left_semi")
    heads = scratch.save(heads.select(F.col("row").alias("id"), "n", "sketch"), "heads")
    scratch.drop("sketched")  # one sketch of each class is enough from here on

    banded = heads.select("id", "n", "sketch").mapInArrow(_band_rows, "id long, n long, keys array<bigint>").select("id", "n", F.explode("keys").alias("key"))
    tops = banded.groupBy("key").agg(F.min(F.struct("id", "n")).alias("top"), F.count("*").alias("held")).filter("held > 1")
    members = spread_join(banded, tops.select("key", "top"), ["key"], hot=too_many(tops, ["key"], "held", heads.count() * BANDS))
    members = scratch.save(members.select("key", "id", "n", F.col("top.id").alias("head"), F.col("top.n").alias("head_n")), "members")
    near = lambda x, y: (100 * F.least(x, y) >= percent * F.greatest(x, y))  # noqa: E731  the smaller set must reach the similarity even if it lies in the larger
    stars = members.filter((F.col("id") != F.col("head")) & near(F.col("n"), F.col("head_n"))).select(F.col("id").alias("a"), F.col("head").alias("b")).distinct()

    # only classes that share a bucket meet others
    shared = scratch.save(members.select("id").distinct(), "shared")
    sketch = heads.join(F.broadcast(shared) if shared.count() <= BROADCAST_IDS else shared, "id", "left_semi").select("id", "sketch", "n")
    sketch = scratch.save(sketch, "sketch")
    scratch.drop("heads", "shared")
    least = percent / 100 - ERRORS * (percent / 100 * (1 - percent / 100) / REGISTERS) ** 0.5

    stars = scratch.save(stars, "stars")
    # by merges at every size, so that what moves grows as the input does
    both = spread_join(stars, sketch.toDF("b", "sb", "nb"), ["b"], merge=True).join(sketch.toDF("a", "sa", "na").hint("merge"), "a")
    likely = both.select("a", "b", "sa", "sb", "na", "nb").mapInArrow(_likely(least), "a long, b long")
    likely = scratch.save(likely, "stars-likely")
    links = scratch.save(_exact(docs, classes, likely, shingle, percent), "stars-links")
    found = connected(links, scratch, "first")

    open_ = members.select("key", "id", "n")
    total = members.count()
    for best in (True, False):
        name = "best" if best else "rest"
        labelled = open_.join(found.select(F.col("node").alias("id"), F.col("root").alias("r")), "id", "left")
        labelled = labelled.withColumn("root", F.coalesce("r", "id")).drop("r")
        parts = labelled.groupBy("key", "root").agg(F.count("*").alias("held"))
        mixed = parts.groupBy("key").agg(F.count("*").alias("roots"), F.max(F.struct("held", "root")).alias("main"), F.sum("held").alias("all")).filter("roots > 1")
        mixed = scratch.save(mixed.select("key", "all", F.col("main.root").alias("main"), F.ceil((F.col("all") - F.col("main.held")) / TILE).alias("us"), F.ceil(F.col("all") / TILE).alias("rs")), f"{name}-mixed")
        labelled = spread_join(labelled, mixed.drop("all"), ["key"], hot=too_many(mixed, ["key"], "all", total))
        labelled = scratch.save(labelled.join(sketch.select("id", "sketch").hint("merge"), "id") if best else labelled, f"{name}-open")
        scratch.drop("members", "sketch") if best else scratch.drop("best-open")  # labelled holds what is still needed
        open_ = labelled.select("key", "id", "n", "sketch")
        more = scratch.save(_exact_likely(docs, classes, scratch.save(_stragglers(labelled, percent, least, best), f"{name}-likely"), shingle, percent), f"{name}-links")
        if not more.isEmpty():
            links = links.unionByName(more)
            found = connected(links, scratch, name)

    nodes = found.select(F.col("node").alias("id"), "root").unionByName(found.select(F.col("root").alias("id"), "root").distinct())
    linked = scratch.save(nodes.join(classes.select("id", "doc_id"), "id"), "linked")
    names = spread_join(linked, linked.groupBy("root").agg(F.min("doc_id").alias("name")), ["root"]).select("id", "name")
    roots = classes.join(names, "id", "left").select(*SAME, F.col("id").alias("class_id"), F.coalesce("name", "doc_id").alias("root"))
    full = spread_join(rows.select("doc_id", *SAME), roots, SAME, "left", hot=too_many(classes, SAME, "held", rows.count()))
    full = full.select(F.nullif("doc_id", F.lit(NO_ID)).alias("doc_id"), F.col("n").alias("n_shingles"), F.nullif(F.coalesce("root", "doc_id"), F.lit(NO_ID)).alias("component_id"), "class_id")
    return full.select("doc_id", "n_shingles", "component_id", F.col("component_id").eqNullSafe(F.col("doc_id")).alias("kept"), "class_id")
