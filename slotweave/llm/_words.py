"""Word and shingle kernels on whole batches of texts, in numpy.

A word is a run of bytes other than 20 and 09-0D (hex); only A-Z is lower-cased. ``bytes.lower`` and
``bytes.split`` follow just these rules.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

U = np.uint64
#: Odd 64-bit multipliers of a common finaliser, and one for the byte polynomial.
MIX_A, MIX_B, STEP = U(0xFF51AFD7ED558CCD), U(0xC4CEB9FE1A85EC53), U(0x9E3779B97F4A7C15)
BASE = 0x100000001B3


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values with good avalanche."""
    x = x ^ (x >> U(33))
    x = x * MIX_A
    x = x ^ (x >> U(33))
    x = x * MIX_B
    return x ^ (x >> U(33))


_powers = np.ones(1, U)


def powers(n: int) -> np.ndarray:
    global _powers
    if len(_powers) < n:
        with np.errstate(over="ignore"):
            _powers = np.concatenate([np.ones(1, U), np.cumprod(np.full(max(n, 1024) - 1, BASE, U))])
    return _powers


def in_slices(column, limit: int = 1_000_000, rows: int = 400) -> Iterator[tuple[int, list[bytes]]]:
    """Runs of encoded texts of an Arrow column, of at most ``rows`` and about ``limit`` bytes; a longer text is a run of its own."""
    for first in range(0, len(column), rows):
        start, held, size = first, [], 0
        for i, text in enumerate(column.slice(first, rows).to_pylist(), first):
            raw = (text or "").encode("utf-8", "surrogatepass")
            if held and size + len(raw) > limit:
                yield start, held
                start, held, size = i, [], 0
            held.append(raw)
            size += len(raw) + 1
        yield start, held


def word_hashes(raws: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit hash of each word, number of the text it stands in), in order."""
    data = np.frombuffer(b" ".join(raws) + b" ", np.uint8)
    lower = data + ((data >= 65) & (data <= 90)).astype(np.uint8) * np.uint8(32)
    space = (data == 32) | ((data >= 9) & (data <= 13))
    edge = np.flatnonzero(np.diff(np.concatenate([[True], space]).astype(np.int8)))
    starts, ends = edge[0::2], edge[1::2]
    if not len(starts):
        return np.zeros(0, U), np.zeros(0, np.int64)
    lengths = ends - starts
    inside = ~space
    place = np.flatnonzero(inside) - np.repeat(starts, lengths)
    with np.errstate(over="ignore"):
        terms = (lower[inside].astype(U) + U(1)) * powers(int(lengths.max()) + 1)[place]
        sums = np.add.reduceat(terms, np.concatenate([[0], np.cumsum(lengths)[:-1]]))
        hashes = mix(sums ^ (lengths.astype(U) * STEP))
    offsets = np.cumsum([0] + [len(r) + 1 for r in raws])
    return hashes, np.searchsorted(offsets, starts, "right") - 1


def shingle_sets(raws: list[bytes], k: int) -> tuple[np.ndarray, np.ndarray]:
    """(distinct shingle hashes text after text, number of them in each text).

    A text of fewer than k words, but at least one, has its whole word sequence as its one shingle.
    """
    hashes, text = word_hashes(raws)
    words = np.bincount(text, minlength=len(raws))
    sets: list[np.ndarray] = []
    with np.errstate(over="ignore"):
        if len(hashes) >= k:
            rolled = np.zeros(len(hashes) - k + 1, U)
            for i in range(k):
                rolled = mix(rolled * STEP + hashes[i : len(hashes) - k + 1 + i] + U(i + 1))
        ends = np.cumsum(words)
        for n, end in zip(words.tolist(), ends.tolist(), strict=True):
            if n >= k:
                sets.append(np.unique(rolled[end - n : end - k + 1]))
            elif n:
                whole = np.zeros(1, U)
                for h in hashes[end - n : end]:
                    whole = mix(whole * STEP + h + U(n * 64))
                sets.append(whole)
            else:
                sets.append(np.zeros(0, U))
    return np.concatenate(sets) if sets else np.zeros(0, U), np.array([len(s) for s in sets], np.int64)
