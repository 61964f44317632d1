"""Byte-level BPE with rank files, by prefix dynamic programming.

For every prefix of a byte string one token can end its encoding: the table keeps that token. A token that ends at i and
starts at j is the right one just when it and the last token of prefix j would stay as they are if both were
merged together from bytes; so the table grows by one entry for each byte, an append only adds entries, and an
edit changes entries only until as many in a row as the longest token has bytes agree with the old ones.

Edge cases: null text is empty: no ids, the hash of no bytes. Text of any length is encoded whole; repeated rows
give equal rows; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
import re
import struct
from collections.abc import Iterator
from functools import cache

import pyarrow as pa
from pyspark.sql import DataFrame

#: Entries of a generation of a worker's table of chunks met.
CACHE = 300_000

#: Fixed values. The split pattern for texts without the characters of RARE, where it cuts as the public pattern does, only faster.
FAST = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+")
RARE = re.compile("[\x1c-\x1f²³¹¼-¾ɐ-‏ -  -₫₭-\U0010ffff]")


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@cache
def public_pattern():
    import public_tokenizers
    import regex

    return regex.compile(public_tokenizers.PATTERN)


def chunks(text: str) -> list[str]:
    return public_pattern().findall(text) if RARE.search(text) else FAST.findall(text)


class Ranks:
    """A rank file's tokens, and which two of them may stand side by side."""

    def __init__(self, path: str):
        with open(path, "rb") as lines:
            self.rank = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        self.token = {i: t for t, i in self.rank.items()}
        self.longest = max(map(len, self.rank))
        self._halves: dict[int, tuple[int, int] | None] = {}
        self._fits: dict[tuple[int, int], bool] = {}
        self._spines: tuple[dict[int, list[int]], dict[int, list[int]]] = ({}, {})
        self.word: dict[bytes, bytes] = {}

    def halves(self, t: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes t; None for a single byte, and for a token that merging never makes: (-1, -1)."""
        if t not in self._halves:
            parts = [self.token[t][i : i + 1] for i in range(len(self.token[t]))]
            while len(parts) > 2:
                ranks = [self.rank.get(a + b, 1 << 40) for a, b in zip(parts, parts[1:], strict=False)]
                best = min(ranks)
                if best >= t:
                    break
                at = ranks.index(best)
                parts[at : at + 2] = [parts[at] + parts[at + 1]]
            self._halves[t] = None if len(parts) == 1 else (self.rank[parts[0]], self.rank[parts[1]]) if len(parts) == 2 else (-1, -1)
        return self._halves[t]

    def made(self, t: int) -> bool:
        return self.halves(t) != (-1, -1)

    def _spine(self, t: int, side: int) -> list[int]:
        """From the byte at t's right (side 1) or left (0) end up to t."""
        if t not in self._spines[side]:
            up = [t]
            while (h := self.halves(up[-1])) is not None:
                up.append(h[side])
            self._spines[side][t] = up[::-1]
        return self._spines[side][t]

    def fits(self, a: int, b: int) -> bool:
        """Whether the bytes of a and b together merge to a, b: no merge across the seam comes before those that build both."""
        key = (a, b)
        if (known := self._fits.get(key)) is None:
            if len(self._fits) > 2_000_000:
                self._fits.clear()
            known = self._fits[key] = self._seam(self._spine(a, 1), self._spine(b, 0))
        return known

    def _seam(self, left: list[int], right: list[int]) -> bool:
        i = j = 0
        never = 1 << 40
        while True:
            across = self.rank.get(self.token[left[i]] + self.token[right[j]], never)
            on_left = left[i + 1] if i + 1 < len(left) else never
            on_right = right[j + 1] if j + 1 < len(right) else never
            if across < on_left and across <= on_right and across < never:
                return False
            if on_left == on_right == never:
                return True
            if on_left <= on_right:
                i += 1
            else:
                j += 1


class PrefixTable:
    """The last token of every prefix of one chunk's bytes."""

    def __init__(self, ranks: Ranks, data: bytes = b""):
        self.ranks, self.data, self.last = ranks, b"", [-1]
        self.append(data)

    def _entry(self, i: int) -> int:
        ranks, data, last = self.ranks, self.data, self.last
        get = ranks.rank.get
        for j in range(max(0, i - ranks.longest), i):
            t = get(data[j:i])
            if t is not None and ranks.made(t) and (j == 0 or ranks.fits(last[j], t)):
                return t
        raise ValueError("a byte has no token")

    def append(self, more: bytes) -> None:
        start = len(self.data)
        self.data += more
        for i in range(start + 1, len(self.data) + 1):
            self.last.append(self._entry(i))

    def edit(self, start: int, end: int, new: bytes) -> int:
        """Replaces bytes start..end; returns how many entries were worked out anew."""
        old, moved = self.last, len(new) - (end - start)
        self.data = self.data[:start] + new + self.data[end:]
        self.last = old[: start + 1]
        agreed = 0
        for i in range(start + 1, len(self.data) + 1):
            t = self._entry(i)
            self.last.append(t)
            agreed = agreed + 1 if i > start + len(new) and old[i - moved] == t else 0
            if agreed >= self.ranks.longest:
                self.last += old[i - moved + 1 :]
                return i - start
        return len(self.data) - start

    def ids(self) -> list[int]:
        out, i = [], len(self.data)
        while i:
            out.append(self.last[i])
            i -= len(self.ranks.token[self.last[i]])
        return out[::-1]


def encode_chunk(ranks: Ranks, data: bytes) -> list[int]:
    """A chunk that is itself a token is that token, whatever the merges would make of it. The prefix table's entries, in one loop."""
    get, fits, made, longest = ranks.rank.get, ranks.fits, ranks.made, ranks.longest
    if (whole := get(data)) is not None:
        return [whole]
    known = ranks._fits.get
    last, back = [-1], [0]
    for i in range(1, len(data) + 1):
        for j in range(max(0, i - longest), i):
            t = get(data[j:i])
            if t is None:
                continue
            fit = known((last[j], t)) if j else None
            if fit or fit is None and made(t) and (not j or fits(last[j], t)):
                last.append(t)
                back.append(j)
                break
    out, i = [], len(data)
    while i:
        out.append(last[i])
        i = back[i]
    return out[::-1]


class _Words(dict):
    """Chunk -> its ids as little-endian 32-bit integers: two generations of CACHE entries, so frequent chunks outlive a full table."""

    def __init__(self, ranks: Ranks):
        self.ranks, self.old = ranks, {}

    def __missing__(self, chunk: str) -> bytes:
        if len(self) >= CACHE:
            self.old = dict(self)
            self.clear()
        packed = self.old.get(chunk)
        if packed is None:
            ids = encode_chunk(self.ranks, chunk.encode("utf-8", "surrogatepass"))
            packed = struct.pack(f"<{len(ids)}I", *ids)
        self[chunk] = packed
        return packed


@cache
def _encoder(path: str) -> tuple[Ranks, _Words]:
    ranks = Ranks(path)
    return ranks, _Words(ranks)


def encode_packed(path: str, text: str | None) -> bytes:
    words = _encoder(path)[1].__getitem__
    return b"".join(map(words, chunks(text or "")))


def decode(path: str, ids: list[int]) -> bytes:
    return b"".join(map(_encoder(path)[0].token.__getitem__, ids))


def encode_documents(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and the ids of its whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            packed = [memoryview(encode_packed(path, t)).cast("I").tolist() for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(packed, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return docs.selectExpr(f"cast(`{id_col}` as long) doc_id", f"cast(`{text_col}` as string) text").mapInArrow(run, "doc_id long, ids array<int>")


def decode_documents(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id and the text that its ids stand for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [decode(path, ids or []).decode("utf-8", "replace") for ids in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def digests(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document the number of ids, and hashes of the ids and of the decoded bytes, from one encoding and decoding."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        token = _encoder(path)[0].token.__getitem__
        for batch in batches:
            n, ids, back = [], [], []
            for text in batch.column(1).to_pylist():
                packed = encode_packed(path, text)
                n.append(len(packed) // 4)
                ids.append(hashlib.sha256(packed).hexdigest())
                back.append(hashlib.sha256(b"".join(map(token, memoryview(packed).cast("I")))).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids), pa.array(back)], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    source = docs.selectExpr(f"cast(`{id_col}` as long) doc_id", f"cast(`{text_col}` as string) text")
    return source.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
