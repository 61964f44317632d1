"""Symbol strings: a sequence of tokens is one string with a code point for each token.

Byte b is code point b and token i is code point i, jumping the surrogates, so a merge is one native replace()
and the order of strings is the order of ids.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SURROGATES, JUMP = 0xD800, 0x800


def symbol(token: int) -> str:
    return chr(token if token < SURROGATES else token + JUMP)


def token_of(symbol: str) -> int:
    code = ord(symbol)
    return code if code < SURROGATES else code - JUMP


def to_symbols(chunk: Column) -> Column:
    return F.decode(F.encode(chunk, "UTF-8"), "ISO-8859-1")


def token_column(symbol: Column) -> Column:
    code = F.ascii(symbol)
    return F.when(code < SURROGATES, code).otherwise(code - JUMP)
