"""The pretokenizer: one grammar whose matches, end to end, are the text again.

Java's and RE2's spellings come from one source. Java repeats a group by recursion, and a long run would exhaust its stack;
so every repeated group is possessive there, which loops instead, and cuts the same because it ends its alternative.
An extension has to end its word; RE2 lacks the look ahead and takes an ASCII word boundary, which differs only before a letter
that isn't ASCII. A single space joins the word, number or other-script span after it; all other white space and marks stand alone.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: File extensions; and marks that group in runs of the same one.
EXTENSIONS = ["javascript", "java", "json", "jsx", "js", "html", "htm", "py"]
MARKS = ".-=,;:!?*#/\\|~_+<>()[]{}\"'`@$%^&"


def grammar(latin: str, again: str, ends: str) -> str:
    """latin: the script's class; again: repeats a group; ends: what follows an extension."""
    extension = "(?:" + "|".join(EXTENSIONS) + ")" + ends
    inner = rf"[{latin}\p{{M}}0-9_]"
    word = rf"[{latin}_]{inner}*"
    runs = [rf"\x{ord(c):02x}+" for c in MARKS if c != "_"]
    return "|".join(
        [
            r"\r\n|\n+|\r+|\t+|\x20{2,}",
            r"</",
            rf"\.{extension}",
            rf"\x20?[{latin}][{latin}\p{{M}}]*-[0-9]+",
            rf"\x20?{word}\.{extension}",
            r"\x20?[A-Za-z](?:\+\+|#)",
            rf"\x20?{word}(?:'{inner}+){again}",
            rf"\x20?[0-9]+(?:[.-][0-9]+){again}",
            rf"\x20?[^\P{{L}}{latin}](?:[^\P{{L}}{latin}]|\p{{M}}){again}",
            *runs,
            r"[\s\S]",
        ]
    )


JAVA = grammar(r"\p{IsLatin}", "*+", r"(?![\p{IsLatin}\p{M}0-9_])")
RE2 = grammar(r"\p{Latin}", "*", r"\b")
PYTHON = grammar(r"\p{Latin}", "*+", r"(?![\p{Latin}\p{M}0-9_])")


def pretokenize(text: Column) -> Column:
    """The chunks of a text; none of a null or empty one."""
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(JAVA), F.lit(0))


def chunks_of(text: Column, pretok: bool = True) -> Column:
    return pretokenize(text) if pretok else F.filter(F.array(F.coalesce(text, F.lit(""))), lambda c: c != "")


KINDS = [
    ("whitespace", r"^\s+$"),
    ("latin", r"^ ?[\p{IsLatin}_]"),
    ("digit", r"^ ?[0-9]"),
    ("other_script", r"^ ?\p{L}"),
    ("punctuation", r"^\p{P}"),
    ("symbol", r"^\p{S}"),
]


def chunk_kind(chunk: Column) -> Column:
    out = F.lit("other")
    for name, pattern in reversed(KINDS):
        out = F.when(chunk.rlike(pattern), name).otherwise(out)
    return out
