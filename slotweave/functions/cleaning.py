"""Light cleaning: nothing here folds case or normalises characters."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def drop_repeated_lines(text: Column) -> Column:
    lines = F.split(text, "\n", -1)
    return F.array_join(F.filter(lines, lambda x, i: (i == 0) | (x != F.get(lines, i - 1))), "\n")


def strip_artifacts(text: Column) -> Column:
    return F.regexp_replace(text, "[\\x00-\\x08\\x0b\\x0c\\x0e-\\x1f\\x7f\\x{FFFD}]", "")


MARKUP = [r"(?s)<!--.*?-->", r"(?is)<script[^>]*>.*?</script>", r"(?is)<style[^>]*>.*?</style>", r"(?is)<nav[^>]*>.*?</nav>", r"(?s)<[^>]*>"]


def strip_markup(html: Column) -> Column:
    out = html
    for pattern in MARKUP:
        out = F.regexp_replace(out, pattern, "")
    return out
