"""Measures over lengths and vocabularies. Percentages come from whole counts and are rounded last."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .encode import length_from_log, vp_length_from_log
from .exposure import exposures
from .train import MergeLog
from .visibility import Tokenizer, required_slots

LENGTHS = "train string, eval string, n_visible int, ratio string, encoder string, tokens long, internal int"


def percent(part: Column, whole: Column, digits: int = 2) -> Column:
    return F.round(F.lit(100.0) * part / whole, digits)


def marginal_reduction(lengths: DataFrame) -> DataFrame:
    """What the next larger standard vocabulary saves."""
    w = Window.partitionBy("train", "eval").orderBy("n_visible")
    std = lengths.filter("ratio = '0'").withColumns({"next": F.lead("tokens").over(w), "next_n": F.lead("n_visible").over(w)}).filter("next is not null")
    return std.select("train", "eval", "n_visible", "next_n", percent(F.col("tokens") - F.col("next"), F.col("tokens")).alias("reduction"))


def reduction(lengths: DataFrame) -> DataFrame:
    """Saved against the standard vocabulary of the same training corpus, evaluation corpus and visible size."""
    keys = ["train", "eval", "n_visible", "encoder"]
    std = lengths.filter("ratio = '0'").select(*keys, F.col("tokens").alias("len_std"))
    vp = lengths.filter("ratio <> '0'").select(*keys, "ratio", F.col("tokens").alias("len_vp"))
    return vp.join(std, keys).select(*keys, "ratio", "len_std", "len_vp", percent(F.col("len_std") - F.col("len_vp"), F.col("len_std"), 4).alias("delta"))


def internal_share(lengths: DataFrame, n_reserved: int = 4) -> DataFrame:
    return lengths.filter("train = eval and ratio <> '0'").select("train", "n_visible", "ratio", "internal", percent(F.col("internal"), F.col("n_visible") - 256 - n_reserved).alias("share"))


def relative_gain(lengths: DataFrame, ratio: str = "0.4") -> DataFrame:
    """The reallocation's saving beside that of the next larger vocabulary."""
    d = reduction(lengths).filter(F.col("ratio") == ratio).select("train", "eval", "n_visible", "delta")
    return marginal_reduction(lengths).join(d, ["train", "eval", "n_visible"]).withColumn("relative", F.round(F.col("delta") / F.col("reduction"), 4))


def decompose(tok: Tokenizer, standard: Tokenizer, log: MergeLog) -> tuple[int, int, int]:
    """(tokens saved by further candidates, tokens spent on expansion, net saving)."""
    gain = length_from_log(log, len(standard.log)) - length_from_log(log, len(tok.log))
    net = length_from_log(log, len(standard.log)) - vp_length_from_log(tok, log)
    return gain, gain - net, net


def support(tok: Tokenizer) -> list[tuple[int, int, int]]:
    """(internal token, direct visible parents, visible ancestors): an orphan has no visible ancestor."""
    parents: dict[int, set[int]] = {}
    for m in tok.log.merges:
        for t in (m.left, m.right):
            parents.setdefault(t, set()).add(m.token)
    above: dict[int, set[int]] = {}
    for t in range(255 + len(tok.log), -1, -1):
        above[t] = set().union(*[{p} | above[p] for p in parents.get(t, ())])
    seen = set(tok.visible)
    return [(t, len(parents.get(t, set()) & seen), len(above[t] & seen)) for t in sorted(tok.internal)]


def chains(tok: Tokenizer) -> list[tuple[int, list[int], list[int]]]:
    """(internal token, the visible tokens merged from it at once, the shortest chain from it over internal tokens to a visible one, of equal ones
    that of the earliest tokens): the chain is empty for an orphan."""
    parents: dict[int, list[int]] = {}
    for m in tok.log.merges:
        for t in {m.left, m.right}:
            parents.setdefault(t, []).append(m.token)
    best: dict[int, list[int]] = {}
    for t in range(255 + len(tok.log), 255, -1):
        if t in tok.internal:
            ways = [[p] if p not in tok.internal else [p, *best[p]] for p in parents.get(t, ()) if p not in tok.internal or best[p]]
            best[t] = min(ways, key=lambda w: (len(w), w), default=[])
    return [(t, [p for p in parents.get(t, ()) if p not in tok.internal], best[t]) for t in sorted(tok.internal)]


def bytes_per_token(size: Column, tokens: Column) -> Column:
    return F.round(size.cast("double") / tokens, 4)


def slot_moves(standard: Tokenizer, vp: Tokenizer, spark: SparkSession) -> DataFrame:
    """Tokens that lost or gained a visible slot."""
    rows = [(t, "lost") for t in sorted(set(standard.visible) - set(vp.visible))] + [(t, "gained") for t in sorted(set(vp.visible) - set(standard.visible))]
    log = vp.log if len(vp.log) >= len(standard.log) else standard.log
    return spark.createDataFrame([(t, m, log.token_bytes(t).hex()) for t, m in rows], "token int, move string, bytes string")


def nesting_violations(low: Tokenizer, high: Tokenizer) -> set[int]:
    """Internal under the lower threshold but not under the higher one: none."""
    return set(low.internal) - set(high.internal)


def token_class(data: bytes) -> str:
    try:
        text = data.decode("utf-8")
    except UnicodeDecodeError:
        return "partial_utf8"
    body = text.strip()
    if not body:
        return "whitespace"
    if any(c in "<>/=&" for c in body):
        return "markup"
    if body.isascii():
        return "latin_fragment" if body.isalnum() else "other"
    return "latin_fragment" if all(ord(c) < 0x250 for c in body if c.isalpha()) else "other_script"


def usage_balance(tok: Tokenizer) -> float:
    """Gini coefficient of exposure over visible learned tokens."""
    e = exposures(tok.log)
    x = sorted(e[t] for t in tok.visible if t >= 256)
    total = sum(x)
    return sum((2 * i - len(x) + 1) * v for i, v in enumerate(x)) / (len(x) * total) if total else 0.0


def training_overhead(tok: Tokenizer, n_visible: int) -> tuple[int, int]:
    """(merges trained beyond the standard ones, of those the ones not retained)."""
    return tok.trained - required_slots(n_visible, tok.n_reserved), tok.trained - len(tok.log)


def choose_ratio(log: MergeLog, on_eval: MergeLog, n_visible: int, ratios: list[str], build) -> str:
    """The ratio of the least length on another corpus."""
    return min(ratios, key=lambda r: (vp_length_from_log(build(log, n_visible, r), on_eval), r))
