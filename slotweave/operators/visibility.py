"""Which tokens the model sees: thresholds, reallocation of slots, export."""

from __future__ import annotations

from dataclasses import dataclass
from decimal import ROUND_CEILING, Decimal

from pyspark.sql import DataFrame, SparkSession

from .exposure import exposures
from .train import MergeLog, TrainingExhausted, train_bpe

RESERVED = 4


class InsufficientCandidates(ValueError):
    """No training, however long, can fill the visible slots."""


def required_slots(n_visible: int, n_reserved: int = RESERVED) -> int:
    n = n_visible - 256 - n_reserved
    if n < 0:
        raise ValueError("fewer slots than bytes and reserved tokens")
    return n


def tau_from_ratio(log: MergeLog, n_required: int, ratio: str | Decimal) -> int:
    """The ratio, as a decimal, of the boundary token's frequency, rounded up."""
    if not n_required:
        return 0
    return int((Decimal(str(ratio)) * log.merges[n_required - 1].freq).to_integral_value(ROUND_CEILING))


@dataclass(frozen=True)
class Tokenizer:
    """Retained merges are a prefix of the log; internal tokens are those that the model doesn't see."""

    log: MergeLog
    internal: frozenset[int]
    n_reserved: int
    trained: int
    tau: int

    @property
    def visible(self) -> list[int]:
        return [t for t in range(256 + len(self.log)) if t not in self.internal]

    @property
    def n_visible(self) -> int:
        return len(self.visible) + self.n_reserved

    def export_ids(self) -> dict[int, int]:
        """Bytes, visible tokens in merge order, specials, then internals: never the ranks."""
        out = {t: i for i, t in enumerate(self.visible)}
        return out | {t: self.n_visible + i for i, t in enumerate(sorted(self.internal))}

    def expansions(self) -> list[list[int]]:
        """The visible tokens that each token becomes."""
        out = [[b] for b in range(256)]
        for m in self.log.merges:
            out.append(out[m.left] + out[m.right] if m.token in self.internal else [m.token])
        return out

    def frame(self, spark: SparkSession) -> DataFrame:
        ids, e = self.export_ids(), exposures(self.log)
        rows = [(t, t - 256 if t >= 256 else None, ids[t], "internal" if t in self.internal else "byte" if t < 256 else "learned", t not in self.internal, bytearray(self.log.token_bytes(t)), e[t]) for t in range(256 + len(self.log))]
        first = len(self.visible)
        rows += [(None, None, first + i, "special", True, bytearray(f"<|special{i}|>".encode()), 0) for i in range(self.n_reserved)]
        return spark.createDataFrame(rows, "token int, rank int, export_id int, kind string, visible boolean, bytes binary, exposure long")


def export_standard(log: MergeLog, n_visible: int, n_reserved: int = RESERVED) -> Tokenizer:
    n = required_slots(n_visible, n_reserved)
    if len(log) < n:
        raise TrainingExhausted(f"{len(log)} merges for {n} slots")
    return Tokenizer(log.prefix(n), frozenset(), n_reserved, n, 0)


def select_visible(log: MergeLog, exposure: list[int], tau: int, n_required: int, n_reserved: int = RESERVED) -> Tokenizer:
    """Scans merges in order until enough are eligible; what comes later is dropped."""
    internal, found = [], 0
    for m in log.merges:
        if found == n_required:
            break
        if exposure[m.token] >= tau:
            found += 1
        else:
            internal.append(m.token)
    if found < n_required:
        raise InsufficientCandidates(f"{found} eligible tokens for {n_required} slots")
    return Tokenizer(log.prefix(found + len(internal)), frozenset(internal), n_reserved, len(log), tau)


def trained_far_enough(log: MergeLog, tau: int, n_required: int, batch: int = 1) -> int | None:
    """The least prefix, n_required plus whole batches, with enough eligible tokens."""
    e = exposures(log, n_required)
    e += [0] * (256 + len(log) - len(e))
    eligible = sum(e[m.token] >= tau for m in log.merges[:n_required])
    m = n_required
    while True:
        if eligible >= n_required and (m - n_required) % batch == 0:
            return m
        if m >= len(log):
            return None
        x = log.merges[m]
        e[x.token] = x.repl
        eligible += x.repl >= tau
        for t in {x.left, x.right}:
            was = e[t] >= tau
            e[t] -= x.repl * (1 + (x.left == x.right))
            if t >= 256:
                eligible += (e[t] >= tau) - was
        m += 1


def reallocate(chunks: DataFrame, log: MergeLog, n_visible: int, ratio: str | None = None, tau: int | None = None, batch: int = 1, n_max: int | None = None, n_reserved: int = RESERVED) -> tuple[Tokenizer, MergeLog]:
    """Trains on until enough tokens are exposed, then exports; also returns the longer log."""
    n = required_slots(n_visible, n_reserved)
    if len(log) < n:
        log = train_bpe(chunks, n, resume=log)
        if len(log) < n:
            raise TrainingExhausted(f"{len(log)} merges for {n} slots")
    tau = tau_from_ratio(log, n, ratio) if tau is None else tau
    most = (n_max - 256) if n_max else 1 << 30
    while (m := trained_far_enough(log.prefix(min(len(log), most)), tau, n, batch)) is None:
        if len(log) >= most:
            raise InsufficientCandidates(f"reached {most} merges with threshold {tau}")
        if log.merges and log.merges[-1].freq < tau:
            raise InsufficientCandidates(f"the best pair has frequency {log.merges[-1].freq}, below the threshold {tau}")
        longer = train_bpe(chunks, min(most, len(log) + max(64, n // 8)), resume=log)
        if len(longer) == len(log):
            raise InsufficientCandidates(f"no pair is left after {len(log)} merges, threshold {tau}")
        log = longer
    return select_visible(log.prefix(m), exposures(log, m), tau, n, n_reserved), log


def prune_only(log: MergeLog, tau: int, n_visible: int, n_reserved: int = RESERVED) -> Tokenizer:
    """The ablation without reallocation: the same merges, fewer visible tokens."""
    n = required_slots(n_visible, n_reserved)
    e = exposures(log, n)
    return Tokenizer(log.prefix(n), frozenset(m.token for m in log.merges[:n] if e[m.token] < tau), n_reserved, n, tau)


def reexport(log: MergeLog, exposure: list[int], tau: int, n_visible: int, n_reserved: int = RESERVED) -> Tokenizer:
    """Another threshold, or the exposure on another corpus, on one trained tree."""
    return select_visible(log, exposure, tau, required_slots(n_visible, n_reserved), n_reserved)
