"""The experiments on the given tables: three trainings, budgets, thresholds, evaluations.

Every workload takes a Study, so the same code runs on the documents, with budgets that follow their size, and on a few passages, where SQL repeats it.
"""

from __future__ import annotations

import functools
import os
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from slotweave.functions.pretok import chunks_of
from slotweave.functions.symbols import to_symbols
from slotweave.operators import measures as ms
from slotweave.operators.corpus import build_corpora
from slotweave.operators.encode import length_from_log, replay, vp_length_from_log
from slotweave.operators.exposure import exposures
from slotweave.operators.mintoken import min_lengths, vocabulary
from slotweave.operators.train import MergeLog, chunk_table, train_bpe
from slotweave.operators.visibility import InsufficientCandidates, Tokenizer, export_standard, prune_only, reallocate, required_slots, tau_from_ratio, trained_far_enough, select_visible
from slotweave.sources.tables import over_all_cores

RATIOS = ["0.2", "0.3", "0.4"]
PARTS = {"A": ["A"], "B": ["B"], "AB": ["A", "B"]}
#: The largest budget is this factor times a power of the corpora's bytes: about 620 at 0.5 MB, 3,700 at 24 MB, 16,000 at 640 MB, and no more than MOST.
FACTOR, POWER, LEAST, MOST = 1.75, 0.45, 544, 20_000


def budgets_for(size: int) -> list[int]:
    """Four budgets and a fifth for the last step's gain, at even steps from half the largest one."""
    top = min(MOST, max(LEAST, int(FACTOR * size**POWER))) // 8
    return [top * i for i in range(4, 9)]


class Study:
    """Chunk tables of some corpora and what is trained on them, each made when first asked for."""

    def __init__(self, spark: SparkSession, chunks: Callable[[str], DataFrame], budgets: list[int], ratios: list[str] = RATIOS, largest: str | None = None):
        self.spark, self.ratios, self.largest = spark, ratios, largest or ratios[-1]
        self._make, self._chunks = chunks, {}
        self._logs: dict[str, MergeLog] = {}
        self._tokenizers: dict[tuple[str, int, str], Tokenizer] = {}
        self._replays: dict[tuple[str, str], MergeLog] = {}
        *self.budgets, self.extra = budgets

    @classmethod
    def of_folder(cls, spark: SparkSession, sf_dir: str) -> Study:
        """The documents' two corpora are cut once, into (corpus, chunk, count); their union adds those counts up."""
        docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
        size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        corpora = build_corpora(over_all_cores(docs))
        cut = corpora.select("corpus", F.explode(chunks_of(F.col("text"))).alias("chunk")).groupBy("corpus", "chunk").agg(F.count("*").alias("n")).select("corpus", to_symbols("chunk").alias("sym"), "n").persist()

        def chunks(name: str) -> DataFrame:
            if name == "AB":
                return cut.groupBy("sym").agg(F.sum("n").alias("n"))
            if name in PARTS:
                return cut.filter(F.col("corpus") == name).select("sym", "n")
            table = spark.read.parquet(f"{sf_dir}/{name}.parquet")
            return chunk_table(over_all_cores(table.select(F.col({"pages": "html"}.get(name, "text")).alias("text"))))

        made = cls(spark, chunks, budgets_for(size))
        made._cut = cut
        return made

    def chunks(self, corpus: str) -> DataFrame:
        if corpus not in self._chunks:
            self._chunks[corpus] = self._make(corpus).persist()
        return self._chunks[corpus]

    def log(self, train: str) -> MergeLog:
        if train not in self._logs:
            self._logs[train] = train_bpe(self.chunks(train), required_slots(self.extra))
        return self._logs[train]

    def tokenizer(self, train: str, n_visible: int, ratio: str = "0") -> Tokenizer:
        key = (train, n_visible, ratio)
        if key not in self._tokenizers:
            if ratio == "0":
                self._tokenizers[key] = export_standard(self.log(train), n_visible)
            else:
                self._tokenizers[key], longer = reallocate(self.chunks(train), self.log(train), n_visible, ratio)
                if len(longer) > len(self._logs[train]):
                    self._logs[train] = longer
        return self._tokenizers[key]

    def replayed(self, train: str, eval_: str) -> MergeLog:
        key = (train, eval_)
        log = self.log(train)
        if train == eval_:
            return log
        if key not in self._replays or len(self._replays[key]) < len(log):
            self._replays[key] = replay(log, self.chunks(eval_))
        return self._replays[key]

    def length(self, train: str, eval_: str, n_visible: int, ratio: str) -> tuple[int, int]:
        tok = self.tokenizer(train, n_visible, ratio)
        return vp_length_from_log(tok, self.replayed(train, eval_)), len(tok.internal)

    _cut: DataFrame | None = None

    def close(self) -> None:
        for c in [*self._chunks.values(), *([self._cut] if self._cut is not None else [])]:
            c.unpersist()


_studies: dict[tuple[str, str], Study] = {}


def study(spark: SparkSession, sf_dir: str) -> Study:
    """The folder's study, kept for the application, so that its queries share the trainings."""
    key = (spark.sparkContext.applicationId, os.path.normpath(sf_dir) if "://" not in sf_dir else sf_dir)
    if key not in _studies:
        for old in [k for k in _studies if k[0] != key[0]]:
            del _studies[old]
        _studies[key] = Study.of_folder(spark, sf_dir)
    return _studies[key]


def forget() -> None:
    for s in _studies.values():
        s.close()
    _studies.clear()


def lengths(s: Study, trains=("A", "B", "AB"), evals: dict[str, list[str]] | None = None, ratios: tuple[str, ...] | None = None, extra: bool = True) -> DataFrame:
    """Encoded lengths of every configuration, from one log per training and one replay per evaluation."""
    evals = evals or {"A": ["A", "B"], "B": ["A", "B"], "AB": ["A", "B", "AB"]}
    ratios = ratios or ("0", *s.ratios)

    def prepare(t: str) -> None:  # the longest logs first, so each replay is made once
        for n in s.budgets:
            for r in ratios:
                s.tokenizer(t, n, r)

    with ThreadPoolExecutor(len(trains)) as pool:  # trainings share nothing, so their jobs run side by side
        list(pool.map(prepare, trains))
    rows = [(t, e, n, r, "native", *s.length(t, e, n, r)) for t in trains for e in evals[t] for n in s.budgets for r in ratios]
    if extra:
        rows += [(t, e, s.extra, "0", "native", length_from_log(s.replayed(t, e), required_slots(s.extra)), 0) for t in trains for e in evals[t]]
    return s.spark.createDataFrame(rows, ms.LENGTHS)


def w02_budget_curve(s: Study) -> DataFrame:
    return ms.marginal_reduction(lengths(s, evals={t: [t] for t in PARTS}, ratios=("0",)))


def w03_lengths(s: Study) -> DataFrame:
    return ms.reduction(lengths(s, extra=False))


def w04_internal_shares(s: Study) -> DataFrame:
    return ms.internal_share(lengths(s, evals={t: [t] for t in PARTS}, extra=False))


def w05_threshold_effect(s: Study) -> DataFrame:
    """Each threshold beside the one below and the next smaller budget: internal tokens, nesting violations, what is saved; and whether more is saved and hidden."""
    saved = ms.reduction(lengths(s, extra=False))
    rows = []
    for t in PARTS:
        for n in s.budgets:
            toks = [s.tokenizer(t, n, r) for r in s.ratios]
            for low, high, r in zip([None, *toks], toks, s.ratios, strict=False):
                rows.append((t, n, r, len(high.internal), len(ms.nesting_violations(low, high)) if low else 0))
    kinds = s.spark.createDataFrame(rows, "train string, n_visible int, ratio string, internal int, violations int")
    by_ratio, by_budget = Window.partitionBy("train", "eval", "n_visible").orderBy("ratio"), Window.partitionBy("train", "eval", "ratio").orderBy("n_visible")
    out = saved.join(kinds, ["train", "n_visible", "ratio"]).withColumns(
        {"internal_below": F.lag("internal").over(by_ratio), "len_below": F.lag("len_vp").over(by_ratio), "internal_smaller": F.lag("internal").over(by_budget)}
    )
    return out.select("train", "eval", "n_visible", "ratio", "internal", "delta", "violations", (F.col("len_vp") < F.col("len_below")).alias("saves_more"), (F.col("internal") >= F.col("internal_below")).alias("hides_more"), (F.col("internal") >= F.col("internal_smaller")).alias("grows"))


def w06_gain_beside_larger_vocabulary(s: Study) -> DataFrame:
    return ms.relative_gain(lengths(s, evals={t: [t] for t in PARTS}), s.largest)


def w07_other_tables(s: Study) -> DataFrame:
    others = ["pages", "conversations", "benchmark"]
    return ms.reduction(lengths(s, trains=("AB",), evals={"AB": others}, extra=False))


def _min_lengths(s: Study, budgets: list[int], evals: list[str], ratios: list[str]) -> DataFrame:
    """One pass over the chunks of each evaluation corpus, with all vocabularies at once; a union's totals are the sums of its parts', so no chunk of it is cut again."""
    toks = {(n, r): s.tokenizer("AB", n, r) for n in budgets for r in ratios}
    words = {k: vocabulary(t) for k, t in toks.items()}
    parts = {e: PARTS.get(e, [e]) for e in evals}
    found = {p: min_lengths(s.chunks(p), words) for p in sorted(set().union(*parts.values()))}
    rows = [("AB", e, n, r, "minimum", sum(found[p][n, r] for p in parts[e]), len(toks[n, r].internal)) for e in evals for n, r in toks]
    return s.spark.createDataFrame(rows, ms.LENGTHS)


def w08_minimum_tokens(s: Study) -> DataFrame:
    return ms.reduction(_min_lengths(s, s.budgets, ["A", "B", "AB"], ["0", s.largest]))


def w09_minimum_below_native(s: Study) -> DataFrame:
    """Every vocabulary on every corpus, both methods: the fewest tokens beside those of the merges."""
    evals = ["A", "B", "AB"]
    keys = ["eval", "n_visible", "ratio"]
    low = _min_lengths(s, s.budgets, evals, ["0", s.largest]).select(*keys, F.col("tokens").alias("minimum"))
    native = lengths(s, trains=("AB",), evals={"AB": evals}, ratios=("0", s.largest), extra=False).select(*keys, F.col("tokens").alias("native"))
    return native.join(low, keys).select(*keys, "native", "minimum", (F.col("minimum") < F.col("native")).alias("below"), ms.percent(F.col("native") - F.col("minimum"), F.col("native"), 4).alias("shorter"))


def w10_internal_tokens(s: Study) -> DataFrame:
    """Internal tokens of the largest budget: the visible tokens made of each at once, and the shortest chain through other internal tokens to a visible one."""
    tok = s.tokenizer("AB", s.budgets[-1], s.largest)
    e, spelled = exposures(tok.log), lambda t: tok.log.token_bytes(t).hex()
    counts = {t: (direct, above) for t, direct, above in ms.support(tok)}
    rows = [(t, spelled(t), ms.token_class(tok.log.token_bytes(t)), tok.log.merges[t - 256].freq, e[t], *counts[t], [spelled(x) for x in direct], [spelled(x) for x in chain]) for t, direct, chain in ms.chains(tok)]
    return s.spark.createDataFrame(rows, "token int, bytes string, kind string, freq long, exposure long, visible_parents int, visible_ancestors int, parents array<string>, chain array<string>")


def w11_token_across_configurations(s: Study) -> DataFrame:
    """For each byte string internal somewhere, a column per training, budget and ratio: internal, visible or absent."""
    configs = {f"{t}_{n}_{round(100 * float(r))}": s.tokenizer(t, n, r) for t in PARTS for n in s.budgets for r in s.ratios}
    inside = {c: {x.log.token_bytes(t) for t in x.internal} for c, x in configs.items()}
    seen = {c: {x.log.token_bytes(t) for t in x.visible} for c, x in configs.items()}
    wanted = sorted(set().union(*inside.values()))
    rows = [(w.hex(), *("internal" if w in inside[c] else "visible" if w in seen[c] else "absent" for c in configs)) for w in wanted]
    return s.spark.createDataFrame(rows, "bytes string, " + ", ".join(f"`{c}` string" for c in configs))


def w12_prune_only(s: Study) -> DataFrame:
    """Standard, pruned and reallocated vocabularies of each training and budget: visible slots and length."""
    rows = []
    for t in PARTS:
        for n in s.budgets:
            vp, log = s.tokenizer(t, n, s.largest), s.log(t)
            toks = (("standard", s.tokenizer(t, n)), ("prune_only", prune_only(log, vp.tau, n)), ("reallocated", vp))
            rows += [(t, n, name, tok.n_visible, vp_length_from_log(tok, log)) for name, tok in toks]
    return s.spark.createDataFrame(rows, "train string, n_visible int, method string, visible int, tokens long")


def w13_domain_export(s: Study) -> DataFrame:
    """One tree trained on AB, for as long as a domain needs, exported by its exposure on another table."""
    n = s.budgets[0]
    need = required_slots(n)
    rows = []
    for domain in ("AB", "pages", "conversations"):
        log, m = s.log("AB"), None
        while True:
            on = s.replayed("AB", domain)
            # the boundary token's own count on the domain: what it made there
            tau = tau_from_ratio(MergeLog(tuple(replace(x, freq=x.repl) for x in on.merges), on.byte_counts), need, s.largest)
            m = trained_far_enough(on, tau, need)
            if m is not None:
                break
            before = len(log)
            log = s._logs["AB"] = train_bpe(s.chunks("AB"), before + need, resume=log)
            if len(log) == before:
                raise InsufficientCandidates(f"{domain}: no pair is left after {before} merges, threshold {tau}")
        tok = select_visible(log.prefix(m), exposures(on, m), tau, need)
        rows.append((domain, tok.tau, len(tok.internal), len(set(tok.visible) ^ set(s.tokenizer("AB", n).visible)), vp_length_from_log(tok, on)))
    return s.spark.createDataFrame(rows, "domain string, tau int, internal int, slots_changed int, tokens long")


def w_decomposition(s: Study) -> DataFrame:
    rows = []
    for t in PARTS:
        for n in s.budgets:
            for r in s.ratios:
                tok = s.tokenizer(t, n, r)
                rows.append((t, n, r, *ms.decompose(tok, s.tokenizer(t, n), s.log(t)), *ms.training_overhead(tok, n), ms.usage_balance(tok)))
    return s.spark.createDataFrame(rows, "train string, n_visible int, ratio string, candidate_gain long, expansion_cost long, net long, extra_merges int, overshoot int, gini double")


def w15_chosen_ratio(s: Study) -> DataFrame:
    """For each budget the ratio that encodes a table outside the training corpus in fewest tokens."""
    for n in s.budgets:
        for r in s.ratios:
            s.tokenizer("AB", n, r)
    rows = [(n, on, ms.choose_ratio(s.log("AB"), s.replayed("AB", on), n, s.ratios, lambda _, size, r: s.tokenizer("AB", size, r))) for on in ("pages", "conversations") for n in s.budgets]
    return s.spark.createDataFrame(rows, "n_visible int, chosen_on string, ratio string")


_OF_STUDY = [w02_budget_curve, w03_lengths, w04_internal_shares, w05_threshold_effect, w06_gain_beside_larger_vocabulary, w07_other_tables, w08_minimum_tokens, w09_minimum_below_native, w10_internal_tokens, w11_token_across_configurations, w12_prune_only, w13_domain_export, w15_chosen_ratio, w_decomposition]


def _on_folder(workload: Callable[[Study], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    @functools.wraps(workload)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return workload(study(spark, sf_dir))

    return run


#: The workloads by name, on a folder's documents.
WORKLOADS = {f.__name__: _on_folder(f) for f in _OF_STUDY}
