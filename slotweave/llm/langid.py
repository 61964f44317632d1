"""Language identification by interpolated Kneser-Ney character models, one for each language.

A word (a run of letters, lower-cased, with a mark at either end) is a sequence of characters; its probability under
a language interpolates character n-grams of orders 1 to ORDER with modified continuation counts. The n-grams of all languages
stand in one sorted array of hashes per order, with a column for each language, and are found by binary search.
A text gets the language of the lowest cross-entropy per character. Its distance from what held-back labelled texts
show decides on rejection: junk in no learned language is far above.

Training takes at most SAMPLE labelled texts of each language, chosen by a hash; this bound is the one parameter that limits what is
learned from. Every text is scored whole, each word counted.

Edge cases: null text, or text without a letter (category L alone: number signs, fractions and marks are none), is ``und`` with score 0, and not rejected as junk but as without language; ties
go to the first language in order; no labelled text at all makes every text ``und``; extra columns are ignored; repeated rows
give equal rows; an empty table gives an empty result.
"""

from __future__ import annotations

import re
import sys
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ._words import STEP, U, mix

ORDER, DISCOUNT, SAMPLE = 4, 0.75, 600


def _numbers() -> str:
    """Ranges of the characters that are numbers, but neither decimal digits nor letters: number signs, fractions, superscripts."""
    odd = [i for i in range(sys.maxunicode + 1) if chr(i).isnumeric() and not chr(i).isalpha() and not chr(i).isdecimal()]
    starts = [odd[0], *[b for a, b in zip(odd, odd[1:], strict=False) if b != a + 1]]
    ends = [*[a for a, b in zip(odd, odd[1:], strict=False) if b != a + 1], odd[-1]]
    return "".join(f"{chr(a)}-{chr(b)}" for a, b in zip(starts, ends, strict=True))


#: Runs of letters alone.
LETTERS = re.compile(rf"[^\W\d_{_numbers()}]+")
CACHE = 200_000
EDGE = 1  # the code point that marks a word's ends
#: A text is rejected when its cross-entropy exceeds the held-back mean by this many of their deviations, and every held-back text's,
#: by so much that the excess over all its characters is EVIDENCE nats: a short text with a stray code in it stays. (Medians instead reject 2 % of
#: the check's documents, which this rule keeps; the price is that a mislabelled text among the held-back ones lets its like stay.)
FAR, EVIDENCE = 12.0, 100.0


def _characters(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of the marked words one after another, and each word's length with marks."""
    text = np.frombuffer("".join(f"\x01{w}\x01" for w in words).encode("utf-32-le", "surrogatepass"), np.uint32)
    return text, np.array([len(w) + 2 for w in words])


def _grams(text: np.ndarray, lengths: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """For n = 1..ORDER the hash of the n characters that end at each place, 0 if they'd begin before the word; places to score."""
    place = np.arange(len(text)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    out = []
    with np.errstate(over="ignore"):
        letters = mix(text.astype(U) + U(7))
        rolled = letters
        for n in range(1, ORDER + 1):
            if n > 1:
                before = np.zeros_like(rolled)
                before[1:] = out[-1][:-1]
                rolled = mix(before * STEP + letters + U(n))
            out.append(np.where(place >= n - 1, rolled, U(0)))
    return out, place > 0


@dataclass
class Models:
    languages: list[str]
    #: per order: sorted hashes; discounted shares [n, languages]
    grams: list[tuple[np.ndarray, np.ndarray]] = field(default_factory=list)
    #: per order: sorted context hashes; weight left for the lower order
    contexts: list[tuple[np.ndarray, np.ndarray]] = field(default_factory=list)
    alphabet: int = 1
    mean: float = 0.0
    spread: float = 1.0
    worst: float = 1e9

    def word_scores(self, words: list[str]) -> np.ndarray:
        """Natural-log probability of each word under each language."""
        text, lengths = _characters(words)
        grams, scored = _grams(text, lengths)
        p = np.full((len(text), len(self.languages)), 1.0 / self.alphabet)
        none = np.zeros(len(text), U)
        for n in range(ORDER):
            context = none if n == 0 else np.concatenate([[U(0)], grams[n - 1][:-1]])
            usable = grams[n] != 0
            share = _find(*self.grams[n], grams[n], 0.0)
            left = _find(*self.contexts[n], context, 1.0) if n else np.broadcast_to(self.contexts[0][1][0], p.shape)
            p = np.where(usable[:, None], share + left * p, p)
        logs = np.where(scored[:, None], np.log(p), 0.0)
        return np.add.reduceat(logs, np.cumsum(lengths) - lengths, axis=0)


def _find(keys: np.ndarray, values: np.ndarray, wanted: np.ndarray, missing: float) -> np.ndarray:
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return np.where((keys[at] == wanted)[:, None], values[at], missing)


def words_of(text: str | None) -> list[str]:
    return LETTERS.findall((text or "").lower())


def fit(texts: list[tuple[str, str]]) -> Models:
    """Models of (language, text) pairs; every fifth text of a language is held back to calibrate rejection."""
    languages = sorted({lang for lang, _ in texts})
    kept: list[Counter] = [Counter() for _ in languages]
    held: list[str] = []
    seen: Counter = Counter()
    for lang, text in texts:
        seen[lang] += 1
        if seen[lang] % 5 == 0:
            held.append(text)
        else:
            kept[languages.index(lang)].update(words_of(text))
    models = Models(languages)
    everywhere = [dict() for _ in range(ORDER)]
    left = [dict() for _ in range(ORDER)]
    alphabet: set[int] = {EDGE}
    for i, counted in enumerate(kept):
        if not counted:
            continue
        words = list(counted)
        text, lengths = _characters(words)
        alphabet.update(np.unique(text).tolist())
        grams, scored = _grams(text, lengths)
        weight = np.repeat(np.array([counted[w] for w in words], float), lengths)
        for n in range(ORDER):
            context = np.zeros(len(text), U) if n == 0 else np.concatenate([[U(0)], grams[n - 1][:-1]])
            ok = scored & (grams[n] != 0)
            if n == ORDER - 1:
                whole = ok
                key, at, count = _summed(grams[n][whole], weight[whole])
            else:
                # continuation: the distinct longer n-grams that end in this one; those at a word's start count by themselves
                longer = grams[n + 1]
                inner = np.flatnonzero(ok & (longer != 0))
                _, first = np.unique(longer[inner], return_index=True)
                starts = ok & (longer == 0)
                places = np.concatenate([inner[first], np.flatnonzero(starts)])
                amount = np.concatenate([np.ones(len(first)), weight[starts]])
                key, at, count = _summed(grams[n][places], amount)
                at = places[at]
            if n == ORDER - 1:
                at = np.flatnonzero(ok)[at]
            c_key, c_of = np.unique(context[at], return_inverse=True)
            total = np.bincount(c_of, count)
            kinds = np.bincount(c_of)
            cut = np.minimum(DISCOUNT, count)
            for k, s in zip(key.tolist(), ((count - cut) / total[c_of]).tolist(), strict=True):
                everywhere[n].setdefault(k, [0.0] * len(languages))[i] = s
            lost = np.bincount(c_of, cut) / total
            for k, g in zip(c_key.tolist(), lost.tolist(), strict=True):
                left[n].setdefault(k, [1.0] * len(languages))[i] = g
            del kinds
    models.alphabet = len(alphabet) + 1
    for n in range(ORDER):
        for table, into, empty in ((everywhere[n], models.grams, 0.0), (left[n], models.contexts, 1.0)):
            table = table or {0: [empty] * len(languages)}
            keys = np.array(sorted(table), U)
            into.append((keys, np.array([table[k] for k in keys.tolist()])))
    entropies = [min(s) for t in held if (s := cross_entropies(models, t)) is not None]
    if entropies:
        models.mean, models.spread, models.worst = float(np.mean(entropies)), float(max(np.std(entropies), 0.02)), float(max(entropies))
    return models


def _summed(keys: np.ndarray, amounts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    found, first, of = np.unique(keys, return_index=True, return_inverse=True)
    return found, first, np.bincount(of, amounts)


def cross_entropies(models: Models, text: str) -> np.ndarray | None:
    words = words_of(text)
    if not words:
        return None
    return -models.word_scores(words).sum(axis=0) / sum(len(w) + 1 for w in words)


class Scorer:
    def __init__(self, models: Models):
        self.models, self.row = models, {}
        self.table = np.zeros((1024, len(models.languages) + 1))

    def learn(self, words: set[str]) -> None:
        new = list(words)
        for start in range(0, len(new), 20_000):
            part = new[start : start + 20_000]
            scores = self.models.word_scores(part)
            base = len(self.row)
            while base + len(part) > len(self.table):
                self.table = np.concatenate([self.table, np.zeros_like(self.table)])
            self.table[base : base + len(part), :-1] = scores
            self.table[base : base + len(part), -1] = [len(w) + 1 for w in part]
            self.row.update(zip(part, range(base, base + len(part)), strict=True))

    def batch(self, texts: list[str | None]) -> list[tuple[str, float, float, bool]]:
        """(language, score, cross-entropy, accepted) of each text."""
        out = []
        for start in range(0, len(texts), 200):
            part = [words_of(t) for t in texts[start : start + 200]]
            new = {w for words in part for w in words if w not in self.row}
            if new and len(self.row) + len(new) > CACHE:
                self.row, new = {}, {w for words in part for w in words}
            if new:
                self.learn(new)
            for words in part:
                if not words:
                    out.append(("und", 0.0, None, False))
                    continue
                sums = self.table[np.fromiter(map(self.row.__getitem__, words), np.int64, len(words))].sum(axis=0)
                entropy = -sums[:-1] / sums[-1]
                best = int(entropy.argmin())
                sure = float(1 / np.exp(-(entropy - entropy[best]) * min(sums[-1], 40.0)).sum())
                m = self.models
                junk = (entropy[best] - max(m.worst, m.mean + FAR * m.spread)) * sums[-1] > EVIDENCE
                out.append((m.languages[best], min(1.0, sure), float(entropy[best]), not junk))
        return out


def sample_labelled(docs: DataFrame, may_learn: Column, bound: int, id_col: str, text_col: str, lang_col: str) -> list[tuple[str, str]]:
    """At most ``bound`` texts of each language: first thinned by a hash to about twice that, so what is ranked is bounded too."""
    rows = docs.filter(may_learn & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    counts = {r[0]: r[1] for r in rows.groupBy(F.col(lang_col).cast("string")).count().collect()}
    if not counts:
        return []
    share = F.create_map(*[x for k, n in counts.items() for x in (F.lit(k), F.lit(min(1.0, (2.0 * bound + 50) / n)))])
    lang, draw = F.col(lang_col).cast("string"), F.xxhash64(F.lit("langid"), F.col(id_col))
    thin = rows.filter(F.pmod(draw, F.lit(1_000_000)) < share[lang] * 1_000_000).select(lang.alias("lang"), F.col(text_col).cast("string").alias("text"), draw.alias("draw"))
    picked = thin.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy("draw", "text"))).filter(F.col("r") <= bound)
    return sorted((r.lang, r.text) for r in picked.collect())


def identify(docs: DataFrame, may_learn: Column | None = None, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", keep: list[str] | None = None) -> DataFrame:
    """A row per document: doc_id, lang_pred, score, cross_entropy, accepted (and the columns named in keep)."""
    spark = docs.sparkSession
    labelled = sample_labelled(docs, F.lit(True) if may_learn is None else may_learn, sample, id_col, text_col, lang_col)
    shared = spark.sparkContext.broadcast(fit(labelled) if labelled else None)
    passed = keep or [id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models = shared.value
        scorer = Scorer(models) if models else None
        for batch in batches:
            texts = batch.column(batch.num_columns - 1).to_pylist()
            got = scorer.batch(texts) if scorer else [("und", 0.0, None, False)] * len(texts)
            columns = [pa.array(c, t) for c, t in zip(zip(*got, strict=True), (pa.string(), pa.float64(), pa.float64(), pa.bool_()), strict=True)] if got else [pa.array([], t) for t in (pa.string(), pa.float64(), pa.float64(), pa.bool_())]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *columns], names=[*batch.schema.names[:-1], "lang_pred", "score", "cross_entropy", "accepted"])

    source = docs.select(*[F.col(c) for c in passed], F.col(text_col).cast("string").alias("__text"))
    schema = ", ".join([*[f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[:-1]], "lang_pred string, score double, cross_entropy double, accepted boolean"])
    return source.mapInArrow(run, schema)
