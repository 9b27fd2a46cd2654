"""Toxicity by a weighted lexicon, matched with an Aho-Corasick automaton over folded text.

Folding: lower case, compatibility forms, letters of other scripts that look Latin, and digits or signs that stand for
letters where they touch letters. A lexicon entry is a word or the head of words, with a weight: the log-odds of documents
that have it under toxic against clean labels. Documents are counted, not words, since the words of one text aren't
independent; and an entry needs a weight that is well above 0 even at the low end of its uncertainty, so that ordinary
words of a few copied texts are no entries. Where entries overlap in a word, the heaviest counts; matches inside an
exception phrase count nothing. The sum of weights, and the sum over the length, go through a logistic curve.

Learning: at most MAX_TRAIN labelled rows (those of least digest; a documented bound for a fitted classifier), out of
which the entries are counted on the executors; the curve is fitted to scores that each half of those rows gets from
the other half's lexicon, so that it has not seen its own words. Text only: no ids, languages, sources in the score.

Defined cases: null and empty texts score as a text without matches; labels with nulls or unknown ids are not used;
several labels of an id: the highest; without both labels among the learned rows the score is their share of toxic
(0 when there are none); repeated rows score alike; extra columns are kept by `reject` and not read.
"""

from __future__ import annotations

import math
import re
import unicodedata
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from copresence.ship import arrow_map

MAX_TRAIN = 12000
HEADS = (4, 5, 6)  # lengths of word heads that may be entries
LEAST = 3  # documents under toxic labels that an entry needs
COUNTED = 120_000  # entries that a task holds before it hands their counts on
LEAST_Z = 3.2  # log-odds over their standard error
LEAST_WEIGHT = 1.5  # log-odds less two standard errors
#: Phrases in which a word of the lexicon is meant otherwise.
EXCEPTIONS = ("clown fish", "clownfish", "trash can", "trash bin", "idiot proof", "idiot light", "pathetic fallacy", "oxymoron", "sore loser rule")

#: Letters of other scripts by the Latin letter that they resemble, and signs by the letter they replace.
LOOKALIKES = {
    "а": "a", "в": "b", "с": "c", "ԁ": "d", "е": "e", "ё": "e", "һ": "h", "і": "i", "ї": "i", "ј": "j", "к": "k", "ӏ": "l", "м": "m", "н": "h", "о": "o", "р": "p", "ԛ": "q", "г": "r", "ѕ": "s", "т": "t", "у": "y", "ѵ": "v", "ԝ": "w", "х": "x",
    "α": "a", "β": "b", "ϲ": "c", "ε": "e", "η": "n", "ι": "i", "κ": "k", "ν": "v", "ο": "o", "ρ": "p", "τ": "t", "υ": "u", "χ": "x", "ω": "w", "ı": "i", "ɑ": "a", "ɡ": "g", "ɩ": "i", "ʟ": "l", "ո": "n", "օ": "o", "ս": "u", "հ": "h",
}
SIGNS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "@": "a", "$": "s", "!": "i", "|": "l"}

_LOOKALIKE = str.maketrans(LOOKALIKES)
_SIGN = str.maketrans(SIGNS)
_OTHER = re.compile("[ıɑ-ʟͰ-֏]")
_INVISIBLE = re.compile("[­​-‏⁠﻿]")
_HAS_SIGN = re.compile(r"[013457@$!|8]")
_SIGN_RUN = re.compile(r"(?<=[^\W\d_])[0134578]+|[0134578]+(?=[^\W\d_])|(?<=[^\W\d_])[@$!|]+(?=[^\W\d_])")
_WORD = re.compile(r"[^\W\d_]+")


def fold(text: str) -> str:
    t = text.lower()
    if not t.isascii():
        t = _INVISIBLE.sub("", t)
        if not unicodedata.is_normalized("NFKC", t):
            t = unicodedata.normalize("NFKC", t).lower()
        if _OTHER.search(t):
            t = t.translate(_LOOKALIKE)
    return _SIGN_RUN.sub(lambda m: m[0].translate(_SIGN), t) if _HAS_SIGN.search(t) else t


class Lexicon:
    """Entries {text: (weight, whole word)} and exception phrases in one automaton."""

    def __init__(self, entries: dict[str, tuple[float, bool]], exceptions: Iterable[str] = EXCEPTIONS):
        self.auto = ahocorasick.Automaton()
        for text, (weight, whole) in entries.items():
            self.auto.add_word(text, (len(text), weight, whole))
        for phrase in exceptions:
            self.auto.add_word(fold(phrase), (len(phrase), None, True))
        self.any = len(self.auto) > 0
        if self.any:
            self.auto.make_automaton()

    def measure(self, text: str | None) -> tuple[float, int]:
        """Sum of matched weights, and length in letters."""
        t = fold(text or "")
        if not self.any:
            return 0.0, len(t)
        best: dict[int, float] = {}
        spared: list[tuple[int, int]] = []
        for end, (n, weight, whole) in self.auto.iter(t):
            start = end - n + 1
            if (start and t[start - 1].isalpha()) or (whole and end + 1 < len(t) and t[end + 1].isalpha()):
                continue
            if weight is None:
                spared.append((start, end))
            elif weight > best.get(start, 0):
                best[start] = weight
        return sum(w for at, w in sorted(best.items()) if not any(a <= at <= b for a, b in spared)), len(t)


@dataclass
class Model:
    entries: dict[str, tuple[float, bool]]
    curve: tuple[float, ...]  # constant, weight of the sum, weight of the density
    exceptions: tuple[str, ...] = EXCEPTIONS

    def score(self, total: float, letters: int) -> float:
        z = float(np.dot(self.curve, traits(total, letters)))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def traits(total: float, letters: int) -> tuple[float, float, float]:
    """1, the sum and the sum for a thousand letters (short texts count as 200 letters), both damped."""
    return 1.0, math.log1p(total), math.log1p(1000 * total / max(letters, 200))


def _pairs(sample: DataFrame) -> DataFrame:
    """sample(text, toxic, half) -> entry, whole and the toxic and clean documents with it by half; combined in each task
    before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: tuple[Counter, Counter] = Counter(), Counter()

        def flush() -> pa.RecordBatch:
            keys = list(dict.fromkeys([*seen[0], *seen[1]]))
            out = pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.bool_()), pa.array([k[2] for k in keys], pa.int32()), pa.array([seen[1][k] for k in keys], pa.int64()), pa.array([seen[0][k] for k in keys], pa.int64())], names=["entry", "whole", "half", "toxic", "clean"])
            for s in seen:
                s.clear()
            return out

        for b in batches:
            for text, toxic, half in zip(b.column(0), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                words = set(_WORD.findall(fold(text.as_py() or "")))
                seen[toxic].update((w, True, half) for w in words)
                seen[toxic].update({(w[:n], False, half) for n in HEADS for w in words if len(w) > n})
                if len(seen[0]) + len(seen[1]) > COUNTED:
                    yield flush()
        yield flush()

    parts = arrow_map(sample.select("text", "toxic", "half"), run, "entry string, whole boolean, half int, toxic long, clean long")
    one = lambda c, h: F.sum(F.when(F.col("half") == h, F.col(c)).otherwise(0)).alias(f"{c}{h}")
    return parts.groupBy("entry", "whole").agg(*[one(c, h) for c in ("toxic", "clean") for h in (0, 1)])


def _z(t: Column, c: Column, all_t: Column, all_c: Column) -> tuple[Column, Column]:
    weight = F.log((t + 0.5) / (all_t - t + 0.5)) - F.log((c + 0.5) / (all_c - c + 0.5))
    return weight, weight / F.sqrt(1 / (t + 0.5) + 1 / (c + 0.5))


def _entries(pairs: DataFrame, halves: tuple[int, ...], totals: dict[str, int]) -> dict[str, tuple[float, bool]]:
    """The lexicon that the given halves teach: words that MAX_TRAIN documents bound come to the driver, none left out."""
    t, c = (sum((F.col(f"{k}{h}") for h in halves), F.lit(0)) for k in ("toxic", "clean"))
    all_t, all_c = (F.lit(sum(totals[f"{k}{h}"] or 0 for h in halves)) for k in ("toxic", "clean"))
    weight, z = _z(t, c, all_t, all_c)
    found = pairs.filter(t >= LEAST).select("entry", "whole", weight.alias("weight"), z.alias("z")).filter((F.col("z") >= LEAST_Z) & (F.col("weight") * (1 - 2 / F.col("z")) >= LEAST_WEIGHT))
    rows = sorted(found.collect(), key=lambda r: (-r["z"], r["entry"], r["whole"]))
    out: dict[str, tuple[float, bool]] = {}
    for r in rows:
        if r["entry"] not in out or out[r["entry"]][1]:  # a head also covers the whole word
            out[r["entry"]] = (float(r["weight"]), bool(r["whole"]))
    return out


def _measured(rows: DataFrame, lexicons: list[dict[str, tuple[float, bool]]]) -> DataFrame:
    """rows(id, text, which) -> id, total, letters by lexicon number `which`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ready = [Lexicon(x) for x in lexicons]
        for b in batches:
            got = [ready[w.as_py()].measure(t.as_py()) for t, w in zip(b.column(1), b.column(2), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([g[0] for g in got], pa.float64()), pa.array([g[1] for g in got], pa.int64())], names=["toxic", "total", "letters"])

    return arrow_map(rows, run, "toxic int, total double, letters long")


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.05, rounds: int = 60) -> np.ndarray:
    w = np.zeros(x.shape[1])
    keep = np.full(x.shape[1], ridge)
    keep[0] = 1e-3
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (p - y) + keep * w
        hess = (x * (p * (1 - p))[:, None]).T @ x + np.diag(keep) + 1e-9 * np.eye(len(w))
        step = np.linalg.solve(hess, grad)
        w -= np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return w


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(True))


def learn(docs: DataFrame, labels: DataFrame, max_train: int = MAX_TRAIN) -> Model:
    """Fit on labelled rows that aren't held out. max_train bounds the labelled rows used, and so what is broadcast."""
    usable = labels.filter("doc_id IS NOT NULL AND toxic IS NOT NULL").filter(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    rank = F.md5(F.col("doc_id").cast("string"))
    chosen = usable.select("doc_id", F.least(F.greatest("toxic", F.lit(0)), F.lit(1)).alias("toxic"), F.pmod(F.crc32(F.concat(F.lit("half"), F.col("doc_id").cast("string")).cast("binary")), F.lit(2)).cast("int").alias("half")).orderBy(rank, "doc_id").limit(max_train)
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("text", "toxic", "half").persist()
    pairs = _pairs(sample).persist()
    totals = sample.agg(*[F.count_if((F.col("toxic") == int(k == "toxic")) & (F.col("half") == h)).alias(f"{k}{h}") for k in ("toxic", "clean") for h in (0, 1)]).first().asDict()
    full, one, two = (_entries(pairs, halves, totals) for halves in ((0, 1), (1,), (0,)))
    rows = _measured(sample.select("toxic", "text", "half"), [one, two]).collect()  # at most max_train rows of three numbers
    pairs.unpersist()
    sample.unpersist()
    y = np.array([r["toxic"] for r in rows], float)
    if len(set(y)) < 2:
        share = float(y.mean()) if len(y) else 0.0
        return Model({}, (math.log((share + 1e-9) / (1 - share + 1e-9)), 0.0, 0.0))
    x = np.array([traits(r["total"], r["letters"]) for r in rows])
    return Model(full, tuple(map(float, _logistic(x, y))))


def _scored(docs: DataFrame, model: Model, name: str) -> DataFrame:
    """docs with a column of scores, row by row."""
    kind = docs.select(F.col("*"), F.lit(0.0).alias(name)).schema
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon = Lexicon(model.entries, model.exceptions)
        for b in batches:
            got = [model.score(*lexicon.measure(t.as_py())) for t in b.column(at)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(got, pa.float64())], names=[*b.schema.names, name])

    return arrow_map(docs, run, kind)


def score(docs: DataFrame, labels: DataFrame, max_train: int = MAX_TRAIN) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted."""
    scored = _scored(docs.select("doc_id", "text"), learn(docs, labels, max_train), "score")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))


def reject(docs: DataFrame, labels: DataFrame, max_train: int = MAX_TRAIN, limit: float = 0.5) -> DataFrame:
    """docs without those that score `limit` or more."""
    return _scored(docs, learn(docs, labels, max_train), "__toxicity").filter(F.col("__toxicity") < limit).drop("__toxicity")
