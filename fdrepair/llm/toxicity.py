"""Toxicity by noisy-channel deobfuscation.

A writer's intended letters pass a channel that swaps letters for look-alikes, repeats them and
puts signs or spaces between them. A token that may have passed it (look-alikes or signs inside,
a letter three times in a row, letters standing alone one after the other) is a lattice of intended
letters; Viterbi decoding under a character trigram model finds the likeliest reading. The restored
words are scored by log-odds of words and word beginnings in toxic and other training texts, and
a logistic curve over a text's strongest evidence gives the probability of label 1.

It is fitted on all labelled rows outside the held-out fold, with their whole texts: counts of letters and of features are made by Spark, each half of the rows is
measured by the odds of the other half, and the curve's Newton steps are sums over the measured rows. The driver gets the letters' model, the odds above the bar and such sums.
Every row is scored over its whole text.

Defined results: null and empty texts hold no evidence and get the score of no evidence; without labels of both
kinds every score is the share of label 1 (0.5 without rows); repeated rows are scored alike; extra columns are kept by ``score``.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_mod, dropped, freed, written
from .quality import _logistic

LEAST_TEXTS = 3  # toxic training texts that a feature occurs in
HELD_WORDS = 300_000
LEAST_ROWS = 4  # of either label
BAR = 1.0  # log-odds that make a feature evidence
# Letters that a sign may stand for.
LOOKS = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "€": "e", "(": "c"}
SWAP, REPEAT, SIGN, KEEP = math.log(0.05), math.log(0.05), math.log(0.02), math.log(1e-5)
FLOOR = math.log(1e-6)

_suspicious = re.compile(r"[^\W\d_][\d@$!|+€(*._\-~^#]+[^\W\d_]|[\d@$!|+€(][^\W\d_]|[^\W\d_][@$!|+€(\d]|([^\W\d_])\1\1").search
_apart = re.compile(r"(?<![^\s])[^\W_](?:[\s.*_\-]+[^\W_](?![^\W_])){2,}(?!\S)").finditer
_edges = re.compile(r"^[^\w@$!|+€(]+|[^\w@$!|+€(]+$").sub
_outer = re.compile(r"^\W+|\W+$").sub
_letter = re.compile(r"[^\W\d_]").match


def plain_words(text: str | None) -> list[str]:
    return [w for w in (_outer("", x) for x in (text or "").lower().split()) if w.isalpha()]


def grams(words: Counter[str]) -> Counter[str]:
    """Counts of three letters in a row, with blanks around each word."""
    three: Counter[str] = Counter()
    for w, n in words.items():
        padded = f"  {w} "
        for k in range(2, len(padded)):
            three[padded[k - 2 : k + 1]] += n
    return three


@dataclass
class Letters:
    """A character trigram model of words."""

    logs: dict[str, float] = field(default_factory=dict)

    @classmethod
    def of(cls, words: Counter[str]) -> Letters:
        return cls.of_grams(grams(words))

    @classmethod
    def of_grams(cls, three: Counter[str]) -> Letters:
        two: Counter[str] = Counter()
        for g, n in three.items():
            two[g[:2]] += n
        return cls({g: math.log(n / (two[g[:2]] + 1.0)) for g, n in three.items()})

    def read(self, token: str) -> str:
        """The likeliest intended word behind a token."""
        get, best = self.logs.get, {"  ": (0.0, "")}
        for c in token:
            letter = _letter(c) is not None
            ways = [(c, 0.0)] if letter else [(x, SWAP) for x in LOOKS.get(c, "")] + ([(c, KEEP)] if c.isdigit() else [("", SIGN)])
            after: dict[str, tuple[float, str]] = {}
            for state, (score, done) in best.items():
                options = ways + [("", REPEAT)] if state[1] == c or any(x == state[1] for x, _ in ways if x) else ways
                for x, cost in options:
                    total = score + cost + (get(state + x, FLOOR) if x else 0.0)
                    new = state[1] + x if x else state
                    if new not in after or total > after[new][0]:
                        after[new] = (total, done + x)
            best = after
        return max((s + get(state + " ", FLOOR), w) for state, (s, w) in best.items())[1]


def restored(token: str, letters: Letters) -> str:
    """A token without signs around it, decoded if it looks disguised."""
    token = token.lower()
    word = _edges("", token)
    if _suspicious(word):
        return letters.read(word)
    return _outer("", word)


def apart(text: str) -> list[str]:
    """Letters that stand alone in a row, put together; a run also without its first or last letter, which may be a word."""
    out = []
    for m in _apart(text):
        run = re.sub(r"[\s.*_\-]+", "", m[0])
        out += [run, run[1:], run[:-1]]
    return out


def features(word: str) -> list[str]:
    return ["=" + word, *(word[:k] for k in (4, 5, 6) if len(word) >= k)] if len(word) > 2 else []


@dataclass
class ToxicityModel:
    letters: Letters
    odds: dict[str, float]
    weights: tuple[float, ...]
    prior: float


class Scorer(dict):
    """Evidence of a token, remembered up to a bound."""

    def __init__(self, model: ToxicityModel) -> None:
        super().__init__()
        self.model = model

    def __missing__(self, token: str) -> float:
        get = self.model.odds.get
        value = max((get(f, 0.0) for f in features(restored(token, self.model.letters))), default=0.0)
        if len(self) >= HELD_WORDS:
            self.clear()
        if len(token) <= 64:
            self[token] = value
        return value

    def evidence(self, text: str | None) -> tuple[float, float]:
        text = text or ""
        tokens = text.split()
        values = [v for v in map(self.__getitem__, tokens + apart(text)) if v > 0]
        if not values:
            return 0.0, 0.0
        return max(values), math.log1p(sum(values))

    def probability(self, text: str | None) -> float:
        if not self.model.weights:
            return self.model.prior
        z = self.model.weights[0] + sum(a * b for a, b in zip(self.model.weights[1:], self.evidence(text)))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def _odds(toxic: list[list[str]], other: list[list[str]]) -> dict[str, float]:
    seen: Counter[str] = Counter()
    for words in toxic:
        seen.update({f for w in words for f in features(w)})
    seen = Counter({f: n for f, n in seen.items() if n >= LEAST_TEXTS})
    plain: Counter[str] = Counter()
    for words in other:
        plain.update({f for w in words for f in features(w)} & seen.keys())
    a, b = len(toxic) + 1.0, len(other) + 1.0
    scored = {f: math.log((n + 0.1) / a) - math.log((plain[f] + 0.5) / b) for f, n in seen.items()}
    return {f: v for f, v in scored.items() if v > BAR}


def fit_model(texts: list[str], labels: list[int]) -> ToxicityModel:
    rows = [(t or "", int(y)) for t, y in zip(texts, labels) if y is not None]
    prior = sum(y for _, y in rows) / len(rows) if rows else 0.5
    words: Counter[str] = Counter()
    for t, _ in rows:
        words.update(plain_words(t))
    letters = Letters.of(words)
    words.clear()
    cache: dict[str, str] = {}

    def read(text: str) -> list[str]:
        return [cache[x] if x in cache else cache.setdefault(x, restored(x, letters)) for x in set(text.split() + apart(text))]

    kinds = [[read(t) for t, y in rows if y == k] for k in (0, 1)]
    raw = [[t for t, y in rows if y == k] for k in (0, 1)]
    cache.clear()
    if min(map(len, kinds)) < LEAST_ROWS:
        return ToxicityModel(letters, {}, (), prior)
    x, y = [], []
    for half in (0, 1):  # each half is scored with odds of the other half
        model = ToxicityModel(letters, _odds(kinds[1][1 - half :: 2], kinds[0][1 - half :: 2]), (), prior)
        scorer = Scorer(model)
        for k in (0, 1):
            for t in raw[k][half::2]:
                x.append(scorer.evidence(t))
                y.append(k)
    w = _logistic(np.array(x), np.array(y, float))
    return ToxicityModel(letters, _odds(kinds[1], kinds[0]), tuple(map(float, w)), prior)


def _letters(rows: DataFrame) -> Letters:
    """The trigram model of all words of the rows' texts."""

    def of(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        three: Counter[str] = Counter()
        for part in parts:
            words: Counter[str] = Counter()
            for t in part["t"]:
                words.update(plain_words(t))
            three.update(grams(words))
            if len(three) >= HELD_WORDS:
                yield pd.DataFrame(list(three.items()), columns=["g", "n"])
                three.clear()
        yield pd.DataFrame(list(three.items()), columns=["g", "n"])

    counted = rows.select("t").mapInPandas(of, "g string, n long").groupBy("g").agg(F.sum("n").alias("n"))
    return Letters.of_grams(Counter({r.g: r.n for r in counted.collect()}))


def _texts_with(rows: DataFrame, letters: Letters) -> DataFrame:
    """f, n<label><half>: how many texts of either label and half hold each feature."""

    def of(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        read: dict[str, list[str]] = {}
        seen: Counter[tuple[str, int]] = Counter()

        def told() -> pd.DataFrame:
            return pd.DataFrame([(f, k, n) for (f, k), n in seen.items()], columns=["f", "k", "n"])

        for part in parts:
            for t, k in zip(part["t"], part["k"]):
                found: set[str] = set()
                for x in set((t or "").split() + apart(t or "")):
                    if x not in read:
                        if len(read) >= HELD_WORDS:
                            read.clear()
                        read[x] = features(restored(x, letters))
                    found.update(read[x])
                seen.update((f, k) for f in found)
            if len(seen) >= HELD_WORDS:
                yield told()
                seen.clear()
        yield told()

    kind = F.col("y") * 2 + F.col("half")
    each = rows.select("t", kind.cast("int").alias("k")).mapInPandas(of, "f string, k int, n long")
    return each.groupBy("f").agg(*[F.sum(F.when(F.col("k") == 2 * y + h, F.col("n")).otherwise(0)).alias(f"n{y}{h}") for y in (0, 1) for h in (0, 1)])


def _odds_of(texts: DataFrame, sizes: dict[tuple[int, int], int]) -> dict[str, dict[str, float]]:
    """Log-odds over the bar, as ``_odds`` gives them, by what they are of: either half ("0", "1") or both ("all")."""
    value = {}
    for name, halves in (("0", (0,)), ("1", (1,)), ("all", (0, 1))):
        toxic, plain = (sum(F.col(f"n{y}{h}") for h in halves) for y in (1, 0))
        a, b = (sum(sizes.get((y, h), 0) for h in halves) + 1.0 for y in (1, 0))
        value[name] = F.when(toxic >= LEAST_TEXTS, F.log((toxic + 0.1) / a) - F.log((plain + 0.5) / b))
    told = texts.select("f", *[F.when(v > BAR, v).alias(k) for k, v in value.items()]).where(" or ".join(f"`{k}` is not null" for k in value)).collect()
    return {k: {r.f: r[k] for r in told if r[k] is not None} for k in value}


def _curve(measured: DataFrame, ridge: float = 1e-3) -> tuple[float, ...]:
    """Newton steps for a logistic regression with an intercept, as ``_logistic`` takes them; measured: x1, x2, y, n (rows alike)."""
    x, w = [F.lit(1.0), F.col("x1"), F.col("x2")], np.zeros(3)
    for _ in range(50):
        z = sum(float(b) * a for a, b in zip(x, w))
        p = 1 / (1 + F.exp(-F.greatest(F.lit(-30.0), F.least(F.lit(30.0), z))))
        sums = [F.sum(F.col("n") * a * (F.col("y") - p)) for a in x] + [F.sum(F.col("n") * x[i] * x[j] * (p * (1 - p) + 1e-9)) for i in range(3) for j in range(3)]
        got = np.array(measured.agg(*[c.alias(f"s{k}") for k, c in enumerate(sums)]).first(), float)
        step = np.linalg.solve(got[3:].reshape(3, 3) + ridge * np.eye(3), got[:3] - ridge * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return tuple(round(float(v), 7) for v in w)  # sums depend on the order of rows beyond that


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", doc_id: str = "doc_id", text: str = "text", folds: int = 3, held_out: int = 1) -> ToxicityModel:
    """Fits on all labelled rows outside the held-out fold."""
    training = crc_mod(F.col("i"), folds) != held_out
    known = labels.select(labels[doc_id].alias("i"), labels[label].cast("int").alias("y")).where(training & F.col("y").isin(0, 1)).distinct()
    half = F.pmod(F.xxhash64("i"), F.lit(2)).cast("int").alias("half")
    rows = written(docs.select(docs[doc_id].alias("i"), docs[text].alias("t")).where(training).join(known.hint("merge"), "i").select("y", half, "t"))  # of any size: one way, so that it grows as small tables show
    freed(docs.sparkSession)
    sizes = {(r.y, r.half): r.n for r in rows.groupBy("y", "half").agg(F.count(F.lit(1)).alias("n")).collect()}
    of = lambda y: sum(n for (k, _), n in sizes.items() if k == y)
    prior = of(1) / (of(0) + of(1)) if sizes else 0.5
    letters = _letters(rows)
    if min(of(0), of(1)) < LEAST_ROWS:
        dropped(rows)
        return ToxicityModel(letters, {}, (), prior)
    odds = _odds_of(_texts_with(rows, letters), sizes)
    halves = [ToxicityModel(letters, odds[str(1 - h)], (), prior) for h in (0, 1)]  # each half is measured by the other half's odds

    @F.pandas_udf("x1 double, x2 double")
    def evidence(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
        scorers = [Scorer(m) for m in halves]
        for texts, which in parts:
            yield pd.DataFrame([scorers[h].evidence(t) for t, h in zip(texts, which)], columns=["x1", "x2"])

    measured = rows.select("y", evidence("t", "half").alias("e")).groupBy("e.x1", "e.x2", "y").agg(F.count(F.lit(1)).alias("n"))
    measured = written(measured)
    model = ToxicityModel(letters, odds["all"], _curve(measured), prior)
    dropped(rows, measured)
    return model


def score(df: DataFrame, model: ToxicityModel, text: str = "text", out: str = "score") -> DataFrame:
    """Adds the probability of label 1."""

    @F.pandas_udf("double")
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        scorer = Scorer(model)
        for part in parts:
            yield pd.Series([scorer.probability(t) for t in part], dtype=float)

    return df.withColumn(out, of.asNondeterministic()(df[text]))
