"""Quality classifier by compression.

Two zstandard dictionaries are made of labelled texts, one of good and one of bad ones. A text is cut
in blocks and each block is compressed on its own with either dictionary and with none; the two
sizes' difference over the plain size says which kind it is closer to, whatever the text's length.
A logistic curve fitted on the training rows (two-fold, so that no text is measured by a dictionary
that holds it) turns that figure into the probability of label 1.

Only fitting is bounded: at most ``FIT_ROWS`` labelled rows are used, those whose id hashes lowest, each with its whole
text. Every row is scored over its whole text.

Defined results: null and empty texts have no block and get the share of label 1 in the training
rows; without usable labels of both kinds every score is that share (0.5 if there are none). Repeated rows are
scored alike. Extra columns are kept by ``score``; a column named as the output is replaced.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_mod

FIT_ROWS = 6000  # labelled rows at most that the classifier is fitted on
PIECE = 64  # bytes in a row that a dictionary takes of a text at least
BLOCK = 2048  # bytes compressed at once
DICTIONARY = 512 * 1024
LEVEL = 6


@dataclass
class CompressionModel:
    good: bytes
    bad: bytes
    bias: float
    slopes: tuple[float, ...]
    prior: float


def _dictionary(texts: list[str]) -> bytes:
    """Raw content of at most ``DICTIONARY`` bytes: pieces of every text, spread evenly over it, each text with the same share."""
    share = max(PIECE, DICTIONARY // max(1, len(texts)))
    return b"".join(part for t in texts for part in _spread(t.encode("utf-8", "replace"), share))[-DICTIONARY:]


def _spread(data: bytes, share: int) -> list[bytes]:
    if len(data) <= share:
        return [data]
    number = max(1, share // PIECE)
    return [data[at : at + share // number] for at in (k * (len(data) - share // number) // max(1, number - 1) for k in range(number))]


class Sizer:
    """Compressed sizes of a text by each dictionary."""

    def __init__(self, good: bytes, bad: bytes) -> None:
        raw = [zstandard.ZstdCompressionDict(x, dict_type=zstandard.DICT_TYPE_RAWCONTENT) for x in (good, bad)]
        for d in raw:
            d.precompute_compress(level=LEVEL)
        options = {"level": LEVEL, "write_content_size": False, "write_checksum": False, "write_dict_id": False}
        self.tools = [zstandard.ZstdCompressor(dict_data=d, **options) for d in raw] + [zstandard.ZstdCompressor(**options)]

    def features(self, text: str | None) -> tuple[float, float, float] | None:
        data = (text or "").encode("utf-8", "replace")
        if not data:
            return None
        blocks = [data[i : i + BLOCK] for i in range(0, len(data), BLOCK)]
        good, bad, plain = (sum(len(tool.compress(b)) for b in blocks) for tool in self.tools)
        return (bad - good) / plain, good / len(data), plain / len(data)


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3) -> np.ndarray:
    """Newton steps for a logistic regression with an intercept."""
    x = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(x.shape[1])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (p * (1 - p) + 1e-9)[:, None]).T @ x + ridge * np.eye(len(w))
        step = np.linalg.solve(h, x.T @ (y - p) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def fit_model(texts: list[str], labels: list[int]) -> CompressionModel:
    """Dictionaries and calibration from labelled texts, in the order given."""
    rows = [(t, int(y)) for t, y in zip(texts, labels) if t and y is not None]
    prior = sum(y for _, y in rows) / len(rows) if rows else 0.5
    kinds = [[t for t, y in rows if y == k] for k in (0, 1)]
    if min(map(len, kinds)) < 2:
        return CompressionModel(b"", b"", 0.0, (), prior)
    x, y = [], []
    for fold in (0, 1):  # each half is measured by the other half's dictionaries
        sizer = Sizer(*(_dictionary(kinds[k][1 - fold :: 2]) for k in (1, 0)))
        for k in (0, 1):
            for t in kinds[k][fold::2]:
                x.append(sizer.features(t))
                y.append(k)
    w = _logistic(np.array(x), np.array(y, float))
    return CompressionModel(_dictionary(kinds[1]), _dictionary(kinds[0]), float(w[0]), tuple(map(float, w[1:])), prior)


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", doc_id: str = "doc_id", text: str = "text", folds: int = 5, held_out: int = 0) -> CompressionModel:
    """Fits on labelled rows outside the held-out fold, at most ``FIT_ROWS`` of them, half of either label where there are enough."""
    known = labels.select(labels[doc_id].alias("i"), labels[label].cast("int").alias("y")).where((crc_mod(F.col("i"), folds) != held_out) & F.col("y").isin(0, 1))
    order = [F.xxhash64("i"), "i"]
    parts = [known.where(F.col("y") == k).dropDuplicates(["i"]).orderBy(*order).limit(FIT_ROWS // 2) for k in (0, 1)]
    chosen = parts[0].unionByName(parts[1])
    rows = docs.select(docs[doc_id].alias("i"), docs[text].alias("t")).join(F.broadcast(chosen), "i").select("i", "y", "t").collect()
    rows.sort(key=lambda r: (hash_order(r.i), r.i, r.t or ""))
    return fit_model([r.t for r in rows], [r.y for r in rows])


def hash_order(i: int) -> int:
    return (int(i) * 0x9E3779B97F4A7C15) & ((1 << 64) - 1)


def score(df: DataFrame, model: CompressionModel, text: str = "text", out: str = "score") -> DataFrame:
    """Adds the probability of label 1."""

    @F.pandas_udf("double")
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        sizer = Sizer(model.good, model.bad) if model.slopes else None
        for part in parts:
            yield pd.Series([_probability(model, sizer.features(t) if sizer else None) for t in part], dtype=float)

    return df.withColumn(out, of.asNondeterministic()(df[text]))


def _probability(model: CompressionModel, x: tuple[float, ...] | None) -> float:
    if x is None:
        return model.prior
    z = model.bias + sum(a * b for a, b in zip(model.slopes, x))
    return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))
