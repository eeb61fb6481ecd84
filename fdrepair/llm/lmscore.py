"""Cross-entropy difference: how much more a text is like the target than like the background.

Two bigram models of the same form share one vocabulary, all words of the corpus: the target's is counted over texts labelled 1, the
background's over all texts. P(w | u) mixes the share of w after u with the add-one share of w. A text's score is
the mean over its words of background loss minus target loss, in bits: positive for texts that are more like the target.

Counts are kept of every word and pair of words, and of the texts that a word ends, so the models grow with the corpus and no worker holds one:

1. documents are dealt to chunks of about ``CHUNK`` characters by a hash of their id; each chunk counts its own words and pairs;
2. a chunk's counts are sorted by key (a 64-bit hash) and cut into key ranges; each range travels as one block of bytes;
3. each range adds up the blocks of all chunks and answers each with the corpus-wide counts, in the order asked;
4. each chunk scores its documents with the answers.

So a frequent word or pair is one entry of each chunk that holds it, not one row of each document, and a worker holds a
chunk or a key range at a time. Number of chunks and of ranges follow the size of the input.

Defined results: null and empty texts have no words, losses and score of 0; repeated rows count and are scored as often as
they occur; an empty target leaves its model uniform; rows with a null id are never labelled; extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import dropped, freed, mix64, written

MIX = 0.7  # weight of the bigram share
CHUNK = 8_000_000  # characters of a chunk's texts, about; also the measure of a key range
LEAST_CHUNKS = 8
PAIR, WORD, BEGIN = 0, 1, 2
START = 0x5851F42D4C957F2D


def words_of(text: str | None) -> list[bytes]:
    return (text or "").lower().encode("utf-8", "replace").split()


class Numbers(dict):
    """Numbers of words in the order in which they come."""

    def __missing__(self, word: bytes) -> int:
        self[word] = n = len(self)
        return n


class Chunk:
    """The words of some texts, and the keys of all words and pairs in them, in order.

    keys and counts are aligned; the rows of counts are how often it occurs and how many texts it ends, in these texts and then in those that
    are target texts. A word is a context as often as it occurs and ends no text; the start of a text counts as a word that begins it.
    """

    def __init__(self, texts, target) -> None:
        numbers, ids, lengths = Numbers(), [], []
        for t in texts:
            words = words_of(t)
            ids.append(np.fromiter(map(numbers.__getitem__, words), np.int64, len(words)))
            lengths.append(len(words))
        self.lengths = np.array(lengths, np.int64)
        self.ids = np.concatenate([*ids, np.empty(0, np.int64)])
        size = len(numbers)
        first = (np.cumsum(self.lengths) - self.lengths)[self.lengths > 0]
        self.before = np.concatenate(([size], self.ids[:-1])) if len(self.ids) else self.ids.copy()
        self.before[first] = size  # the start of a text
        weight = np.repeat(np.asarray(target, float), self.lengths)
        hashes = np.fromiter((xxhash.xxh64_intdigest(w) for w in numbers), np.uint64, size)
        hashes = np.append(hashes, np.uint64(START))
        pairs, self.pair = np.unique(self.before * (size + 1) + self.ids, return_inverse=True)
        u, w = np.divmod(pairs, size + 1)
        made = (mix64(hashes[u] * np.uint64(0x9E3779B97F4A7C15) + mix64(hashes[w])), mix64(hashes[:size]), mix64(hashes[size:]))
        keys = np.concatenate([k & ~np.uint64(3) | np.uint64(kind) for kind, k in enumerate(made)])
        last = (np.cumsum(self.lengths) - 1)[self.lengths > 0]
        rows, none = [], np.zeros(len(pairs))
        for mass in (np.ones(len(self.ids)), weight):
            begun = [mass[first].sum()]
            rows.append(np.concatenate([np.bincount(self.pair, mass, len(pairs)), np.bincount(self.ids, mass, size), begun]))
            rows.append(np.concatenate([none, np.bincount(self.ids[last], mass[last], size), [0.0]]))
        order = np.argsort(keys, kind="stable")
        self.place = np.empty(len(keys), np.int64)  # where a pair's or word's entry stands in the order of keys
        self.place[order] = np.arange(len(keys))
        self.sizes = (len(pairs), size)
        self.keys, self.counts = keys[order], np.stack(rows)[:, order].astype(np.uint32)

    def losses(self, counts: np.ndarray, ends: np.ndarray, words: float, vocabulary: int) -> np.ndarray:
        """Bits of each word by corpus-wide counts, in the order of keys."""
        n, size = self.sizes
        pair, word = counts[self.place[:n]].astype(float), counts[self.place[n : n + size]].astype(float)
        context = (counts[self.place[n:]].astype(float) - ends[self.place[n:]])[self.before]
        after = np.divide(pair[self.pair], context, out=np.zeros(len(self.ids)), where=context > 0)
        mix = np.where(context > 0, MIX, 0.0)
        return -np.log2(mix * after + (1 - mix) * (word[self.ids] + 1) / (words + vocabulary + 1))

    def means(self, values: np.ndarray) -> np.ndarray:
        """Of each text, 0 for one without words."""
        out, full = np.zeros(len(self.lengths)), self.lengths > 0
        if full.any():
            out[full] = np.add.reduceat(values, (np.cumsum(self.lengths) - self.lengths)[full]) / self.lengths[full]
        return out


def ranges(keys: np.ndarray, number: int) -> Iterator[tuple[int, int, int]]:
    """(range, from, to) of sorted keys; empty ranges are left out."""
    at = ((keys >> np.uint64(32)) * np.uint64(number) >> np.uint64(32)).astype(np.int64)
    starts = np.flatnonzero(np.diff(at, prepend=-1))
    for a, b in zip(starts.tolist(), [*starts[1:].tolist(), len(keys)]):
        yield int(at[a]), a, b


def packed(*arrays: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(b"".join(a.tobytes() for a in arrays))


def steps(keys: np.ndarray) -> np.ndarray:
    """Sorted keys as the differences between them, byte by byte of all: the upper ones are mostly 0 and compress."""
    return np.diff(keys, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T.copy()


def climbed(block: bytes, n: int) -> np.ndarray:
    """The keys back."""
    return np.cumsum(np.frombuffer(block, np.uint8, 8 * n).reshape(8, n).T.copy().view(np.uint64).ravel(), dtype=np.uint64)


def opened(block: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(block)


def dealt(docs: DataFrame, number: int) -> DataFrame:
    """doc_id (as text), text, chunk."""
    by = F.when(F.col("doc_id").isNull(), F.xxhash64("text")).otherwise(F.xxhash64("doc_id"))
    return docs.select(F.col("doc_id").cast("string"), "text", F.pmod(by, F.lit(number)).cast("int").alias("chunk"))


def asked(docs: DataFrame, target: DataFrame, number: int) -> DataFrame:
    """range, chunk, n, block: the counts of each chunk by key range. docs: doc_id, text; target: doc_id of its texts."""
    texts = dealt(docs, number).withColumn("marks", F.lit(False))
    marks = dealt(target.select("doc_id", F.lit(None).cast("string").alias("text")), number).withColumn("marks", F.lit(True))

    def count(rows: pd.DataFrame) -> pd.DataFrame:
        marks = rows["marks"].to_numpy(bool)
        wanted = rows["doc_id"].isin(rows["doc_id"][marks].dropna())
        own = Chunk(rows["text"][~marks], wanted[~marks])
        chunk = int(rows["chunk"].iloc[0])
        out = [(k, chunk, b - a, packed(steps(own.keys[a:b]), own.counts[:, a:b])) for k, a, b in ranges(own.keys, number)]
        return pd.DataFrame(out, columns=["range", "chunk", "n", "block"])

    return texts.unionByName(marks).groupBy("chunk").applyInPandas(count, "range int, chunk int, n int, block binary")


def answered(blocks: DataFrame) -> DataFrame:
    """chunk, range, n, block: corpus-wide counts in the order asked; and, without a chunk, the words, target_words and different words of each range."""

    def add(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("chunk")
        parts = [opened(b) for b in rows["block"]]
        sizes = rows["n"].to_numpy()
        keys = np.concatenate([climbed(p, n) for p, n in zip(parts, sizes)])
        counts = np.concatenate([np.frombuffer(p, np.uint32, 4 * n, 8 * n).reshape(4, n) for p, n in zip(parts, sizes)], axis=1)
        every, place = np.unique(keys, return_inverse=True)
        both = np.stack([np.bincount(place, c, minlength=len(every)) for c in counts.astype(float)])
        words = (every & np.uint64(3)) == WORD
        found = both[:, place].astype(np.uint64)
        k, out, at = int(rows["range"].iloc[0]), [], 0
        for chunk, n in zip(rows["chunk"], sizes):
            out.append((int(chunk), k, int(n), packed(found[:, at : at + n]), 0.0, 0.0, 0.0))
            at += n
        out.append((None, k, 0, b"", *both[::2, words].sum(axis=1), float(words.sum())))
        return pd.DataFrame(out, columns=["chunk", "range", "n", "block", "words", "target_words", "different"]).astype({"chunk": "Int32"})

    return blocks.groupBy("range").applyInPandas(add, "chunk int, range int, n int, block binary, words double, target_words double, different double")


_SCORES = "doc_id string, n_words long, target_bits double, background_bits double, score double"


def scored(docs: DataFrame, answers: DataFrame, number: int, totals: tuple[float, float, float]) -> DataFrame:
    """doc_id, n_words, target_bits, background_bits, score."""
    all_words, target_words, vocabulary = totals

    def score(rows: pd.DataFrame, told: pd.DataFrame) -> pd.DataFrame:
        own = Chunk(rows["text"], np.zeros(len(rows)))
        if len(own.keys) and len(told):
            parts = [np.frombuffer(opened(b), np.uint64).reshape(4, n) for b, n in told.sort_values("range")[["block", "n"]].itertuples(False)]
            every = np.concatenate(parts, axis=1)
        else:
            every = np.zeros((4, len(own.keys)), np.uint64)
        a, b = own.means(own.losses(*every[2:], target_words, vocabulary)).round(6), own.means(own.losses(*every[:2], all_words, vocabulary)).round(6)
        return pd.DataFrame({"doc_id": rows["doc_id"], "n_words": own.lengths, "target_bits": a, "background_bits": b, "score": (b - a).round(6)})

    found = dealt(docs, number).groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInPandas(score, _SCORES)
    return found.withColumn("doc_id", F.col("doc_id").cast(docs.schema["doc_id"].dataType))


def cross_entropy_difference(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", label: str = "quality", value: int = 1) -> DataFrame:
    """doc_id with n_words, target_bits, background_bits and score, for every row; the target is what ``labels`` gives the value."""
    slim = docs.select(docs[doc_id].alias("doc_id"), docs[text].alias("text"))
    target = labels.where(labels[label] == value).select(labels[doc_id].cast(slim.schema["doc_id"].dataType).alias("doc_id")).where("doc_id is not null").distinct()
    size = slim.agg(F.sum(F.length("text")).alias("n")).first().n or 0
    number = max(LEAST_CHUNKS, -(-size // CHUNK))
    blocks = written(asked(slim, target, number))
    freed(docs.sparkSession)
    answers = written(answered(blocks))
    dropped(blocks)
    freed(docs.sparkSession)
    totals = answers.where("chunk is null").agg(*[F.coalesce(F.sum(c), F.lit(0.0)) for c in ("words", "target_words", "different")]).first()
    return scored(slim, answers.where("chunk is not null").select("chunk", "range", "n", "block"), number, tuple(totals))
