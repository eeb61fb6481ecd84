"""Removal of repeated passages with suffix automata of reference shards.

``against`` takes a reference table: it is cut into shards of at most ``SHARD_WORDS`` words, a suffix automaton of
each is broadcast, documents stream past it for their matching statistics (how long a run that ends at
each word also occurs in the shard), and the maximal spans at or above the threshold go.

``repeats`` makes the corpus its own reference: a window of ``WINDOW`` words goes where its word sequence starts earlier
(smaller id, or the same document further left). Sending every document past every shard would be quadratic, so
shards are made of what can match:

1. every window is named by the smallest hash among its runs of ``RUN`` words (equal windows have equal
   names at equal places); consecutive windows of one name are a segment of at most 2 * WINDOW - RUN words, kept with a hash of its words;
2. segments meet by name and are put in order; one with the same words as an earlier one is repeated altogether,
   and names whose segments are all the same need no more. Names with more than ``SPLIT`` segments and more than one in ``HOT`` of all segments (so
   ``HOT`` names at most) are first treated in parts, and then over the parts' first segments;
3. the different segments of a name are a shard: each streams past the automaton of those before it, windows whose matching
   statistic reaches WINDOW are repeated, and the automaton is extended by the segment. A name with more than ``SHARD`` different segments is resolved by
   counting its windows instead, in partial sums, so that no task holds an unbounded shard.

Texts are moved twice: those with different segments of a repeated name for step 3, and all when the ranges come back to them.
Each step is written and the files of the one before it are deleted, so disk holds one step at a time.

Defined results: null and empty texts have no words; texts of fewer than WINDOW words stay; rows with the same id are
taken for copies of one document and none of them is earlier than the other; rows with a null id stay whole and repeat nothing; extra columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from numpy.lib.stride_tricks import sliding_window_view
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WordHashes, dropped, freed, mix64, rolled, written

WINDOW, RUN = 20, 5
SPLIT = 100_000
HOT = 10_000
COARSE = 1 << 16  # groups of names that are counted to find the hot ones
SHARD = 5_000
SHARD_WORDS = 200_000
SHARDS_AT_ONCE = 8


def words_of(text: str | None) -> list[bytes]:
    """Words between the ASCII white space characters."""
    return (text or "").encode("utf-8", "surrogatepass").split()


class SuffixAutomaton:
    """An automaton of all runs of the sequences added so far."""

    def __init__(self) -> None:
        self.next: list[dict] = [{}]
        self.link, self.length = [-1], [0]

    def _clone(self, p: int, q: int, w) -> int:
        """Splits state q where it is reached from p by w over a shorter path."""
        copy = len(self.next)
        self.next.append(self.next[q].copy())
        self.link.append(self.link[q])
        self.length.append(self.length[p] + 1)
        while p >= 0 and self.next[p].get(w) == q:
            self.next[p][w] = copy
            p = self.link[p]
        self.link[q] = copy
        return copy

    def add(self, words) -> None:
        """Adds a sequence; runs don't cross from one sequence to another."""
        last = 0
        for w in words:
            p, q = last, self.next[last].get(w)
            if q is not None:
                last = q if self.length[q] == self.length[p] + 1 else self._clone(p, q, w)
                continue
            new = len(self.next)
            self.next.append({})
            self.link.append(0)
            self.length.append(self.length[p] + 1)
            while p >= 0 and w not in self.next[p]:
                self.next[p][w] = new
                p = self.link[p]
            if p >= 0:
                q = self.next[p][w]
                self.link[new] = q if self.length[q] == self.length[p] + 1 else self._clone(p, q, w)
            last = new

    def statistics(self, words) -> list[int]:
        """For each word, the length of the longest run ending there that occurs in an added sequence."""
        out, state, n = [], 0, 0
        follow, link, length = self.next, self.link, self.length
        for w in words:
            while state and w not in follow[state]:
                state = link[state]
                n = length[state]
            if w in follow[state]:
                state, n = follow[state][w], n + 1
            out.append(n)
        return out


def spans(statistics: list[int], least: int) -> list[tuple[int, int]]:
    """Merged word spans that are covered by runs of at least ``least`` words."""
    out: list[tuple[int, int]] = []
    for k, n in enumerate(statistics):
        if n >= least:
            a, b = k + 1 - n, k + 1
            while out and out[-1][1] >= a:
                a = min(a, out.pop()[0])
            out.append((a, b))
    return out


def segments(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(name, first window, behind the last window) of each segment of a sequence of word hashes."""
    if len(ids) < WINDOW:
        return np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64)
    runs, width = rolled(ids, RUN), WINDOW - RUN + 1
    view = sliding_window_view(runs, width)[:, ::-1]
    place = np.arange(len(view)) + width - 1 - view.argmin(axis=1)
    first = np.flatnonzero(np.concatenate(([True], place[1:] != place[:-1])))
    return runs[place[first]], first, np.append(first[1:], len(view))


_ODD = 0x9E3779B97F4A7C15


class RunHashes:
    """64-bit hashes of runs of any length of a sequence, from prefix sums with an invertible base."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def __call__(self, ids: np.ndarray, first: np.ndarray, behind: np.ndarray) -> np.ndarray:
        n = len(ids) + 1
        if len(self.up) < n:
            powers = lambda x: np.concatenate((np.ones(1, np.uint64), np.cumprod(np.full(2 * n, x, np.uint64))))
            self.up, self.down = powers(_ODD), powers(pow(_ODD, -1, 1 << 64))
        sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(mix64(ids) * self.down[: len(ids)])))
        return mix64((sums[behind] - sums[first]) * self.up[first] + (behind - first).astype(np.uint64))


def listed(docs: DataFrame) -> DataFrame:
    """name, doc_id, first, behind, words_hash of every segment; docs: doc_id, text."""

    def of(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        hashes, runs = WordHashes(), RunHashes()
        for frame in frames:
            out = []
            for i, t in zip(frame["doc_id"], frame["text"]):
                ids = hashes.array(words_of(t))
                name, first, behind = segments(ids)
                out.append((name.view(np.int64), np.full(len(name), i), first, behind, runs(ids, first, behind - 1 + WINDOW).view(np.int64)))
            if out:
                yield pd.DataFrame(dict(zip(("name", "doc_id", "first", "behind", "words_hash"), map(np.concatenate, zip(*out)))))

    return docs.select("doc_id", "text").mapInPandas(of, "name long, doc_id long, first int, behind int, words_hash long")


def hot_names(rows: DataFrame) -> DataFrame:
    """name, parts of the names that are treated in parts, at most ``HOT`` of them."""
    size = F.greatest(F.lit(SPLIT), F.floor(F.sum("k").over(Window.partitionBy()) / HOT))  # over one row for each group of names
    group = F.pmod("name", F.lit(COARSE))
    heavy = rows.groupBy(group.alias("g")).agg(F.count(F.lit(1)).alias("k")).withColumn("size", size).where("k > size").select("g", "size")
    found = rows.select("name").join(F.broadcast(heavy), group == F.col("g")).groupBy("name", "size").agg(F.count(F.lit(1)).alias("k"))
    return found.where("k > size").select("name", F.ceil(F.col("k") / F.col("size")).alias("parts"))


def resolved(rows: DataFrame, hot: DataFrame) -> DataFrame:
    """kind (0 repeated, 1 first of its words), name, doc_id, first, behind, of the segments of repeated names in the order of documents.

    First segments are told only of names in parts and of names with several of them.
    """
    place = F.struct("doc_id", "first")
    same = Window.partitionBy("name", "part", "words_hash")
    name = Window.partitionBy("name", "part")
    dealt = rows.join(F.broadcast(hot), "name", "left").withColumn("part", F.coalesce(F.pmod("doc_id", "parts"), F.lit(0)).cast("int"))
    seen = dealt.repartition("name", "part").withColumn("least", F.min(place).over(same)).withColumns({"low": F.min("words_hash").over(name), "high": F.max("words_hash").over(name)})
    told = seen.withColumn("kind", F.when(place > F.col("least"), 0).when(F.col("parts").isNotNull() | (F.col("low") != F.col("high")), 1))
    return told.where("kind is not null").select("kind", "name", "doc_id", "first", "behind")


_RANGE = "doc_id long, start int, stop int"


def matched(shards: DataFrame) -> DataFrame:
    """doc_id, start, stop: repeated words of the segments of small shards; shards: name, doc_id, first, words."""

    def of(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        name, automaton, whole = None, None, {}
        for frame in frames:
            out = []
            for n, i, first, text in frame[["name", "doc_id", "first", "words"]].itertuples(False):
                if n != name:
                    name, automaton, whole = n, SuffixAutomaton(), {}
                if text in whole:
                    if whole[text] != (i, first):
                        out.append((i, first, first + text.count(" ") + 1))
                    continue
                whole[text] = (i, first)
                words = text.split(" ")
                out += [(i, first + a, first + b) for a, b in spans(automaton.statistics(words), WINDOW)]
                automaton.add(words)
            yield pd.DataFrame(out, columns=["doc_id", "start", "stop"])

    ordered = shards.repartition("name").sortWithinPartitions("name", "doc_id", "first")
    return ordered.select("name", "doc_id", "first", "words").mapInPandas(of, _RANGE)


def counted(shards: DataFrame) -> DataFrame:
    """The same of large shards, by the first place of each window's words."""
    words = F.split("words", " ", -1)
    each = shards.withColumn("w", words).select("doc_id", "first", "w", F.explode(F.sequence(F.lit(0), F.size("w") - WINDOW)).alias("k"))
    window = each.select("doc_id", (F.col("first") + F.col("k")).alias("start"), F.sha2(F.array_join(F.slice("w", F.col("k") + 1, WINDOW), " ").cast("binary"), 256).alias("h"))
    first = window.groupBy("h").agg(F.min(F.struct("doc_id", "start")).alias("least"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    met = window.join(first, "h").where(F.struct("doc_id", "start") > F.col("least"))
    return met.select("doc_id", "start", (F.col("start") + WINDOW).alias("stop"))


def repeated_ranges(docs: DataFrame) -> DataFrame:
    """doc_id, ranges (start, stop in words): what is repeated in each document; docs: doc_id, text."""
    known = docs.where("doc_id is not null and text is not null")
    rows = written(listed(known))
    hot = written(hot_names(rows))
    found = written(resolved(rows, hot))
    dropped(rows, hot)
    freed(docs.sparkSession)
    same = found.where("kind = 0").select("doc_id", F.col("first").alias("start"), (F.col("behind") - 1 + WINDOW).alias("stop"))
    firsts = found.where("kind = 1")
    sizes = firsts.groupBy("name").agg(F.count(F.lit(1)).alias("n"))
    asked = firsts.join(sizes, "name").groupBy("doc_id").agg(F.collect_list(F.struct("name", "first", "behind", "n")).alias("asked"))

    @F.pandas_udf("array<struct<name:long,first:int,n:long,words:string>>")
    def content(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for texts, asked in parts:
            out = []
            for t, rows in zip(texts, asked):
                words = words_of(t)
                out.append([{"name": x["name"], "first": x["first"], "n": x["n"], "words": b" ".join(words[x["first"] : x["behind"] - 1 + WINDOW]).decode("utf-8", "surrogatepass")} for x in rows if x["behind"] - 1 + WINDOW <= len(words)])
            yield pd.Series(out)

    shards = known.join(asked, "doc_id").select("doc_id", F.inline(content("text", "asked")))
    small, large = matched(shards.where(F.col("n") <= SHARD)), counted(shards.where(F.col("n") > SHARD))
    out = written(same.unionByName(small).unionByName(large).groupBy("doc_id").agg(F.collect_list(F.struct("start", "stop")).alias("ranges")))
    dropped(found)
    freed(docs.sparkSession)
    return out


def kept_words(words: list[bytes], ranges) -> list[bytes]:
    if ranges is None or not len(ranges):
        return words
    gone = np.zeros(len(words) + 1, np.int64)
    for r in ranges:
        gone[min(r["start"], len(words))] += 1
        gone[min(r["stop"], len(words))] -= 1
    keep = np.cumsum(gone)[:-1] == 0
    return [w for w, k in zip(words, keep) if k]


def repeats(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, text, ranges: every row, with the word ranges to remove (null: none)."""
    slim = docs.select(docs[doc_id].alias("doc_id"), docs[text].alias("text"))
    return slim.join(repeated_ranges(slim), "doc_id", "left")


def digests(rows: DataFrame) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of what ``repeats`` gives."""

    @F.pandas_udf("n_words long, n_removed long, kept_sha256 string")
    def of(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
        for texts, ranges in parts:
            out = []
            for t, r in zip(texts, ranges):
                words = words_of(t)
                kept = kept_words(words, r)
                out.append((len(words), len(words) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest()))
            yield pd.DataFrame(out, columns=["n_words", "n_removed", "kept_sha256"])

    return rows.select("doc_id", of("text", "ranges").alias("d")).select("doc_id", "d.*")


def without_repeats(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id and text without its repeated words (joined by one space where words went)."""

    @F.pandas_udf("string")
    def of(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for texts, ranges in parts:
            yield pd.Series([t if r is None or not len(r) else b" ".join(kept_words(words_of(t), r)).decode("utf-8", "surrogatepass") for t, r in zip(texts, ranges)], dtype=object)

    rows = repeats(docs, doc_id, text)
    return rows.select("doc_id", of("text", "ranges").alias("text"))


def against(docs: DataFrame, reference: DataFrame, text: str = "text", reference_text: str = "text", least: int = WINDOW, shard_words: int = SHARD_WORDS, out: str = "ranges", at_once: int = SHARDS_AT_ONCE) -> DataFrame:
    """Adds the word ranges of each document that also occur in the reference; one broadcast automaton for each shard of bounded size.

    The reference is read one partition at a time. At most ``at_once`` automata exist together: what they find is written before the next ones are made.
    """
    sc = docs.sparkSession.sparkContext
    docs = docs.withColumn(out, F.array().cast("array<struct<start:int,stop:int>>"))

    def matcher(held):
        @F.pandas_udf("array<struct<start:int,stop:int>>")
        def of(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for part in parts:
                yield pd.Series([[{"start": a, "stop": b} for a, b in spans(held.value.statistics(words_of(t)), least)] for t in part])

        return of

    def shards() -> Iterator[SuffixAutomaton]:
        automaton, size = SuffixAutomaton(), 0
        for row in reference.select(reference_text).toLocalIterator():
            words = words_of(row[0])
            for k in range(0, len(words), shard_words):  # a long text is cut with an overlap of one window
                piece = words[max(0, k - least + 1) : k + shard_words]
                automaton.add(piece)
                size += len(piece)
                if size >= shard_words:
                    yield automaton
                    automaton, size = SuffixAutomaton(), 0
        if size:
            yield automaton

    waiting, before = [], None
    for automaton in shards():
        if len(waiting) == at_once:
            done = written(_searched(docs, waiting, matcher, text, out))
            for b in waiting:
                b.unpersist()
            if before is not None:
                dropped(before)
            docs = before = done
            waiting = []
        waiting.append(sc.broadcast(automaton))
    return _searched(docs, waiting, matcher, text, out)


def _searched(docs: DataFrame, held: list, matcher, text: str, out: str) -> DataFrame:
    return docs.withColumn(out, F.concat(docs[out], *[matcher(b)(docs[text]) for b in held])) if held else docs
