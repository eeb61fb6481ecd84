"""Byte-level BPE encoding and decoding with a hierarchical-bitmap rank queue.

A pre-token's adjacent pairs are queued by the rank of what they would merge to. One bucket per rank
holds the positions of its pairs in the linked list of parts; a bitmap marks the ranks that have a
bucket and a bitmap over that bitmap's words marks the words that are not zero, so that
find-first-set on two integers gives the smallest rank. Merging a pair changes its neighbours' ranks;
their old entries stay queued and are skipped when popped. Cost: O(log) per merge for pre-tokens of
any length. The new pre-tokens of some texts share a queue: its fixed costs come once for all of them,
and their merges are those of each alone, as no pair crosses two of them.

Defined results: a null text counts as the empty text (no ids, empty decoding); the longest text is
one row like any other; repeated rows give repeated results; extra columns are kept by ``encode`` and
``decode`` (a column of the same name as the new one is replaced).
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterable, Iterator
from itertools import accumulate, chain

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import given_back

WIDTH = 8  # bits of a rank that select a bit of its bitmap word: words of 256 ranks
LOW = (1 << WIDTH) - 1
CACHED_WORDS = 250_000
CACHED_LENGTH = 64
TOGETHER = 500_000  # characters of texts whose new pre-tokens are collected
QUEUED = 1000  # new pre-tokens that share a queue: more are slower, as they leave the processor's cache


def vocabulary(path: str) -> dict[bytes, int]:
    """Token bytes to ranks, from a file of base64 tokens and ranks."""
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


class ByteBPE(dict):
    """An encoder; as a dict it remembers the ids of short pre-tokens, up to a bound."""

    def __init__(self, ranks: dict[bytes, int], pattern: str) -> None:
        super().__init__()
        self.ranks = ranks
        self.pieces = regex.compile(pattern).findall
        self.tokens = [b""] * (max(ranks.values(), default=-1) + 1)
        for token, rank in ranks.items():
            self.tokens[rank] = token
        self.names = [str(i) for i in range(len(self.tokens))]
        self.older: dict[str, tuple[int, ...]] = {}
        self.bytes, self.pairs = np.full(256, -1), np.full(1 << 16, -1)
        for token, rank in ranks.items():
            if 0 < len(token) <= 2:
                (self.bytes, self.pairs)[len(token) - 1][int.from_bytes(token)] = rank

    def __missing__(self, word: str) -> tuple[int, ...]:
        ids = self.older.get(word)
        if ids is None:
            ids = tuple(self.ids(word.encode("utf-8", "replace")))
        if len(word) <= CACHED_LENGTH:
            self.kept({word: ids})
        return ids

    def forget(self) -> None:
        self.older = {}
        self.clear()

    def kept(self, words: dict[str, tuple[int, ...]]) -> None:
        """Remembers ids; what was not asked again while half of the bound filled is forgotten."""
        if len(self) + len(words) > CACHED_WORDS // 2:
            self.older = dict(self)
            self.clear()
        self.update(words)

    def ids(self, piece: bytes) -> list[int]:
        """The ids of one pre-token; one that is itself a token is not split."""
        return self.all_ids([piece])[0]

    def all_ids(self, pieces: list[bytes]) -> list[list[int]]:
        """The ids of each of several pre-tokens, which go through one queue: no pair crosses two of them, so each is merged as if it were alone."""
        out = [[whole] if (whole := self.ranks.get(x)) is not None else None for x in pieces]
        text = b"".join(x for x, ids in zip(pieces, out) if ids is None)
        rank_of, n = self.ranks.get, len(text)
        first = bytearray(n + 1)  # where a pre-token begins
        first[0] = first[n] = 1
        for stop in accumulate(len(x) for x, ids in zip(pieces, out) if ids is None):
            first[stop] = 1
        data = np.frombuffer(text, np.uint8).astype(np.int64)
        ranks = np.full(n, -1)
        ranks[:-1] = np.where(np.frombuffer(first, np.uint8)[1:n], -1, self.pairs[data[:-1] * 256 + data[1:]])
        pending, token = ranks.tolist(), self.bytes[data].tolist()
        end, before = list(range(1, n + 1)), np.where(np.frombuffer(first, np.uint8)[:n], -1, np.arange(n) - 1).tolist()
        order = np.argsort(ranks, kind="stable")[np.count_nonzero(ranks < 0) :]
        starts = np.flatnonzero(np.diff(ranks[order], prepend=-1))
        buckets = {r: at.tolist() for r, at in zip(ranks[order[starts]].tolist(), np.split(order, starts[1:]))}
        words: dict[int, int] = {}
        summary, push, pop = 0, heapq.heappush, heapq.heappop
        for rank in buckets if len(order) else ():
            words[rank >> WIDTH] = words.get(rank >> WIDTH, 0) | 1 << (rank & LOW)
            summary |= 1 << (rank >> WIDTH)
        while summary:
            word = (summary & -summary).bit_length() - 1
            bits = words[word]
            rank = (word << WIDTH) + (bits & -bits).bit_length() - 1
            bucket, least = buckets[rank], rank
            while bucket:
                at = pop(bucket)
                if pending[at] != rank:  # stale: one of its parts has changed since
                    continue
                gone = end[at]
                after = end[gone]
                end[at], pending[gone], pending[at], token[at] = after, -1, -1, rank
                left = before[at]
                if first[after]:
                    changed = ((left, after),) if left >= 0 else ()
                else:
                    before[after] = at
                    changed = ((left, after), (at, end[after])) if left >= 0 else ((at, end[after]),)
                for start, stop in changed:
                    found = rank_of(text[start:stop])
                    if found is None:
                        pending[start] = -1
                        continue
                    pending[start] = found
                    if found in buckets:
                        push(buckets[found], start)
                    else:
                        buckets[found] = [start]
                        place = found >> WIDTH
                        words[place] = words.get(place, 0) | 1 << (found & LOW)
                        summary |= 1 << place
                    if found < least:
                        least = found
                if least < rank:  # comes before the rest of this bucket
                    break
            else:
                del buckets[rank]
                words[word] &= ~(1 << (rank & LOW))
                if not words[word]:
                    summary &= ~(1 << word)
        at = 0
        for k, ids in enumerate(out):
            if ids is None:
                out[k], stop = [], at + len(pieces[k])
                while at < stop:
                    out[k].append(token[at] if token[at] >= 0 else self.ranks[text[at : end[at]]])
                    at = end[at]
        return out

    def cut(self, texts: list[str | None]) -> list[list[str]]:
        """The pre-tokens of each text; those that are new go through shared queues and are remembered."""
        found = [self.pieces(t or "") for t in texts]
        asked = list({w for words in found for w in words if w not in self and len(w) <= CACHED_LENGTH})[: CACHED_WORDS // 2]
        ids = {w: self.older[w] for w in asked if w in self.older}
        new = [w for w in asked if w not in ids]
        for k in range(0, len(new), QUEUED):
            part = new[k : k + QUEUED]
            ids.update(zip(part, map(tuple, self.all_ids([w.encode("utf-8", "replace") for w in part]))))
        if ids:
            self.kept(ids)
        return found

    def encode_all(self, texts: Iterable[str | None]) -> Iterator[list[int]]:
        """The ids of each text, about ``TOGETHER`` characters at a time."""
        held, size = [], 0
        for t in chain(texts, [None]):
            if held and (size + len(t or "") > TOGETHER or len(held) >= 1000):
                yield from ([*chain.from_iterable(map(self.__getitem__, words))] for words in self.cut(held))
                held, size = [], 0
            held.append(t)
            size += len(t or "")
        yield from ([*chain.from_iterable(map(self.__getitem__, words))] for words in self.cut(held[:-1]))

    def encode(self, text: str | None) -> list[int]:
        return list(chain.from_iterable(map(self.__getitem__, self.pieces(text or ""))))

    def decode(self, ids) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))


_built: dict[tuple[str, str], ByteBPE] = {}


def codec(path: str, pattern: str) -> ByteBPE:
    """One encoder for a vocabulary file in each Python worker."""
    if (path, pattern) not in _built:
        _built[path, pattern] = ByteBPE(vocabulary(path), pattern)
    return _built[path, pattern]


def encode(df: DataFrame, path: str, pattern: str, text: str = "text", out: str = "ids") -> DataFrame:
    """Adds the ids of each text."""

    @F.pandas_udf("array<int>")
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        bpe = codec(path, pattern)
        for part in parts:
            yield pd.Series(list(bpe.encode_all(part)))

    return df.withColumn(out, of(df[text]))


def decode(df: DataFrame, path: str, pattern: str, ids: str = "ids", out: str = "decoded") -> DataFrame:
    """Adds the bytes that the ids stand for (null ids: none)."""

    @F.pandas_udf("binary")
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        bpe = codec(path, pattern)
        for part in parts:
            yield pd.Series([bpe.decode(() if x is None else x) for x in part])

    return df.withColumn(out, of(df[ids]))


def digests(df: DataFrame, path: str, pattern: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Encodes and decodes in one pass and keeps what identifies both: doc_id, n_tokens, ids_sha256, decoded_sha256."""

    @F.pandas_udf("n_tokens long, ids_sha256 string, decoded_sha256 string")
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        bpe = codec(path, pattern)
        sha = hashlib.sha256
        for part in parts:
            rows = []
            for ids in bpe.encode_all(part):
                listed = " ".join(map(bpe.names.__getitem__, ids)).encode()
                rows.append((len(ids), sha(listed).hexdigest(), sha(bpe.decode(ids)).hexdigest()))
            yield pd.DataFrame(rows, columns=["n_tokens", "ids_sha256", "decoded_sha256"])
        bpe.forget()
        given_back()

    return df.select(df[doc_id].alias("doc_id"), of(df[text]).alias("d")).select("doc_id", "d.*")
