"""Near-duplicate groups by DartMinHash over weighted word shingles.

A text is the multiset of its runs of five words (lower case, words are runs of letters, digits and
underscores; fewer than five words make one run); the weight of a run is how often it occurs.
Hashed darts fall on the (element, weight, rank) space as a Poisson process that depends on the
element alone, so all texts that hold an element see the same darts below their weight. Each dart
belongs to one of ``HASHES`` coordinates, and the earliest one in each is the text's signature:
two texts agree in a coordinate with the probability of their weighted Jaccard similarity. Only about
``HASHES * (ln HASHES + 2)`` darts are thrown for a text of any length.

``BANDS`` bands of ``ROWS`` coordinates give candidate buckets (a pair of similarity 0.8 shares none
with a probability of 4e-5). Texts with the same words are one node from the start. A bucket of at most
``SMALL`` nodes proposes all its pairs at once. A larger one proposes in rounds, every member with a pivot: first the member of the most
bucket rows, which is closest to the others, then members drawn by hash, ``GROWTH`` times as many each round. Every proposed pair is checked
exactly, and links of similarity >= ``SIMILARITY`` join nodes to classes. A bucket is done when its members are of one class or have all been pivots.

Between rounds members that can have no further link are left out by a bound: what a text shares with any text of another class weighs
at most as much as its runs that occur in one at all. If these are less than ``SIMILARITY`` of its weight it has no link there; and a pair is
proposed only if the runs in question suffice for both texts' weight: those of either text, and the sum over ``PARTS`` parts of all runs of what
the poorer of both has in a part. Two copies of one text that were changed in different places lack runs in different parts. So copies with many changes of their own, which share buckets
with a whole group but belong to no class, cost a pass over their runs and not a pair with each of the others. No pair
that could be a link is left out: classes are those of all pairs that share a bucket.

Defined results: texts without words (null, empty, blank) are alone in their class, also if equal;
repeated rows with the same id are one document; a null id stays null and alone; an empty table
gives no rows; columns other than the id and the text are not read by ``classes``.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.components import components
from .common import WordHashes, dropped, freed, given_back, mix64, rolled, written

WORDS = 5
SIMILARITY = 0.8
BANDS, ROWS = 26, 5
HASHES = BANDS * ROWS
SMALL = 8
GROWTH = 16
PART_BITS = 6
PARTS = 1 << PART_BITS
BLOCK = 500_000  # runs that a Python worker holds at once
_words = re.compile(r"\w+").findall
_UNIT = 2.0**-53


def words_of(text: str | None) -> list[str]:
    return _words((text or "").lower())


def weighted_shingles(ids: np.ndarray, words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of a sequence of word hashes, and their counts."""
    if 0 < len(ids) < words:
        return rolled(ids, len(ids)), np.ones(1)
    values, counts = np.unique(rolled(ids, words), return_counts=True)
    return values, counts.astype(float)


def dart_signature(elements: np.ndarray, weights: np.ndarray, hashes: int = HASHES) -> np.ndarray:
    """The earliest dart's hash in each coordinate; weights are positive."""
    strips_e, strips_w, strips_from, strips_len = [elements], [weights], [np.zeros(len(elements))], [np.ones(len(elements))]
    low = 1.0
    while (heavy := weights > low).any():  # weight is cut in strips 0-1, 1-2, 2-4, 4-8, ...
        strips_e.append(mix64(elements[heavy] ^ np.uint64(int(low) * 0x632BE5AB)))
        strips_w.append(weights[heavy])
        strips_from.append(np.full(heavy.sum(), low))
        strips_len.append(np.full(heavy.sum(), low))
        low *= 2
    cell, weight, start, length = map(np.concatenate, (strips_e, strips_w, strips_from, strips_len))
    theta = hashes * (np.log(hashes) + 2) / weights.sum()
    while True:
        darts = _darts(cell, weight, start, length, theta, hashes)
        if darts is not None:
            return darts
        theta *= 2


def _darts(cell, weight, start, length, theta: float, hashes: int) -> np.ndarray | None:
    """Darts of ranks up to theta, the earliest by coordinate; None if a coordinate has none."""
    ranks, values, at = [], [], np.zeros(len(cell))
    live, first = np.arange(len(cell)), 0
    while len(live):
        wide = int(np.ceil(theta * length[live].max() * 0.5)) + 2 if first else max(1, int(theta * length[live].max() * 1.1))
        wide = min(wide, max(1, 200_000 // len(live)))
        number = np.arange(first, first + wide, dtype=np.uint64)
        h = mix64(cell[live][:, None] + (number * np.uint64(0xD1342543DE82EF95))[None, :])
        gap = -np.log(((h >> np.uint64(11)).astype(float) + 1) * _UNIT) / length[live][:, None]
        gap[:, 0] += at[live]
        rank = np.cumsum(gap, axis=1)
        other = mix64(h ^ np.uint64(0xA0761D6478BD642F))
        place = start[live][:, None] + length[live][:, None] * ((other >> np.uint64(11)).astype(float) * _UNIT)
        hit = (rank <= theta) & (place < weight[live][:, None])
        ranks.append(rank[hit])
        values.append(other[hit])
        at[live] = rank[:, -1]
        live = live[rank[:, -1] <= theta]
        first += wide
    rank, value = np.concatenate(ranks), np.concatenate(values)
    order = np.argsort(-rank, kind="stable")
    coordinate = (mix64(value) % np.uint64(hashes)).astype(np.int64)[order]
    out, seen = np.zeros(hashes, np.uint64), np.zeros(hashes, bool)
    out[coordinate] = value[order]  # the last one written is the earliest
    seen[coordinate] = True
    return out if seen.all() else None


def band_keys(signature: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    grid = signature.reshape(bands, rows)
    key = mix64(np.arange(1, bands + 1, dtype=np.uint64))
    for k in range(rows):
        key = mix64(key * np.uint64(0x9E3779B97F4A7C15) + grid[:, k])
    return key.view(np.int64)


def similarity(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Weighted Jaccard similarity of two shingle multisets."""
    _, at, bt = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    common = np.minimum(a[1][at], b[1][bt]).sum()
    total = a[1].sum() + b[1].sum() - common
    return float(common / total) if total else 0.0


def signatures(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, words_hash (of the word sequence, null without words), keys (of the bands)."""

    @F.pandas_udf("words_hash binary, keys array<long>")
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        hashes = WordHashes()
        for part in parts:
            rows = []
            for t in part:
                words = words_of(t)
                if not words:
                    rows.append((None, None))
                    continue
                whole = xxhash.xxh128_digest(" ".join(words))
                rows.append((whole, band_keys(dart_signature(*weighted_shingles(hashes.array(words))))))
            yield pd.DataFrame(rows, columns=["words_hash", "keys"])
        hashes.clear()
        given_back()

    return docs.select(docs[doc_id].alias("doc_id"), of(docs[text]).alias("s")).select("doc_id", "s.*")


def ordered(pairs: DataFrame) -> DataFrame:
    """Pairs (a, b), a < b, of (node, other), each once."""
    return pairs.where("node <> other").select(F.least("node", "other").alias("a"), F.greatest("node", "other").alias("b")).distinct()


def open_members(large: DataFrame, classes: DataFrame) -> DataFrame:
    """key, node, root, n (members of the bucket) of the buckets whose members are of several classes; classes: node, root (others are alone)."""
    told = classes.select(F.col("node").alias("__node"), "root")
    named = written(large.select("key", "node").join(told, F.col("node") == F.col("__node"), "left").select("key", "node", F.coalesce("root", "node").alias("root")))
    several = named.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high"), F.count(F.lit(1)).alias("n")).where("low <> high").select("key", "n")
    return named.join(several, "key")


def run_blocks(members: DataFrame, split: int) -> DataFrame:
    """block, share, at, nodes, roots, n, e, c: the runs of each text and how often they occur, as bytes, texts and their numbers of runs side by side; members: node, root, text.

    A run belongs to one of ``PARTS << split`` shares by its hash. A row holds what the texts of a block have of one share, with their places in the block, so rows don't grow with
    the texts' lengths. Texts come in the order of their nodes, so a task that runs again makes the same blocks.
    """

    def block(number: int, nodes: list, roots: list, found: list) -> pd.DataFrame:
        e, c = map(np.concatenate, zip(*found))
        text = np.repeat(np.arange(len(found), dtype=np.int32), [len(x) for x, _ in found])
        share = (e >> np.uint64(64 - PART_BITS - split)).astype(np.int64)
        order = np.argsort(share, kind="stable")
        shares, starts = np.unique(share[order], return_index=True)
        rows = []
        for k, mine in zip(shares, np.split(order, starts[1:])):
            at, n = np.unique(text[mine], return_counts=True)
            rows.append((number, int(k), at.tobytes(), [nodes[i] for i in at], [roots[i] for i in at], n.astype(np.int32).tobytes(), e[mine].tobytes(), c[mine].astype(np.int32).tobytes()))
        return pd.DataFrame(rows, columns=["block", "share", "at", "nodes", "roots", "n", "e", "c"])

    def of(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        hashes, number = WordHashes(), TaskContext.get().partitionId() << 32
        for part in parts:
            nodes, roots, found, size = [], [], [], 0
            for node, root, text in zip(part["node"].tolist(), part["root"].tolist(), part["text"]):
                nodes.append(node)
                roots.append(root)
                found.append(weighted_shingles(hashes.array(words_of(text))))
                size += len(found[-1][0])
                if size >= BLOCK:
                    yield block(number, nodes, roots, found)
                    nodes, roots, found, size, number = [], [], [], 0, number + 1
            if size:
                yield block(number, nodes, roots, found)
                number += 1
        hashes.clear()
        given_back()

    kind = members.schema["node"].dataType.simpleString()
    in_order = members.select("node", "root", "text").sortWithinPartitions("node")
    return in_order.mapInPandas(of, f"block long, share int, at binary, nodes array<{kind}>, roots array<{kind}>, n binary, e binary, c binary")


def weights(members: DataFrame, split: int) -> DataFrame:
    """node, w (weight of a text's runs), s (of those that occur in another class), parts (s by the runs' hash); of a node with several texts, the least w and the greatest s and parts."""

    def of(blocks: pd.DataFrame) -> pd.DataFrame:
        root = pd.factorize(np.concatenate(blocks["roots"].to_numpy()))[0]
        e, c, n = (np.concatenate([np.frombuffer(x, kind) for x in blocks[k]]) for k, kind in (("e", np.uint64), ("c", np.int32), ("n", np.int32)))
        text = np.repeat(np.arange(len(n)), n)
        order = np.argsort(e, kind="stable")
        starts = np.flatnonzero(np.concatenate([[True], np.diff(e[order]) != 0]))
        owner = root[text[order]]
        several = np.minimum.reduceat(owner, starts) != np.maximum.reduceat(owner, starts)
        common = np.zeros(len(e), bool)
        common[order] = np.repeat(several, np.diff(starts, append=len(e)))
        ends = np.cumsum([len(x) for x in blocks["nodes"]])[:-1]
        w, s = (np.split(np.bincount(text, x, len(n)).astype(np.int64), ends) for x in (c, c * common))
        told = {"w": [x.tobytes() for x in w], "s": [x.tobytes() for x in s]}
        return blocks[["block", "at", "nodes"]].assign(part=np.int32(blocks["share"].iloc[0] >> split), **told)

    def gathered(shares: pd.DataFrame) -> pd.DataFrame:
        at = np.concatenate([np.frombuffer(x, np.int32) for x in shares["at"]])
        w, s = (np.concatenate([np.frombuffer(x, np.int64) for x in shares[k]]) for k in ("w", "s"))
        places, first, text = np.unique(at, return_index=True, return_inverse=True)
        part = np.repeat(shares["part"].to_numpy(), [len(x) for x in shares["nodes"]])
        parts = np.bincount(text * PARTS + part, s, len(places) * PARTS).astype(np.int32).reshape(-1, PARTS)
        nodes = np.concatenate(shares["nodes"].to_numpy())[first]
        return pd.DataFrame({"node": nodes, "w": np.bincount(text, w).astype(np.int64), "s": np.bincount(text, s).astype(np.int64), "parts": list(parts)})

    kind = members.schema["node"].dataType.simpleString()
    told = run_blocks(members, split).groupBy("share").applyInPandas(of, f"block long, at binary, nodes array<{kind}>, part int, w binary, s binary")
    texts = told.groupBy("block").applyInPandas(gathered, f"node {kind}, w long, s long, parts array<int>")
    whole = texts.groupBy("node").agg(F.min("w").alias("w"), F.max("s").alias("s"), F.collect_set("parts").alias("all"))
    most = F.transform(F.sequence(F.lit(0), F.lit(PARTS - 1)), lambda k: F.array_max(F.transform("all", lambda x: F.get(x, k))))
    return whole.select("node", "w", "s", F.when(F.size("all") == 1, F.get("all", F.lit(0))).otherwise(most).alias("parts"))


def bounded(large: DataFrame, texts: DataFrame, threshold: float) -> DataFrame:
    """large with w (weight of a member's runs), s (of those that occur in another class) and parts (s by the runs' hash), without members that can have no link in a bucket."""
    member = large.select("node", "root").distinct()
    runs = (texts.agg(F.sum(F.length("text"))).first()[0] or 0) // 4
    split = max(0, runs // (PARTS * BLOCK)).bit_length()
    weight = written(weights(texts.join(member, "node"), split))
    rated = large.join(weight.where(F.col("s") >= F.col("w") * (threshold - 1e-9)), "node")
    bucket = Window.partitionBy("key")
    of_all = {"least": F.min("w").over(bucket), "low": F.min("root").over(bucket), "high": F.max("root").over(bucket), "n": F.count(F.lit(1)).over(bucket)}
    enough = F.col("s") >= (F.col("w") + F.col("least")) * (threshold / (1 + threshold) - 1e-9)
    for _ in range(2):  # the lightest member left bounds what the others need; buckets of one class are done
        rated = rated.withColumns(of_all).where((F.col("low") != F.col("high")) & enough).drop("least", "low", "high")
    return rated


def pivot_pairs(large: DataFrame, pivots: DataFrame, threshold: float) -> DataFrame:
    """Pairs (node, other) of the members of a bucket with its pivots of another class, where the bounds allow a link: two texts share in each part at most what the poorer one has there."""
    other = pivots.select("key", F.col("node").alias("other"), F.col("root").alias("its"), F.col("w").alias("w2"), F.col("s").alias("s2"), F.col("parts").alias("parts2"))
    need = (F.col("w") + F.col("w2")) * (threshold / (1 + threshold) - 1e-9)
    shared = F.aggregate(F.zip_with("parts", "parts2", lambda x, y: F.least(x, y)), F.lit(0), lambda x, y: x + y)
    return large.join(other, "key").where((F.col("root") != F.col("its")) & (F.col("s") >= need) & (F.col("s2") >= need) & (shared >= need)).select("node", "other")


def linked(nodes: DataFrame, texts: DataFrame, threshold: float = SIMILARITY) -> DataFrame:
    """node, root: the least node of each class of the links among all pairs that share a bucket; nodes without links don't occur."""
    rows = nodes.select("node", F.explode("keys").alias("key"))
    sizes = rows.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    member = written(rows.join(sizes, "key"))
    small = member.where(F.col("n") <= SMALL).groupBy("key").agg(F.collect_list("node").alias("all"))
    large = member.where(F.col("n") > SMALL)
    large = written(large.select("key", "node", F.sum("n").over(Window.partitionBy("node")).alias("met")))
    first = large.groupBy("key").agg(F.min(F.struct((-F.col("met")).alias("m"), F.xxhash64("node").alias("h"), "node")).getField("node").alias("other"))
    pairs = small.select(F.explode("all").alias("node"), "all").select("node", F.explode("all").alias("other"))
    pairs = written(ordered(pairs.union(large.join(first, "key").select("node", "other"))))
    links = written(verified(pairs, texts, threshold).select("a", "b"))
    dropped(member)
    freed(nodes.sparkSession)
    checked, few, turn, held = pairs, pairs.count(), 0, None
    while True:
        turn += 1
        found = components(links, stored=True)
        large = written(open_members(large, found))
        if large.isEmpty():
            return found
        if held is None:
            held = written(texts.join(large.select("node").distinct(), "node", "left_semi"))
        rated = written(bounded(large, held, threshold))
        if rated.isEmpty():
            return found
        rest = rated.agg(F.sum((F.col("n") - 1) / 2)).first()[0] or 0  # pairs in these buckets
        drawn = F.pmod(F.xxhash64("node", "key", F.lit(turn)), F.lit(1 << 30)) / F.lit(float(1 << 30))
        pivot = F.lit(True) if rest <= few else drawn < F.lit(float(GROWTH**turn)) / F.col("n")
        pairs = written(ordered(pivot_pairs(rated, rated.where(pivot), threshold)).join(checked, ["a", "b"], "left_anti"))
        links = links.union(written(verified(pairs, held, threshold).select("a", "b")))
        checked = checked.union(pairs)
        large = rated.where(~pivot)


def verified(pairs: DataFrame, texts: DataFrame, threshold: float = SIMILARITY) -> DataFrame:
    """The pairs (a, b) whose texts' exact similarity reaches the threshold; texts: (node, text)."""

    @F.pandas_udf("double")
    def of(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        hashes, recent = WordHashes(), {}

        def vector(t: str):
            key = xxhash.xxh128_digest(t)
            if key not in recent:
                if len(recent) > 64:
                    recent.clear()
                recent[key] = weighted_shingles(hashes.array(words_of(t)))
            return recent[key]

        for left, right in parts:
            yield pd.Series([similarity(vector(x), vector(y)) for x, y in zip(left, right)], dtype=float)
        hashes.clear()
        recent.clear()
        given_back()

    left = texts.select(F.col("node").alias("a"), F.col("text").alias("ta"))
    right = texts.select(F.col("node").alias("b"), F.col("text").alias("tb"))
    full = pairs.join(left, "a").join(right, "b")
    return full.select("a", "b", of.asNondeterministic()("ta", "tb").alias("similarity")).where(F.col("similarity") >= threshold)


def classes(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, class_id: the least id of the documents that are linked to it, directly or through others."""
    docs = docs.select(docs[doc_id].alias("doc_id"), docs[text].alias("text"))
    signed = written(signatures(docs))
    same = signed.where("words_hash is not null and doc_id is not null").groupBy("words_hash").agg(F.min("doc_id").alias("node"), F.first("keys").alias("keys"))
    nodes = same.select("node", "keys")
    texts = docs.where("doc_id is not null and text is not null").select(F.col("doc_id").alias("node"), "text")
    found = linked(nodes, texts)
    members = signed.join(same.select("words_hash", "node"), "words_hash", "left")
    named = members.join(found, "node", "left")
    return named.select("doc_id", F.coalesce("root", "node", "doc_id").alias("class_id")).distinct()


def keep_one(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents with one left of each class, all columns kept; rows with a null id stay."""
    kept = classes(docs, doc_id, text).where("doc_id = class_id").select(F.col("doc_id").alias("kept_id"))
    joined = docs.join(kept, docs[doc_id] == kept.kept_id, "left_semi").dropDuplicates([doc_id])
    return joined.unionByName(docs.where(docs[doc_id].isNull()))
