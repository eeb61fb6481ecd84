"""Connected components by contraction of links, for merging values that must share one right side."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import checkpointed, written

HELD = 100_000


def united(links: list[tuple]) -> dict:
    """The least member of each node's component, by links in memory."""
    root: dict = {}

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for a, b in links:
        root.setdefault(a, a)
        root.setdefault(b, b)
        a, b = sorted((find(a), find(b)))
        root[b] = a
    return {i: find(i) for i in root}


def _ended(edges: DataFrame) -> DataFrame:
    """node, root by links that fit in memory."""
    kind = edges.schema["a"].dataType.simpleString()
    return edges.sparkSession.createDataFrame(list(united([(r.a, r.b) for r in edges.collect()]).items()), f"node {kind}, root {kind}")


def components(links: DataFrame, held: int = HELD, stored: bool = False) -> DataFrame:
    """node, root (the least node of its component) of links (a, b).

    Each round every node moves to the one of its neighbours and itself that comes first in an order by hash, another order each
    round, and the links are drawn between the new places. Less than a fixed share of the nodes stays on average whatever the links are like,
    so rounds grow with the logarithm of the nodes; they end when no link is left. stored: the links are read from a table already. What is left of at most ``held`` rows is finished in memory.
    """
    links = links.select("a", "b") if stored else written(links.select("a", "b"))
    if links.count() <= held:
        return _ended(links)
    edges = checkpointed(links.union(links.select("b", "a")).distinct())
    places = edges.select(F.col("a").alias("node"), F.col("a").alias("place")).distinct()
    edges = edges.where("a <> b")
    turn = 0
    while (n := edges.count()) > held:
        turn += 1
        first = F.min(F.struct(F.xxhash64(F.lit(turn), "b").alias("h"), F.col("b").alias("to")))
        own = F.struct(F.xxhash64(F.lit(turn), "a").alias("h"), F.col("a").alias("to"))
        moves = checkpointed(edges.groupBy("a").agg(first.alias("near")).select(F.col("a").alias("from"), F.least("near", own).getField("to").alias("to")))
        places = checkpointed(places.join(moves, F.col("place") == F.col("from"), "left").select("node", F.coalesce("to", "place").alias("place")))
        left = edges.join(moves, F.col("a") == F.col("from")).select(F.col("to").alias("a"), "b")
        right = moves.select(F.col("from").alias("from2"), F.col("to").alias("to2"))
        edges = checkpointed(left.join(right, F.col("b") == F.col("from2")).select("a", F.col("to2").alias("b")).where("a <> b").distinct())
    if n:
        ends = _ended(edges).withColumnsRenamed({"node": "from", "root": "to"})
        places = places.join(ends, F.col("place") == F.col("from"), "left").select("node", F.coalesce("to", "place").alias("place"))
    least = places.groupBy("place").agg(F.min("node").alias("root"))
    return checkpointed(places.join(least, "place").select("node", "root"))
