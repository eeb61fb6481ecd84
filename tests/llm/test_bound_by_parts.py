"""Pairs that the bound by parts leaves out, and runs that travel in blocks."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from fdrepair.llm import neardup
from fdrepair.llm.common import WordHashes


@pytest.fixture
def copies(spark):
    """Copies of one text, each changed in seven places of its own so that none is similar to another, and one pair that is."""
    draw = random.Random(3)
    base = [f"w{k}" for k in range(400)]
    rows = []
    for k in range(60):
        copy = list(base)
        at = draw.sample(range(0, 360, 6), 7)
        for x in at:
            copy[x : x + 1] = [f"x{k}y{x}"]
        rows.append((k, " ".join(copy)))
    rows.append((60, rows[7][1].replace("w399", "other")))
    texts = spark.createDataFrame(rows, "node long, text string")
    vectors = {k: neardup.weighted_shingles(WordHashes().array(neardup.words_of(t))) for k, t in rows}
    return texts, vectors, {(a, b) for a, b in itertools.combinations(vectors, 2) if neardup.similarity(vectors[a], vectors[b]) >= 0.8}


def test_copies_changed_in_different_places_are_no_pairs(spark, copies):
    texts, vectors, links = copies
    large = texts.select(F.lit(1).cast("long").alias("key"), "node", F.col("node").alias("root"), F.lit(61).alias("n"))
    rated = neardup.bounded(large, texts, 0.8)
    pairs = {(r.a, r.b) for r in neardup.ordered(neardup.pivot_pairs(rated, rated, 0.8)).collect()}
    assert (7, 60) in links <= pairs and rated.count() > 50
    assert len(pairs) < len(vectors) ** 2 / 10  # by weights alone nearly all of the 1,830 pairs


@pytest.mark.parametrize("split, block", [(0, 500_000), (2, 900)])
def test_runs_travel_in_blocks(spark, copies, monkeypatch, split, block):
    monkeypatch.setattr(neardup, "BLOCK", block)
    texts, vectors, _ = copies
    members = texts.withColumn("root", F.col("node") % 20)
    where = {}
    for k, (e, _) in vectors.items():
        for x in e:
            where.setdefault(x, set()).add(k % 20)
    want = {k: (sum(c), sum(n for x, n in zip(e, c) if len(where[x]) > 1)) for k, (e, c) in vectors.items()}
    got = neardup.weights(members, split).collect()
    assert {r.node: (r.w, r.s) for r in got} == want and all(sum(r.parts) == r.s and len(r.parts) == neardup.PARTS for r in got)
    plan = neardup.weights(members, split)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and neardup.run_blocks(members, 0).count() <= 64 * 61


def test_weights_travel_by_blocks_and_shares(spark, copies, monkeypatch):
    """A share's row names only the texts that have runs in it, and gathering gives a row for each text: no rows of a text and a part."""
    monkeypatch.setattr(neardup, "BLOCK", 8_000)
    texts, vectors, _ = copies
    members = texts.withColumn("root", F.col("node"))
    for r in neardup.run_blocks(members, 4).collect():
        assert len(r.nodes) == len(r.roots) == len(r.at) // 4 == len(r.n) // 4 < len(vectors)
    adaptive = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    found = neardup.weights(members.coalesce(1), 0)
    assert found.count() == len(vectors)
    found.collect()
    made, nodes = [], [found._jdf.queryExecution().executedPlan()]
    spark.conf.set("spark.sql.adaptive.enabled", adaptive)
    while nodes:
        p = nodes.pop()
        nodes += [p.children().apply(k) for k in range(p.children().size())]
        if "FlatMapGroups" in p.nodeName():
            made.append(p.metrics().apply("pythonNumRowsReceived").value())
    assert len(made) == 2 and min(made) == len(vectors) and max(made) <= 3 * neardup.PARTS


def test_repeated_rows_keep_their_links(spark, copies):
    """A row that stands twice weighs what it weighs, and two texts of one id are bounded by what either may share."""
    texts, vectors, links = copies
    twice = texts.union(texts.where("node = 7")).union(texts.where("node = 60").withColumn("text", F.lit("a few other words that nobody else has")))
    large = texts.select(F.lit(1).cast("long").alias("key"), "node", F.col("node").alias("root"), F.lit(61).alias("n"))
    w = {r.node: r.w for r in neardup.weights(twice.withColumn("root", F.col("node")), 0).collect()}
    assert w[7] == sum(vectors[7][1]) and w[60] == 4 and len(w) == len(vectors)
    rated = neardup.bounded(large, twice, 0.8)
    assert (7, 60) in links <= {(r.a, r.b) for r in neardup.ordered(neardup.pivot_pairs(rated, rated, 0.8)).collect()}
