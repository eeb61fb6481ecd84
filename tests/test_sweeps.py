"""Sweeps: plans that the driver can hold, and similar texts without many candidates."""

from itertools import combinations

from fdrepair import workloads
from fdrepair.baselines.similarity import left_overs, similar_texts
from fdrepair.operators import patterns, quality
from fdrepair.operators.store import written
from fdrepair.plans import build_plan
from test_properties import SETS, frame, random_rows


def test_edges_hold_none_of_the_steps_that_made_them(spark):
    df = frame(spark, random_rows(3))
    plan = build_plan(SETS["chain"], df.schema, reach="distinct")
    edges = quality.edge_quality(written(patterns.project(df, plan.attributes, "tid")), plan)
    for t in edges.tables.values():
        assert "Join" not in t._jdf.queryExecution().optimizedPlan().toString()


def test_strategies_share_edges_and_conf_is_restored(spark):
    df = frame(spark, random_rows(4))
    shared = workloads.Shared(df, SETS["chain"])
    assert shared.repair("greedy").edges is shared.repair("hybrid", theta=0.5).edges
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    with workloads.by_measured_size(spark):
        assert spark.conf.get("spark.sql.autoBroadcastJoinThreshold") == "-1"
    assert spark.conf.get("spark.sql.autoBroadcastJoinThreshold") == before


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def test_similar_texts_of_all_lengths(spark):
    texts = [f"{k * 37}|{k % 5}" for k in range(60)] + ["abcdefgh", "abcdefghij", "abcdefgxhij", "abdefgxhij", "a" * 14, "a" * 15, "a" * 17, "abcdefghijklmno", "abcdefghijkl", "xbcdefghijklmno", "é1234", "e1234", "", "a", "ab", "abcd", "abcde"]
    p = spark.createDataFrame([(t,) for t in texts], "text string")
    want = {(a, b) for x, y in combinations(texts, 2) if x != y and distance(x, y) * 1000 <= max(len(x), len(y)) * 200 for a, b in ((x, y), (y, x))}
    assert {tuple(r) for r in similar_texts(p).collect()} == want and len(want) > 20
    rests = left_overs(spark.createDataFrame([(f"{k}|7",) for k in range(10_000, 12_000)], "text string"), 200)
    met = rests.join(rests.toDF("text2", "rest"), "rest").where("text < text2").count()
    assert met < 100_000  # pairs of letters proposed nearly all of the 2 million pairs


def test_rates_go_through_one_repair(spark, monkeypatch):
    """All rates at once give what each gives alone, by as many plans as one rate."""
    truth = written(frame(spark, random_rows(5)))
    algorithms = ("greedy", "cover", "hybrid", "greedy_confidence", "majority", "conflict_cover", "sampling")
    made, rates = [], (0.1, 0.3)
    edges = workloads.edge_quality
    alone = [tuple(r) for rate in rates for r in workloads.measure(truth, SETS["chain"], algorithms, rate, "mix").collect()]
    monkeypatch.setattr(workloads, "edge_quality", lambda *a, **k: made.append(1) or edges(*a, **k))
    got = [tuple(r) for r in workloads.rate_sweep(truth, SETS["chain"], rates, "mix", algorithms).collect()]
    assert len(made) == 3  # by quality, by confidence, by frequency
    assert sorted(map(str, got)) == sorted(map(str, alone))
    empty = workloads.rate_sweep(written(truth.where("false")), SETS["chain"], (0.1, 0.3), "swap", ("greedy",)).collect()
    assert [(r["rate"], r["changed"], r["f1"]) for r in sorted(empty)] == [(0.1, 0, None), (0.3, 0, None)]
