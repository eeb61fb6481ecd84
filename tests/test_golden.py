"""Worked examples: the numbers that the method gives on small tables of cyclists."""

import pytest
from conftest import FOUR, TWO
from fdrepair.operators import chase, metrics, patterns, quality, select
from fdrepair.plans import FD, build_plan


def edges_of(df, fds, **options):
    weight = options.pop("weight", "uniform")
    plan = build_plan(fds, df.schema, **options)
    return quality.edge_quality(patterns.project(df, plan.attributes, "tid"), plan, weight=weight, keep=False)


def q(edges, fd, lhs, rhs):
    rows = edges.long().where(f"fd = '{fd}' and lhs = '{lhs}' and rhs = '{rhs}'").collect()
    return rows[0].quality_fp / 1e9


def test_instance_quality_and_gain(spark, t5):
    good = t5.replace("Russia", "Germany", ["country"])
    bad = t5.selectExpr("tid", "rank", "cyclist", "if(tid = 2, 'Russia', country) country", "capital")
    assert metrics.instance_quality(t5, TWO).first()[0] == 22
    assert metrics.gain(good, t5, TWO).first().asDict() == {"before": 22, "after": 32, "gain": 10}
    assert metrics.gain(bad, t5, TWO).first()["gain"] == -2


def test_quality_of_forward_and_closing_edges(t5):
    e = edges_of(t5, FOUR, prefer_bound=["rank"], reach="path", back_edges="outside")
    assert q(e, "rank->cyclist", "166", "Marcel Kittel") == pytest.approx(5.4667 / 10, abs=1e-4)
    assert q(e, "cyclist->rank", "Marcel Kittel", "166") == pytest.approx(0.58, abs=1e-4)
    e = edges_of(t5, FOUR, prefer_bound=["rank"], reach="path")
    assert q(e, "cyclist->rank", "Marcel Kittel", "166") == pytest.approx(10.4 / 18, abs=1e-4)
    e = edges_of(t5, FOUR, prefer_bound=["rank"], reach="distinct")
    assert q(e, "cyclist->rank", "Marcel Kittel", "166") == pytest.approx(8.6 / 16, abs=1e-4)


@pytest.mark.parametrize("reach", ["path", "distinct", "auto"])
def test_quality_of_a_chain(t5, reach):
    e = edges_of(t5, TWO, reach=reach)
    for lhs, rhs, value in (("Marcel Kittel", "Russia", 0.475), ("Marcel Kittel", "Germany", 0.625), ("Paul Martens", "Germany", 0.75)):
        assert q(e, "cyclist->country", lhs, rhs) == pytest.approx(value, abs=1e-6)
    assert q(e, "country->capital", "Russia", "Berlin") == pytest.approx(0.60, abs=1e-6)
    assert q(e, "country->capital", "Germany", "Berlin") == pytest.approx(0.90, abs=1e-6)


def test_cover_scores(t5):
    e = edges_of(t5, TWO)
    f = FD(("cyclist",), "country")
    of = lambda anchor: {r.y: r.cover_fp / 1e9 for r in select.cover_scores(e, f, anchor).where("x_cyclist = 'Marcel Kittel'").collect()}
    assert of(True) == pytest.approx({"Russia": 0.5375, "Germany": 0.7625}, abs=1e-6)
    assert of(False)["Germany"] == pytest.approx(0.825, abs=1e-6)


@pytest.mark.parametrize("strategy", ["greedy", "cover", "hybrid"])
def test_small_repair(t5, strategy):
    r = chase.repair(t5, TWO, "tid", strategy)
    assert [tuple(x) for x in r.delta.collect()] == [(1, "country", "Russia", "Germany")]
    assert r.cost().first()[0] == 1 and r.df.count() == 5
    shown = {x.cyclist: x.expression for x in r.expressions.collect()}
    assert shown["Marcel Kittel"] == "[cyclist->country: Marcel Kittel -> Germany] > [country->capital: Germany -> Berlin]"
    assert r.explain(1).where("attribute = 'country'").count() == 2
    assert r.conflicts.count() == 0


def test_cycle_bound_on_either_side(t6):
    r = chase.repair(t6, FOUR, "tid", "hybrid", prefer_bound=["cyclist"])
    assert sorted(map(tuple, r.delta.collect())) == [(1, "country", "Russia", "Germany"), (3, "rank", "166", "133")]
    r = chase.repair(t6, FOUR, "tid", "greedy", prefer_bound=["cyclist"])
    got = {(x.cyclist, x["rank"]) for x in r.df.collect()}
    assert {c: k for c, k in got}["Andre Greipel"] == 133
    r = chase.repair(t6, FOUR, "tid", "greedy", prefer_bound=["rank"])
    values = {x.tid: x.cyclist for x in r.df.collect()}
    assert values[1] == values[2] == values[3] == "Andre Greipel"
    assert r.conflicts.count() > 0


def test_t6_values(t6):
    e = edges_of(t6, FOUR, prefer_bound=["rank"], reach="path")
    assert q(e, "rank->cyclist", "166", "Andre Greipel") == pytest.approx(0.6111, abs=1e-4)
    assert q(e, "rank->cyclist", "166", "Marcel Kittel") == pytest.approx(0.5333, abs=1e-4)
    e = edges_of(t6, FOUR, prefer_bound=["cyclist"])
    assert q(e, "cyclist->rank", "Andre Greipel", "166") == pytest.approx(q(e, "cyclist->rank", "Andre Greipel", "133"), abs=1e-6)


def test_case2_counterexample(spark):
    rows = [(k, "a1", "b1", "c1") for k in range(3)] + [(k + 3, "a2", "b1", "c2") for k in range(3)]
    df = spark.createDataFrame(rows, "tid int, a string, b string, c string")
    kept = chase.repair(df, "a -> c; b -> c", "tid")
    assert kept.cost().first()[0] == 0 and kept.conflicts.count() == 1
    merged = chase.repair(df, "a -> c; b -> c", "tid", on_conflict="component")
    assert {r.c for r in merged.df.collect()} == {"c1"}
    assert {(r.fd, r.lhs): r.rhs for r in kept.repair_tables().collect()}[("b->c", "b1")] == "c1"


def test_repeated_rounds(t6):
    r, rounds = chase.repair_until_stable(t6, FOUR, "tid", "greedy", prefer_bound=["cyclist"], lhs_source="input")
    assert r.cost().first()[0] == 0 and 1 < rounds <= 5


def test_deferred_claims(t6):
    e = edges_of(t6, FOUR, prefer_bound=["rank"])
    got = {r.x_rank: (r.y, r.rounds) for r in chase.deferred(e, FD(("rank",), "cyclist")).collect()}
    # 133 and 166 both lead to one cyclist; the better claimant keeps it and 166 takes its other one
    assert len({y for y, _ in got.values()}) == len(got) and set(got) == {166, 133, 21, 98}
