"""Properties of repairs on small random tables, against a row-by-row chase in plain Python and exact answers."""

import random

import pytest
from fdrepair.baselines import best_of, conflict_cover, exact_minimal, exact_pattern_preserving, majority, sampling, similarity
from fdrepair.operators import chase, detect, errors, metrics, patterns, quality, select
from fdrepair.operators.patterns import x
from fdrepair.plans import build_plan

SETS = {"chain": "a -> b; b -> c", "case1": "a -> b; a -> c", "case2": "a -> c; b -> c", "cycle": "a -> b; b -> a; b -> c", "composite": "a, b -> c; c -> d"}


def random_rows(seed, n=40, nulls=0.0):
    rnd = random.Random(seed)
    value = lambda p, k: None if rnd.random() < nulls else f"{p}{rnd.randrange(k)}"
    return [(t, value("a", 6), value("b", 4), value("c", 3), value("d", 2)) for t in range(n)]


def frame(spark, rows):
    return spark.createDataFrame(rows, "tid long, a string, b string, c string, d string")


def by_row(df, plan, decisions):
    """The chase one row after the other, with a table for each FD."""
    chosen = {f: {tuple(r[x(a)] for a in f.lhs): r.y for r in t.collect()} for f, t in decisions.items()}
    tables = {f: {} for f in plan.fds}
    out = {}
    for r in sorted(df.collect(), key=lambda r: r.tid):
        values = {a: r[a] for a in plan.bound}
        for f in plan.fds:
            key = tuple(values.get(a) for a in f.lhs)
            if None in key:
                values.setdefault(f.rhs, None)
                continue
            if key in tables[f]:
                told = tables[f][key]
            elif values.get(f.rhs) is not None:
                told = tables[f][key] = values[f.rhs]
            else:
                told = tables[f][key] = chosen[f].get(key)
            if values.get(f.rhs) is None:
                values[f.rhs] = told
        out[r.tid] = {a: values.get(a) if values.get(a) is not None else r[a] for a in plan.attributes}
    return out


@pytest.mark.parametrize("name", SETS)
@pytest.mark.parametrize("strategy", ["greedy", "cover"])
def test_chase_as_row_by_row(spark, name, strategy):
    df = frame(spark, random_rows(len(name)))
    plan = build_plan(SETS[name], df.schema)
    projected = patterns.project(df, plan.attributes, "tid")
    decisions = select.choose(quality.edge_quality(projected, plan), strategy)
    r = chase.finish(df, plan, projected, None, decisions, "tid")
    got = {row.tid: {a: row[a] for a in plan.attributes} for row in r.df.collect()}
    assert got == by_row(df, plan, decisions)
    assert r.df.count() == 40 and r.df.columns == df.columns
    assert all(got[t][a] == v for t, row in ((q.tid, q) for q in df.collect()) for a, v in ((a, row[a]) for a in plan.bound))
    if name in ("chain", "case1", "composite"):
        assert detect.satisfies(r.df, SETS[name])
        again = chase.repair(r.df, SETS[name], "tid", strategy)
        assert again.cost().first()[0] == 0


def test_component_policy_always_satisfies(spark):
    for seed in (1, 2):
        df = frame(spark, random_rows(seed, 25))
        r = chase.repair(df, SETS["case2"], "tid", "greedy", on_conflict="component")
        assert detect.satisfies(r.df, SETS["case2"])


def test_order_of_rows_and_partitions_changes_nothing(spark):
    rows = random_rows(9)
    one = chase.repair(frame(spark, rows), SETS["cycle"], "tid").delta.collect()
    random.Random(1).shuffle(rows)
    two = chase.repair(frame(spark, rows).repartition(5), SETS["cycle"], "tid").delta.collect()
    assert sorted(map(str, one)) == sorted(map(str, two))


def test_nulls(spark):
    df = frame(spark, random_rows(4, nulls=0.2))
    r = chase.repair(df, SETS["chain"], "tid", "greedy")
    got = {q.tid: q for q in r.df.collect()}
    for q in df.collect():
        if q.a is not None:
            assert got[q.tid].b is not None
        else:
            assert got[q.tid].b == q.b
    assert chase.repair(df, SETS["chain"], "tid", "greedy", nulls="value").df.count() == 40


def test_quality_bounds_and_reach(spark):
    df = frame(spark, random_rows(5))
    for name in SETS:
        plan = build_plan(SETS[name], df.schema)
        e = quality.edge_quality(patterns.project(df, plan.attributes, "tid"), plan).long()
        assert e.where("quality_fp < 0 or quality_fp > 1000000000").isEmpty()
    both = [quality.edge_quality(patterns.project(df, ("a", "b", "c"), "tid"), build_plan(SETS["chain"], df.schema, reach=r)).long().orderBy("fd", "lhs", "rhs").collect() for r in ("path", "distinct")]
    assert both[0] == both[1]


def test_two_ways_to_a_value_count_once_or_twice(spark):
    rows = [(0, "a", "b", "c1", "d", "e"), (1, "a", "b", "c2", "d", "e")]
    df = spark.createDataFrame(rows, "tid long, a string, b string, c string, d string, e string")
    fds = "a -> b; b -> c; c -> d; d -> e"
    n = {}
    for reach in ("path", "distinct"):
        plan = build_plan(fds, df.schema, reach=reach)
        n[reach] = quality.edge_quality(patterns.project(df, plan.attributes, "tid"), plan).long().where("fd = 'a->b'").first().reach_n
    assert n == {"path": 6, "distinct": 5}
    assert build_plan(fds, df.schema).reach == "distinct"


def test_thresholds_at_the_ends(spark):
    df = frame(spark, random_rows(6))
    run = lambda s, **o: sorted(map(str, chase.repair(df, SETS["chain"], "tid", s, **o).delta.collect()))
    assert run("hybrid", theta=0.0) == run("greedy")
    assert run("hybrid", theta=1.1) == run("cover")


def test_tie_takes_the_smaller_value(spark):
    df = spark.createDataFrame([(0, "a", "y"), (1, "a", "x")], "tid long, a string, b string")
    assert {r.b for r in chase.repair(df, "a -> b", "tid", "greedy").df.collect()} == {"x"}


@pytest.mark.parametrize("rows", [[], [(1, "a", "b", "c", "d")], [(k, "a", "b", "c", "d") for k in range(5)]])
def test_nothing_to_repair(spark, rows):
    r = chase.repair(frame(spark, rows), SETS["chain"], "tid")
    assert r.cost().first()[0] == 0 and r.df.count() == len(rows)


def test_exact_references(spark, t5):
    small = t5.where("tid <= 3")
    fds = "cyclist -> country; country -> capital"
    least = exact_minimal(small, fds, "tid")
    assert {r.cost for r in least.collect()} == {1}
    best = exact_pattern_preserving(small, fds, "tid").collect()
    assert len({r.quality for r in best}) == 1
    ours = chase.repair(small, fds, "tid")
    assert ours.cost().first()[0] == 1
    assert metrics.instance_quality(ours.df, fds).first()[0] <= best[0].quality
    with pytest.raises(ValueError):
        exact_minimal(frame(spark, random_rows(1, 13)), SETS["chain"], "tid")


@pytest.fixture(scope="module")
def experiment(spark):
    rnd = random.Random(3)
    rows = [(t, f"a{k}", f"b{k % 7}", f"c{k % 7 % 3}", "d") for t, k in enumerate(rnd.choices(range(30), k=400))]
    truth = frame(spark, rows)
    return truth, errors.inject(truth, SETS["chain"], "tid", 0.06, kind="typo")[0]


def test_errors_are_logged_and_detectable(spark, experiment):
    truth, _ = experiment
    for kind in ("swap", "typo", "null", "mix"):
        dirty, log = errors.inject(truth, SETS["chain"], "tid", 0.06, kind=kind)
        rows = log.collect()
        assert 10 < len(rows) < 100 and dirty.count() == 400
        assert metrics.accuracy(dirty, truth, truth, "tid", ("b", "c")).first().precision == 1
    assert errors.inject(truth, SETS["chain"], "tid", 0.0)[1].count() == 0
    assert metrics.accuracy(truth, truth, truth, "tid", ("b", "c")).first().recall is None
    assert errors.inject(truth, SETS["chain"], "tid", 0.06, side="lhs")[1].where("attribute = 'a'").count() > 0


def test_own_variants_against_baselines(experiment):
    truth, dirty = experiment
    score = lambda df: metrics.accuracy(dirty, df, truth, "tid", ("b", "c")).first()
    own = score(chase.repair(dirty, SETS["chain"], "tid", "hybrid", weight="confidence").df)
    assert own.recall > 0.9 and own.precision > 0.9
    for base in (majority, sampling, similarity):
        assert 0 <= score(base(dirty, SETS["chain"], "tid").df).recall <= 1
    drawn = score(sampling(dirty, SETS["chain"], "tid", 1).df)
    assert own.f1 > drawn.f1
    best, scores = best_of(dirty, SETS["chain"], "tid", truth)
    assert scores.count() == 5 and score(best.df).f1 >= drawn.f1
    covered = conflict_cover(dirty, SETS["chain"], "tid")
    assert detect.satisfies(covered.df, SETS["chain"]) and covered.rounds <= 10


def test_fresh_values_where_groups_disagree(spark):
    rows = [(0, "a1", "b1", "c1", "d"), (1, "a1", "b2", "c2", "d"), (2, "a2", "b2", "c1", "d"), (3, "a1", "b3", "c1", "d"), (4, "a3", "b2", "c2", "d")]
    r = conflict_cover(frame(spark, rows), SETS["case2"], "tid")
    assert {f.attribute: f.fresh_values for f in r.fresh.collect()}["c"] > 0


def test_plans_read_little_and_join_without_products(spark):
    from fdrepair.sources.tables import CHAIN, orders_wide

    df = orders_wide(spark, "/root/testdata/sf0.001")
    plan = build_plan(CHAIN, df.schema)
    text = patterns.project(df, plan.attributes, "tid")._jdf.queryExecution().toString()
    assert "o_totalprice" not in text.split("== Physical Plan ==")[1] and "c_acctbal" not in text.split("== Physical Plan ==")[1]
    physical = chase.repair(df, CHAIN, "tid").df._jdf.queryExecution().toString().split("== Physical Plan ==")[1]
    assert "CartesianProduct" not in physical and "PythonUDF" not in physical


@pytest.mark.parametrize("held", [0, 100, 100_000])
def test_components_of_a_long_path(spark, held):
    """A path whose ids are in no order has one component, in rounds far below its length."""
    from fdrepair.operators.components import components

    ids = list(range(400))
    random.Random(4).shuffle(ids)
    links = spark.createDataFrame([*zip(ids, ids[1:]), (900, 900), (902, 901)], "a long, b long")
    assert {(r.node, r.root) for r in components(links, held).collect()} == {(i, 0) for i in ids} | {(900, 900), (901, 901), (902, 901)}
