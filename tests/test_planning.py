"""FD reasoning: implication, covers, components, order, bound attributes."""

import pytest
from fdrepair.plans import FD, build_plan, parse
from fdrepair.plans import fd as fds_
from hypothesis import given, settings
from hypothesis import strategies as st

attribute = st.sampled_from("abcde")
fd = st.builds(lambda lhs, rhs: FD(tuple(sorted(lhs)), rhs), st.sets(attribute, min_size=1, max_size=2), attribute).filter(lambda f: f.rhs not in f.lhs)
fd_sets = st.lists(fd, min_size=1, max_size=6, unique=True)


def test_parse():
    assert parse("a, b -> c, d; c -> e") == [FD(("a", "b"), "c"), FD(("a", "b"), "d"), FD(("c",), "e")]
    assert parse(["a -> b", "a -> b"]) == [FD(("a",), "b")]
    for wrong in ("a -> a", "a", "-> b", "a ->"):
        with pytest.raises(ValueError):
            parse(wrong)


def test_parse_checks_the_schema(spark):
    df = spark.createDataFrame([(1, {"k": 1}, [1.0])], "a int, m map<string,int>, v array<double>")
    for wrong in ("a -> z", "a -> m", "v -> a"):
        with pytest.raises(ValueError):
            parse(wrong, df.schema)


@settings(max_examples=200, deadline=None)
@given(fd_sets)
def test_minimal_cover_is_equivalent(found):
    cover = fds_.minimal_cover(found)
    assert all(fds_.implies(cover, f) for f in found) and all(fds_.implies(found, f) for f in cover)
    assert all(not fds_.implies([g for g in cover if g != f], f) for f in cover)


@settings(max_examples=200, deadline=None)
@given(fd_sets)
def test_plan_of_any_set(found):
    plan = build_plan(found)
    assert sorted(plan.fds) == sorted(found)
    assert set(plan.bound) | set(plan.free) == {a for f in found for a in f.attributes} and not set(plan.bound) & set(plan.free)
    known = set(plan.bound)
    for f in plan.fds:  # every left side has a value at its turn
        assert known.issuperset(f.lhs)
        known.add(f.rhs)
    assert all(any(f.rhs == a for f in found) for a in plan.free)


def test_components_and_layers():
    graph = fds_.dependency_graph(parse("e -> a; a -> b; b -> a; b -> c"))
    assert sorted(map(tuple, fds_.sccs(graph))) == [("a", "b"), ("c",), ("e",)]
    assert fds_.layers(graph) == [(0, ["e"]), (1, ["a", "b"]), (2, ["c"])]


def test_bound_and_free():
    of = lambda text, **o: build_plan(text, **o)
    assert set(of("a,b -> c; c,d -> e").bound) == {"a", "b", "d"}
    assert len(of("a -> b; b -> a").bound) == 1
    assert of("a -> b; b -> a", prefer_bound=["b"]).bound == ("b",)
    assert of("a -> b; b -> a", distinct={"a": 3, "b": 9}).bound == ("b",)
    assert of("e -> a; a -> b; b -> a").bound == ("e",)
    assert len(of("a -> b; b -> c; c -> a").bound) == 1


def test_order_and_interaction():
    plan = build_plan("c,d -> e; a,b -> c")
    assert [f.name for f in plan.fds] == ["a,b->c", "c,d->e"]
    f = lambda t: parse(t)[0]
    assert fds_.interaction(f("a->b"), f("a->c")) == "same_lhs"
    assert fds_.interaction(f("a->c"), f("b->c")) == "same_rhs"
    assert fds_.interaction(f("a->b"), f("b->c")) == "chain"
    assert fds_.interaction(f("a->b"), f("b->a")) == "cycle"
    assert fds_.interaction(f("a->b"), f("c->d")) == "none"
    assert [len(p) for p in fds_.parts(parse("a->b; a->c; c->d"))] == [1, 2]
    with pytest.raises(ValueError):
        build_plan("a->b; b->c; a->c", minimal="strict")
    assert len(build_plan("a->b; b->c; a->c", minimal="reduce").fds) == 2
