"""Composition of patterns: composable and independent pairs, and composed patterns as columns.

A pattern is a struct (fds array<string>, vals map<string,string>): the FDs it holds and the value of each of their attributes.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import FD, RepairPlan
from ..plans.fd import interaction
from .patterns import simple, x

EMPTY = "named_struct('fds', cast(array() as array<string>), 'vals', cast(map() as map<string,string>))"


def pattern(f: FD, lhs: list[Column], rhs: Column) -> Column:
    """A simple pattern."""
    pairs = [part for a, c in zip((*f.lhs, f.rhs), (*lhs, rhs)) for part in (F.lit(a), c.cast("string"))]
    return F.struct(F.array(F.lit(f.name)).alias("fds"), F.create_map(*pairs).alias("vals"))


def shared_agree(p: Column, q: Column) -> tuple[Column, Column]:
    """(whether two patterns share an attribute, whether all shared ones have one value)."""
    common = F.array_intersect(F.map_keys(p["vals"]), F.map_keys(q["vals"]))
    return F.size(common) > 0, F.forall(common, lambda k: F.element_at(p["vals"], k) == F.element_at(q["vals"], k))


def composable(p: Column, q: Column) -> Column:
    """Their FDs share an attribute, and the shared attributes have the same values."""
    shared, agree = shared_agree(p, q)
    return shared & agree


def independent(p: Column, q: Column, plan: RepairPlan) -> Column:
    """They share nothing, disagree on what they share, or only start from the same left side."""
    pairs = [f"{f.name} {g.name}" for f in plan.fds for g in plan.fds if f != g and interaction(f, g) == "same_lhs"]
    listed = F.array(*map(F.lit, pairs)) if pairs else F.array().cast("array<string>")
    one = (F.size(p["fds"]) == 1) & (F.size(q["fds"]) == 1)
    same_lhs = one & F.array_contains(listed, F.concat_ws(" ", p["fds"][0], q["fds"][0]))
    return ~composable(p, q) | same_lhs


def compose(p: Column, q: Column) -> Column:
    """The union of both if they are composable, else the empty pattern; commutative, since keys are sorted."""
    entries = F.array_sort(F.array_distinct(F.concat(F.map_entries(p["vals"]), F.map_entries(q["vals"]))))
    # the map is made only where the values agree, as a key with two values would be an error
    vals = F.map_from_entries(F.when(composable(p, q), entries).otherwise(F.array_sort(F.map_entries(p["vals"]))))
    made = F.struct(F.array_sort(F.array_distinct(F.concat(p["fds"], q["fds"]))).alias("fds"), vals.alias("vals"))
    return F.when(composable(p, q), made).otherwise(F.expr(EMPTY))


def maximal(patterns: Column, plan: RepairPlan) -> Column:
    """An array of simple patterns folded into one composition, members that don't fit left out; as many rounds as there are FDs."""
    one = patterns[0]
    for _ in plan.fds:
        one = F.aggregate(patterns, one, lambda acc, p: F.when(composable(acc, p), compose(acc, p)).otherwise(acc))
    return one


def render(p: Column) -> Column:
    """fds and values as text."""
    vals = F.array_sort(F.transform(F.map_entries(p["vals"]), lambda e: F.concat(e["key"], F.lit("="), e["value"])))
    return F.concat(F.array_join(p["fds"], ","), F.lit("{"), F.array_join(vals, ","), F.lit("}"))


def composable_pairs(projected: DataFrame, plan: RepairPlan) -> DataFrame:
    """fd1, lhs1, rhs1, fd2, lhs2, rhs2, kind: patterns of two FDs that share attributes and agree on all of them.

    projected: the distinct projection. An equi-join on the shared attributes, on either side of either FD; the kind of meeting comes from the plan.
    """
    tables = {f: simple(projected, f, plan.nulls) for f in plan.fds}
    out = None
    for k, f in enumerate(plan.fds):
        for g in plan.fds[k + 1 :]:
            kind = interaction(f, g)
            if kind == "none":
                continue
            left, right = tables[f].alias("p"), tables[g].alias("q")
            on = [F.col(f"p.{side(f, a)}").eqNullSafe(F.col(f"q.{side(g, a)}")) for a in sorted(f.attributes & g.attributes)]
            shown = [c for n, h, name in ((1, f, "p"), (2, g, "q")) for c in (F.lit(h.name).alias(f"fd{n}"), F.concat_ws("|", *[F.col(f"{name}.{x(a)}").cast("string") for a in h.lhs]).alias(f"lhs{n}"), F.col(f"{name}.y").cast("string").alias(f"rhs{n}"))]
            part = left.join(right, on).select(*shown, F.lit(kind).alias("kind"))
            out = part if out is None else out.unionByName(part)
    if out is None:
        return projected.sparkSession.createDataFrame([], "fd1 string, lhs1 string, rhs1 string, fd2 string, lhs2 string, rhs2 string, kind string")
    return out


def side(f: FD, attribute: str) -> str:
    """The column of an attribute in f's pattern table."""
    return "y" if attribute == f.rhs else x(attribute)
