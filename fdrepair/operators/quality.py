"""Quality of patterns: own confidence and support together with those of all patterns that can be reached.

Reach is a property of the value that a pattern leads to. ``path`` adds up along ways (each node's sums are made of its
successors' sums, one aggregation and one join for each FD, from the right to the left); ``distinct`` counts each reachable pattern
once, from a closure table grown in the same order. The plan says where both are the same.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import FD, RepairPlan
from .patterns import SCALE, simple, values, x
from .store import written, written_all

N_SCALE = 1_000_000  # weighted numbers of reachable patterns are kept as integers of so many parts


@dataclass
class Edges:
    """Per-FD edge tables: the pattern columns with reach_fp, reach_n, most_fp, least_fp, score_fp, quality_fp."""

    plan: RepairPlan
    tables: dict[FD, DataFrame]
    weight: str = "uniform"

    def long(self) -> DataFrame:
        """fd, lhs, rhs, cnt, lhs_cnt, conf_fp, sup_fp, score_fp, reach_n, quality_fp, quality of all FDs."""
        from .patterns import text_of

        out = None
        for f, t in self.tables.items():
            part = t.select(*text_of(f), "cnt", "lhs_cnt", "conf_fp", "sup_fp", "score_fp", "reach_n", "quality_fp", F.round(F.col("quality_fp") / SCALE, 6).alias("quality"))
            out = part if out is None else out.unionByName(part)
        return out


def own() -> Column:
    return F.col("conf_fp") + F.col("sup_fp")


def floored(c: Column) -> Column:
    return F.floor(c).cast("long")


def downstream_path(plan: RepairPlan, done: dict[FD, DataFrame], attribute: str, weight: str, skip: frozenset[int] = frozenset()) -> DataFrame | None:
    """v, d_s, d_n, d_hi, d_lo: what follows from each value of an attribute, over FDs whose edges are done; n in parts of N_SCALE."""
    out = None
    for g in plan.after(attribute):
        if plan.component[g.rhs] in skip:
            continue
        t = done[g].withColumn("v", F.col(x(attribute)))
        if weight == "best":
            pick = F.struct(-F.col("conf_fp"), -F.col("cnt"), F.col("y"))
            t = t.groupBy(*[F.col(x(a)) for a in g.lhs]).agg(F.min(F.struct(pick.alias("o"), F.col("v").alias("v"), "conf_fp", "sup_fp", "reach_fp", "reach_parts", "most_fp", "least_fp")).alias("b")).select("b.*")
        share = F.col("conf_fp") / F.lit(float(SCALE)) if weight == "confidence" else F.lit(1.0)
        term, number = own() + F.col("reach_fp"), F.col("reach_parts") + N_SCALE
        if weight == "confidence":
            term, number = floored(share * term), floored(share * number)
        part = t.select("v", term.alias("s"), number.alias("n"), F.greatest(own(), "most_fp").alias("hi"), F.least(own(), "least_fp").alias("lo"))
        out = part if out is None else out.unionByName(part)
    if out is None:
        return None
    return out.groupBy("v").agg(F.sum("s").alias("d_s"), F.sum("n").alias("d_n"), F.max("hi").alias("d_hi"), F.min("lo").alias("d_lo"))


def edge_key(f: FD) -> Column:
    """Text that names an edge among all edges."""
    return F.concat_ws("\x1f", F.lit(f.name), *[F.coalesce(F.col(x(a)).cast("string"), F.lit("\x00")) for a in f.lhs], F.coalesce(F.col("y").cast("string"), F.lit("\x00")))


def downstream_distinct(plan: RepairPlan, tables: dict[FD, DataFrame], attribute: str, closures: dict[str, DataFrame], skip: frozenset[int] = frozenset(), store=lambda t: t) -> DataFrame | None:
    """v, e (an edge), own_fp: each edge that can be reached from a value, once. store: what is done with each closure, as several follow from it."""
    kept = "|".join(map(str, sorted(skip)))
    if attribute + kept in closures:
        return closures[attribute + kept]
    out = None
    for g in plan.after(attribute):
        if plan.component[g.rhs] in skip:
            continue
        t = tables[g]
        part = t.select(F.col(x(attribute)).alias("v"), edge_key(g).alias("e"), own().alias("own_fp"))
        further = downstream_distinct(plan, tables, g.rhs, closures, store=store)
        if further is not None:
            reached = t.select(F.col(x(attribute)).alias("v"), "y").distinct().join(further.select(F.col("v").alias("w"), "e", "own_fp"), F.col("y").eqNullSafe(F.col("w"))).select("v", "e", "own_fp")
            part = part.unionByName(reached)
        out = part if out is None else out.unionByName(part)
    if out is not None:
        out = closures[attribute + kept] = store(out.distinct())
    return out


def reached(closure: DataFrame | None) -> DataFrame | None:
    if closure is None:
        return None
    return closure.groupBy("v").agg(F.sum("own_fp").alias("d_s"), (F.count(F.lit(1)) * N_SCALE).alias("d_n"), F.max("own_fp").alias("d_hi"), F.min("own_fp").alias("d_lo"))


def with_reach(t: DataFrame, follow: DataFrame | None, on: str) -> DataFrame:
    """Adds what follows from the value in column ``on``."""
    if follow is None:
        zero = F.lit(0).cast("long")
        return t.withColumns({"reach_fp": zero, "reach_parts": zero, "most_fp": own(), "least_fp": own()})
    met = t.join(follow, F.col(on).eqNullSafe(F.col("v")), "left")
    return met.withColumns({"reach_fp": F.coalesce("d_s", F.lit(0)), "reach_parts": F.coalesce("d_n", F.lit(0)), "most_fp": F.greatest(own(), F.coalesce("d_hi", own())), "least_fp": F.least(own(), F.coalesce("d_lo", own()))}).drop("v", "d_s", "d_n", "d_hi", "d_lo")


def rated(t: DataFrame, score: str, normalize: str) -> DataFrame:
    """Adds score_fp, reach_n and quality_fp."""
    full = own() + F.col("reach_fp")
    if score != "full":
        value = {"freq": F.col("cnt") * SCALE, "conf": F.col("conf_fp"), "sup": F.col("sup_fp"), "local": floored(own() / 2)}[score]
        return t.withColumns({"score_fp": value, "reach_n": floored(F.col("reach_parts") / N_SCALE), "quality_fp": value})
    number = F.col("reach_parts").cast("double") / N_SCALE
    quality = {"avg": floored(full.cast("double") / (2 * (number + 1))), "sum": full, "max": floored(F.col("most_fp") / 2), "min": floored(F.col("least_fp") / 2)}[normalize]
    return t.withColumns({"score_fp": full, "reach_n": floored(number), "quality_fp": quality})


def edge_quality(projected: DataFrame, plan: RepairPlan, *, score: str = "full", normalize: str = "avg", weight: str = "uniform", keep: bool = True, tables: int = 1) -> Edges:
    """Edges of all FDs with their quality.

    score: full, or one of the plainer ones (freq, conf, sup, local). weight: how continuations count (uniform, by confidence, or
    the best one only); other than uniform goes by ways. keep: write the pattern tables, closures and edges, which are used
    several times, to the shared folder; a decision's plan then holds none of the steps that made them. tables: of one size in projected, with no value in common.
    """
    patterns = {f: simple(projected, f, plan.nulls, tables) for f in plan.fds}
    if keep:
        patterns = written_all(patterns)
    store = written if keep else lambda t: t
    by_path = plan.reach == "path" or weight != "uniform"
    done: dict[FD, DataFrame] = {}
    closures: dict[str, DataFrame] = {}

    def follow(attribute: str, skip: frozenset[int] = frozenset()) -> DataFrame | None:
        if by_path:
            return downstream_path(plan, done, attribute, weight, skip)
        return reached(downstream_distinct(plan, patterns, attribute, closures, skip, store))

    for f in _right_to_left(plan):
        done[f] = store(with_reach(patterns[f], follow(f.rhs), "y"))
    for f in plan.closing:
        if plan.back_edges == "outside" and len(f.lhs) == 1:
            done[f] = store(with_reach(patterns[f], follow(f.lhs[0], frozenset((plan.component[f.rhs],))), x(f.lhs[0])))
        else:
            done[f] = store(with_reach(patterns[f], follow(f.rhs), "y"))
    return Edges(plan, {f: rated(done[f], score, normalize) for f in plan.fds}, weight)


def _right_to_left(plan: RepairPlan) -> list[FD]:
    """Forward FDs, each after all that follow from it."""
    rest, out = list(plan.forward), []
    while rest:
        f = next(f for f in rest if not any(f.rhs in g.lhs for g in rest if g != f))
        rest.remove(f)
        out.append(f)
    return out


def vertex_quality(edges: Edges) -> DataFrame:
    """attribute, val, sum_fp, avg_fp: scores of the edges that leave a node, added up and averaged."""
    out = None
    for f, t in edges.tables.items():
        part = t.groupBy(F.lit(",".join(f.lhs)).alias("attribute"), values(lambda a: F.col(x(a)), f).alias("values")).agg(F.sum("score_fp").alias("s"), F.count(F.lit(1)).alias("k"))
        out = part if out is None else out.unionByName(part)
    both = out.groupBy("attribute", "values").agg(F.sum("s").alias("sum_fp"), F.floor(F.sum("s") / F.sum("k")).cast("long").alias("avg_fp"))
    return both.select("attribute", F.array_join("values", "|").alias("val"), "sum_fp", "avg_fp")


def composed_quality(qualities: Column) -> Column:
    """Mean quality of the members of a composed pattern (an array of quality_fp)."""
    return floored(F.aggregate(qualities, F.lit(0).cast("long"), lambda a, b: a + b) / F.size(qualities))
