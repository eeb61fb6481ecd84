"""Repair: the chase over distinct bound assignments, repair tables, expressions and the change log.

The edge chosen for a left-side value depends on the graph alone, so the chase runs over distinct bound values, one join for each FD in
its order. Where a right side already has a value (several FDs with one right side, or a cycle), the repair
table holds what the first row (least id) with that left side got.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import FD, RepairPlan, build_plan
from ..plans.fd import parts
from .components import components
from .patterns import SCALE, project, x
from .quality import Edges, edge_quality
from .select import choose
from .store import written, written_all


@dataclass
class RepairResult:
    """df has the table's columns with free attributes repaired; the rest says how and why."""

    df: DataFrame
    plan: RepairPlan
    chase: DataFrame
    rtables: dict[FD, DataFrame]
    edges: Edges | None
    decisions: dict[FD, DataFrame]
    delta: DataFrame
    tid: str
    conflicts: DataFrame | None = None

    def cost(self) -> DataFrame:
        """changed: how many cells changed."""
        return self.delta.agg(F.count(F.lit(1)).alias("changed"))

    @property
    def expressions(self) -> DataFrame:
        """The bound attributes and the expression of each assignment."""
        return self.chase.select(*[F.col(a) for a in key_of(self.plan)], expression(self.plan).alias("expression"))

    def repair_tables(self) -> DataFrame:
        """fd, lhs, rhs, origin of all repair tables."""
        out = None
        for f, t in self.rtables.items():
            part = t.select(F.lit(f.name).alias("fd"), F.concat_ws("|", *[F.col(x(a)).cast("string") for a in f.lhs]).alias("lhs"), F.col("y").cast("string").alias("rhs"), "origin")
            out = part if out is None else out.unionByName(part)
        return out

    def explain(self, tid) -> DataFrame:
        """attribute, fd, lhs, rhs, score, rival, rival_score: the chosen edge behind each free cell of a row, with the edges it was chosen from."""
        row = self.df.where(F.col(self.tid) == tid)
        out = None
        for f in self.plan.fds:
            mine = row.select(*[F.col(a).alias(x(a)) for a in f.lhs], F.col(f.rhs).cast("string").alias("rhs"))
            chosen = self.decisions[f].select(*map(x, f.lhs), F.round(F.col("score_fp") / SCALE, 6).alias("score"), "origin")
            rivals = self.edges.tables[f].select(*map(x, f.lhs), F.col("y").cast("string").alias("rival"), F.round(F.col("quality_fp") / SCALE, 6).alias("rival_quality"))
            lhs = F.concat_ws("|", *[F.col(x(a)).cast("string") for a in f.lhs])
            met = mine.join(chosen, list(map(x, f.lhs)), "left").join(rivals, list(map(x, f.lhs)), "left")
            part = met.select(F.lit(f.name).alias("fd"), lhs.alias("lhs"), F.lit(f.rhs).alias("attribute"), "rhs", "score", "origin", "rival", "rival_quality")
            out = part if out is None else out.unionByName(part)
        return out


def key_of(plan: RepairPlan) -> tuple[str, ...]:
    """What a row's chase depends on: its bound values, or all of them where left sides are read from the input."""
    return plan.bound if plan.lhs_source == "chased" else plan.attributes


def known(plan: RepairPlan, f: FD) -> list[Column]:
    """Left-side values that the chase uses: what it has assigned so far, or the input's."""
    return [F.col(f"v_{a}") if plan.lhs_source == "chased" else F.col(a) for a in f.lhs]


def chase(projected: DataFrame, plan: RepairPlan, decisions: dict[FD, DataFrame]) -> tuple[DataFrame, dict[FD, DataFrame]]:
    """One row for each assignment: its key, __min_tid, __w, v_<attribute> for all attributes, __conflict and __trace; and the repair tables."""
    cur = projected.groupBy(*key_of(plan)).agg(F.min("__min_tid").alias("__min_tid"), F.sum("__w").alias("__w"))
    cur = cur.withColumns({f"v_{a}": F.col(a) for a in plan.bound}).withColumn("__conflict", F.lit(0)).withColumn("__trace", F.array().cast("array<struct<fd:string,lhs:string,rhs:string,origin:string>>"))
    tables: dict[FD, DataFrame] = {}
    assigned = set(plan.bound)
    for f in plan.fds:
        decision = decisions[f].select(*map(x, f.lhs), F.col("y"), F.col("origin"))
        value = f"v_{f.rhs}"
        if f.rhs not in assigned:
            tables[f] = decision
            cur = _looked_up(cur, plan, f, decision).withColumn(value, F.col("__y"))
        else:
            mine = cur.groupBy(*[c.alias(x(a)) for a, c in zip(f.lhs, known(plan, f))]).agg(F.min_by(value, F.when(F.col(value).isNotNull(), F.col("__min_tid"))).alias("told"))
            for a in f.lhs:
                mine = mine.where(F.col(x(a)).isNotNull())
            both = mine.alias("m").join(decision.alias("d"), [F.col(f"m.{x(a)}") == F.col(f"d.{x(a)}") for a in f.lhs], "left")
            tables[f] = both.select(*[F.col(f"m.{x(a)}") for a in f.lhs], F.coalesce("told", "y").alias("y"), F.when(F.col("told").isNotNull(), "first_row").otherwise(F.col("origin")).alias("origin"))
            cur = _looked_up(cur, plan, f, tables[f])
            cur = cur.withColumn("__conflict", F.col("__conflict") + F.when(F.col("__y").isNotNull() & F.col(value).isNotNull() & (F.col("__y") != F.col(value)), 1).otherwise(0))
            if plan.on_conflict == "overwrite":
                cur = cur.withColumn(value, F.coalesce("__y", value))
            else:
                cur = cur.withColumn(value, F.coalesce(value, "__y"))
        assigned.add(f.rhs)
        step = F.struct(F.lit(f.name).alias("fd"), F.concat_ws("|", *[c.cast("string") for c in known(plan, f)]).alias("lhs"), F.col(value).cast("string").alias("rhs"), F.col("__origin").alias("origin"))
        cur = cur.withColumn("__trace", F.concat("__trace", F.array(step))).drop("__y", "__origin")
    return cur, tables


def _looked_up(cur: DataFrame, plan: RepairPlan, f: FD, table: DataFrame) -> DataFrame:
    """cur with __y and __origin of its left-side values."""
    names = {x(a): f"__k_{a}" for a in f.lhs}
    t = table.select(*[F.col(a).alias(b) for a, b in names.items()], F.col("y").alias("__y"), F.col("origin").alias("__origin"))
    same = (lambda a, b: a.eqNullSafe(b)) if plan.nulls == "value" else (lambda a, b: a == b)
    return cur.join(t, [same(c, F.col(f"__k_{a}")) for a, c in zip(f.lhs, known(plan, f))], "left").drop(*names.values())


def merged(cur: DataFrame, plan: RepairPlan, edges: Edges) -> DataFrame:
    """cur with one value for each shared right side in each component of left-side values that occur together.

    Components join the left-side values of all FDs with that right side; the value is the one with the greatest sum of
    edge quality times rows. The FDs after it see the merged value, so shared right sides go in the plan's order.
    """
    for attribute in plan.shared_rhs():
        fds = [f for f in plan.fds if f.rhs == attribute]
        names = [F.concat_ws("\x1f", F.lit(f.name), *[F.col(f"v_{a}").cast("string") for a in f.lhs]) for f in fds]
        links = None
        for n in names:
            part = cur.select(names[0].alias("a"), n.alias("b"))
            links = part if links is None else links.union(part)
        found = components(links.distinct())
        votes = None
        for f in fds:
            t = edges.tables[f].select(F.concat_ws("\x1f", F.lit(f.name), *[F.col(x(a)).cast("string") for a in f.lhs]).alias("node"), "y", (F.col("quality_fp").cast("decimal(38,0)") * F.col("cnt")).alias("votes"))
            votes = t if votes is None else votes.unionByName(t)
        sums = votes.join(found, "node").groupBy("root", "y").agg(F.sum("votes").alias("s"))
        best = sums.groupBy("root").agg(F.min(F.struct((-F.col("s")).alias("s"), "y")).getField("y").alias("y"))
        told = found.select(F.col("node").alias("__node"), F.col("root").alias("__root")).join(best.select(F.col("root").alias("__root"), F.col("y").alias("__y")), "__root")
        cur = cur.withColumn("__node", names[0]).join(told, "__node", "left").withColumn(f"v_{attribute}", F.coalesce("__y", f"v_{attribute}")).drop("__node", "__root", "__y")
    return cur.withColumn("__conflict", F.lit(0))


def expression(plan: RepairPlan) -> Column:
    """The composed patterns of a chase row as text: members of one composition joined by " > ", independent ones by " & "."""
    shown = []
    for group in parts(plan.fds):
        wanted = F.array(*[F.lit(f.name) for f in group])
        steps = F.filter("__trace", lambda s: F.array_contains(wanted, s.fd) & s.rhs.isNotNull())
        shown.append(F.array_join(F.transform(steps, lambda s: F.concat(F.lit("["), s.fd, F.lit(": "), s.lhs, F.lit(" -> "), s.rhs, F.lit("]"))), " > "))
    return F.array_join(F.filter(F.array(*shown), lambda t: t != ""), " & ")


def apply(df: DataFrame, plan: RepairPlan, chased: DataFrame) -> DataFrame:
    """The table with free attributes as chased (a value stays where the chase has none), old values in __old_<attribute>.

    One join on the bound attributes, the only step that touches all columns.
    """
    key = key_of(plan)
    changing = plan.free if plan.on_conflict != "overwrite" else plan.attributes
    small = chased.select(*[F.col(a).alias(f"__k_{a}") for a in key], *[F.col(f"v_{a}").alias(f"__n_{a}") for a in changing], "__conflict")
    met = df.join(small, [df[a].eqNullSafe(small[f"__k_{a}"]) for a in key], "left")
    return met.select(*[F.coalesce(F.col(f"__n_{c}"), F.col(c)).alias(c) if c in changing else F.col(c) for c in df.columns], *[F.col(a).alias(f"__old_{a}") for a in changing], "__conflict")


def changes(applied: DataFrame, attributes, tid: str) -> DataFrame:
    """tid, attribute, old, new of the cells that differ; only changed rows are unfolded."""
    cells = [F.struct(F.lit(a).alias("attribute"), F.col(f"__old_{a}").cast("string").alias("old"), F.col(a).cast("string").alias("new"), (~F.col(a).eqNullSafe(F.col(f"__old_{a}"))).alias("differs")) for a in attributes]
    any_change = F.lit(False)
    for a in attributes:
        any_change = any_change | ~F.col(a).eqNullSafe(F.col(f"__old_{a}"))
    return applied.where(any_change).select(F.col(tid).alias("tid"), F.inline(F.array(*cells))).where("differs").drop("differs")


def repair(
    df: DataFrame,
    fds,
    tid: str,
    strategy: str = "hybrid",
    theta: float = 0.5,
    *,
    plan: RepairPlan | None = None,
    score: str = "full",
    normalize: str = "avg",
    weight: str = "uniform",
    theta_on: str = "quality",
    strict: bool = False,
    anchor: bool = True,
    scope: Column | None = None,
    keep: bool = True,
    edges: Edges | None = None,
    projected: DataFrame | None = None,
    **options,
) -> RepairResult:
    """Repairs df by the FDs; tid is a column with a unique id of each row.

    options go to the plan (reach, back_edges, on_conflict, nulls, lhs_source, prefer_bound, ...). scope: rows to repair; all
    rows are counted. keep: write the distinct projection and the patterns, which are used several times, to the shared folder.
    edges, projected: those of another repair of df with the same plan, score and weight, so that several strategies share them.
    """
    plan = plan or (edges.plan if edges else build_plan(fds, df.schema, **options))
    if projected is None:
        projected = project(df, plan.attributes, tid)
        if keep:
            projected = written(projected)
    edges = edges or edge_quality(projected, plan, score=score, normalize=normalize, weight=weight, keep=keep)
    decisions = choose(edges, strategy, theta=theta, theta_on=theta_on, strict=strict, anchor=anchor)
    if plan.on_conflict == "deferred":
        inside = [f for f in plan.fds if all(plan.component[a] == plan.component[f.rhs] for a in f.lhs)]
        decisions = with_claims(edges, decisions, inside)
    if keep:
        decisions = written_all(decisions)
    return finish(df, plan, projected, edges, decisions, tid, scope)


def finish(df: DataFrame, plan: RepairPlan, projected: DataFrame, edges: Edges | None, decisions: dict[FD, DataFrame], tid: str, scope: Column | None = None) -> RepairResult:
    """Chase and application of given decisions."""
    chased, tables = chase(projected, plan, decisions)
    if plan.on_conflict == "component":
        chased = merged(chased, plan, edges)
    target = df if scope is None else df.where(scope)
    applied = apply(target, plan, chased)
    touched = plan.free if plan.on_conflict != "overwrite" else plan.attributes
    repaired = applied.select(*df.columns)
    if scope is not None:
        repaired = repaired.unionByName(df.where(~F.coalesce(scope, F.lit(False))))
    conflicts = chased.where("__conflict > 0")
    return RepairResult(repaired, plan, chased, tables, edges, decisions, changes(applied, touched, tid), tid, conflicts)


def repair_until_stable(df: DataFrame, fds, tid: str, strategy: str = "hybrid", max_rounds: int = 5, **options) -> tuple[RepairResult, int]:
    """(the last round's result, rounds): repairs the repaired table again until nothing changes.

    Needed only where left sides are read from the input or where conflicts remain; a chain is stable after one round. The number of
    changed cells is all that the driver sees of a round.
    """
    current, result, rounds = df, None, 0
    for rounds in range(1, max_rounds + 1):
        result = repair(current, fds, tid, strategy, **options)
        if result.delta.isEmpty():
            break
        current = written(result.df)
    return result, rounds


def deferred(edges: Edges, f: FD) -> DataFrame:
    """x_<lhs>, y, rounds: decisions for an FD of a cycle in which no two left sides share a right side where that can be avoided.

    In each round every left side without a value claims its best value that is still free, and each value keeps its best
    claimant (quality, count, then the smaller left side); the others claim their next best. Rounds end when nothing is claimed.
    """
    key = list(map(x, f.lhs))
    rest = written(edges.tables[f].select(*key, "y", "quality_fp", "cnt"))
    kept, n = None, 0
    while not rest.isEmpty():
        n += 1
        claim = rest.groupBy(*key).agg(F.min(F.struct((-F.col("quality_fp")).alias("q"), (-F.col("cnt")).alias("c"), "y")).alias("b")).select(*key, "b.*")
        won = written(claim.groupBy("y").agg(F.min(F.struct("q", "c", *key)).alias("b")).select(*[F.col(f"b.{a}").alias(a) for a in key], "y", F.lit(n).alias("rounds")))
        kept = won if kept is None else kept.unionByName(won)
        rest = written(rest.join(won.select(*key), key, "left_anti").join(won.select("y"), "y", "left_anti"))
    return kept if kept is not None else rest.select(*key, "y", F.lit(0).alias("rounds"))


def with_claims(edges: Edges, decisions: dict[FD, DataFrame], fds) -> dict[FD, DataFrame]:
    """decisions with those of the given FDs replaced by deferred claims; left sides that got no value of their own keep the decision they had."""
    out = dict(decisions)
    for f in fds:
        key = list(map(x, f.lhs))
        claims = deferred(edges, f).select(*key, F.col("y").alias("__y"))
        told = decisions[f].join(claims, key, "left")
        columns = decisions[f].columns
        out[f] = told.withColumn("origin", F.when(F.col("__y").isNotNull(), "claim").otherwise(F.col("origin"))).withColumn("y", F.coalesce("__y", "y")).select(*columns)
    return out
