"""Choice of one edge for each left-side value: greedy, by repair covers, or mixed by a threshold."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import FD
from .patterns import SCALE, x
from .quality import Edges, floored


def _best(t: DataFrame, f: FD, score: str, origin: Column) -> DataFrame:
    """x_<lhs>..., y, score_fp, quality_fp, cnt, rivals, origin: the best edge of each left side; ties by count, then the smaller value."""
    pick = F.struct((-F.col(score)).alias("s"), (-F.col("cnt")).alias("c"), "y", "quality_fp", origin.alias("origin"))
    best = t.groupBy(*map(x, f.lhs)).agg(F.min(pick).alias("b"), F.count(F.lit(1)).alias("rivals"))
    return best.select(*map(x, f.lhs), F.col("b.y").alias("y"), (-F.col("b.s")).alias("score_fp"), F.col("b.quality_fp").alias("quality_fp"), (-F.col("b.c")).alias("cnt"), "rivals", F.col("b.origin").alias("origin"))


def node_best(edges: Edges, f: FD, anchor: bool = True) -> list[DataFrame]:
    """For each FD that touches f's right-side attribute: y, q, the best incident edge of each value; f's own only without anchor."""
    out = []
    for g, t in edges.tables.items():
        if g == f:
            if not anchor:
                out.append(t.groupBy("y").agg(F.max("quality_fp").alias("q")))
        elif g.rhs == f.rhs:
            out.append(t.groupBy("y").agg(F.max("quality_fp").alias("q")))
        elif f.rhs in g.lhs:
            out.append(t.groupBy(F.col(x(f.rhs)).alias("y")).agg(F.max("quality_fp").alias("q")))
    return out


def cover_scores(edges: Edges, f: FD, anchor: bool = True, candidates: DataFrame | None = None) -> DataFrame:
    """Edges of f with cover_fp: the mean quality of the best repair cover of the value they lead to.

    The best cover takes the best edge of each FD on its own, so covers are never listed. With anchor the edge of f is the candidate
    itself, else any edge of f to the same value. A bound attribute's values have no cover: the edge's own quality stands.
    """
    t = edges.tables[f] if candidates is None else candidates
    if f.rhs in edges.plan.bound:
        return t.withColumn("cover_fp", F.col("quality_fp"))
    total, number = (F.col("quality_fp"), F.lit(1)) if anchor else (F.lit(0).cast("long"), F.lit(0))
    for k, best in enumerate(node_best(edges, f, anchor)):
        t = t.join(best.select(F.col("y").alias(f"y{k}"), F.col("q").alias(f"q{k}")), F.col("y").eqNullSafe(F.col(f"y{k}")), "left").drop(f"y{k}")
        total = total + F.coalesce(F.col(f"q{k}"), F.lit(0))
        number = number + F.when(F.col(f"q{k}").isNotNull(), 1).otherwise(0)
    helpers = [c for c in t.columns if c[:1] == "q" and c[1:].isdigit()]
    return t.withColumn("cover_fp", floored(total.cast("double") / number)).drop(*helpers)


def greedy(edges: Edges, f: FD) -> DataFrame:
    return _best(edges.tables[f], f, "quality_fp", F.lit("greedy"))


def cover(edges: Edges, f: FD, anchor: bool = True) -> DataFrame:
    return _best(cover_scores(edges, f, anchor), f, "cover_fp", F.lit("cover"))


def hybrid(edges: Edges, f: FD, theta: float = 0.5, theta_on: str = "quality", strict: bool = False, anchor: bool = True) -> DataFrame:
    """Greedy where the best adjacent edge reaches theta, covers for the other left sides only."""
    measure, bar = ("quality_fp" if theta_on == "quality" else "conf_fp"), int(round(theta * SCALE))
    t = edges.tables[f]
    top = t.groupBy(*[F.col(x(a)).alias(f"t_{a}") for a in f.lhs]).agg(F.max(measure).alias("top_fp"))
    met = t.join(top, [F.col(x(a)).eqNullSafe(F.col(f"t_{a}")) for a in f.lhs]).drop(*[f"t_{a}" for a in f.lhs])
    enough = F.col("top_fp") > bar if strict else F.col("top_fp") >= bar
    easy = met.where(enough).drop("top_fp")
    hard = met.where(~enough).drop("top_fp")
    return _best(easy, f, "quality_fp", F.lit("greedy")).unionByName(_best(cover_scores(edges, f, anchor, hard), f, "cover_fp", F.lit("cover")))


def choose(edges: Edges, strategy: str = "hybrid", **options) -> dict[FD, DataFrame]:
    """A decision table for each FD: the edge to take from each left-side value. None of it depends on a row of the table."""
    ways = {"greedy": greedy, "cover": cover, "hybrid": hybrid}
    if strategy not in ways:
        raise ValueError(f"{strategy!r} is none of {', '.join(ways)}")
    used = {"greedy": (), "cover": ("anchor",), "hybrid": ("theta", "theta_on", "strict", "anchor")}[strategy]
    return {f: ways[strategy](edges, f, **{k: v for k, v in options.items() if k in used}) for f in edges.plan.fds}


def long(decisions: dict[FD, DataFrame]) -> DataFrame:
    """fd, lhs, rhs, score_fp, rivals, origin of all decisions."""
    out = None
    for f, t in decisions.items():
        part = t.select(F.lit(f.name).alias("fd"), F.concat_ws("|", *[F.col(x(a)).cast("string") for a in f.lhs]).alias("lhs"), F.col("y").cast("string").alias("rhs"), "score_fp", "rivals", "origin")
        out = part if out is None else out.unionByName(part)
    return out


def mix(decisions: dict[FD, DataFrame]) -> DataFrame:
    """fd, origin, decisions: how many were taken greedily and how many by covers."""
    return long(decisions).groupBy("fd", "origin").agg(F.count(F.lit(1)).alias("decisions"))
