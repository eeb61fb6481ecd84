"""One of the possible repairs, drawn by a seed: each left side takes the right side of one of its rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import chase, metrics
from ..operators.chase import RepairResult
from ..operators.errors import MODULUS
from ..operators.patterns import project, x
from ..operators.store import written
from ..plans import build_plan


def draw(tid: Column, seed: int) -> Column:
    """A number that orders the rows of a group differently for each seed, in plain integer arithmetic."""
    h = (tid.cast("long") * 40_503 + F.lit(seed * 7_919).cast("long")) % MODULUS
    return (h * h + F.lit(seed * 104_729).cast("long") + tid) % MODULUS


def sampling(df: DataFrame, fds, tid: str, seed: int = 1, projected: DataFrame | None = None, **options) -> RepairResult:
    """The FDs in their order, each left side with the right side of the row that the seed draws among those with that left side. projected: df's, if there is one."""
    plan = build_plan(fds, df.schema, **options)
    projected = written(project(df, plan.attributes, tid)) if projected is None else projected
    decisions = {}
    for f in plan.fds:
        rows = df
        for a in (*f.lhs, f.rhs):
            rows = rows.where(F.col(a).isNotNull())
        drawn = rows.groupBy(*[F.col(a).alias(x(a)) for a in f.lhs]).agg(F.min(F.struct(draw(F.col(tid), seed).alias("h"), F.col(tid).alias("t"), F.col(f.rhs).alias("y"))).alias("b"), F.count_distinct(f.rhs).alias("rivals"))
        zero = F.lit(0).cast("long")
        decisions[f] = written(drawn.select(*map(x, f.lhs), F.col("b.y").alias("y"), zero.alias("score_fp"), zero.alias("quality_fp"), zero.alias("cnt"), "rivals", F.lit("drawn").alias("origin")))
    return chase.finish(df, plan, projected, None, decisions, tid)


def best_of(df: DataFrame, fds, tid: str, truth: DataFrame, seeds=(1, 2, 3, 4, 5), **options) -> tuple[RepairResult, DataFrame]:
    """(the repair of the seed with the greatest F1, the scores of all seeds). One row of scores for each seed is all that the driver sees."""
    projected = written(project(df, build_plan(fds, df.schema, **options).attributes, tid))
    results, scores = {}, None
    for s in seeds:
        r = results[s] = sampling(df, fds, tid, s, projected, **options)
        one = written(metrics.accuracy(df, r.df, truth, tid, r.plan.free).withColumn("seed", F.lit(s)))
        scores = one if scores is None else scores.unionByName(one)
    best = scores.orderBy(F.desc_nulls_last("f1"), "seed").first()
    return results[best["seed"]], scores
