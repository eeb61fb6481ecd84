"""Pattern counts that grow with new rows: counts add up, so old rows are not read again."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import FD
from .patterns import x


def counted(df: DataFrame, f: FD, tid: str) -> DataFrame:
    """x_<lhs>..., y, cnt, first_tid of some rows."""
    rows = df
    for a in (*f.lhs, f.rhs):
        rows = rows.where(F.col(a).isNotNull())
    return rows.groupBy(*[F.col(a).alias(x(a)) for a in f.lhs], F.col(f.rhs).alias("y")).agg(F.count(F.lit(1)).alias("cnt"), F.min(tid).alias("first_tid"))


def merged(old: DataFrame, new: DataFrame, f: FD) -> DataFrame:
    """Both counts together."""
    return old.unionByName(new).groupBy(*map(x, f.lhs), "y").agg(F.sum("cnt").alias("cnt"), F.min("first_tid").alias("first_tid"))


def affected(old: DataFrame, new: DataFrame, f: FD) -> DataFrame:
    """x_<lhs>... of the left sides whose most frequent right side is another after the new rows (ties: the smaller value), or that are new."""
    best = lambda t, name: t.groupBy(*map(x, f.lhs)).agg(F.min(F.struct((-F.col("cnt")).alias("c"), "y")).getField("y").alias(name))
    touched = new.select(*map(x, f.lhs)).distinct()
    after = best(merged(old, new, f).join(touched, list(map(x, f.lhs)), "left_semi"), "after")
    before = best(old.join(touched, list(map(x, f.lhs)), "left_semi"), "before")
    return after.join(before, list(map(x, f.lhs)), "left").where("not (after <=> before)").select(*map(x, f.lhs))
