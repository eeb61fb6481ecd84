"""Accuracy against the truth, cost, instance quality and gain."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import parse


def accuracy(dirty: DataFrame, repaired: DataFrame, truth: DataFrame, tid: str, attributes) -> DataFrame:
    """changed, correct, dirty, fixed, precision, recall, f1 over the cells of the attributes.

    Precision: changed cells that equal the truth over changed cells (null if none changed). Recall: dirty cells that equal the
    truth over dirty cells (null if none was dirty).
    """
    pick = lambda df, p: df.select(F.col(tid).alias(f"{p}_tid"), *[F.col(a).alias(f"{p}_{a}") for a in attributes])
    d, r, t = pick(dirty, "d"), pick(repaired, "r"), pick(truth, "t")
    met = d.join(r, F.col("d_tid") == F.col("r_tid")).join(t, F.col("d_tid") == F.col("t_tid"))
    one = met.agg(*tallies([(F.col(f"d_{a}"), F.col(f"r_{a}"), F.col(f"t_{a}")) for a in attributes]))
    return shares(one)


def tallies(cells, rows: Column | None = None) -> list[Column]:
    """Aggregates changed, correct, dirty, fixed of cells given as (dirty, repaired, true); rows: how many rows a row stands for."""
    rows = F.lit(1) if rows is None else rows
    sums = {"changed": F.lit(0), "correct": F.lit(0), "dirty": F.lit(0), "fixed": F.lit(0)}
    for was, now, true in cells:
        changed, wrong, right = ~was.eqNullSafe(now), ~was.eqNullSafe(true), now.eqNullSafe(true)
        for name, c in (("changed", changed), ("correct", changed & right), ("dirty", wrong), ("fixed", wrong & right)):
            sums[name] = sums[name] + F.when(c, 1).otherwise(0)
    return [F.coalesce(F.sum(c * rows), F.lit(0)).cast("long").alias(n) for n, c in sums.items()]


def shares(tallied: DataFrame, *labels: str) -> DataFrame:
    """The labels and tallies with precision, recall and f1."""
    precision, recall = F.col("correct") / F.nullif(F.col("changed"), F.lit(0)), F.col("fixed") / F.nullif(F.col("dirty"), F.lit(0))
    f1 = 2 * precision * recall / F.nullif(precision + recall, F.lit(0.0))
    return tallied.select(*labels, "changed", "correct", "dirty", "fixed", F.round(precision, 6).alias("precision"), F.round(recall, 6).alias("recall"), F.round(f1, 6).alias("f1"))


def cost(before: DataFrame, after: DataFrame, tid: str, attributes) -> DataFrame:
    """attribute, changed: cells that differ, by attribute (a cell counts 0 if equal and 1 if not)."""
    b, a = before.select(F.col(tid).alias("b_tid"), *[F.col(c).alias(f"b_{c}") for c in attributes]), after.select(F.col(tid).alias("a_tid"), *[F.col(c).alias(f"a_{c}") for c in attributes])
    cells = F.array(*[F.struct(F.lit(c).alias("attribute"), F.when(F.col(f"b_{c}").eqNullSafe(F.col(f"a_{c}")), 0).otherwise(1).alias("d")) for c in attributes])
    return b.join(a, F.col("b_tid") == F.col("a_tid")).select(F.inline(cells)).groupBy("attribute").agg(F.sum("d").alias("changed"))


def instance_quality(df: DataFrame, fds) -> DataFrame:
    """quality: for every row, how often each of its patterns occurs, added up; the sum over patterns of their squared counts."""
    out = None
    for f in parse(fds, df.schema):
        rows = df
        for a in f.attributes:
            rows = rows.where(F.col(a).isNotNull())
        part = rows.groupBy(*f.lhs, f.rhs).agg(F.count(F.lit(1)).alias("__c")).agg(F.coalesce(F.sum(F.col("__c") * F.col("__c")), F.lit(0)).alias("q"))
        out = part if out is None else out.unionByName(part)
    return out.agg(F.sum("q").alias("quality"))


def gain(after: DataFrame, before: DataFrame, fds) -> DataFrame:
    """before, after, gain: instance quality of both and its increase."""
    return instance_quality(before, fds).withColumnRenamed("quality", "before").crossJoin(instance_quality(after, fds).withColumnRenamed("quality", "after")).withColumn("gain", F.col("after") - F.col("before"))
