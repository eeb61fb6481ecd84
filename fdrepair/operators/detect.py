"""Consistency of a table with its FDs: violating groups, rows, pairs, and how many rows would have to go."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import FD, parse


def _counts(df: DataFrame, f: FD) -> DataFrame:
    rows = df
    for a in (*f.lhs, f.rhs):
        rows = rows.where(F.col(a).isNotNull())
    each = rows.groupBy(*f.lhs, f.rhs).agg(F.count(F.lit(1)).alias("__c"))
    return each.groupBy(*f.lhs).agg(F.sum("__c").alias("__s"), F.max("__c").alias("__m"), F.sum(F.col("__c") * F.col("__c")).alias("__q"), F.count(F.lit(1)).alias("__k"))


def violations(df: DataFrame, fds) -> DataFrame:
    """fd, groups, violating_groups, violating_rows, violating_pairs, g3: one row for each FD, without making pairs."""
    out = None
    for f in parse(fds, df.schema):
        bad = F.col("__k") > 1
        total = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("long")
        part = _counts(df, f).agg(F.count(F.lit(1)).alias("groups"), total(F.when(bad, 1).otherwise(0)).alias("violating_groups"), total(F.when(bad, F.col("__s")).otherwise(0)).alias("violating_rows"), total(F.when(bad, F.expr("(__s * __s - __q) div 2")).otherwise(0)).alias("violating_pairs"), total(F.col("__s") - F.col("__m")).alias("g3"))
        part = part.select(F.lit(f.name).alias("fd"), "*")
        out = part if out is None else out.unionByName(part)
    return out


def satisfies(df: DataFrame, fds) -> bool:
    return violations(df, fds).where("violating_groups > 0").isEmpty()


def fd_error(df: DataFrame, fd) -> DataFrame:
    """fd, g3, n, ratio: rows to drop until the FD holds."""
    f = parse([fd], df.schema)[0]
    return _counts(df, f).agg(F.coalesce(F.sum(F.col("__s") - F.col("__m")), F.lit(0)).alias("g3"), F.coalesce(F.sum("__s"), F.lit(0)).alias("n")).select(F.lit(f.name).alias("fd"), "g3", "n", F.round(F.col("g3") / F.greatest("n", F.lit(1)), 6).alias("ratio"))


def violating_rows(df: DataFrame, fd, tid: str) -> DataFrame:
    """Ids of the rows in violating groups."""
    f = parse([fd], df.schema)[0]
    bad = _counts(df, f).where("__k > 1").select(*[F.col(a).alias(f"b_{a}") for a in f.lhs])
    return df.join(bad, [df[a] == bad[f"b_{a}"] for a in f.lhs], "left_semi").select(tid)


def bound_distinct(df: DataFrame, attributes) -> dict[str, int]:
    """Approximate numbers of distinct values, for choosing what is bound in a cycle; one pass."""
    row = df.agg(*[F.approx_count_distinct(a).alias(a) for a in attributes]).first()
    return row.asDict()
