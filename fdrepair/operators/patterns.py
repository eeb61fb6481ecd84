"""Weighted distinct projection, FD patterns with their counts, and the instance graph."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans import FD, RepairPlan

SCALE = 1_000_000_000  # shares are kept as integers of so many parts, so that sums do not depend on the order of rows


def x(attribute: str) -> str:
    """Column of a left-side attribute in a pattern table."""
    return f"x_{attribute}"


def values(column, f: FD) -> Column:
    """The left-side values of an FD as a list of texts: a key for tables that hold several FDs. column: gives an attribute's column."""
    return F.array(*[column(a).cast("string") for a in f.lhs])


def project(df: DataFrame, attributes, tid: str) -> DataFrame:
    """The distinct values of the attributes with __w (how many rows) and __min_tid (the first of them).

    Everything that follows works on this: one shuffle after a partial aggregation, few columns of the table read.
    """
    return df.groupBy(*attributes).agg(F.count(F.lit(1)).alias("__w"), F.min(tid).alias("__min_tid"))


def simple(projected: DataFrame, f: FD, nulls: str = "missing", tables: int = 1) -> DataFrame:
    """x_<lhs>..., y, cnt, first_tid, lhs_cnt, n, conf_fp, sup_fp: the patterns of one FD.

    n is the number of rows of the table (tables: how many of that size are in projected, with no value in common). Patterns with a null on either side are no patterns unless nulls count as values.
    """
    total = F.broadcast(projected.agg((F.sum("__w") if tables == 1 else F.floor(F.sum("__w") / tables)).alias("n")))  # one row
    rows = projected
    if nulls == "missing":
        for a in (*f.lhs, f.rhs):
            rows = rows.where(F.col(a).isNotNull())
    left = [F.col(a).alias(x(a)) for a in f.lhs]
    counted = rows.groupBy(*left, F.col(f.rhs).alias("y")).agg(F.sum("__w").alias("cnt"), F.min("__min_tid").alias("first_tid"))
    full = counted.withColumn("lhs_cnt", F.sum("cnt").over(Window.partitionBy(*map(x, f.lhs)))).crossJoin(total)
    share = lambda a, b: F.floor(F.col(a).cast("double") / F.col(b) * SCALE).cast("long")
    return full.withColumns({"conf_fp": share("cnt", "lhs_cnt"), "sup_fp": share("cnt", "n")})


def text_of(f: FD) -> list:
    """fd, lhs (values as text, joined), rhs (as text): a pattern as the long tables show it."""
    return [F.lit(f.name).alias("fd"), F.concat_ws("|", *[F.col(x(a)).cast("string") for a in f.lhs]).alias("lhs"), F.col("y").cast("string").alias("rhs")]


def pattern_table(projected: DataFrame, plan: RepairPlan) -> DataFrame:
    """fd, lhs, rhs, cnt, lhs_cnt, n, conf_fp, sup_fp of all FDs."""
    out = None
    for f in plan.fds:
        part = simple(projected, f, plan.nulls).select(*text_of(f), "cnt", "lhs_cnt", "n", "conf_fp", "sup_fp")
        out = part if out is None else out.unionByName(part)
    return out


def pattern_counts_one_pass(projected: DataFrame, plan: RepairPlan) -> DataFrame:
    """fd, lhs, rhs, cnt of all FDs by one aggregation; for tables whose projection can't be kept.

    Left sides are grouped as lists of values, so values that hold the sign between them stay apart.
    """
    sides = F.array(*[F.struct(F.lit(f.name).alias("fd"), values(F.col, f).alias("left"), F.col(f.rhs).cast("string").alias("rhs")) for f in plan.fds])
    rows = projected.select("__w", F.inline(sides))
    if plan.nulls == "missing":
        rows = rows.where(F.col("rhs").isNotNull() & ~F.exists("left", lambda v: v.isNull()))
    return rows.groupBy("fd", "left", "rhs").agg(F.sum("__w").alias("cnt")).select("fd", F.array_join("left", "|").alias("lhs"), "rhs", "cnt")


def instance_graph(patterns: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(nodes: attribute, val; edges: fd, src_attribute, src, dst_attribute, dst, cnt) of a pattern table."""
    edges = patterns.select("fd", F.split_part("fd", F.lit("->"), F.lit(1)).alias("src_attribute"), F.col("lhs").alias("src"), F.split_part("fd", F.lit("->"), F.lit(2)).alias("dst_attribute"), F.col("rhs").alias("dst"), "cnt")
    nodes = edges.select(F.col("src_attribute").alias("attribute"), F.col("src").alias("val")).union(edges.select("dst_attribute", "dst")).distinct()
    return nodes, edges


def of_tuples(df: DataFrame, plan: RepairPlan, tid: str) -> DataFrame:
    """tid, fd, lhs, rhs: the patterns of each row."""
    made = [F.struct(F.lit(f.name).alias("fd"), F.concat_ws("|", *[F.col(a).cast("string") for a in f.lhs]).alias("lhs"), F.col(f.rhs).cast("string").alias("rhs")) for f in plan.fds]
    return df.select(F.col(tid).alias("tid"), F.inline(F.array(*made)))


def sizes(projected: DataFrame, plan: RepairPlan) -> DataFrame:
    """n, distinct_rows, edges, nodes, max_fan_out: how large the graph is and how far the projection shrinks the table."""
    table = pattern_table(projected, plan)
    nodes, edges = instance_graph(table)
    fan = edges.groupBy("fd", "src").agg(F.count(F.lit(1)).alias("k"))
    one = projected.agg(F.sum("__w").alias("n"), F.count(F.lit(1)).alias("distinct_rows"))
    return one.crossJoin(edges.agg(F.count(F.lit(1)).alias("edges"))).crossJoin(nodes.agg(F.count(F.lit(1)).alias("nodes"))).crossJoin(fan.agg(F.max("k").alias("max_fan_out")))
