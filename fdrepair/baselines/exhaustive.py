"""Exact answers for tiny tables: all repairs of least cost, the one among them with most gain, and the best chase.

Exponential by nature; inputs are guarded.
"""

from __future__ import annotations

from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.patterns import x
from ..operators.quality import Edges
from ..plans import parse

MOST = 300_000


def all_repairs(df: DataFrame, fds, tid: str) -> DataFrame:
    """cost, quality, cells (array of rows as text): every instance over the active domain that satisfies the FDs.

    Alternatives of each row are crossed with those of the other rows, on the executors; the number of combinations is checked first.
    """
    listed = parse(fds, df.schema)
    attributes = list(dict.fromkeys(a for f in listed for a in (*f.lhs, f.rhs)))
    rows = df.select(tid, *attributes).orderBy(tid).collect()
    if len(rows) > 12:
        raise ValueError("only for tiny tables")
    domains = {a: sorted({r[a] for r in rows if r[a] is not None}, key=str) for a in attributes}
    alternatives = 1
    for a in attributes:
        alternatives *= max(1, len(domains[a]))
    if alternatives ** len(rows) > MOST:
        raise ValueError(f"{alternatives}^{len(rows)} instances are too many")
    spark, out = df.sparkSession, None
    for k, r in enumerate(rows):
        made = [(tuple(map(str, v)), sum(str(r[a]) != str(w) for a, w in zip(attributes, v))) for v in product(*(domains[a] for a in attributes))]
        choice = spark.createDataFrame(made, f"t{k} struct<{','.join(f'`{a}`:string' for a in attributes)}>, c{k} int").coalesce(1)
        out = choice if out is None else out.crossJoin(choice)
    n = len(rows)
    for f in listed:
        for i in range(n):
            for j in range(i + 1, n):
                same = F.lit(True)
                for a in f.lhs:
                    same = same & (F.col(f"t{i}.{a}") == F.col(f"t{j}.{a}"))
                out = out.where(~same | (F.col(f"t{i}.{f.rhs}") == F.col(f"t{j}.{f.rhs}")))
    quality = F.lit(0)
    for f in listed:
        for i in range(n):
            for j in range(n):
                same = F.lit(True)
                for a in (*f.lhs, f.rhs):
                    same = same & (F.col(f"t{i}.{a}") == F.col(f"t{j}.{a}"))
                quality = quality + F.when(same, 1).otherwise(0)
    cost = F.lit(0)
    for k in range(n):
        cost = cost + F.col(f"c{k}")
    cells = F.array(*[F.concat_ws("|", *[F.col(f"t{k}.{a}") for a in attributes]) for k in range(n)])
    return out.select(cost.alias("cost"), quality.alias("quality"), cells.alias("cells"))


def exact_minimal(df: DataFrame, fds, tid: str) -> DataFrame:
    """All repairs of least cost."""
    every = all_repairs(df, fds, tid)
    return every.join(every.agg(F.min("cost").alias("least")), F.col("cost") == F.col("least")).drop("least")


def exact_pattern_preserving(df: DataFrame, fds, tid: str, k: int | None = None) -> DataFrame:
    """Repairs with the greatest instance quality among those of least cost, or among those of cost at most k."""
    pool = exact_minimal(df, fds, tid) if k is None else all_repairs(df, fds, tid).where(F.col("cost") <= k)
    return pool.join(pool.agg(F.max("quality").alias("most")), F.col("quality") == F.col("most")).drop("most")


def exact_chase(edges: Edges, betas: DataFrame) -> DataFrame:
    """The bound values, v_<attribute> and total_fp of the chase with the greatest sum of edge qualities for each bound assignment.

    Every edge of each FD is followed, so the work grows with the product of the fan-outs.
    """
    plan = edges.plan
    cur = betas.select(*plan.bound).distinct()
    cur = cur.withColumns({f"v_{a}": F.col(a) for a in plan.bound} | {"total_fp": F.lit(0).cast("long")})
    assigned = set(plan.bound)
    for f in plan.fds:
        t = edges.tables[f].select(*[F.col(x(a)).alias(f"k_{a}") for a in f.lhs], F.col("y"), F.col("quality_fp"))
        on = [F.col(f"v_{a}") == F.col(f"k_{a}") for a in f.lhs]
        if f.rhs in assigned:
            on.append(F.col(f"v_{f.rhs}") == F.col("y"))
        cur = cur.join(t, on, "left").withColumn("total_fp", F.col("total_fp") + F.coalesce("quality_fp", F.lit(0)))
        if f.rhs not in assigned:
            cur = cur.withColumn(f"v_{f.rhs}", F.col("y"))
        assigned.add(f.rhs)
        cur = cur.drop("y", "quality_fp", *[f"k_{a}" for a in f.lhs])
    free = [F.col(f"v_{a}") for a in plan.free]
    best = cur.groupBy(*plan.bound).agg(F.min(F.struct((-F.col("total_fp")).alias("t"), *free)).alias("b"))
    return best.select(*plan.bound, *[F.col(f"b.v_{a}").alias(f"v_{a}") for a in plan.free], (-F.col("b.t")).alias("total_fp"))
