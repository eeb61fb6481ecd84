"""Few changes by the conflicts of all FDs together: cells with most conflicts are given up, and take what the FDs that determine them agree on, or a fresh value.

Two rows of a group with different right sides are a conflict, and every cell of the FD in either row is part of it. A cell's
degree is the number of its conflicts, added up over all FDs; it comes from group sizes (rows of the group less rows with the same
value), so pairs are never made. In each round every violating group keeps one value, the one whose cells have the lowest mean degree, and each row with
another value gives up its cell of highest degree among the FD's attributes, on the left or on the right; so all conflicts are covered. A cell given up takes the value that
the kept values of all FDs with it on the right agree on, if that is another one than it had, else a fresh value. A fresh value is
unknown: it is equal to no value and in conflict with none (a marked text between rounds, null in columns of other types and in the result). Rounds after
``max_rounds`` assign fresh values only, which makes no new conflict, so one of them ends it.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from ..operators.store import written
from ..plans import FD, build_plan

FRESH = "⊥"
PARTS = 1000  # of a mean degree


@dataclass
class CoverResult:
    df: DataFrame
    delta: DataFrame
    fresh: DataFrame
    rounds: int


def known(df: DataFrame, attribute: str) -> Column:
    """The value of a cell, null if it is fresh."""
    value = F.col(attribute)
    return F.when(~value.startswith(FRESH), value) if isinstance(df.schema[attribute].dataType, StringType) else value


def degrees(df: DataFrame, fds: list[FD]) -> DataFrame:
    """df with __conf<k>, the conflicts of each row by FD k, and __deg_<attribute>, those of its cells over all FDs."""
    out = df
    for k, f in enumerate(fds):
        rows = df.select(*[known(df, a).alias(f"__g_{a}") for a in f.lhs], known(df, f.rhs).alias("__v")).na.drop()
        each = rows.groupBy(*[f"__g_{a}" for a in f.lhs], "__v").agg(F.count(F.lit(1)).alias("__c"))
        whole = each.groupBy(*[F.col(f"__g_{a}").alias(f"__h_{a}") for a in f.lhs]).agg(F.sum("__c").alias("__s"), F.count(F.lit(1)).alias("__k")).where("__k > 1")
        conflicts = each.join(whole, [F.col(f"__g_{a}") == F.col(f"__h_{a}") for a in f.lhs]).select(*[f"__g_{a}" for a in f.lhs], "__v", (F.col("__s") - F.col("__c")).alias(f"__conf{k}"))
        out = out.join(conflicts, [out[a] == F.col(f"__g_{a}") for a in f.lhs] + [out[f.rhs] == F.col("__v")], "left").drop("__v", *[f"__g_{a}" for a in f.lhs])
    zero = F.lit(0).cast("long")
    out = out.withColumns({f"__conf{k}": F.coalesce(F.col(f"__conf{k}"), zero) for k in range(len(fds))})
    touched = dict.fromkeys(a for f in fds for a in (*f.lhs, f.rhs))
    return out.withColumns({f"__deg_{a}": sum((F.col(f"__conf{k}") for k, f in enumerate(fds) if a in f.attributes), zero) for a in touched})


def one_round(df: DataFrame, fds, tid: str, only_fresh: bool = False, tag: int = 1) -> DataFrame:
    """df with the cells given up of one round, all FDs at once."""
    fds = list(fds)
    rated = written(degrees(df, fds))
    out = rated
    for k, f in enumerate(fds):
        rows = rated.select(*[known(df, a).alias(f"__g_{a}") for a in f.lhs], known(df, f.rhs).alias("__v"), f"__deg_{f.rhs}").na.drop()
        each = rows.groupBy(*[f"__g_{a}" for a in f.lhs], "__v").agg(F.count(F.lit(1)).alias("__c"), F.sum(f"__deg_{f.rhs}").alias("__d"))
        mean = F.expr(f"__d * {PARTS} div __c")
        kept = each.groupBy(*[f"__g_{a}" for a in f.lhs]).agg(F.min(F.struct(mean.alias("d"), (-F.col("__c")).alias("c"), F.col("__v").alias("v"))).getField("v").alias(f"__kept{k}"))
        out = out.join(kept, [out[a] == F.col(f"__g_{a}") for a in f.lhs], "left").drop(*[f"__g_{a}" for a in f.lhs])
    gone: dict[str, Column] = {}
    for k, f in enumerate(fds):
        loses = (F.col(f"__conf{k}") > 0) & (F.col(f.rhs) != F.col(f"__kept{k}"))
        cells = [f.rhs, *f.lhs]  # ties go to the first
        most = F.greatest(*[F.col(f"__deg_{a}") for a in cells])
        before = F.lit(False)
        for a in cells:
            here = (F.col(f"__deg_{a}") == most) & ~before
            before = before | here
            gone[a] = gone.get(a, F.lit(False)) | F.coalesce(loses & here, F.lit(False))
    new = {}
    for a, given_up in gone.items():
        kind = df.schema[a].dataType
        fresh = F.concat(F.lit(f"{FRESH}{a}#"), F.col(tid).cast("string"), F.lit(f"#{tag}")) if isinstance(kind, StringType) else F.lit(None).cast(kind)
        told = [F.col(f"__kept{k}") for k, f in enumerate(fds) if f.rhs == a]
        if told and not only_fresh:
            agreed = F.coalesce(*told) if len(told) > 1 else told[0]
            clash = F.lit(False)
            for t in told:
                clash = clash | F.coalesce(t != agreed, F.lit(False))
            fresh = F.when(agreed.isNotNull() & ~clash & (agreed != F.col(a)), agreed).otherwise(fresh)
        new[a] = F.when(given_up, fresh).otherwise(F.col(a))
    return out.select(*[new[c].alias(c) if c in new else F.col(c) for c in df.columns])


def unsettled(df: DataFrame, fds) -> DataFrame:
    """Violating groups by FD, fresh values left out."""
    from ..operators.detect import violations

    attributes = dict.fromkeys(a for f in fds for a in (*f.lhs, f.rhs))
    return violations(df.select(*[known(df, a).alias(a) for a in attributes]), fds).where("violating_groups > 0")


def conflict_cover(df: DataFrame, fds, tid: str, max_rounds: int = 4, **options) -> CoverResult:
    """Rounds until no group has two values. fresh: attribute, fresh_values."""
    from ..operators.metrics import cost

    plan = build_plan(fds, df.schema, **options)
    current, rounds = df, 0
    while not unsettled(current, plan.fds).isEmpty():
        rounds += 1
        current = written(one_round(current, plan.fds, tid, only_fresh=rounds > max_rounds, tag=rounds))
    cells = list(dict.fromkeys(a for f in plan.fds for a in (*f.lhs, f.rhs)))
    made = F.array(*[F.struct(F.lit(a).alias("attribute"), known(current, a).isNull().alias("new")) for a in cells])
    fresh = current.select(F.inline(made)).groupBy("attribute").agg(F.sum(F.when(F.col("new"), 1).otherwise(0)).alias("fresh_values"))
    done = current.withColumns({a: known(current, a) for a in cells})
    return CoverResult(done, cost(df, done, tid, cells), fresh, rounds)
