"""Deterministic errors for experiments: which cells are hit is integer arithmetic on the row's id, the same in any SQL engine."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import NumericType

from ..plans import parse

# Fixed values of the hash.
MODULUS, A, B, C = 1_000_003, 48_271, 104_729, 15_485_863


def place(tid: Column, salt: int) -> Column:
    """A row's number below MODULUS; squaring keeps different salts apart."""
    h = (tid * A + F.lit(salt * B).cast("long")) % MODULUS
    return (h * h + F.lit(salt * C).cast("long") + tid) % MODULUS


def hit(tid: Column, salt: int, rate: float) -> Column:
    """Whether a row is hit."""
    return place(tid, salt) < int(rate * MODULUS)


def swapped(df: DataFrame, column: str) -> DataFrame:
    """__v, __other: for each value of a column the next one in order (the first after the last)."""
    values = df.select(F.col(column).alias("__v")).where("__v is not null").distinct()
    order = Window.orderBy("__v")  # over distinct values of one column
    return values.select("__v", F.coalesce(F.lead("__v").over(order), F.first("__v").over(order)).alias("__other"))


def inject(df: DataFrame, fds, tid: str, rate: float, seed: int = 1, kind: str = "swap", side: str = "rhs", detectable: bool = True) -> tuple[DataFrame, DataFrame]:
    """(dirty, log): for each FD, about ``rate`` of the rows get a wrong right side.

    kind: swap (another value of the column), typo (a sign added, or 1000 to a number), null, or mix (swap on even ids, typo
    on odd ones). side: rhs, or lhs (its first attribute). detectable: only rows whose left side occurs twice or more. log: tid, attribute, truth, dirty.
    """
    listed = parse(fds, df.schema)
    out, truth = df, {}
    for k, f in enumerate(listed):
        column = f.rhs if side == "rhs" else f.lhs[0]
        salt = k + 10 * seed
        chosen = hit(F.col(tid).cast("long"), salt, rate)
        if detectable:
            groups = df.groupBy(*[F.col(a).alias(f"__g_{a}") for a in f.lhs]).agg(F.count(F.lit(1)).alias("__size")).where("__size > 1")
            keyed = df.join(groups, [df[a] == groups[f"__g_{a}"] for a in f.lhs], "left_semi").where(chosen).select(F.col(tid).alias("__tid"))
            out = out.join(keyed.withColumn("__hit", F.lit(True)), out[tid] == keyed["__tid"], "left").drop("__tid").withColumn("__hit", F.coalesce("__hit", F.lit(False)))
        else:
            out = out.withColumn("__hit", chosen)
        value = F.col(column)
        typo = value + 1000 if isinstance(df.schema[column].dataType, NumericType) else F.concat(value, F.lit("~"))
        if kind in ("swap", "mix"):
            others = swapped(df, column)
            out = out.join(others, out[column] == others["__v"], "left").drop("__v")
            even = F.pmod(F.col(tid).cast("long"), F.lit(2)) == 0
            wrong = F.col("__other") if kind == "swap" else F.when(even, F.col("__other")).otherwise(typo)
        else:
            wrong = typo if kind == "typo" else F.lit(None)
        truth.setdefault(column, True)
        out = out.withColumn(column, F.when(F.col("__hit"), wrong.cast(df.schema[column].dataType)).otherwise(value)).drop("__hit", "__other")
    out = out.select(*df.columns)
    cells = list(truth)
    left, right = df.select(F.col(tid).alias("t"), *[F.col(c).alias(f"t_{c}") for c in cells]), out.select(F.col(tid).alias("d"), *[F.col(c).alias(f"d_{c}") for c in cells])
    pairs = F.array(*[F.struct(F.lit(c).alias("attribute"), F.col(f"t_{c}").cast("string").alias("truth"), F.col(f"d_{c}").cast("string").alias("dirty")) for c in cells])
    log = left.join(right, F.col("t") == F.col("d")).select(F.col("t").alias("tid"), F.inline(pairs)).where("not (truth <=> dirty)")
    return out, log


def inject_each(df: DataFrame, fds, tid: str, rates, seed: int = 1, kind: str = "swap") -> DataFrame:
    """The dirty tables that ``inject`` gives for several rates, in one: setting (the rate's position), df's columns, and t_<column> with the truth of those hit.

    What a row may be hit by doesn't depend on the rate, so it is found once, in the table itself; only then is there a row for each rate.
    """
    listed = parse(fds, df.schema)
    out, first = df, {}
    for k, f in enumerate(listed):
        groups = df.groupBy(*[F.col(a).alias(f"__g_{a}") for a in f.lhs]).agg(F.count(F.lit(1)).alias("__size")).where("__size > 1")
        out = out.join(groups, [out[a] == groups[f"__g_{a}"] for a in f.lhs], "left")
        at = F.when(F.col("__size").isNotNull(), place(F.col(tid).cast("long"), k + 10 * seed))
        out = out.withColumn(f"__at{k}", at).drop("__size", *[f"__g_{a}" for a in f.lhs])
        if kind in ("swap", "mix") and f.rhs not in first:
            others = swapped(df, f.rhs)
            out = out.join(others, out[f.rhs] == others["__v"], "left").drop("__v").withColumnRenamed("__other", f"__other{k}")
        first.setdefault(f.rhs, k)
    settings = F.array(*[F.struct(F.lit(n).alias("setting"), F.lit(int(r * MODULUS)).alias("__limit")) for n, r in enumerate(rates)])
    out = out.withColumns({f"t_{a}": F.col(a) for a in first}).select("*", F.inline(settings))
    even = F.pmod(F.col(tid).cast("long"), F.lit(2)) == 0
    for k, f in enumerate(listed):
        value, number = F.col(f.rhs), isinstance(df.schema[f.rhs].dataType, NumericType)
        typo = value + 1000 if number else F.concat(value, F.lit("~"))
        if kind in ("swap", "mix"):
            if first[f.rhs] != k:  # what an FD before it left
                others = swapped(df, f.rhs)
                out = out.join(others, out[f.rhs] == others["__v"], "left").drop("__v").withColumnRenamed("__other", f"__other{k}")
            other = F.col(f"__other{k}")
            wrong = other if kind == "swap" else F.when(even, other).otherwise(typo)
        else:
            wrong = typo if kind == "typo" else F.lit(None)
        out = out.withColumn(f.rhs, F.when(F.col(f"__at{k}") < F.col("__limit"), wrong.cast(df.schema[f.rhs].dataType)).otherwise(value))
    return out.select("setting", *df.columns, *[f"t_{a}" for a in first])
