"""The experiments: accuracy against size and error rate, ablations, and run time, on tables that stand in for the original ones."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator
from contextlib import contextmanager
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .baselines import best_of, conflict_cover, sampling, similarity
from .operators import chase, errors, metrics
from .operators.patterns import project
from .operators.quality import edge_quality
from .operators.store import freed, written
from .plans import build_plan

#: Own strategies by name: strategy and options.
OWN = {
    "greedy": ("greedy", {}),
    "cover": ("cover", {}),
    "hybrid": ("hybrid", {"theta": 0.5}),
    "greedy_confidence": ("greedy", {"weight": "confidence"}),
    "cover_confidence": ("cover", {"weight": "confidence"}),
    "hybrid_confidence": ("hybrid", {"theta": 0.5, "weight": "confidence", "theta_on": "confidence"}),
    "greedy_best": ("greedy", {"weight": "best"}),
    "majority": ("greedy", {"score": "freq"}),
    "no_reach": ("greedy", {"score": "local"}),
    "declared_order": ("greedy", {"ordered": False}),
    "input_lhs": ("greedy", {"lhs_source": "input"}),
}
MADE_BY = ("score", "normalize", "weight")  # options that edges depend on; the plan's are the others


class Shared:
    """Repairs of one dirty table; those with the same plan and weights have one projection and one set of edges."""

    def __init__(self, dirty: DataFrame, fds, tid: str = "tid", projected: DataFrame | None = None, tables: int = 1) -> None:
        self.dirty, self.fds, self.tid, self.tables, self.made = dirty, fds, tid, tables, {} if projected is None else {"projected": projected}

    def edges(self, **options):
        key = tuple(sorted(options.items()))
        if key not in self.made:
            rating = {k: v for k, v in options.items() if k in MADE_BY}
            plan = build_plan(self.fds, self.dirty.schema, **{k: v for k, v in options.items() if k not in MADE_BY})
            if "projected" not in self.made:
                self.made["projected"] = written(project(self.dirty, plan.attributes, self.tid))
            self.made[key] = edge_quality(self.made["projected"], plan, tables=self.tables, **rating)
        return self.made[key]

    def repair(self, strategy: str, **options) -> chase.RepairResult:
        choice = {k: options.pop(k) for k in ("theta", "theta_on") if k in options}
        edges = self.edges(**options)
        return chase.repair(self.dirty, self.fds, self.tid, strategy, edges=edges, projected=self.made["projected"], **choice)


#: Algorithms by name: (dirty, fds, tid, truth) -> (repaired, free attributes).
ALGORITHMS = {name: lambda d, f, t, _, w=way: _own(Shared(d, f, t).repair(w[0], **w[1])) for name, way in OWN.items()} | {
    "sampling": lambda d, f, t, truth: _own(best_of(d, f, t, truth)[0]),
    "sampling_once": lambda d, f, t, _: _own(sampling(d, f, t, 1)),
    "similarity": lambda d, f, t, _: _own(similarity(d, f, t)),
    "conflict_cover": lambda d, f, t, _: (conflict_cover(d, f, t).df, tuple(build_plan(f, d.schema).free)),
}


def _own(result) -> tuple[DataFrame, tuple[str, ...]]:
    return result.df, result.plan.free


@contextmanager
def by_measured_size(spark: SparkSession) -> Iterator[None]:
    """Joins are broadcast by the size that a shuffle has measured only: repetitive tables are many times as large in memory as their files, and a broadcast table passes the driver."""
    static, measured = "spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold"
    before = {k: spark.conf.get(k, None) for k in (static, measured)}
    spark.conf.set(measured, before[measured] or spark.conf.get(static))
    spark.conf.set(static, "-1")
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def measure(truth: DataFrame, fds, algorithms: Iterable[str], rate: float, kind: str, seed: int = 1, **labels) -> DataFrame:
    """One row of accuracy for each algorithm on one error setting; algorithms run one after the other. truth: read many times, so a stored table."""
    dirty = written(errors.inject(truth, fds, "tid", rate, seed, kind)[0])
    shared, algorithms = Shared(dirty, fds), list(algorithms)
    for name in algorithms:
        if name in OWN:
            shared.edges(**{k: v for k, v in OWN[name][1].items() if not k.startswith("theta")})

    def one(name: str) -> DataFrame:
        repaired, free = _own(shared.repair(OWN[name][0], **OWN[name][1])) if name in OWN else ALGORITHMS[name](dirty, fds, "tid", truth)
        row = metrics.accuracy(dirty, repaired, truth, "tid", free)
        return written(row.select(*[F.lit(v).alias(k) for k, v in labels.items()], F.lit(name).alias("algorithm"), F.lit(kind).alias("kind"), F.lit(rate).alias("rate"), "*"))

    return one_by_one(truth.sparkSession, one, algorithms)


def kept_apart(dirty: DataFrame, attributes) -> DataFrame:
    """Values of different settings become different values, in the same order: an attribute holds records of the setting and the value, null where that is null."""
    return dirty.withColumns({a: F.when(F.col(a).isNotNull(), F.struct("setting", F.col(a).alias("value"))) for a in attributes})


def measure_rates(truth: DataFrame, fds, algorithms: Iterable[str], rates, kind: str, seed: int = 1) -> DataFrame:
    """What ``measure`` gives for each rate, from one repair by each algorithm: the dirty tables of all rates are repaired as one that holds no value of two of them.

    So there are as many plans and jobs as for one rate. Own strategies see values alone, so equal rows are one with their number.
    """
    spark, plan, algorithms = truth.sparkSession, build_plan(fds, truth.schema), list(algorithms)
    dirty = kept_apart(errors.inject_each(truth, fds, "tid", rates, seed, kind), plan.attributes)
    true, value = [f"t_{a}" for a in plan.free], {f"d_{a}": F.col(a)["value"] for a in plan.free}
    dirty = dirty.select("setting", "tid", *plan.attributes, *true)
    if not OWN.keys() >= set(algorithms):
        dirty = written(dirty)
        rows = dirty.withColumns(value | {"__n": F.lit(1)})
    own = [name for name in algorithms if name in OWN]
    if own:
        equal = written(dirty.groupBy("setting", *plan.attributes, *true).agg(F.count(F.lit(1)).alias("__n"), F.min("tid").alias("tid")))
        projected = written(equal.groupBy(*plan.attributes).agg(F.sum("__n").alias("__w"), F.min("tid").alias("__min_tid")))
        equal = equal.withColumns(value)
        shared = Shared(equal, fds, projected=projected, tables=len(rates))
        for name in own:
            shared.edges(**{k: v for k, v in OWN[name][1].items() if not k.startswith("theta")})
            freed(spark)
    settings = F.inline(F.array(*[F.struct(F.lit(n).alias("setting"), F.lit(float(r)).alias("rate")) for n, r in enumerate(rates)]))

    def scored(repaired: DataFrame) -> DataFrame:
        cells = [(F.col(f"d_{a}"), F.col(a)["value"], F.col(f"t_{a}")) for a in plan.free]
        one = repaired.groupBy("setting").agg(*metrics.tallies(cells, F.col("__n")))
        return metrics.shares(spark.range(1).select(settings).join(one, "setting", "left").na.fill(0, ["changed", "correct", "dirty", "fixed"]), "setting", "rate")

    def one(name: str) -> DataFrame:
        if name in OWN:
            out = scored(shared.repair(OWN[name][0], **OWN[name][1]).df)
        elif name == "conflict_cover":
            out = scored(conflict_cover(rows, fds, "tid").df)
        else:
            drawn = lambda s: written(scored(sampling(rows, fds, "tid", s).df).withColumn("seed", F.lit(s)))
            best = F.row_number().over(Window.partitionBy("setting").orderBy(F.desc_nulls_last("f1"), "seed"))
            out = one_by_one(spark, drawn, [1, 2, 3, 4, 5] if name == "sampling" else [1]).withColumn("best", best).where("best = 1").drop("best", "seed")
        return written(out.select(F.lit(name).alias("algorithm"), F.lit(kind).alias("kind"), "rate", *[c for c in out.columns if c not in ("setting", "rate")]))

    return one_by_one(spark, one, algorithms)


def one_by_one(spark: SparkSession, job: Callable[..., DataFrame], items: list) -> DataFrame:
    """The union of what a job gives for each item; the driver lets go of a job's plans before the next, since its heap grows to its bound otherwise and stays there."""
    out = []
    for i in items:
        out.append(job(i))
        freed(spark)
    return reduce(DataFrame.unionByName, out)


def prefix(df: DataFrame, percent: int, tid: str = "tid", order: str | None = None) -> DataFrame:
    """The share of a table with the smallest ids: a size step of an experiment, not a sample of a result."""
    most = df.agg(F.max(tid).alias("m"))
    return df.crossJoin(F.broadcast(most)).where(F.col(tid) * 100 <= F.col("m") * percent).drop("m")


def size_sweep(truth: DataFrame, fds, percents=(20, 40, 60, 80, 100), rate: float = 0.05, kind: str = "swap", algorithms=("greedy", "cover", "hybrid", "majority")) -> DataFrame:
    """Precision and recall against size; sizes one after the other, so that the driver holds the plans of one."""
    with by_measured_size(truth.sparkSession):
        return reduce(DataFrame.unionByName, [measure(written(prefix(truth, p)), fds, algorithms, rate, kind, percent=p) for p in percents])


def rate_sweep(truth: DataFrame, fds, rates=(0.01, 0.02, 0.04, 0.06, 0.08, 0.10), kind: str = "swap", algorithms=("greedy", "cover", "hybrid", "majority")) -> DataFrame:
    """Precision and recall against the error rate. All rates go through one repair, but for algorithms that compare the texts of values: those take rates one after the other."""
    with by_measured_size(truth.sparkSession):
        truth, alike = written(truth), [n for n in algorithms if n != "similarity"]
        parts = [measure_rates(truth, fds, alike, rates, kind)] if alike else []
        return reduce(DataFrame.unionByName, parts + [measure(truth, fds, ("similarity",), r, kind) for r in rates if "similarity" in algorithms])


def ablate(truth: DataFrame, fds, rate: float = 0.05, kind: str = "mix", thetas=(0.0, 0.25, 0.5, 0.75, 1.1)) -> DataFrame:
    """Parts of the method left out, and thresholds of the mixed strategy on both scales."""
    with by_measured_size(truth.sparkSession):
        truth = written(truth)
        out = measure(truth, fds, ("greedy", "no_reach", "declared_order", "input_lhs", "majority"), rate, kind).withColumn("theta", F.lit(None).cast("double"))
        dirty = written(errors.inject(truth, fds, "tid", rate, 1, kind)[0])
        shared = Shared(dirty, fds)
        shared.edges()

        def mixed(way: tuple[float, str]) -> DataFrame:
            theta, scale = way
            r = shared.repair("hybrid", theta=theta, theta_on=scale)
            row = metrics.accuracy(dirty, r.df, truth, "tid", r.plan.free)
            return written(row.select(F.lit(f"hybrid_{scale}").alias("algorithm"), F.lit(kind).alias("kind"), F.lit(rate).alias("rate"), "*", F.lit(theta).alias("theta")))

        return out.unionByName(one_by_one(truth.sparkSession, mixed, [(t, s) for t in thetas for s in ("quality", "confidence")]))


def run_times(spark: SparkSession, truth: DataFrame, fds, percents=(20, 60, 100), algorithms=("greedy", "hybrid", "cover"), rate: float = 0.05) -> list[dict]:
    """percent, rows, algorithm, seconds, prepared, shuffle_mb: wall time of each repair, its result read in full and thrown away.

    prepared: the part before the result is read (patterns, quality and decisions are written by then). shuffle_mb: what tasks wrote for shuffles, where the status store is at hand.
    """
    out = []
    for p in percents:
        dirty = written(errors.inject(prefix(truth, p), fds, "tid", rate)[0])
        rows = dirty.count()
        for name in algorithms:
            before, began = shuffled(spark), time.perf_counter()
            repaired = ALGORITHMS[name](dirty, fds, "tid", dirty)[0]
            prepared = time.perf_counter() - began
            repaired.write.format("noop").mode("overwrite").save()
            out.append({"percent": p, "rows": rows, "algorithm": name, "seconds": round(time.perf_counter() - began, 3), "prepared": round(prepared, 3), "shuffle_mb": round(shuffled(spark) - before, 1)})
    return out


def shuffled(spark: SparkSession) -> float:
    """MB that this application's tasks have written for shuffles so far."""
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(executors.apply(k).totalShuffleWrite() for k in range(executors.size())) / 1e6
