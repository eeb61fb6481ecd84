"""Queries of baselines, exact references, worked examples and experiments."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import workloads
from ..baselines import best_of, conflict_cover, exact_chase, exact_minimal, exact_pattern_preserving, majority, sampling, similarity
from ..baselines.similarity import similar_pairs
from ..operators import chase, errors, metrics, patterns, quality
from ..operators.store import written
from ..plans import build_plan, parse
from ..sources.tables import CHAIN, CUSTOMER_SCORED, VIEWS, table
from . import twin
from .methods import RATE, SETS, dirty, script

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

# The example table of cyclists.
CYCLISTS = "values (1, 166, 'Marcel Kittel', 'Russia', 'Berlin'), (2, 166, 'Marcel Kittel', 'Germany', 'Berlin'), (3, 166, 'Andre Greipel', 'Germany', 'Berlin'), (4, 21, 'Emanuel Buchmann', 'Germany', 'Berlin'), (5, 98, 'Paul Martens', 'Germany', 'Berlin')"
TOUR = f"select * from ({CYCLISTS}) as t(tid, rank, cyclist, country, capital)"
TOUR_FDS = "cyclist -> country; country -> capital"


def add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def _baselines() -> None:
    def major(spark, sf_dir):
        _, df, fds = dirty(spark, sf_dir, "orders", "mix")
        r = majority(df, fds, "tid")
        return r.df.select("tid", *r.plan.attributes)

    s = script("orders", "mix")
    s.repair(CHAIN, "greedy", score="freq")
    add("base_majority", major, s.say(s.repaired()))

    def drawn(spark, sf_dir):
        _, df, fds = dirty(spark, sf_dir, "orders")
        r = sampling(df, fds, "tid", 1)
        return r.df.select("tid", *r.plan.attributes)

    s = script("orders")
    s.drawn(CHAIN)
    add("base_sampling_seed", drawn, s.say(s.repaired()))
    runs = []
    for seed in range(1, 6):
        s = script("customer")
        s.drawn(CUSTOMER_SCORED, seed)
        runs.append(s.say(f"select *, {seed} as seed from ({s.accuracy()})"))
    add("base_sampling_best_of_5", lambda spark, d: (lambda x: best_of(x[1], x[2], "tid", x[0])[1])(dirty(spark, d, "customer")), " union all ".join(f"select * from ({r})" for r in runs))

    def pairs(spark, sf_dir):
        _, df, fds = dirty(spark, sf_dir, "customer", "typo")
        plan = build_plan(fds, df.schema)
        f = next(f for f in plan.fds if f.name == "n_name->r_name")
        return similar_pairs(written(patterns.simple(patterns.project(df, plan.attributes, "tid"), f)), f)

    s = script("customer", "typo")
    s.plan(CUSTOMER_SCORED)
    f = next(f for f in s.p.fds if f.name == "n_name->r_name")
    base = f"select {s.key(f)} as lhs, y as rhs, cnt, {s.key(f)} || '|' || y as text from {s.pat[f]}"
    near = "levenshtein(a.text, b.text) * 1000 <= greatest(length(a.text), length(b.text)) * 200"
    add("base_similarity_pairs", pairs, s.say(f"select a.lhs, a.rhs, a.cnt, b.lhs as lhs2, b.rhs as rhs2, b.cnt as cnt2 from ({base}) a join ({base}) b on a.text <> b.text where (b.cnt > a.cnt or (b.cnt = a.cnt and b.text < a.text)) and {near}"))

    def similar(spark, sf_dir):
        truth, df, fds = dirty(spark, sf_dir, "customer", "typo")
        r = similarity(df, fds, "tid")
        return metrics.accuracy(df, r.df, truth, "tid", r.plan.free)

    s = script("customer", "typo")
    s.similar(CUSTOMER_SCORED)
    add("base_similarity", similar, s.say(s.accuracy()))

    def covered(spark, sf_dir, part, which, kind):
        truth, df, fds = dirty(spark, sf_dir, which, kind)
        r = conflict_cover(df, fds, "tid")
        if part == "fresh":
            return r.fresh
        return r.delta if part == "cost" else metrics.accuracy(df, r.df, truth, "tid", build_plan(fds, df.schema).free)

    for name, which, kind in (("base_conflict_cover", "orders", "mix"), ("base_conflict_cover_customer", "customer", "swap"), ("base_conflict_cover_case2", "case2", "swap"), ("base_conflict_cover_composite", "composite", "swap")):
        s = script(which, kind)
        last = s.conflict_cover(SETS[which][1])
        cells = list(dict.fromkeys(a for f in s.p.fds for a in (*f.lhs, f.rhs)))
        add(name, lambda spark, d, w=which, k=kind: covered(spark, d, "accuracy", w, k), s.say(s.accuracy()))
        fresh = " union all ".join(f"select '{a}' as attribute, coalesce(sum(case when {s.known(a)} is null then 1 else 0 end), 0)::bigint as fresh_values from {last}" for a in cells)
        add(name.replace("base_conflict_cover", "metric_fresh_values"), lambda spark, d, w=which, k=kind: covered(spark, d, "fresh", w, k), s.say(fresh))

    def rounds(spark, sf_dir, which, n):
        from ..baselines.conflict_cover import one_round

        _, df, fds = dirty(spark, sf_dir, which)
        plan = build_plan(fds, df.schema)
        for k in range(n):
            df = written(one_round(df, plan.fds, "tid", tag=k + 1))
        return df.select("tid", *plan.attributes)

    for which, n in (("case2", 1), ("orders", 1), ("orders", 2)):
        s = script(which)
        fds = build_plan(SETS[which][1]).fds
        for k in range(n):
            s.cover_round(fds, k + 1)
        add(f"base_conflict_round{n}" + ("" if which == "case2" else f"_{which}"), lambda spark, d, w=which, n=n: rounds(spark, d, w, n), s.say(f"select tid, {', '.join(build_plan(SETS[which][1]).attributes)} from {s.dirty}"))


FLAGS = "select row_number() over (order by l_returnflag, l_linestatus) as tid, * from (select distinct l_returnflag, l_linestatus from lineitem)"
FLAG_FDS = "l_returnflag -> l_linestatus; l_linestatus -> l_returnflag"


def _flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The different pairs of flag and status of all line items, six in any size of the table."""
    pairs = table(spark, sf_dir, "lineitem").select("l_returnflag", "l_linestatus").distinct()
    return pairs.withColumn("tid", F.row_number().over(Window.orderBy("l_returnflag", "l_linestatus")))


def _instances(fds: str, rows: int, rule: str) -> str:
    """Every instance of the pairs of flag and status that satisfies the FDs, over the values that occur, by enumeration; and the rule that picks some."""
    listed = build_plan(fds).fds
    listed = parse(fds)
    attributes = list(dict.fromkeys(a for f in listed for a in (*f.lhs, f.rhs)))
    domain = ", ".join(f"(select distinct {a} from base) d_{a}" for a in attributes)
    every = f"with base as materialized ({FLAGS}), alt as materialized (select {', '.join(f'd_{a}.{a}' for a in attributes)} from {domain})"
    ids = range(1, rows + 1)
    same = lambda i, j, names: "(" + " and ".join(f"a{i}.{a} = a{j}.{a}" for a in names) + ")"
    holds = [f"({'not ' + same(i, j, f.lhs)} or a{i}.{f.rhs} = a{j}.{f.rhs})" for f in listed for i in ids for j in ids if i < j]
    cost = " + ".join(f"(a{i}.{a} <> b{i}.{a})::int" for i in ids for a in attributes)
    quality = " + ".join(f"{same(i, j, (*f.lhs, f.rhs))}::int" for f in listed for i in ids for j in ids)
    cells = "concat_ws('; ', " + ", ".join(f"concat_ws('|', {', '.join(f'a{i}.{a}' for a in attributes)})" for i in ids) + ")"
    tables = ", ".join([*(f"alt a{i}" for i in ids), *(f"(select * from base where tid = {i}) b{i}" for i in ids)])
    found = f"found as materialized (select ({cost})::int as cost, ({quality})::int as quality, {cells} as cells from {tables} where {' and '.join(holds)})"
    return f"{every}, {found} {rule}"


def _exact() -> None:
    shown = lambda df: df.select("cost", "quality", F.array_join("cells", "; ").alias("cells"))
    least = "cost = (select min(cost) from found)"
    add("exact_minimal", lambda spark, d: shown(exact_minimal(_flags(spark, d), FLAG_FDS, "tid")), _instances(FLAG_FDS, 6, f"select * from found where {least}"))
    add("exact_pattern_preserving", lambda spark, d: shown(exact_pattern_preserving(_flags(spark, d), FLAG_FDS, "tid")), _instances(FLAG_FDS, 6, f"select * from found where {least} and quality = (select max(quality) from found where {least})"))
    add("exact_knapsack", lambda spark, d: shown(exact_pattern_preserving(_flags(spark, d), FLAG_FDS, "tid", k=5)), _instances(FLAG_FDS, 6, "select * from found where cost <= 5 and quality = (select max(quality) from found where cost <= 5)"))

    def best(spark, sf_dir):
        df = VIEWS["customer_wide"](spark, sf_dir)
        _, df, fds = dirty(spark, sf_dir, "customer")
        plan = build_plan(fds, df.schema)
        projected = written(patterns.project(df, plan.attributes, "tid"))
        return exact_chase(quality.edge_quality(projected, plan), projected)

    s = script("customer")
    p = s.plan(CUSTOMER_SCORED)
    s.quality()
    cur = f"select distinct {', '.join(p.bound)}, {', '.join(f'{a} as v_{a}' for a in p.bound)}, 0::bigint as t from {s.proj}"
    assigned = set(p.bound)
    for f in p.fds:
        on = " and ".join(f"c.v_{a} = q.x_{a}" for a in f.lhs)
        if f.rhs in assigned:
            cur = f"select c.* exclude (t), c.t + coalesce(q.quality_fp, 0) as t from ({cur}) c left join {s.q[f]} q on {on} and c.v_{f.rhs} = q.y"
        else:
            cur = f"select c.* exclude (t), q.y as v_{f.rhs}, c.t + coalesce(q.quality_fp, 0) as t from ({cur}) c left join {s.q[f]} q on {on}"
        assigned.add(f.rhs)
    free = ", ".join(f"v_{a}" for a in p.free)
    bound = ", ".join(p.bound)
    add("exact_chase", best, s.say(f"select {bound}, {free}, t as total_fp from (select *, row_number() over (partition by {bound} order by t desc, {free}) as k from ({cur})) where k = 1"))


def _examples() -> None:
    # the examples' FDs, with customers for cyclists, nations for countries and regions for capitals
    chain, ranked = "c_name -> n_name; n_name -> r_name", "o_custkey -> c_name; c_name -> o_custkey; c_name -> n_name; n_name -> r_name"
    for name, fds, options in (("example_tour", chain, {}), ("example_tour_rank", ranked, {"prefer_bound": ["o_custkey"], "reach": "path", "back_edges": "outside"})):
        s = twin.Script("orders_wide").inject(fds, RATE, kind="swap")
        s.plan(fds, **options)
        s.quality()

        def rated(spark, sf_dir, fds=fds, options=options):
            df = errors.inject(VIEWS["orders_wide"](spark, sf_dir), fds, "tid", RATE)[0]
            plan = build_plan(fds, df.schema, **options)
            return quality.edge_quality(written(patterns.project(df, plan.attributes, "tid")), plan).long()

        add(f"{name}_quality", rated, s.say(s.quality_long()))
    s = twin.Script(TOUR)
    s.repair(TOUR_FDS, "hybrid")
    add("example_tour_repair", lambda spark, d: chase.repair(spark.sql(TOUR), TOUR_FDS, "tid").delta, s.say(s.delta()))
    add("example_tour_expressions", lambda spark, d: chase.repair(spark.sql(TOUR), TOUR_FDS, "tid").expressions, s.say(s.expressions()))

    def gained(spark, sf_dir):
        df = spark.sql(TOUR)
        return metrics.gain(chase.repair(df, TOUR_FDS, "tid").df, df, TOUR_FDS)

    before, after = twin.quality_of(s.dirty, TOUR_FDS), twin.quality_of(s.fixed, TOUR_FDS)
    add("example_tour_gain", gained, s.say(f"select b::bigint as before, a::bigint as after, (a - b)::bigint as gain from (select {before} as b, {after} as a)"))


STRATEGIES = {"greedy": ("greedy", {}), "cover": ("cover", {}), "hybrid": ("hybrid", {}), "greedy_confidence": ("greedy", {"weight": "confidence"}), "cover_confidence": ("cover", {"weight": "confidence"}), "majority": ("greedy", {"score": "freq"})}


def _sweep_sql(which: str, algorithms, kind: str, settings: list[tuple[int | None, float]]) -> str:
    """Accuracy rows of a sweep: one script for each setting and algorithm."""
    view, fds = SETS[which]
    out = []
    for percent, rate in settings:
        where = "true" if percent is None else f"tid * 100 <= (select max(tid) from ({twin.VIEWS[view]})) * {percent}"
        first = "" if percent is None else f"{percent} as percent, "
        for name in algorithms:
            said = []
            for seed in range(1, 6) if name == "sampling" else (1,):
                s = twin.Script(view, where).inject(fds, rate, kind=kind)
                if name == "sampling":
                    s.drawn(fds, seed)
                elif name == "similarity":
                    s.similar(fds)
                elif name == "conflict_cover":
                    s.conflict_cover(fds)
                else:
                    strategy, options = STRATEGIES[name]
                    s.repair(fds, strategy, **options)
                said.append(s.say(f"select *, {seed} as seed from ({s.accuracy()})"))
            best = " union all ".join(f"select * from ({x})" for x in said)
            out.append(f"select {first}'{name}' as algorithm, '{kind}' as kind, {rate}::double as rate, * exclude (seed) from ({best}) order by f1 desc nulls last, seed limit 1")
    return " union all ".join(f"select * from ({o})" for o in out)


PERCENTS, RATES = (20, 40, 60, 80, 100), (0.01, 0.02, 0.04, 0.06, 0.08, 0.10)


def _sweeps() -> None:
    """Precision and recall of all algorithms against size and error rate on two tables, five sizes and six rates; sampling is the best of five runs."""
    families = {"own": ("greedy", "cover", "hybrid"), "base": ("majority", "conflict_cover"), "similarity": ("similarity",), "sampling": ("sampling",)}
    for which in ("orders", "customer"):
        view, fds = SETS[which]
        for family, names in families.items():
            add(f"w1_size_{which}_{family}", lambda spark, d, v=view, f=fds, n=names: workloads.size_sweep(VIEWS[v](spark, d), f, PERCENTS, algorithms=n), _sweep_sql(which, names, "swap", [(p, 0.05) for p in PERCENTS]))
            add(f"w2_rate_{which}_{family}", lambda spark, d, v=view, f=fds, n=names: workloads.rate_sweep(VIEWS[v](spark, d), f, RATES, algorithms=n), _sweep_sql(which, names, "swap", [(None, r) for r in RATES]))
    own = ("greedy", "cover", "hybrid", "greedy_confidence", "majority")
    for which, kind in (("orders", "typo"), ("orders", "mix"), ("customer", "typo"), ("orders", "null")):
        view, fds = SETS[which]
        add(f"w2_rate_{which}_{kind}", lambda spark, d, v=view, f=fds, k=kind: workloads.rate_sweep(VIEWS[v](spark, d), f, (0.02, 0.10), kind=k, algorithms=own), _sweep_sql(which, own, kind, [(None, 0.02), (None, 0.1)]))
    thetas = (0.0, 0.5, 1.1)
    ways: list[tuple[str, str, dict, float | None]] = [("greedy", "greedy", {}, None), ("no_reach", "greedy", {"score": "local"}, None), ("declared_order", "greedy", {"ordered": False}, None), ("input_lhs", "greedy", {"lhs_source": "input"}, None), ("majority", "greedy", {"score": "freq"}, None)]
    ways += [(f"hybrid_{scale}", "hybrid", {"choice": {"theta": theta, "theta_on": scale}}, theta) for theta in thetas for scale in ("quality", "confidence")]
    out = []
    for name, strategy, options, theta in ways:
        s = script("orders", "mix")
        s.repair(CHAIN, strategy, **options)
        out.append(s.say(f"select '{name}' as algorithm, 'mix' as kind, 0.05::double as rate, *, {'null' if theta is None else theta}::double as theta from ({s.accuracy()})"))
    add("w6_ablation_orders", lambda spark, d: workloads.ablate(VIEWS["orders_wide"](spark, d), CHAIN, thetas=thetas), " union all ".join(f"select * from ({o})" for o in out))


for part in (_baselines, _exact, _examples, _sweeps):
    part()
