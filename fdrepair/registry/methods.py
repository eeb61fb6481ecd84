"""Queries of the repair methods, each with its SQL twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import chase, compose, detect, errors, metrics, patterns, quality, select
from ..operators.patterns import SCALE
from ..operators.store import written
from ..plans import build_plan
from ..sources.tables import CASE2, CHAIN, COMPOSITE, CUSTOMER, CUSTOMER_SCORED, CYCLE, LINES, VIEWS
from . import twin

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

RATE = 0.05
CLAIMS = 8  # rounds of claims in SQL, more than the data need
SETS = {"orders": ("orders_wide", CHAIN), "customer": ("customer_wide", CUSTOMER_SCORED), "line": ("lineitem_wide", LINES), "cycle": ("orders_wide", CYCLE), "case2": ("orders_wide", CASE2), "composite": ("customer_desk", COMPOSITE), "four": ("customer_wide", CUSTOMER)}


def add(name: str, query: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def dirty(spark: SparkSession, sf_dir: str, which: str, kind: str = "swap", rate: float = RATE) -> tuple[DataFrame, DataFrame, str]:
    """(truth, dirty, fds) of an experiment's table."""
    view, fds = SETS[which]
    truth = VIEWS[view](spark, sf_dir)
    return truth, errors.inject(truth, fds, "tid", rate, kind=kind)[0], fds


def script(which: str, kind: str = "swap", rate: float = RATE) -> twin.Script:
    view, fds = SETS[which]
    return twin.Script(view).inject(fds, rate, kind=kind)


def edges_for(spark, sf_dir, which, kind="swap", score="full", normalize="avg", weight="uniform", **plan_options):
    _, df, fds = dirty(spark, sf_dir, which, kind)
    plan = build_plan(fds, df.schema, **plan_options)
    return quality.edge_quality(written(patterns.project(df, plan.attributes, "tid")), plan, score=score, normalize=normalize, weight=weight)


def _patterns() -> None:
    for which in SETS:
        s = script(which)
        s.plan(SETS[which][1])

        def table(spark, sf_dir, which=which):
            _, df, fds = dirty(spark, sf_dir, which)
            plan = build_plan(fds, df.schema)
            return patterns.pattern_table(written(patterns.project(df, plan.attributes, "tid")), plan)

        add(f"pat_{which}", table, s.say(s.patterns_long()))
    s = script("orders")
    s.plan(CHAIN)

    def one_pass(spark, sf_dir, which="orders"):
        _, df, fds = dirty(spark, sf_dir, which)
        plan = build_plan(fds, df.schema)
        return patterns.pattern_counts_one_pass(patterns.project(df, plan.attributes, "tid"), plan)

    add("pat_one_pass", one_pass, s.say(f"select fd, lhs, rhs, cnt from ({s.patterns_long()})"))
    c = script("composite")
    c.plan(COMPOSITE)
    add("pat_one_pass_composite", lambda spark, d: one_pass(spark, d, "composite"), c.say(f"select fd, lhs, rhs, cnt from ({c.patterns_long()})"))
    graph = f"select fd, split_part(fd, '->', 1) as src_attribute, lhs as src, split_part(fd, '->', 2) as dst_attribute, rhs as dst, cnt from ({s.patterns_long()})"
    nodes = f"select src_attribute as attribute, src as val from ({graph}) union select dst_attribute, dst from ({graph})"

    def graph_of(spark, sf_dir, part):
        return patterns.instance_graph(QUERIES["pat_orders"](spark, sf_dir))[part]

    add("pat_nodes", lambda spark, d: graph_of(spark, d, 0), s.say(nodes))
    add("pat_edges", lambda spark, d: graph_of(spark, d, 1), s.say(graph))

    def sized(spark, sf_dir):
        _, df, fds = dirty(spark, sf_dir, "orders")
        plan = build_plan(fds, df.schema)
        return patterns.sizes(written(patterns.project(df, plan.attributes, "tid")), plan)

    add("metric_sizes", sized, s.say(f"select (select sum(w)::bigint from {s.proj}) as n, (select count(*) from {s.proj}) as distinct_rows, (select count(*) from ({graph})) as edges, (select count(*) from ({nodes})) as nodes, (select max(k) from (select count(*) as k from ({graph}) group by fd, src)) as max_fan_out"))

    def tuples(spark, sf_dir):
        df = VIEWS["customer_wide"](spark, sf_dir)
        return patterns.of_tuples(df, build_plan(CUSTOMER_SCORED, df.schema), "tid")

    plan = build_plan(CUSTOMER_SCORED)
    add("pat_of_tuples", tuples, twin.Script("customer_wide").say(" union all ".join(f"select tid, '{f.name}' as fd, {f.lhs[0]}::varchar as lhs, {f.rhs}::varchar as rhs from clean" for f in plan.fds)))

    from ..plans.fd import interaction

    for name, which in (("compose_pairs", "customer"), ("compose_pairs_composite", "composite")):
        view, fds = SETS[which]

        def pairs(spark, sf_dir, view=view, fds=fds):
            df = VIEWS[view](spark, sf_dir)
            plan = build_plan(fds, df.schema)
            return compose.composable_pairs(written(patterns.project(df, plan.attributes, "tid")), plan)

        s = twin.Script(view)
        s.plan(fds)
        found = []
        for k, f in enumerate(s.p.fds):
            for g in s.p.fds[k + 1 :]:
                kind = interaction(f, g)
                if kind != "none":
                    on = " and ".join(f"p.{compose.side(f, a)} = q.{compose.side(g, a)}" for a in sorted(f.attributes & g.attributes))
                    p, q = (f"(select {s.key(h)} as lhs, y::varchar as rhs, * from {s.pat[h]})" for h in (f, g))
                    found.append(f"select '{f.name}' as fd1, p.lhs as lhs1, p.rhs as rhs1, '{g.name}' as fd2, q.lhs as lhs2, q.rhs as rhs2, '{kind}' as kind from {p} p join {q} q on {on}")
        add(name, pairs, s.say(" union all ".join(found)))

    def composed(spark, sf_dir):
        df = VIEWS["customer_wide"](spark, sf_dir)
        plan = build_plan("c_nationkey -> n_name; n_name -> r_name", df.schema)
        a, b = plan.fds
        p = compose.pattern(a, [F.col("c_nationkey")], F.col("n_name"))
        q = compose.pattern(b, [F.col("n_name")], F.col("r_name"))
        return df.select("tid", p.alias("p"), q.alias("q")).select("tid", compose.render(compose.compose(F.col("p"), F.col("q"))).alias("composed"), compose.render(compose.maximal(F.array("p", "q"), plan)).alias("largest"), compose.independent(F.col("p"), F.col("q"), plan).alias("apart"))

    text = "'c_nationkey->n_name,n_name->r_name{c_nationkey=' || c_nationkey || ',n_name=' || n_name || ',r_name=' || r_name || '}'"
    add("compose_chain", composed, twin.Script("customer_wide").say(f"select tid, {text} as composed, {text} as largest, false as apart from clean"))


def _quality() -> None:
    grid = {
        "quality_path_orders": ("orders", {"reach": "path"}, {}),
        "quality_distinct_orders": ("orders", {"reach": "distinct"}, {}),
        "quality_confidence_orders": ("orders", {}, {"weight": "confidence"}),
        "quality_best_orders": ("orders", {}, {"weight": "best"}),
        "quality_line": ("line", {}, {}),
        "quality_composite": ("composite", {}, {}),
        "quality_composite_path": ("composite", {"reach": "path"}, {}),
        "quality_case2": ("case2", {}, {}),
        "quality_closing_target": ("cycle", {"reach": "path"}, {}),
        "quality_closing_outside": ("cycle", {"reach": "path", "back_edges": "outside"}, {}),
        "quality_closing_distinct": ("customer", {"reach": "distinct"}, {}),
        "quality_normalize_sum": ("orders", {"reach": "path"}, {"normalize": "sum"}),
        "quality_normalize_max": ("orders", {"reach": "path"}, {"normalize": "max"}),
        "quality_normalize_min": ("orders", {"reach": "path"}, {"normalize": "min"}),
        "quality_ablation_freq": ("orders", {}, {"score": "freq"}),
        "quality_ablation_conf": ("orders", {}, {"score": "conf"}),
        "quality_ablation_sup": ("orders", {}, {"score": "sup"}),
        "quality_ablation_local": ("orders", {}, {"score": "local"}),
    }
    for name, (which, plan_options, options) in grid.items():
        s = script(which)
        s.plan(SETS[which][1], **plan_options)
        s.quality(**options)
        add(name, lambda spark, d, w=which, p=plan_options, o=options: edges_for(spark, d, w, **o, **p).long(), s.say(s.quality_long()))
    s = script("orders")
    s.plan(CHAIN, reach="path")
    s.quality()
    each = " union all ".join(f"select '{','.join(f.lhs)}' as attribute, {s.key(f)} as val, score_fp from {t}" for f, t in s.q.items())
    add("quality_vertex", lambda spark, d: quality.vertex_quality(edges_for(spark, d, "orders", reach="path")), s.say(f"select attribute, val, sum(score_fp)::bigint as sum_fp, floor(sum(score_fp)::double / count(*))::bigint as avg_fp from ({each}) group by all"))


    def along(spark, sf_dir):
        e = edges_for(spark, sf_dir, "orders", reach="path")
        f, g = (next(h for h in e.plan.fds if h.name == n) for n in ("c_nationkey->n_name", "n_name->n_regionkey"))
        left, right = e.tables[f].alias("p"), e.tables[g].alias("q")
        met = left.join(right, F.col("p.y") == F.col("q.x_n_name"))
        return met.select(F.col("p.x_c_nationkey").alias("c_nationkey"), F.col("p.y").alias("n_name"), F.col("q.y").alias("n_regionkey"), quality.composed_quality(F.array("p.quality_fp", "q.quality_fp")).alias("quality_fp"))

    f, g = (next(h for h in s.p.fds if h.name == n) for n in ("c_nationkey->n_name", "n_name->n_regionkey"))
    add("quality_composed", along, s.say(f"select p.x_c_nationkey as c_nationkey, p.y as n_name, q.y as n_regionkey, floor((p.quality_fp + q.quality_fp) / 2.0)::bigint as quality_fp from {s.q[f]} p join {s.q[g]} q on p.y = q.x_n_name"))


def _selection() -> None:
    grid = {
        "select_greedy_orders": ("orders", "greedy", {}),
        "select_cover_orders": ("orders", "cover", {}),
        "select_cover_unanchored": ("orders", "cover", {"anchor": False}),
        "select_hybrid_orders": ("orders", "hybrid", {}),
        "select_hybrid_theta_on_confidence": ("orders", "hybrid", {"theta_on": "confidence"}),
        "select_hybrid_strict": ("orders", "hybrid", {"theta": 0.4, "strict": True}),
        "select_cover_cycle": ("cycle", "cover", {}),
        "select_hybrid_line": ("line", "hybrid", {}),
        "select_greedy_case2": ("case2", "greedy", {}),
        "select_cover_composite": ("composite", "cover", {}),
        "select_hybrid_four": ("four", "hybrid", {}),
    }
    for name, (which, strategy, options) in grid.items():
        s = script(which)
        s.plan(SETS[which][1])
        s.quality()
        s.choose(strategy, **options)
        add(name, lambda spark, d, w=which, st=strategy, o=options: select.long(select.choose(edges_for(spark, d, w), st, **o)), s.say(s.decisions_long()))
        if name == "select_hybrid_theta_on_confidence":
            add("metric_hybrid_mix", lambda spark, d, w=which, st=strategy, o=options: select.mix(select.choose(edges_for(spark, d, w), st, **o)), s.say(f"select fd, origin, count(*) as decisions from ({s.decisions_long()}) group by all"))


def fixed(spark, sf_dir, which, kind="swap", strategy="hybrid", theta=0.5, **options) -> chase.RepairResult:
    _, df, fds = dirty(spark, sf_dir, which, kind)
    return chase.repair(df, fds, "tid", strategy, theta, **options)


def _repairs() -> None:
    grid = {
        "repair_orders_greedy": ("orders", "swap", "greedy", {}),
        "repair_orders_cover": ("orders", "swap", "cover", {}),
        "repair_orders_hybrid": ("orders", "swap", "hybrid", {}),
        "repair_orders_path_typo": ("orders", "typo", "cover", {"reach": "path"}),
        "repair_orders_confidence_mix": ("orders", "mix", "hybrid", {"weight": "confidence"}),
        "repair_orders_best": ("orders", "mix", "greedy", {"weight": "best"}),
        "repair_orders_input_lhs": ("orders", "swap", "greedy", {"lhs_source": "input"}),
        "repair_orders_nulls": ("orders", "null", "greedy", {"weight": "confidence"}),
        "repair_customer_cycle": ("customer", "swap", "hybrid", {}),
        "repair_orders_cycle": ("cycle", "swap", "greedy", {"prefer_bound": ["o_custkey"]}),
        "repair_composite": ("composite", "swap", "hybrid", {}),
        "repair_composite_confidence": ("composite", "mix", "cover", {"weight": "confidence"}),
        "repair_four": ("four", "swap", "greedy", {}),
        "repair_line_case1": ("line", "swap", "hybrid", {}),
        "repair_case2_keep_first": ("case2", "swap", "greedy", {}),
        "repair_case2_overwrite": ("case2", "swap", "greedy", {"on_conflict": "overwrite"}),
    }
    for name, (which, kind, strategy, options) in grid.items():
        s = script(which, kind)
        s.repair(SETS[which][1], strategy, **options)

        def run(spark, sf_dir, which=which, kind=kind, strategy=strategy, options=options):
            r = fixed(spark, sf_dir, which, kind, strategy, **options)
            return r.df.select("tid", *r.plan.attributes)

        add(name, run, s.say(s.repaired()))
        stem = name.removeprefix("repair_")
        if name in ("repair_orders_hybrid", "repair_customer_cycle", "repair_line_case1", "repair_case2_overwrite", "repair_composite"):
            add(f"delta_{stem}", lambda spark, d, a=(which, kind, strategy), o=options: fixed(spark, d, *a, **o).delta, s.say(s.delta()))
        if name in ("repair_orders_hybrid", "repair_orders_cycle", "repair_case2_keep_first", "repair_line_case1", "repair_composite"):
            add(f"rtab_{stem}", lambda spark, d, a=(which, kind, strategy), o=options: fixed(spark, d, *a, **o).repair_tables(), s.say(s.tables_long()))
            add(f"expr_{stem}", lambda spark, d, a=(which, kind, strategy), o=options: fixed(spark, d, *a, **o).expressions, s.say(s.expressions()))
        if name in ("repair_case2_keep_first", "repair_orders_cycle"):
            key = ", ".join(s.key_columns)
            add(f"conflicts_{stem}", lambda spark, d, a=(which, kind, strategy), o=options: (lambda r: r.conflicts.select(*chase.key_of(r.plan), F.col("__conflict").alias("conflict")))(fixed(spark, d, *a, **o)), s.say(f"select {key}, conflict from {s.cur} where conflict > 0"))
    s = script("orders")
    s.repair(CHAIN, "hybrid")
    lines = [f"select '{f.rhs}' as attribute, '{f.name}' as fd, {', '.join(f'{a}::varchar' for a in f.lhs)} as lhs, {f.rhs}::varchar as rhs from {s.fixed} where tid = 7" for f in s.p.fds]
    picked = " union all ".join(f"select '{f.name}' as fd, {s.key(f)} as lhs, round(score_fp / 1e9, 6) as score, origin from {t}" for f, t in s.d.items())
    rivals = f"select fd, lhs, rhs as rival, round(quality_fp / 1e9, 6) as rival_quality from ({s.quality_long()})"
    add("explain_orders", lambda spark, d: fixed(spark, d, "orders").explain(7), s.say(f"select fd, lhs, attribute, rhs, score, origin, rival, rival_quality from ({' union all '.join(lines)}) left join ({picked}) using (fd, lhs) left join ({rivals}) using (fd, lhs)"))
    # merging: one value for each component of left sides
    s = script("case2")
    s.plan(CASE2)
    s.quality()
    s.choose("greedy")
    s.chase()
    s.merge()
    s.apply()
    add("repair_case2_component", lambda spark, d: (lambda r: r.df.select("tid", *r.plan.attributes))(fixed(spark, d, "case2", strategy="greedy", on_conflict="component")), s.say(s.repaired()))

    # deferred claims inside a cycle, alone and in a repair
    s = script("cycle")
    s.plan(CYCLE, prefer_bound=["o_custkey"])
    s.quality()
    inside = [f for f in s.p.fds if all(s.p.component[a] == s.p.component[f.rhs] for a in f.lhs)]
    add("deferred_claims", lambda spark, d: chase.deferred(edges_for(spark, d, "cycle", prefer_bound=["o_custkey"]), inside[0]).withColumn("rounds", F.col("rounds").cast("int")), s.say(s.claims(inside[0], CLAIMS)))
    s.choose("greedy")
    for f in inside:
        told = s.add("claims", s.claims(f, CLAIMS))
        s.d[f] = s.add("pick", f"select d.* replace (coalesce(w.y, d.y) as y, case when w.y is not null then 'claim' else d.origin end as origin) from {s.d[f]} d left join {told} w using ({', '.join(f'x_{a}' for a in f.lhs)})")
    s.chase()
    s.apply()
    add("repair_cycle_deferred", lambda spark, d: (lambda r: r.df.select("tid", *r.plan.attributes))(fixed(spark, d, "cycle", strategy="greedy", on_conflict="deferred", prefer_bound=["o_custkey"])), s.say(s.repaired()))

    # repaired again until nothing changes
    def stable(spark, sf_dir):
        _, df, fds = dirty(spark, sf_dir, "customer")
        r, _ = chase.repair_until_stable(df, fds, "tid", "greedy", max_rounds=3, lhs_source="input")
        return r.df.select("tid", *r.plan.attributes)

    s = script("customer")
    for _ in range(3):
        s.repair(CUSTOMER_SCORED, "greedy", lhs_source="input")
        s.dirty = s.add("again", f"select * exclude ({', '.join(f'old_{a}' for a in s.touched())}) from {s.fixed}")
    add("repair_until_stable", stable, s.say(s.repaired()))

    def scoped(spark, sf_dir):
        _, df, fds = dirty(spark, sf_dir, "orders")
        r = chase.repair(df, fds, "tid", "greedy", scope=F.col("c_mktsegment") == "BUILDING")
        return r.delta

    s = script("orders")
    s.repair(CHAIN, "greedy")
    add("repair_orders_scope", scoped, s.say(f"select * from ({s.delta()}) where tid in (select tid from clean where c_mktsegment = 'BUILDING')"))


def _measures() -> None:
    for which, kind, strategy, options in (("orders", "swap", "hybrid", {}), ("orders", "typo", "greedy", {"weight": "confidence"}), ("customer", "swap", "cover", {}), ("line", "mix", "hybrid", {"weight": "confidence"})):
        s = script(which, kind)
        s.repair(SETS[which][1], strategy, **options)

        def measured(spark, sf_dir, which=which, kind=kind, strategy=strategy, options=options):
            truth, df, fds = dirty(spark, sf_dir, which, kind)
            r = chase.repair(df, fds, "tid", strategy, **options)
            return metrics.accuracy(df, r.df, truth, "tid", r.plan.free)

        add(f"metric_accuracy_{which}_{kind}", measured, s.say(s.accuracy()))
    s = script("orders")
    s.repair(CHAIN, "hybrid")

    def cost(spark, sf_dir):
        _, df, fds = dirty(spark, sf_dir, "orders")
        r = chase.repair(df, fds, "tid")
        return metrics.cost(df, r.df, "tid", r.plan.free)

    add("metric_cost", cost, s.say(" union all ".join(f"select '{a}' as attribute, sum(case when {a} is distinct from old_{a} then 1 else 0 end)::bigint as changed from {s.fixed}" for a in s.p.free)))

    def gained(spark, sf_dir):
        _, df, fds = dirty(spark, sf_dir, "orders")
        return metrics.gain(chase.repair(df, fds, "tid").df, df, fds)

    before, after = twin.quality_of(s.dirty, CHAIN), twin.quality_of(s.fixed, CHAIN)
    add("metric_gain", gained, s.say(f"select b::bigint as before, a::bigint as after, (a - b)::bigint as gain from (select {before} as b, {after} as a)"))
    add("metric_instance_quality", lambda spark, d: metrics.instance_quality(dirty(spark, d, "orders")[1], CHAIN), s.say(f"select ({before})::bigint as quality"))
    for which, (_, fds) in SETS.items():
        s = script(which)
        add(f"detect_violations_{which}", lambda spark, d, w=which: (lambda x: detect.violations(x[1], x[2]))(dirty(spark, d, w)), s.say(twin.violations(s.dirty, fds)))
    s = script("orders")
    bad = f"select o_custkey from {s.dirty} group by 1 having count(distinct c_nationkey) > 1"
    add("detect_rows", lambda spark, d: detect.violating_rows(dirty(spark, d, "orders")[1], "o_custkey -> c_nationkey", "tid"), s.say(f"select tid from {s.dirty} where o_custkey in ({bad})"))
    for name, view, fd in (("discover_user_event", "events_user", "user_id -> event_type"), ("discover_digest_source", "documents_src", "digest -> source"), ("discover_turn_role", "conv_role", "turn -> role"), ("discover_host_lang", "pages_lang", "host -> html_lang"), ("discover_path_lang", "pages_lang", "path_lang -> html_lang")):
        s = twin.Script(view)
        add(name, lambda spark, d, v=view, f=fd: detect.fd_error(VIEWS[v](spark, d), f), s.say(f"select fd, g3, (select count(*) from clean) as n, round(g3::double / (select count(*) from clean), 6) as ratio from ({twin.violations('clean', fd)})"))
    for which, kind in (("orders", "swap"), ("orders", "typo"), ("orders", "mix"), ("orders", "null"), ("line", "mix"), ("customer", "swap")):
        s = script(which, kind)
        cells = list(dict.fromkeys(f.rhs for f in build_plan(SETS[which][1]).fds))

        def log(spark, sf_dir, which=which, kind=kind):
            view, fds = SETS[which]
            return errors.inject(VIEWS[view](spark, sf_dir), fds, "tid", RATE, kind=kind)[1]

        add(f"errors_{which}_{kind}", log, s.say(" union all ".join(f"select c.tid, '{a}' as attribute, c.{a}::varchar as truth, d.{a}::varchar as dirty from clean c join {s.dirty} d using (tid) where c.{a} is distinct from d.{a}" for a in cells)))


def _natural() -> None:
    """Dirty data as they are: no truth, so cost, gain and what is left."""
    for name, view, fds in (("natural_documents", "documents_src", "digest -> source; digest -> lang"), ("natural_events", "events_user", "user_id -> event_type"), ("natural_conversations", "conv_role", "turn -> role"), ("natural_pages", "pages_lang", "host -> html_lang; path_lang -> html_lang")):
        s = twin.Script(view)
        s.repair(fds, "hybrid")

        def run(spark, sf_dir, view=view, fds=fds):
            df = VIEWS[view](spark, sf_dir)
            r = chase.repair(df, fds, "tid")
            before, after = detect.violations(df, fds), detect.violations(r.df, fds)
            pair = before.select("fd", F.col("violating_groups").alias("before")).join(after.select("fd", F.col("violating_groups").alias("after")), "fd")
            return pair.crossJoin(r.cost())

        add(name, run, s.say(f"select b.fd, b.violating_groups as before, a.violating_groups as after, (select count(*) from ({s.delta()})) as changed from ({twin.violations(s.dirty, fds)}) b join ({twin.violations(s.fixed, fds)}) a using (fd)"))


def _incremental() -> None:
    from ..operators import incremental
    from ..plans import FD

    f = FD(("user_id",), "event_type")

    def halves(spark, sf_dir):
        df = VIEWS["events_user"](spark, sf_dir)
        return incremental.counted(df.where("tid % 3 > 0"), f, "tid"), incremental.counted(df.where("tid % 3 = 0"), f, "tid")

    add("incremental_counts", lambda spark, d: incremental.merged(*halves(spark, d), f), "select user_id as x_user_id, event_type as y, count(*) as cnt, min(event_id) as first_tid from events group by all")
    best = "select user_id, first(event_type order by c desc, event_type) as y from (select user_id, event_type, count(*) as c from events where {} group by all) group by user_id"
    add("incremental_affected", lambda spark, d: incremental.affected(*halves(spark, d), f), f"select a.user_id as x_user_id from ({best.format('true')}) a left join ({best.format('event_id % 3 > 0')}) b using (user_id) where a.y is distinct from b.y and user_id in (select user_id from events where event_id % 3 = 0)")


for part in (_incremental, _patterns, _quality, _selection, _repairs, _measures, _natural):
    part()
