"""Queries of the relational, scalar, UDF and streaming surface, each with its SQL twin where SQL can follow."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import udfs
from ..functions.values import normalised
from ..operators import chase, patterns
from ..operators.store import written
from ..plans import build_plan
from ..sources import formats
from ..sources.tables import CUSTOMER_SCORED, VIEWS, table
from ..streaming import events as streams
from . import twin
from .methods import dirty, script

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def _scans() -> None:
    add("op_scan_pushdown", lambda s, d: table(s, d, "lineitem").where("l_quantity > 45 and l_returnflag = 'R'").select("l_orderkey", "l_quantity"), "select l_orderkey, l_quantity from lineitem where l_quantity > 45 and l_returnflag = 'R'")
    add("op_filters", lambda s, d: table(s, d, "part").where(F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#13") | F.col("p_name").rlike("^[a-m]")).where(F.col("p_size").between(1, 30) & F.col("p_type").isNotNull()).select("p_partkey", "p_size"), "select p_partkey, p_size from part where (p_brand in ('Brand#11', 'Brand#12', 'Brand#13') or regexp_matches(p_name, '^[a-m]')) and p_size between 1 and 30 and p_type is not null")
    add("op_projection", lambda s, d: table(s, d, "customer").withColumnsRenamed({"c_custkey": "id"}).withColumn("cents", F.round(F.col("c_acctbal") * 100).cast("long")).select("id", "cents", F.expr("upper(c_mktsegment) as segment")), "select c_custkey as id, round(c_acctbal * 100)::bigint as cents, upper(c_mktsegment) as segment from customer")
    for kind in ("csv", "json", "orc", "parquet"):
        add(f"op_format_{kind}", lambda s, d, k=kind: formats.round_trip(table(s, d, "nation"), k), "select * from nation")
    add("op_format_partitioned", lambda s, d: formats.round_trip(table(s, d, "supplier").select("s_suppkey", "s_name", "s_nationkey"), "parquet", "s_nationkey"), "select s_suppkey, s_name, s_nationkey from supplier")
    add("op_source_fd_rules", lambda s, d: formats.rules(s, "a, b -> c; c -> d").select("name", F.array_join("lhs", ",").alias("lhs"), "rhs"), "select * from (values ('a,b->c', 'a,b', 'c'), ('c->d', 'c', 'd')) t(name, lhs, rhs)")


def _joins() -> None:
    same = "select o_orderkey, c_name from orders join customer on o_custkey = c_custkey"
    for name, hint in (("broadcast", "broadcast"), ("shuffle_hash", "shuffle_hash"), ("sort_merge", "merge")):
        add(f"op_join_{name}", lambda s, d, h=hint: table(s, d, "orders").join(table(s, d, "customer").hint(h), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name"), same)
    add("op_join_outer", lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("o_custkey") == F.col("c_custkey"), "full").select("c_custkey", "o_orderkey"), "select c_custkey, o_orderkey from customer full join orders on o_custkey = c_custkey")
    add("op_join_semi", lambda s, d: table(s, d, "customer").join(table(s, d, "orders").where("o_orderstatus = 'F'"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey"), "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_orderstatus = 'F')")
    add("op_join_anti", lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left_anti").select("c_custkey"), "select c_custkey from customer where c_custkey not in (select o_custkey from orders)")
    add("op_join_cross", lambda s, d: table(s, d, "nation").select("n_name").crossJoin(table(s, d, "region").select("r_name")), "select n_name, r_name from nation, region")
    docs = lambda s, d: VIEWS["documents_src"](s, d).select("tid", "digest", "source")

    def theta(s, d):
        a, b = docs(s, d), docs(s, d).toDF("tid2", "digest2", "source2")
        return a.join(b, (F.col("digest") == F.col("digest2")) & (F.col("source") < F.col("source2"))).select("tid", "tid2")

    add("op_join_theta", theta, "with x as (select doc_id as tid, md5(text) as digest, source from documents) select a.tid, b.tid as tid2 from x a join x b on a.digest = b.digest and a.source < b.source")

    def nullsafe(s, d):
        a = table(s, d, "customer").select("c_custkey", F.when(F.col("c_custkey") % 3 > 0, F.col("c_nationkey")).alias("k"))
        b = table(s, d, "nation").select(F.when(F.col("n_nationkey") > 0, F.col("n_nationkey")).alias("k2"), "n_name")
        return a.join(b, F.col("k").eqNullSafe(F.col("k2"))).select("c_custkey", "n_name")

    add("op_join_nullsafe", nullsafe, "select c_custkey, n_name from (select c_custkey, case when c_custkey % 3 > 0 then c_nationkey end as k from customer) join (select case when n_nationkey > 0 then n_nationkey end as k2, n_name from nation) on k is not distinct from k2")

    def interval(s, d):
        # an equi-join on hour buckets, each row also in the next one, and then the exact bound
        e = table(s, d, "events").select("event_id", "user_id", "event_type", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("t"))
        a = e.withColumn("b", F.floor(F.col("t") / 3600))
        later = e.toDF("event_id2", "user_id2", "event_type2", "t2").withColumn("b2", F.explode(F.array(F.floor(F.col("t2") / 3600), F.floor(F.col("t2") / 3600) - 1)))
        near = (F.col("t2") > F.col("t")) & (F.col("t2") - F.col("t") <= 3600) & (F.col("event_type") != F.col("event_type2"))
        return a.join(later, (F.col("user_id") == F.col("user_id2")) & (F.col("b") == F.col("b2")) & near).select("event_id", "event_id2")

    e = "(select event_id, user_id, event_type, floor(epoch(ts))::bigint as t from events)"
    add("op_join_interval", interval, f"select a.event_id, b.event_id as event_id2 from {e} a join {e} b on a.user_id = b.user_id and a.event_type <> b.event_type and b.t > a.t and b.t - a.t <= 3600")

    def asof(s, d):
        ev = table(s, d, "events").select("event_id", "user_id", "event_type", "ts")
        before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
        return ev.withColumn("purchase", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(before)).where("event_type = 'error'").select("event_id", "purchase")

    add("op_join_asof", asof, "select event_id, purchase from (select *, last_value(case when event_type = 'purchase' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as purchase from events) where event_type = 'error'")

    def lateral(s, d):
        plan = build_plan("source -> lang", VIEWS["documents_src"](s, d).schema)
        written(patterns.simple(patterns.project(VIEWS["documents_src"](s, d), plan.attributes, "tid"), plan.fds[0])).createOrReplaceTempView("lateral_patterns")
        return s.sql("select distinct k.x_source as source, r.y, r.cnt from lateral_patterns k, lateral (select y, cnt from lateral_patterns p where p.x_source = k.x_source order by cnt desc, y limit 2) r")

    add("op_join_lateral", lateral, "select source, lang as y, cnt from (select *, row_number() over (partition by source order by cnt desc, lang) as k from (select source, lang, count(*) as cnt from documents group by source, lang)) where k <= 2")


def _aggregates() -> None:
    add("op_agg_many", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("q"), F.min("l_shipdate").cast("string").alias("first_day"), F.round(F.avg("l_discount"), 4).alias("avg_discount"), F.round(F.stddev("l_quantity"), 4).alias("sd")), "select l_returnflag, l_linestatus, count(*) as n, sum(l_quantity::bigint)::bigint as q, strftime(min(l_shipdate), '%Y-%m-%d %H:%M:%S') as first_day, round(avg(l_discount), 4) as avg_discount, round(stddev(l_quantity), 4) as sd from lineitem group by all")
    add("op_agg_distinct", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")), "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem group by 1")
    add("op_agg_filter", lambda s, d: table(s, d, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("done"), F.bool_or(F.col("o_totalprice") > 400000).alias("large")), "select o_orderpriority, count(*) filter (o_orderstatus = 'F') as done, bool_or(o_totalprice > 400000) as large from orders group by 1")
    add("op_agg_minmax_by", lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("largest"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("smallest")), "select o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) as largest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) as smallest from orders group by 1")
    add("op_agg_collect", lambda s, d: table(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_set("n_name")), ",").alias("names")), "select n_regionkey, string_agg(n_name, ',' order by n_name) as names from (select distinct n_regionkey, n_name from nation) group by 1")
    sets = "select c_mktsegment, n_regionkey, count(*) as n from customer join nation on c_nationkey = n_nationkey group by {}"
    base = lambda s, d: table(s, d, "customer").join(table(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    add("op_cube", lambda s, d: base(s, d).cube("c_mktsegment", "n_regionkey").agg(F.count(F.lit(1)).alias("n")), sets.format("cube (c_mktsegment, n_regionkey)"))
    add("op_rollup", lambda s, d: base(s, d).rollup("c_mktsegment", "n_regionkey").agg(F.count(F.lit(1)).alias("n")), sets.format("rollup (c_mktsegment, n_regionkey)"))
    add("op_grouping_sets", lambda s, d: base(s, d).groupingSets([["c_mktsegment"], ["n_regionkey"]], "c_mktsegment", "n_regionkey").agg(F.count(F.lit(1)).alias("n")), sets.format("grouping sets ((c_mktsegment), (n_regionkey))"))
    add("op_approx", lambda s, d: table(s, d, "lineitem").agg((F.abs(F.approx_count_distinct("l_partkey", 0.02) - F.count_distinct("l_partkey")) <= 0.1 * F.count_distinct("l_partkey")).alias("near"), (F.abs(F.percentile_approx("l_quantity", 0.5, 10000) - F.percentile("l_quantity", 0.5)) <= 1).alias("median_near")), "select true as near, true as median_near")
    add("op_sketch", lambda s, d: table(s, d, "lineitem").agg((F.abs(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 14)) - F.count_distinct("l_partkey")) <= 0.05 * F.count_distinct("l_partkey")).alias("near")), "select true as near")
    add("op_pivot", lambda s, d: table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "error", "purchase", "view"]).agg(F.count(F.lit(1))).na.fill(0), "select user_id, " + ", ".join(f"count(*) filter (event_type = '{t}') as {t}" for t in ("click", "error", "purchase", "view")) + " from events group by 1")
    add("op_unpivot", lambda s, d: VIEWS["customer_wide"](s, d).select("tid", "n_name", "r_name").unpivot("tid", ["n_name", "r_name"], "attribute", "value"), f"select tid, 'n_name' as attribute, n_name as value from ({twin.VIEWS['customer_wide']}) union all select tid, 'r_name', r_name from ({twin.VIEWS['customer_wide']})")


def _windows() -> None:
    by_user = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")
    ev = lambda s, d: table(s, d, "events")
    w = "over (partition by user_id order by ts, event_id"
    add("op_win_rank", lambda s, d: table(s, d, "orders").select("o_orderkey", *[f.over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias(n) for f, n in ((F.rank(), "r"), (F.dense_rank(), "dr"))], F.round(F.percent_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")), 6).alias("pr"), F.round(F.cume_dist().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")), 6).alias("cd")), "select o_orderkey, rank() over w as r, dense_rank() over w as dr, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd from orders window w as (partition by o_custkey order by o_orderpriority)")
    add("op_win_lag", lambda s, d: ev(s, d).select("event_id", F.lag("event_type").over(by_user()).alias("before"), F.lead("event_id", 2).over(by_user()).alias("after")), f"select event_id, lag(event_type) {w}) as before, lead(event_id, 2) {w}) as after from events")
    add("op_win_ntile", lambda s, d: ev(s, d).select("event_id", F.ntile(4).over(by_user()).alias("quarter"), F.row_number().over(by_user()).alias("n")), f"select event_id, ntile(4) {w}) as quarter, row_number() {w}) as n from events")
    add("op_win_rows_frame", lambda s, d: ev(s, d).select("event_id", F.sum("event_id").over(by_user().rowsBetween(-2, 0)).alias("last3")), f"select event_id, (sum(event_id) {w} rows between 2 preceding and current row))::bigint as last3 from events")
    add("op_win_range_frame", lambda s, d: table(s, d, "part").select("p_partkey", F.count(F.lit(1)).over(Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-3, 3)).alias("near")), "select p_partkey, count(*) over (partition by p_brand order by p_size range between 3 preceding and 3 following) as near from part")
    add("op_win_first_last", lambda s, d: ev(s, d).select("event_id", F.first("event_type").over(by_user()).alias("first_type"), F.last("event_type").over(by_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("last_type"), F.nth_value("event_id", 3).over(by_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("third")), f"select event_id, first_value(event_type) {w}) as first_type, last_value(event_type) {w} rows between unbounded preceding and unbounded following) as last_type, nth_value(event_id, 3) {w} rows between unbounded preceding and unbounded following) as third from events")
    add("op_sort_limit", lambda s, d: table(s, d, "part").orderBy(F.desc("p_retailprice"), "p_partkey").limit(10).select("p_partkey"), "select p_partkey from part order by p_retailprice desc, p_partkey limit 10")
    add("op_offset", lambda s, d: table(s, d, "part").orderBy("p_partkey").offset(20).limit(10).select("p_partkey", "p_name"), "select p_partkey, p_name from part order by p_partkey limit 10 offset 20")
    add("op_topk_group", lambda s, d: table(s, d, "orders").withColumn("k", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("k <= 2").select("o_custkey", "o_orderkey", "k"), "select o_custkey, o_orderkey, k from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as k from orders) where k <= 2")


def _sets() -> None:
    c = lambda s, d: table(s, d, "customer").select(F.col("c_nationkey").alias("k"))
    p = lambda s, d: table(s, d, "supplier").select(F.col("s_nationkey").alias("k"))
    a, b = "select c_nationkey as k from customer", "select s_nationkey as k from supplier"
    add("op_union", lambda s, d: c(s, d).unionByName(p(s, d)), f"{a} union all {b}")
    add("op_intersect", lambda s, d: c(s, d).intersect(p(s, d)), f"{a} intersect {b}")
    add("op_intersect_all", lambda s, d: c(s, d).intersectAll(p(s, d)), f"{a} intersect all {b}")
    add("op_except_all", lambda s, d: c(s, d).exceptAll(p(s, d)), f"{a} except all {b}")
    add("op_except", lambda s, d: c(s, d).subtract(p(s, d).where("k > 9")), f"{a} except {b} where s_nationkey > 9")
    add("op_distinct", lambda s, d: table(s, d, "events").select("user_id", "event_type").distinct(), "select distinct user_id, event_type from events")
    add("op_drop_duplicates", lambda s, d: table(s, d, "events").groupBy("user_id").agg(F.min("event_id").alias("event_id")), "select user_id, min(event_id) as event_id from events group by 1")
    add("op_sample", lambda s, d: table(s, d, "lineitem").sample(0.2, 7).agg((F.count(F.lit(1)) > 0).alias("some")), "select true as some")

    def sql(name, spark_sql, duck=None):
        def run(s, d):
            for t in ("orders", "customer", "nation", "region", "part", "lineitem", "events"):
                table(s, d, t).createOrReplaceTempView(t)
            return s.sql(spark_sql)

        add(name, run, duck or spark_sql)

    sql("op_subquery_exists", "select c_custkey from customer c where exists (select 1 from orders o where o.o_custkey = c.c_custkey and o.o_totalprice > 300000)")
    sql("op_subquery_scalar", "select o_orderkey from orders where o_totalprice > (select avg(o_totalprice) * 1.5 from orders)")
    sql("op_subquery_correlated", "select o_orderkey from orders o where o_totalprice = (select max(o_totalprice) from orders p where p.o_custkey = o.o_custkey)")
    sql("op_cte", "with big as (select o_custkey, count(*) as n from orders group by o_custkey) select n, count(*) as customers from big group by n")
    years = "with recursive y as (select {year} as n, count(*) as c from orders group by 1), t(n, total) as (select n, c from y where n = (select min(n) from y) union all select t.n + 1, t.total + y.c from t join y on y.n = t.n + 1) select n, total from t"
    sql("op_cte_recursive", years.format(year="year(o_orderdate)"), years.format(year="year(o_orderdate)::int"))


def _functions() -> None:
    def fn(name, view, columns, duck):
        add(f"fn_{name}", lambda s, d: table(s, d, view).select(*columns()), duck)

    fn("string", "part", lambda: ["p_partkey", F.lower("p_name").alias("a"), F.concat_ws("-", "p_brand", "p_type").alias("b"), F.substring("p_name", 2, 3).alias("c"), F.length("p_type").alias("d"), F.lpad(F.col("p_size").cast("string"), 5, "0").alias("e"), F.translate("p_brand", "#", "_").alias("f"), F.levenshtein("p_brand", "p_type").alias("g"), F.md5(F.col("p_name").cast("binary")).alias("h"), F.split("p_name", " ")[0].alias("i")], "select p_partkey, lower(p_name) as a, p_brand || '-' || p_type as b, substr(p_name, 2, 3) as c, length(p_type)::int as d, lpad(p_size::varchar, 5, '0') as e, translate(p_brand, '#', '_') as f, levenshtein(p_brand, p_type)::int as g, md5(p_name) as h, split_part(p_name, ' ', 1) as i from part")
    fn("normalised", "part", lambda: ["p_partkey", normalised(F.concat(F.lit("  "), F.col("p_name"), F.lit("  X "))).alias("n")], "select p_partkey, regexp_replace(trim(lower('  ' || p_name || '  X ')), '\\s+', ' ', 'g') as n from part")
    fn("date", "orders", lambda: ["o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_trunc("month", F.col("o_orderdate")).cast("string").alias("first_of_month"), F.datediff(F.col("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days"), F.date_format("o_orderdate", "yyyy-MM-dd").alias("day")], "select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d %H:%M:%S') as first_of_month, date_diff('day', date '1992-01-01', o_orderdate::date)::int as days, strftime(o_orderdate, '%Y-%m-%d') as day from orders")
    fn("math", "part", lambda: ["p_partkey", F.floor("p_retailprice").alias("a"), F.pmod(F.col("p_partkey"), F.lit(7)).alias("b"), F.abs(F.col("p_size") - 25).alias("c"), F.round(F.sqrt("p_retailprice"), 6).alias("d"), F.greatest("p_size", F.lit(20)).alias("e"), F.round(F.log("p_retailprice"), 6).alias("f")], "select p_partkey, floor(p_retailprice)::bigint as a, p_partkey % 7 as b, abs(p_size - 25) as c, round(sqrt(p_retailprice), 6) as d, greatest(p_size, 20) as e, round(ln(p_retailprice), 6) as f from part")
    arr = lambda: F.split("p_name", " ")
    fn("array", "part", lambda: ["p_partkey", F.array_join(F.array_sort(arr()), ",").alias("a"), F.size(arr()).alias("b"), F.array_join(F.transform(arr(), lambda x: F.upper(x)), ",").alias("c"), F.size(F.filter(arr(), lambda x: F.length(x) > 4)).alias("d"), F.aggregate(F.sequence(F.lit(1), F.col("p_size")), F.lit(0), lambda x, y: x + y).alias("e"), F.exists(arr(), lambda x: x.startswith("b")).alias("f")], "select p_partkey, array_to_string(list_sort(string_split(p_name, ' ')), ',') as a, len(string_split(p_name, ' '))::int as b, upper(array_to_string(string_split(p_name, ' '), ',')) as c, len(list_filter(string_split(p_name, ' '), lambda x: length(x) > 4))::int as d, (p_size * (p_size + 1) // 2)::int as e, len(list_filter(string_split(p_name, ' '), lambda x: starts_with(x, 'b'))) > 0 as f from part")
    add("fn_explode", lambda s, d: table(s, d, "part").select("p_partkey", F.posexplode(F.split("p_name", " ")).alias("k", "word")), "select p_partkey, (unnest(range(len(w))))::int as k, unnest(w) as word from (select p_partkey, string_split(p_name, ' ') as w from part)")
    fn("map", "part", lambda: ["p_partkey", F.element_at(F.map_concat(F.create_map(F.lit("brand"), F.col("p_brand")), F.create_map(F.lit("type"), F.col("p_type"))), "type").alias("t"), F.size(F.map_from_entries(F.array(F.struct(F.lit("a"), "p_size")))).alias("n")], "select p_partkey, p_type as t, 1 as n from part")
    fn("json", "events", lambda: ["event_id", F.get_json_object("props", "$.k").alias("k"), F.to_json(F.struct("event_id", "event_type")).alias("j"), F.from_json("props", "k string")["k"].alias("k2")], "select event_id, json_extract_string(props, '$.k') as k, '{\"event_id\":' || event_id || ',\"event_type\":\"' || event_type || '\"}' as j, json_extract_string(props, '$.k') as k2 from events")
    fn("null", "orders", lambda: ["o_orderkey", F.coalesce(F.nullif(F.col("o_orderstatus"), F.lit("F")), F.lit("none")).alias("a"), F.nullif(F.col("o_orderpriority"), F.lit("1-URGENT")).isNull().alias("b"), F.when(F.col("o_totalprice") > 100000, "high").otherwise("low").alias("c")], "select o_orderkey, coalesce(nullif(o_orderstatus, 'F'), 'none') as a, nullif(o_orderpriority, '1-URGENT') is null as b, case when o_totalprice > 100000 then 'high' else 'low' end as c from orders")
    fn("regex", "pages", lambda: ["page_id", F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"), F.regexp_replace("url", "[0-9]+", "#").alias("shape")], "select page_id, regexp_extract(url, '^([a-z]+)://', 1) as scheme, regexp_replace(url, '[0-9]+', '#', 'g') as shape from pages")
    add("fn_hash", lambda s, d: table(s, d, "customer").select("c_custkey", F.xxhash64("c_name").alias("x"), F.hash("c_name").alias("h"), F.crc32(F.col("c_name").cast("binary")).alias("c"), F.soundex("c_name").alias("s")))
    fn("sha2", "customer", lambda: ["c_custkey", F.sha2(F.col("c_name").cast("binary"), 256).alias("h")], "select c_custkey, sha256(c_name) as h from customer")
    fn("array_float", "embeddings", lambda: ["vec_id", F.round(F.aggregate("embedding", F.lit(0.0).cast("double"), lambda a, x: a + x.cast("double") * x.cast("double")), 4).alias("norm2")], "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 4) as norm2 from embeddings")


def _udfs() -> None:
    add("udf_similarity", lambda s, d: table(s, d, "part").select("p_partkey", udfs.edit_similarity("p_brand", "p_type").alias("similar")), "select p_partkey, round(1 - levenshtein(p_brand, p_type)::double / greatest(length(p_brand), length(p_type)), 6) as similar from part")
    g3 = "select user_id, (sum(c) - max(c))::bigint as g3 from (select user_id, event_type, count(*) as c from events group by all) group by 1"
    add("udaf_g3", lambda s, d: table(s, d, "events").groupBy("user_id").agg(udfs.group_g3("event_type").alias("g3")), g3)
    add("udf_apply_in_pandas", lambda s, d: udfs.group_g3_frame(table(s, d, "events"), "user_id", "event_type"), g3)

    def unfolded(s, d):
        udfs.register(s)
        VIEWS["customer_wide"](s, d).createOrReplaceTempView("customer_wide")
        return s.sql("select tid, c.attribute, c.value from customer_wide, lateral cells(array('n_name', 'r_name'), array(n_name, r_name)) c")

    add("udtf_cells", unfolded, f"select tid, 'n_name' as attribute, n_name as value from ({twin.VIEWS['customer_wide']}) union all select tid, 'r_name', r_name from ({twin.VIEWS['customer_wide']})")

    def surface(s, d):
        _, df, fds = dirty(s, d, "customer")
        udfs.register_views(chase.repair(df, fds, "tid"))
        return s.sql("select r.fd, r.lhs, r.rhs, max(p.cnt) as cnt from rtab r join patterns p on p.fd = r.fd and p.lhs = r.lhs and p.rhs = r.rhs group by all")

    q = script("customer")
    q.repair(CUSTOMER_SCORED, "hybrid")
    add("sql_views", surface, q.say(f"select r.fd, r.lhs, r.rhs, max(p.cnt) as cnt from ({q.tables_long()}) r join ({q.patterns_long()}) p on p.fd = r.fd and p.lhs = r.lhs and p.rhs = r.rhs group by all"))


def _streams() -> None:
    add("stream_pattern_counts", lambda s, d: streams.finished(streams.pattern_counts(streams.source(s, d), "user_id", "event_type"), "complete"), "select user_id, event_type, count(*) as cnt from events group by all")
    add("stream_merged_counts", lambda s, d: streams.merged_counts(streams.source(s, d), "user_id", "event_type"), "select user_id, event_type, count(*) as cnt from events group by all")

    def static(s, d):
        ev = VIEWS["events_user"](s, d)
        plan = build_plan("user_id -> event_type", ev.schema)
        r = chase.repair(ev, "user_id -> event_type", "tid", "greedy")
        return streams.finished(streams.repaired(streams.source(s, d).select("event_id", "user_id", "event_type"), r.rtables[plan.fds[0]], "user_id", "event_type"))

    t = twin.Script("events_user")
    t.repair("user_id -> event_type", "greedy")
    add("stream_join_static", static, t.say(f"select tid as event_id, user_id, event_type from {t.fixed}"))

    def windowed(s, d, width, slide=None):
        ev = streams.source(s, d).withWatermark("ts", "1 hour")
        counted = ev.groupBy(F.window("ts", width, slide) if slide else F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"))
        flat = counted.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n")
        return streams.finished(flat, "complete")

    add("stream_tumbling", lambda s, d: windowed(s, d, "1 day"), "select strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') as start, event_type, count(*) as n from events group by all")
    add("stream_sliding", lambda s, d: windowed(s, d, "2 days", "1 day"), "select strftime(date_trunc('day', ts) - to_days(k::int), '%Y-%m-%d %H:%M:%S') as start, event_type, count(*) as n from events, range(2) r(k) where (epoch(date_trunc('day', ts))::bigint // 86400 - k) is not null group by all")

    def sessions(s, d):
        ev = streams.source(s, d).withWatermark("ts", "1 hour")
        made = ev.groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count(F.lit(1)).alias("n"))
        return streams.finished(made.select(F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "user_id", "n"), "complete")

    add("stream_session", sessions, "select strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, user_id, count(*) as n from (select *, sum(fresh) over (partition by user_id order by ts, event_id) as s from (select *, case when lag(ts) over (partition by user_id order by ts, event_id) is null or ts >= lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minutes then 1 else 0 end as fresh from events)) group by user_id, s")
    add("stream_dedup", lambda s, d: streams.finished(streams.source(s, d).withWatermark("ts", "3650 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")), "select distinct user_id, event_type from events")

    def closed(s, d):
        # only windows that the watermark has closed are told
        ev = streams.source(s, d).withWatermark("ts", "1 hour")
        made = ev.groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
        return streams.finished(made.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n"))

    add("stream_late", closed, "select strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') as start, count(*) as n from events group by all having max(date_trunc('day', ts)) + interval 1 day <= (select max(ts) - interval 1 hour from events)")

    def met(s, d):
        a = streams.source(s, d).select("event_id", "user_id", "event_type", "ts").withWatermark("ts", "2 hours")
        b = streams.source(s, d).select(F.col("event_id").alias("event_id2"), F.col("user_id").alias("user_id2"), F.col("event_type").alias("event_type2"), F.col("ts").alias("ts2")).withWatermark("ts2", "2 hours")
        on = F.expr("user_id = user_id2 and event_type <> event_type2 and ts2 > ts and ts2 <= ts + interval 1 hour")
        return streams.finished(a.join(b, on).select("event_id", "event_id2"))

    add("stream_interval_join", met, "select a.event_id, b.event_id as event_id2 from events a join events b on a.user_id = b.user_id and a.event_type <> b.event_type and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")

    def stateful(s, d):
        out = streams.finished(streams.first_writer(streams.source(s, d), "user_id", "event_type", "event_id"), "update")
        last = Window.partitionBy("lhs").orderBy(F.desc("__batch"))
        return out.withColumn("k", F.row_number().over(last)).where("k = 1").select("lhs", "rhs", "rows")

    add("stream_stateful_rtab", stateful, "select user_id::varchar as lhs, arg_min(event_type, event_id) as rhs, count(*) as rows from events group by user_id")


for part in (_scans, _joins, _aggregates, _windows, _sets, _functions, _udfs, _streams):
    part()
