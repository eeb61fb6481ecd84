"""SQL for DuckDB that computes what the engine computes: views, errors, patterns, qualities, decisions and the chase, as chained common table expressions."""

from __future__ import annotations

from ..plans import FD, RepairPlan, build_plan
from ..plans.fd import parts, parse
from ..sources.tables import LINE

VIEWS = {
    "orders_wide": "select o_orderkey as tid, o_custkey, c_name, c_nationkey, n_name, n_regionkey, r_name, c_mktsegment from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey",
    "customer_wide": "select c_custkey as tid, c_custkey, c_nationkey, n_name, n_regionkey, r_name, c_mktsegment from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey",
    "customer_desk": "select c_custkey as tid, n_name, c_mktsegment, r_name || '|' || c_mktsegment as desk, r_name, c_nationkey from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey",
    "lineitem_wide": f"select tid, l_partkey, p_name, p_brand, p_type, l_suppkey, s_name, s_nationkey, n_name from (select *, l_orderkey * 1000 + row_number() over (partition by l_orderkey order by {', '.join(LINE)}) as tid from lineitem) join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey",
    "pages_lang": "select page_id as tid, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as host, regexp_extract(url, '^[a-z]+://[^/]+/([a-z]+)/', 1) as path_lang, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) as html_lang from pages",
    "documents_src": "select doc_id as tid, md5(text) as digest, lang, source, n_chars from documents",
    "events_user": "select event_id as tid, user_id, event_type, json_extract_string(props, '$.k') as k from events",
    "conv_role": "select conv_id * 1000 + turn as tid, turn, role from conversations",
}
NUMBERS = {"o_custkey", "c_nationkey", "n_regionkey", "c_custkey", "l_partkey", "l_suppkey", "s_nationkey", "n_chars", "turn", "user_id"}


class Script:
    """Common table expressions in order; ``say`` closes them with a query."""

    def __init__(self, view: str, where: str = "true") -> None:
        self.ctes: list[tuple[str, str]] = []
        self.view = self.add("clean", f"select * from ({VIEWS.get(view, view)}) where {where}")
        self.dirty = self.view

    def add(self, name: str, body: str) -> str:
        taken = {n for n, _ in self.ctes}
        while name in taken:
            name += "_"
        self.ctes.append((name, body))
        return name

    def say(self, query: str) -> str:
        walks = any(n.startswith("walk_") for n, _ in self.ctes)
        return f"with {'recursive ' * walks}" + ",\n".join(f"{n} as ({b})" if n.startswith("walk_") else f"{n} as materialized ({b})" for n, b in self.ctes) + "\n" + query

    def inject(self, fds: str, rate: float, seed: int = 1, kind: str = "swap") -> Script:
        for k, f in enumerate(parse(fds)):
            c, salt = f.rhs, k + 10 * seed
            h = f"((tid * 48271 + {salt * 104729}) % 1000003)"
            hit = f"({h} * {h} + {salt * 15485863} + tid) % 1000003 < {int(rate * 1000003)}"
            sizes = self.add(f"size{k}", f"select {', '.join(f.lhs)} from {self.view} group by {', '.join(f.lhs)} having count(*) > 1")
            marked = self.add(f"hit{k}", f"select tid from {self.view} semi join {sizes} using ({', '.join(f.lhs)}) where {hit}")
            values = self.add(f"vals{k}", f"select v, coalesce(lead(v) over (order by v), first_value(v) over (order by v)) as other from (select distinct {c} as v from {self.dirty} where {c} is not null)")
            typo = f"{c} + 1000" if c in NUMBERS else f"{c} || '~'"
            wrong = {"swap": "other", "typo": typo, "mix": f"case when tid % 2 = 0 then other else {typo} end", "null": "null"}[kind]
            self.dirty = self.add(f"dirty{k}", f"select d.* exclude (v, other, h) replace (case when h is not null then {wrong} else {c} end as {c}) from (select a.*, b.v, b.other, m.tid as h from {self.dirty} a left join {values} b on a.{c} = b.v left join {marked} m on a.tid = m.tid) d")
        return self

    def plan(self, fds: str, **options) -> RepairPlan:
        self.p: RepairPlan = build_plan(fds, **options)
        attrs = ", ".join(self.p.attributes)
        self.proj = self.add("proj", f"select {attrs}, count(*) as w, min(tid) as min_tid from {self.dirty} group by {attrs}")
        self.pat: dict[FD, str] = {}
        for k, f in enumerate(self.p.fds):
            xs = ", ".join(f"{a} as x_{a}" for a in f.lhs)
            keep = " and ".join(f"{a} is not null" for a in (*f.lhs, f.rhs))
            grouped = f"select {xs}, {f.rhs} as y, sum(w)::bigint as cnt from {self.proj} where {keep} group by all"
            total = f"(select sum(w)::bigint from {self.proj})"
            part = ", ".join(f"x_{a}" for a in f.lhs)
            base = f"select *, (sum(cnt) over (partition by {part}))::bigint as lhs_cnt, {total} as n from ({grouped})"
            self.pat[f] = self.add(f"pat{k}", f"select *, floor(cnt::double / lhs_cnt * 1e9)::bigint as conf_fp, floor(cnt::double / n * 1e9)::bigint as sup_fp from ({base})")
        return self.p

    def key(self, f: FD) -> str:
        return f"concat_ws('|', {', '.join(f'x_{a}::varchar' for a in f.lhs)})"

    def patterns_long(self) -> str:
        return " union all ".join(f"select '{f.name}' as fd, {self.key(f)} as lhs, y::varchar as rhs, cnt, lhs_cnt, n, conf_fp, sup_fp from {t}" for f, t in self.pat.items())

    def quality(self, score: str = "full", normalize: str = "avg", weight: str = "uniform") -> dict[FD, str]:
        p, self.q = self.p, {}
        by_path = p.reach == "path" or weight != "uniform"
        closures: dict[tuple, str | None] = {}
        done: dict[FD, str] = {}

        def closure(attribute: str, skip: int | None = None) -> str | None:
            if (attribute, skip) in closures:
                return closures[attribute, skip]
            out = []
            for g in p.after(attribute):
                if skip is not None and p.component[g.rhs] == skip:
                    continue
                name = f"concat_ws(chr(31), '{g.name}', {', '.join(f'x_{a}::varchar' for a in g.lhs)}, y::varchar)"
                out.append(f"select x_{attribute} as v, {name} as e, conf_fp + sup_fp as own from {self.pat[g]}")
                further = closure(g.rhs)
                if further:
                    out.append(f"select t.x_{attribute} as v, c.e, c.own from {self.pat[g]} t join {further} c on t.y = c.v")
            closures[attribute, skip] = self.add(f"reach_{attribute}", " union ".join(f"select * from ({o})" for o in out)) if out else None
            return closures[attribute, skip]

        def follow(attribute: str, skip: int | None = None) -> str | None:
            if not by_path:
                c = closure(attribute, skip)
                return c and f"select v, sum(own)::bigint as s, count(*) * 1000000 as m, max(own) as hi, min(own) as lo from {c} group by v"
            out = []
            for g in p.after(attribute):
                if skip is not None and p.component[g.rhs] == skip:
                    continue
                term, number = "conf_fp + sup_fp + reach_fp", "reach_parts + 1000000"
                source = done[g]
                if weight == "confidence":
                    term, number = f"floor(conf_fp / 1e9 * ({term}))::bigint", f"floor(conf_fp / 1e9 * ({number}))::bigint"
                elif weight == "best":
                    part = ", ".join(f"x_{a}" for a in g.lhs)
                    source = f"(select * from (select *, row_number() over (partition by {part} order by conf_fp desc, cnt desc, y) as k from {source}) where k = 1)"
                out.append(f"select x_{attribute} as v, {term} as s, {number} as m, greatest(conf_fp + sup_fp, most_fp) as hi, least(conf_fp + sup_fp, least_fp) as lo from {source}")
            return f"select v, sum(s)::bigint as s, sum(m)::bigint as m, max(hi) as hi, min(lo) as lo from ({' union all '.join(out)}) group by v" if out else None

        def reach(f: FD, told: str | None, on: str) -> None:
            own = "conf_fp + sup_fp"
            if told is None:
                body = f"select *, 0::bigint as reach_fp, 0::bigint as reach_parts, {own} as most_fp, {own} as least_fp from {self.pat[f]}"
            else:
                body = f"select t.*, coalesce(d.s, 0) as reach_fp, coalesce(d.m, 0) as reach_parts, greatest({own}, coalesce(d.hi, {own})) as most_fp, least({own}, coalesce(d.lo, {own})) as least_fp from {self.pat[f]} t left join ({told}) d on t.{on} = d.v"
            done[f] = self.add("follow" + self.pat[f][3:], body)

        rest = list(p.forward)
        while rest:
            f = next(f for f in rest if not any(f.rhs in g.lhs for g in rest if g != f))
            rest.remove(f)
            reach(f, follow(f.rhs), "y")
        for f in p.closing:
            if p.back_edges == "outside":
                reach(f, follow(f.lhs[0], p.component[f.rhs]), f"x_{f.lhs[0]}")
            else:
                reach(f, follow(f.rhs), "y")
        full = "conf_fp + sup_fp + reach_fp"
        plain = {"freq": "cnt * 1000000000", "conf": "conf_fp", "sup": "sup_fp", "local": "floor((conf_fp + sup_fp) / 2.0)::bigint"}
        value = plain.get(score, full)
        rated = plain.get(score) or {"avg": f"floor(({full})::double / (2 * (reach_parts::double / 1000000 + 1)))::bigint", "sum": full, "max": "floor(most_fp / 2.0)::bigint", "min": "floor(least_fp / 2.0)::bigint"}[normalize]
        for f in p.fds:
            self.q[f] = self.add("qual" + self.pat[f][3:], f"select *, {value} as score_fp, floor(reach_parts / 1000000.0)::bigint as reach_n, {rated} as quality_fp from {done[f]}")
        return self.q

    def quality_long(self) -> str:
        return " union all ".join(f"select '{f.name}' as fd, {self.key(f)} as lhs, y::varchar as rhs, cnt, lhs_cnt, conf_fp, sup_fp, score_fp, reach_n, quality_fp, round(quality_fp / 1e9, 6) as quality from {t}" for f, t in self.q.items())

    def covers(self, f: FD, anchor: bool = True) -> str:
        """A query: f's edges with cover_fp."""
        if f.rhs in self.p.bound:
            return f"select *, quality_fp as cover_fp from {self.q[f]}"
        terms, joins = (["t.quality_fp"] if anchor else []), []
        k = 0
        for g, t in self.q.items():
            column = "y" if g.rhs == f.rhs and (g != f or not anchor) else f"x_{f.rhs}" if f.rhs in g.lhs else None
            if column:
                joins.append(f"left join (select {column} as v, max(quality_fp) as q from {t} group by 1) b{k} on t.y = b{k}.v")
                terms.append(f"b{k}.q")
                k += 1
        total = " + ".join(f"coalesce({x}, 0)" for x in terms)
        number = " + ".join(f"case when {x} is not null then 1 else 0 end" for x in terms)
        return f"select t.*, floor(({total})::double / ({number}))::bigint as cover_fp from {self.q[f]} t {' '.join(joins)}"

    def choose(self, strategy: str = "hybrid", theta: float = 0.5, theta_on: str = "quality", strict: bool = False, anchor: bool = True) -> dict[FD, str]:
        self.d = {}
        bar = int(round(theta * 1e9))
        measure = "quality_fp" if theta_on == "quality" else "conf_fp"
        for f in self.p.fds:
            part = ", ".join(f"x_{a}" for a in f.lhs)
            source = self.add("cover" + self.pat[f][3:], self.covers(f, anchor)) if strategy != "greedy" else self.add("cover" + self.pat[f][3:], f"select *, 0::bigint as cover_fp from {self.q[f]}")
            easy = {"greedy": "true", "cover": "false", "hybrid": f"max({measure}) over (partition by {part}) {'>' if strict else '>='} {bar}"}[strategy]
            scored = f"select *, case when easy then quality_fp else cover_fp end as s, case when easy then 'greedy' else 'cover' end as origin from (select *, {easy} as easy from {source})"
            self.d[f] = self.add("pick" + self.pat[f][3:], f"select {part}, y, s as score_fp, quality_fp, cnt, rivals, origin from (select *, count(*) over (partition by {part}) as rivals, row_number() over (partition by {part} order by s desc, cnt desc, y) as k from ({scored})) where k = 1")
        return self.d

    def decisions_long(self) -> str:
        return " union all ".join(f"select '{f.name}' as fd, {self.key(f)} as lhs, y::varchar as rhs, score_fp, rivals, origin from {t}" for f, t in self.d.items())

    def chase(self) -> str:
        p = self.p
        key = p.bound if p.lhs_source == "chased" else p.attributes
        cur = self.add("cur", f"select {', '.join(key)}, min(min_tid) as min_tid, sum(w)::bigint as w, {', '.join(f'{a} as v_{a}' for a in p.bound)}, 0 as conflict from {self.proj} group by {', '.join(key)}")
        self.key_columns, assigned, self.r = key, set(p.bound), {}
        for k, f in enumerate(p.fds):
            known = [f"v_{a}" if p.lhs_source == "chased" else a for a in f.lhs]
            on = " and ".join(f"c.{c} = t.x_{a}" for a, c in zip(f.lhs, known))
            extra = f"t.origin as o{k}, concat_ws('|', {', '.join(f'c.{c}::varchar' for c in known)}) as l{k}"
            if f.rhs not in assigned:
                self.r[f] = self.d[f]
                cur = self.add("cur", f"select c.*, t.y as v_{f.rhs}, t.y::varchar as r{k}, {extra} from {cur} c left join {self.d[f]} t on {on}")
            else:
                xs = ", ".join(f"{c} as x_{a}" for a, c in zip(f.lhs, known))
                told = f"select {xs}, arg_min(v_{f.rhs}, min_tid) filter (v_{f.rhs} is not null) as told from {cur} where {' and '.join(f'{c} is not null' for c in known)} group by {', '.join(known)}"
                using = " and ".join(f"m.x_{a} = d.x_{a}" for a in f.lhs)
                self.r[f] = self.add(f"rtab{k}", f"select {', '.join(f'm.x_{a}' for a in f.lhs)}, coalesce(told, y) as y, case when told is not null then 'first_row' else origin end as origin from ({told}) m left join {self.d[f]} d on {using}")
                value = f"coalesce(t.y, c.v_{f.rhs})" if p.on_conflict == "overwrite" else f"coalesce(c.v_{f.rhs}, t.y)"
                cur = self.add("cur", f"select c.* replace ({value} as v_{f.rhs}, c.conflict + case when t.y <> c.v_{f.rhs} then 1 else 0 end as conflict), ({value})::varchar as r{k}, {extra} from {cur} c left join {self.r[f]} t on {on}")
            assigned.add(f.rhs)
        self.cur = cur
        return cur

    def touched(self) -> tuple[str, ...]:
        return self.p.free if self.p.on_conflict != "overwrite" else self.p.attributes

    def apply(self) -> str:
        on = " and ".join(f"d.{a} is not distinct from c.{a}" for a in self.key_columns)
        new = ", ".join(f"coalesce(c.v_{a}, d.{a}) as {a}" for a in self.touched())
        old = ", ".join(f"d.{a} as old_{a}" for a in self.touched())
        self.fixed = self.add("fixed", f"select d.* exclude ({', '.join(self.touched())}), {new}, {old} from {self.dirty} d left join {self.cur} c on {on}")
        return self.fixed

    def repair(self, fds: str, strategy: str = "hybrid", score: str = "full", normalize: str = "avg", weight: str = "uniform", choice: dict | None = None, **options) -> str:
        self.plan(fds, **options)
        self.quality(score, normalize, weight)
        self.choose(strategy, **(choice or {}))
        self.chase()
        return self.apply()

    def repaired(self) -> str:
        return f"select tid, {', '.join(self.p.attributes)} from {self.fixed}"

    def delta(self) -> str:
        return " union all ".join(f"select tid, '{a}' as attribute, old_{a}::varchar as old, {a}::varchar as new from {self.fixed} where {a} is distinct from old_{a}" for a in self.touched())

    def accuracy(self) -> str:
        sums = []
        for name, test in (("changed", "{a} is distinct from old_{a}"), ("correct", "{a} is distinct from old_{a} and {a} is not distinct from t_{a}"), ("dirty", "old_{a} is distinct from t_{a}"), ("fixed", "old_{a} is distinct from t_{a} and {a} is not distinct from t_{a}")):
            sums.append("coalesce(sum(" + " + ".join(f"case when {test.format(a=a)} then 1 else 0 end" for a in self.p.free) + f"), 0)::bigint as {name}")
        truth = f"select tid as t_tid, {', '.join(f'{a} as t_{a}' for a in self.p.free)} from {self.view}"
        one = f"select {', '.join(sums)} from {self.fixed} join ({truth}) on tid = t_tid"
        both = f"select *, correct::double / nullif(changed, 0) as p, fixed::double / nullif(dirty, 0) as r from ({one})"
        return f"select changed, correct, dirty, fixed, round(p, 6) as precision, round(r, 6) as recall, round(2 * p * r / nullif(p + r, 0), 6) as f1 from ({both})"

    def known(self, a: str) -> str:
        return a if a in NUMBERS else f"case when {a} not like '⊥%' then {a} end"

    def cover_round(self, fds, tag: int = 1, only_fresh: bool = False) -> str:
        """One round of the conflict cover over the current table."""
        fds, cur = list(fds), self.dirty
        touched = list(dict.fromkeys(a for f in fds for a in (*f.lhs, f.rhs)))
        conf, kept = [], []
        for f in fds:
            seen = f"select {', '.join(f'{self.known(a)} as g_{a}' for a in f.lhs)}, {self.known(f.rhs)} as v from {cur}"
            full = " and ".join([*(f"g_{a} is not null" for a in f.lhs), "v is not null"])
            conf.append(self.add("conf", f"select *, sum(c) over (partition by {', '.join(f'g_{a}' for a in f.lhs)}) - c as n from (select *, count(*) as c from ({seen}) where {full} group by all)"))
        joins = " ".join(f"left join {t} c{k} on {' and '.join(f'd.{a} = c{k}.g_{a}' for a in f.lhs)} and d.{f.rhs} = c{k}.v" for k, (f, t) in enumerate(zip(fds, conf)))
        each = ", ".join(f"coalesce(c{k}.n, 0)::bigint as conf{k}" for k in range(len(fds)))
        rated = self.add("rated", f"select *, {', '.join(' + '.join(f'conf{k}' for k, f in enumerate(fds) if a in f.attributes) + f' as deg_{a}' for a in touched)} from (select d.*, {each} from {cur} d {joins})")
        for f in fds:
            seen = f"select {', '.join(f'{self.known(a)} as g_{a}' for a in f.lhs)}, {self.known(f.rhs)} as v, deg_{f.rhs} as deg from {rated}"
            full = " and ".join([*(f"g_{a} is not null" for a in f.lhs), "v is not null"])
            left = ", ".join(f"g_{a}" for a in f.lhs)
            kept.append(self.add("kept", f"select {left}, v from (select *, row_number() over (partition by {left} order by (d * 1000) // c, c desc, v) as k from (select {left}, v, count(*) as c, sum(deg)::bigint as d from ({seen}) where {full} group by all)) where k = 1"))
        gone: dict[str, list[str]] = {}
        for k, f in enumerate(fds):
            cells, earlier = [f.rhs, *f.lhs], []
            for a in cells:
                here = f"deg_{a} = greatest({', '.join(f'deg_{b}' for b in cells)})"
                gone.setdefault(a, []).append("(" + " and ".join([f"conf{k} > 0", f"{f.rhs} <> k{k}.v", here, *earlier]) + ")")
                earlier.append(f"not ({here})")
        new = []
        for a, ways in gone.items():
            fresh = "null" if a in NUMBERS else f"'⊥{a}#' || tid || '#{tag}'"
            told = [f"k{k}.v" for k, f in enumerate(fds) if f.rhs == a]
            if told and not only_fresh:
                agreed = f"coalesce({', '.join(told)})"
                same = " and ".join(f"coalesce({t} = {agreed}, true)" for t in told)
                fresh = f"case when {agreed} is not null and {same} and {agreed} <> {a} then {agreed} else {fresh} end"
            new.append(f"case when {' or '.join(f'coalesce({w}, false)' for w in ways)} then {fresh} else {a} end as {a}")
        joins = " ".join(f"left join {t} k{k} on {' and '.join(f'd.{a} = k{k}.g_{a}' for a in f.lhs)}" for k, (f, t) in enumerate(zip(fds, kept)))
        helpers = ", ".join([*(f"conf{k}" for k in range(len(fds))), *(f"deg_{a}" for a in touched)])
        self.dirty = self.add("covered", f"select d.* exclude ({helpers}) replace ({', '.join(new)}) from {rated} d {joins}")
        return self.dirty

    def conflict_cover(self, fds, rounds: int = 4) -> str:
        """Rounds of the conflict cover and one of fresh values; rounds without conflicts change nothing. The result goes to ``fixed``."""
        before = self.dirty
        self.p = build_plan(fds)
        for k in range(1, rounds + 2):
            self.cover_round(self.p.fds, k, k > rounds)
        free = self.p.free
        done = f"select tid, {', '.join(f'{self.known(a)} as {a}' for a in free)} from {self.dirty}"
        self.fixed = self.add("fixed", f"select n.*, {', '.join(f'o.{a} as old_{a}' for a in free)} from ({done}) n join {before} o using (tid)")
        return self.dirty

    def similar(self, fds: str, tau: int = 800) -> str:
        """Decisions of the similarity baseline by comparing all patterns of an FD, then the chase."""
        self.plan(fds)
        self.d = {}
        for k, f in enumerate(self.p.fds):
            left = ", ".join(f"x_{a}" for a in f.lhs)
            base = self.add("texts", f"select {left}, y, cnt, {self.key(f)} as k, y::varchar as r, concat_ws('|', {self.key(f)}, y::varchar) as text from {self.pat[f]}")
            near = f"levenshtein(a.text, b.text) * 1000 <= greatest(length(a.text), length(b.text)) * {1000 - tau}"
            more = "(b.cnt > a.cnt or (b.cnt = a.cnt and b.text < a.text))"
            better = self.add("better", f"select k, r, r2, c2 from (select a.k, a.r, b.r as r2, b.cnt as c2, row_number() over (partition by a.k, a.r order by b.cnt desc, b.r) as n from {base} a join {base} b on abs(length(a.text) - length(b.text)) * 1000 <= greatest(length(a.text), length(b.text)) * {1000 - tau} where a.text <> b.text and {more} and {near}) where n = 1")
            met = f"select t.*, coalesce(b.r2, t.r) as goal, coalesce(b.c2, t.cnt) as votes from {base} t left join {better} b using (k, r)"
            kind = "bigint" if f.rhs in NUMBERS else "varchar"
            self.d[f] = self.add("alike", f"select {left}, goal::{kind} as y, 'similar' as origin from (select *, row_number() over (partition by {left} order by votes desc, cnt desc, goal) as n from ({met})) where n = 1")
        self.chase()
        return self.apply()

    def drawn(self, fds: str, seed: int = 1) -> str:
        """Decisions of the sampling baseline, then the chase."""
        self.plan(fds)
        h = f"((tid * 40503 + {7919 * seed}) % 1000003)"
        self.d = {}
        for f in self.p.fds:
            left = ", ".join(f.lhs)
            keep = " and ".join(f"{a} is not null" for a in (*f.lhs, f.rhs))
            self.d[f] = self.add("drawn", f"select {', '.join(f'{a} as x_{a}' for a in f.lhs)}, {f.rhs} as y, 'drawn' as origin from (select *, row_number() over (partition by {left} order by ({h} * {h} + {104729 * seed} + tid) % 1000003, tid) as k from {self.dirty} where {keep}) where k = 1")
        self.chase()
        return self.apply()

    def claims(self, f: FD, rounds: int) -> str:
        """Rounds of deferred claims of an FD: left side, y, rounds."""
        left = [f"x_{a}" for a in f.lhs]
        keys, rest, won = ", ".join(left), f"select {', '.join(left)}, y, quality_fp, cnt from {self.q[f]}", []
        for n in range(1, rounds + 1):
            rest = self.add("rest", rest)
            claim = f"select * from (select *, row_number() over (partition by {keys} order by quality_fp desc, cnt desc, y) as k from {rest}) where k = 1"
            won.append(self.add("won", f"select {keys}, y, {n} as rounds from (select *, row_number() over (partition by y order by quality_fp desc, cnt desc, {keys}) as j from ({claim})) where j = 1"))
            rest = f"select r.* from {rest} r anti join {won[-1]} w using ({keys}) anti join {won[-1]} v on r.y = v.y"
        return " union all ".join(f"select * from {w}" for w in won)

    def merge(self) -> str:
        """One value for each component of left-side values of a shared right side (by recursion), in place of the chase's."""
        for a in self.p.shared_rhs():
            fds = [f for f in self.p.fds if f.rhs == a]
            names = [f"concat_ws(chr(31), '{f.name}', {', '.join(f'v_{b}::varchar' for b in f.lhs)})" for f in fds]
            links = self.add("links", " union ".join(f"select {names[0]} as a, {n} as b from {self.cur}" for n in names))
            both = self.add("sides", f"select a, b from {links} union select b, a from {links}")
            self.ctes.append((f"walk_{a}(a, b)", f"select a, a from {both} union select walk_{a}.a, e.b from walk_{a} join {both} e on walk_{a}.b = e.a"))
            roots = self.add("roots", f"select a as node, min(b) as root from walk_{a} group by a")
            votes = " union all ".join(f"select concat_ws(chr(31), '{f.name}', {', '.join(f'x_{b}::varchar' for b in f.lhs)}) as node, y, quality_fp::hugeint * cnt as s from {self.q[f]}" for f in fds)
            best = self.add("best", f"select root, y from (select root, y, row_number() over (partition by root order by sum(s) desc, y) as k from ({votes}) join {roots} using (node) group by root, y) where k = 1")
            self.cur = self.add("cur", f"select c.* replace (coalesce(b.y, c.v_{a}) as v_{a}) from (select *, {names[0]} as node from {self.cur}) c left join {roots} r using (node) left join {best} b using (root)")
        return self.cur

    def tables_long(self) -> str:
        return " union all ".join(f"select '{f.name}' as fd, {self.key(f)} as lhs, y::varchar as rhs, origin from {t}" for f, t in self.r.items())

    def expressions(self) -> str:
        groups = []
        for group in parts(self.p.fds):
            steps = [f"case when r{k} is not null then '[{f.name}: ' || l{k} || ' -> ' || r{k} || ']' end" for k, f in enumerate(self.p.fds) if f in group]
            groups.append(f"nullif(concat_ws(' > ', {', '.join(steps)}), '')")
        return f"select {', '.join(self.key_columns)}, concat_ws(' & ', {', '.join(groups)}) as expression from {self.cur}"


def quality_of(relation: str, fds: str) -> str:
    """Instance quality as a scalar query."""
    return " + ".join(f"(select coalesce(sum(c * c), 0) from (select count(*) as c from {relation} where {' and '.join(f'{a} is not null' for a in sorted(f.attributes))} group by {', '.join((*f.lhs, f.rhs))}))" for f in parse(fds))


def violations(relation: str, fds: str) -> str:
    out = []
    for f in parse(fds):
        lhs = ", ".join(f.lhs)
        keep = " and ".join(f"{a} is not null" for a in (*f.lhs, f.rhs))
        each = f"select {lhs}, sum(c) as s, max(c) as m, sum(c * c) as q, count(*) as k from (select {lhs}, {f.rhs}, count(*) as c from {relation} where {keep} group by {lhs}, {f.rhs}) group by {lhs}"
        out.append(f"select '{f.name}' as fd, count(*) as groups, coalesce(sum(case when k > 1 then 1 else 0 end), 0)::bigint as violating_groups, coalesce(sum(case when k > 1 then s else 0 end), 0)::bigint as violating_rows, coalesce(sum(case when k > 1 then (s * s - q) // 2 else 0 end), 0)::bigint as violating_pairs, coalesce(sum(s - m), 0)::bigint as g3 from ({each})")
    return " union all ".join(out)
