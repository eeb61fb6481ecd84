"""SQL (DuckDB) for the operators whose results SQL can give by plainer, quadratic means on small tables."""

#: Windows of 20 words by their text; each but the first of a text removes its words.
SUBSTRINGS = r"""
with d as materialized (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as w from documents),
t as materialized (select doc_id, w, unnest(range(1, len(w) - 18)) as p from d where len(w) >= 20),
h as materialized (select doc_id, p, md5(array_to_string(w[p:p + 19], ' ')) as h from t),
f as materialized (select h, min((doc_id, p)) as first from h group by h),
x as materialized (select h.doc_id, h.p from h join f using (h) where (h.doc_id, h.p) > f.first),
c as materialized (select distinct doc_id, unnest(range(p, p + 20)) as i from x),
k as materialized (select doc_id, unnest(range(1, len(w) + 1)) as i, unnest(w) as word from d),
kept as materialized (select k.doc_id, string_agg(word, ' ' order by i) as text, count(*) as n from k anti join c using (doc_id, i) group by k.doc_id)
select d.doc_id, len(w)::bigint as n_words, (len(w) - coalesce(n, 0))::bigint as n_removed, sha256(coalesce(kept.text, '')) as kept_sha256
from d left join kept using (doc_id)
"""

#: Weighted Jaccard of five-word runs over all pairs that share one, and the least id of each component.
NEAR_DUPLICATES = r"""
with recursive d as materialized (select doc_id, regexp_extract_all(lower(coalesce(text, '')), '[\p{L}\p{N}_]+') as w from documents),
s as materialized (
    select doc_id, array_to_string(w[p:p + 4], ' ') as s from (select doc_id, w, unnest(range(1, greatest(len(w) - 3, 2))) as p from d where len(w) > 0)
),
r as materialized (select doc_id, md5(s) as s, count(*) as c from s group by all),
n as materialized (select doc_id, sum(c) as n from r group by doc_id),
m as materialized (select a.doc_id as a, b.doc_id as b, sum(least(a.c, b.c)) as m from r a join r b on a.s = b.s and a.doc_id < b.doc_id group by all),
l as materialized (select a, b from m join n x on x.doc_id = a join n y on y.doc_id = b where m::double / (x.n + y.n - m) >= 0.8),
e as materialized (select a, b from l union all select b, a from l),
reach(a, b) as (select a, b from e union select reach.a, e.b from reach join e on reach.b = e.a)
select doc_id, least(doc_id, coalesce(min(b), doc_id)) as class_id from d left join reach on a = doc_id group by doc_id
"""
