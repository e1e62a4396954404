"""DuckDB statements for the queries that plain SQL can express, by brute force over all rows."""

from __future__ import annotations

from wavefront.llm.licences import TEMPLATES, THRESHOLD, bigrams

_LOW = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

NEAR_DUPLICATES = rf"""
with recursive w as (select doc_id, regexp_extract_all({_LOW}, '[^\x20\x09-\x0D]+') as w from documents),
s as (select distinct doc_id, unnest(case when len(w) >= 5 then list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) when len(w) > 0 then ['(' || len(w) || ')' || array_to_string(w, ' ')] else [] end) as g from w),
n as (select doc_id, count(*) as n from s group by doc_id),
p as (select a.doc_id as u, b.doc_id as v, count(*) as common from s a join s b on a.g = b.g and a.doc_id <> b.doc_id group by 1, 2),
l as (select p.u, p.v from p join n x on p.u = x.doc_id join n y on p.v = y.doc_id where 100 * common >= 85 * (x.n + y.n - common)),
r(u, v) as (select doc_id, doc_id from documents union select r.u, l.v from r join l on r.v = l.u),
c as (select u, min(v) as component_id from r group by u)
select d.doc_id, coalesce(n.n, 0) as n_shingles, c.component_id, d.doc_id = c.component_id as kept from documents d left join n using (doc_id) join c on c.u = d.doc_id"""

NEAR_VECTORS = """
with recursive v as (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings),
good as (select * from v where e is not null and len(e) > 0 and len(list_filter(e, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(e, lambda x: x <> 0)) > 0),
l as (select a.vec_id as u, b.vec_id as w from good a join good b on a.vec_id <> b.vec_id and len(a.e) = len(b.e) and list_cosine_similarity(a.e, b.e) >= 0.9),
r(u, w) as (select vec_id, vec_id from v union select r.u, l.w from r join l on r.w = l.u),
c as (select u, min(w) as component_id from r group by u), n as (select u, count(*) as n from l group by u)
select v.vec_id, coalesce(n.n, 0) as n_links, c.component_id, v.vec_id = c.component_id as kept from v join c on c.u = v.vec_id left join n on n.u = v.vec_id"""


def licences() -> str:
    rows = ", ".join(f"('{name}', [{', '.join(chr(39) + g + chr(39) for g in bigrams(t))}])" for name, texts in sorted(TEMPLATES.items()) for t in texts)
    return rf"""
with t(licence, t) as (values {rows}),
u as (select doc_id, unnest(list_distinct([text] || regexp_split_to_array(text, '\n\s*\n') || regexp_split_to_array(text, '\n'))) as unit from documents),
w as (select doc_id, string_split(trim(regexp_replace(lower(unit), '[^\p{{L}}\p{{N}}]+', ' ', 'g')), ' ') as w from u),
g as (select doc_id, list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) as g from w where len(w) > 1),
m as (select doc_id, licence, 2.0::double * len(list_intersect(g, t)) / (len(g) + len(t)) as dice from g join t on len(g) between len(t) * {THRESHOLD / (2 - THRESHOLD)} and len(t) / {THRESHOLD / (2 - THRESHOLD)}),
b as (select doc_id, licence, dice from m where dice >= {THRESHOLD} qualify row_number() over (partition by doc_id order by dice desc, licence) = 1)
select d.doc_id, b.licence, b.dice from documents d left join b using (doc_id)"""
