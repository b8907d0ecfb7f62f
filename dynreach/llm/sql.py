"""SQL twins of the operators that SQL can express, for DuckDB: brute force over whole tables."""

from __future__ import annotations

from dynreach.llm.secret_scan import BASE_RULES, MORE_RULES, Rule, at_least

_SPREAD = "l as (select a, b from p union select b, a from p), r(x, y) as (select {id}, {id} from v where {id} is not null union select r.x, l.b from r join l on l.a = r.y), c as (select x, min(y) component_id from r group by 1)"

OP4 = f"""
with recursive v as materialized (select vec_id, embedding::double[] e, label, list_sum(list_transform(embedding::double[], lambda x: x * x)) q from embeddings),
ok as (select * from v where label is not null and q > 0 and not isinf(q) and not isnan(q) and len(list_filter(e, lambda x: x is null)) = 0),
p as materialized (select a.vec_id a, b.vec_id b from ok a join ok b on a.label = b.label and a.vec_id < b.vec_id where list_inner_product(a.e, b.e) / sqrt(a.q * b.q) >= 0.93),
{_SPREAD.format(id="vec_id")}
select vec_id, (select count(*) from l where a = vec_id) n_links, component_id, vec_id = component_id kept from v join c on x = vec_id
"""

OP8 = f"""
with recursive w as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') w from documents),
v as materialized (select doc_id, case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')] else list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) end s from w),
s as materialized (select doc_id, unnest(s) g from v), shared as (select a.doc_id a, b.doc_id b, count(*) n from s a join s b on a.g = b.g and a.doc_id < b.doc_id group by 1, 2),
p as materialized (select a, b from shared join v x on x.doc_id = a join v y on y.doc_id = b where 100 * n >= 85 * (len(x.s) + len(y.s) - n)),
{_SPREAD.format(id="doc_id")}
select doc_id, len(s)::bigint n_shingles, component_id, doc_id = component_id kept from v join c on x = doc_id
"""

OP9 = """
with v as materialized (select vec_id, embedding::double[] e from embeddings),
d as (select a.vec_id query_id, b.vec_id, list_reduce(list_transform(list_zip(a.e, b.e), lambda z: z[1] * z[2]), lambda x, y: x + y) score from v a join v b on a.vec_id <> b.vec_id where a.vec_id % 20 = 0),
k as (select *, row_number() over (partition by query_id order by score desc, vec_id)::int rank from d)
select query_id, rank, vec_id, score from k where rank <= 20
"""


def _spans(rule: Rule, order: int) -> str:
    """Places are sums of the lengths of what lies between matches and of the matches before."""
    short = at_least(rule) == rule.pattern
    quoted = (rule.pattern if short else f"{rule.pattern[:-1]}{{{rule.least},}}").replace("'", "''")
    part = f"regexp_extract(m[i], '{quoted}', {rule.group})"
    return f"""
select doc_id, {order} o, '{rule.kind}' kind, place s, place + len(m[i]) e from (
  select *, list_sum(list_transform(g[1:i], lambda x: len(x))) + coalesce(list_sum(list_transform(m[1:i - 1], lambda x: len(x))), 0) place
  from (select *, unnest(range(1, len(m) + 1)) i from (select doc_id, string_split_regex(t, '{quoted}') g, regexp_extract_all(t, '{quoted}') m from docs where regexp_matches(t, '{quoted}')))) where len({part}) >= {rule.least}"""


_SPANS = " union all ".join(_spans(r, i) for i, r in enumerate(BASE_RULES + MORE_RULES))
_JOINED = "coalesce(string_agg(kind || ':' || s::bigint || ':' || e::bigint, ',' order by s, o){keep}, '')"

OP6 = f"""
with docs as (select doc_id, coalesce(text, '') t from documents), found as ({_SPANS})
select d.doc_id, count(*) filter (where kind = 'assign') n_assign, count(*) filter (where kind = 'access') n_access, count(*) filter (where kind = 'hex') n_hex,
sha256({_JOINED.format(keep=" filter (where o < 3)")}) base_sha256, {_JOINED.format(keep="")} spans
from docs d left join found f on f.doc_id = d.doc_id group by d.doc_id
"""
