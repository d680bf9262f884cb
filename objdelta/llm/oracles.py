"""DuckDB SQL for the operators whose rows SQL can express; brute force over all pairs or all windows, for small tables."""

from __future__ import annotations

_LOW = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
#: Smallest id reachable over links (a, b), given both ways, from every node.
_REACH = "reach(node, m) as (select id, id from nodes union select l.b, r.m from reach r join links l on l.a = r.node), low as (select node, min(m) as component_id from reach group by node)"

VECTORS = f"""
with recursive vectors as (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings),
usable as (select vec_id, e, sqrt(list_dot_product(e, e)) as n from vectors where e is not null and not list_contains(list_transform(e, lambda x: x is not null and isfinite(x)), false) and list_dot_product(e, e) > 0),
links as (select a.vec_id as a, b.vec_id as b from usable a join usable b on a.vec_id <> b.vec_id where list_dot_product(a.e, b.e) / (a.n * b.n) >= 0.95),
nodes as (select vec_id as id from embeddings), {_REACH},
degree as (select a, count(*) as n from links group by a)
select v.id as vec_id, coalesce(d.n, 0)::bigint as n_links, l.component_id::bigint as component_id, v.id = l.component_id as kept
from nodes v join low l on l.node = v.id left join degree d on d.a = v.id"""

SHINGLES = f"""
with recursive words as (select doc_id, regexp_extract_all({_LOW}, '[^\\x20\\x09-\\x0D]+') as w from documents),
sets as (select doc_id, list_distinct(case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')]
  else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) end) as s from words),
held as (select doc_id, len(s) as n, unnest(s) as g from sets),
pairs as (select a.doc_id as a, b.doc_id as b, any_value(a.n) as x, any_value(b.n) as y, count(*) as c from held a join held b on a.g = b.g and a.doc_id <> b.doc_id group by 1, 2),
links as (select a, b from pairs where 100 * c >= 75 * (x + y - c)),
nodes as (select doc_id as id from documents), {_REACH}
select s.doc_id, len(s.s)::bigint as n_shingles, l.component_id::bigint as component_id from sets s join low l on l.node = s.doc_id"""

SUFFIXES = """
with bytes as (select doc_id, hex(encode(coalesce(text, ''))) as h, octet_length(encode(coalesce(text, ''))) as n from documents),
windows as (select doc_id, i, md5_number(substr(h, 2 * i + 1, 100)) as s from (select doc_id, h, unnest(range(0, n - 49)) as i from bytes where n >= 50)),
firsts as (select s, min(doc_id) as f from windows group by s having min(doc_id) < max(doc_id)),
repeated as (select w.doc_id, w.i from windows w join firsts x on x.s = w.s where w.doc_id > x.f),
hit as (select b.doc_id, b.h, b.n, unnest(range(0, b.n)) as i from bytes b where b.doc_id in (select doc_id from repeated)),
marked as (select h.doc_id, h.i, substr(h.h, 2 * h.i + 1, 2) as byte,
  coalesce(max(r.i) over (partition by h.doc_id order by h.i rows between 49 preceding and current row), -1) >= 0 as gone
  from hit h left join repeated r on r.doc_id = h.doc_id and r.i = h.i),
runs as (select *, gone and not coalesce(lag(gone) over (partition by doc_id order by i), false) as opens from marked),
cut as (select doc_id, count(*) filter (where gone) as n_removed, count(*) filter (where opens) as n_spans, sha256(unhex(coalesce(string_agg(byte, '' order by i) filter (where not gone), ''))) as kept from runs group by doc_id)
select b.doc_id, b.n::bigint as n_bytes, coalesce(c.n_removed, 0)::bigint as n_removed, coalesce(c.n_spans, 0)::bigint as n_spans,
  coalesce(c.kept, sha256(unhex(b.h))) as kept_sha256
from bytes b left join cut c on c.doc_id = b.doc_id"""
