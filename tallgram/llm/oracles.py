"""DuckDB SQL of the corpus queries that SQL can express on whole tables."""

from __future__ import annotations

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORDS = rf"regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

CONTAMINATION = f"""
with d as (select doc_id, {_WORDS} as w from documents),
b as (select item_id, {_WORDS} as w from benchmark),
test_windows as (
  select distinct item_id, k, array_to_string(w[p : p + k - 1], ' ') as g
  from (select item_id, w, k, unnest(range(1, len(w) - k + 2)) as p from (select item_id, w, least(10, len(w)) as k from b where len(w) > 0))),
places as (
  select item_id, k, q, array_to_string(w[q : q + k - 1], ' ') as g
  from (select item_id, w, k, unnest(range(1, len(w) - k + 2)) as q from (select item_id, w, least(10, len(w)) as k from b where len(w) > 0))),
windows as (
  select doc_id, p, k, array_to_string(w[p : p + k - 1], ' ') as g
  from (select doc_id, w, k, unnest(range(1, len(w) - k + 2)) as p from d, (select distinct k from test_windows) where len(w) >= k)),
hits as (select doc_id, p, windows.k as k, item_id from windows join test_windows using (k, g)),
words_hit as (select doc_id, count(distinct q) as n from (select doc_id, unnest(range(p, p + k)) as q from hits) group by doc_id),
diagonals as (
  select doc_id, item_id, p, p - q as diagonal, windows.k as k, p - row_number() over (partition by doc_id, item_id, p - q order by p) as island
  from windows join places using (k, g)),
runs as (select doc_id, max(p) - min(p) + max(k) as n from diagonals group by doc_id, item_id, diagonal, island),
longest as (select doc_id, max(n) as n from runs group by doc_id),
items as (select doc_id, count(*) as n, string_agg(item, ',' order by item) as ids from (select distinct doc_id, item_id::varchar as item from hits) group by doc_id)
select d.doc_id, len(d.w)::bigint as n_words, coalesce(words_hit.n, 0)::bigint as n_hit, coalesce(items.n, 0)::bigint as n_items,
  sha256(coalesce(items.ids, '')) as items_sha256, coalesce(words_hit.n, 0) > 0 as contaminated, coalesce(longest.n, 0)::bigint as longest
from d left join words_hit using (doc_id) left join items using (doc_id) left join longest using (doc_id)
"""

CLASSES = f"""
with recursive d as (select doc_id, text, {_WORDS} as w from documents where text is not null),
places as (select doc_id, w, unnest(range(1, greatest(len(w) - 4, least(len(w), 1)) + 1)) as p from d),
bags as (select doc_id, g, count(*) as c from (select doc_id, array_to_string(w[p : p + 4], ' ') as g from places) group by doc_id, g),
sizes as (select doc_id, sum(c) as n from bags group by doc_id),
common as (select a.doc_id as a, b.doc_id as b, sum(least(a.c, b.c)) as n from bags a join bags b on a.g = b.g and a.doc_id < b.doc_id group by 1, 2),
links as (
  select a, b from common join sizes x on x.doc_id = a join sizes y on y.doc_id = b where common.n::double / (x.n + y.n - common.n) >= 0.8
  union select x.doc_id, y.doc_id from d x join d y on x.text = y.text and x.doc_id < y.doc_id),
edges as (select a, b from links union select b, a from links),
reach(doc_id, root) as (select doc_id, doc_id from documents union select edges.b, reach.root from reach join edges on edges.a = reach.doc_id and edges.b > reach.root)
select doc_id, min(root) as class_id, doc_id = min(root) as is_kept from reach group by doc_id
"""
