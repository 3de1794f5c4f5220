"""SQL for DuckDB of the operators that SQL can express, by their definitions and not by their methods."""

from __future__ import annotations

from . import url_filter

AZ = "translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
PLAIN = r"'[^\x20\x09-\x0D]+'"
ALNUM = r"'[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'"

REPEATED_WORDS = f"""
with w as (select doc_id, coalesce(regexp_extract_all(text, {PLAIN}), []) as ws from documents),
windows as (select doc_id, i, array_to_string(list_slice(ws, i, i + 12), ' ') as k from (select doc_id, ws, unnest(range(1, len(ws) - 11)) as i from w)),
earliest as (select k, min(doc_id) as least from windows group by k),
gone as (select distinct doc_id, unnest(range(i, i + 13)) as p from windows join earliest using (k) where least < doc_id),
positions as (select doc_id, unnest(ws) as word, unnest(range(1, len(ws) + 1)) as p from w),
kept as (select doc_id, string_agg(word, ' ' order by p) as s from positions anti join gone using (doc_id, p) group by doc_id),
lost as (select doc_id, count(*) as n from gone group by doc_id)
select w.doc_id, len(ws) as n_words, coalesce(lost.n, 0) as n_removed, sha256(coalesce(s, '')) as kept_sha256
from w left join lost using (doc_id) left join kept using (doc_id)
"""

NEAR_COPIES = f"""
with recursive w as (select doc_id, coalesce(regexp_extract_all({AZ}, {PLAIN}), []) as ws from documents),
sets as (select doc_id, list_distinct(case when len(ws) > 1 then list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]) else ws end) as s from w),
flat as (select doc_id, unnest(s) as shingle from sets),
common as (select a.doc_id as a, b.doc_id as b, count(*) as n from flat a join flat b on a.shingle = b.shingle and a.doc_id <> b.doc_id group by 1, 2),
links as (select a, b from common join sets x on x.doc_id = a join sets y on y.doc_id = b where 100 * n >= 80 * (len(x.s) + len(y.s) - n)),
reach(doc_id, other) as (select doc_id, doc_id from documents union select r.doc_id, l.b from reach r join links l on r.other = l.a),
least as (select doc_id, min(other) as component_id from reach group by doc_id)
select doc_id, len(s) as n_shingles, component_id, doc_id = component_id as kept from sets join least using (doc_id)
"""

CONTAMINATION = f"""
with i as (select item_id, regexp_extract_all({AZ}, {ALNUM}) as ws from benchmark),
sized as (select item_id, ws, least(10, len(ws)) as m from i where len(ws) > 0),
windows as (select distinct item_id, m, array_to_string(list_slice(ws, p, p + m - 1), ' ') as k from (select *, unnest(range(1, len(ws) - m + 2)) as p from sized)),
d as (select doc_id, coalesce(regexp_extract_all({AZ}, {ALNUM}), []) as ws from documents),
places as (select doc_id, m, p, array_to_string(list_slice(ws, p, p + m - 1), ' ') as k from (select doc_id, ws, m, unnest(range(1, len(ws) - m + 2)) as p from d, (select distinct m from windows))),
hits as (select doc_id, item_id, p, windows.m from places join windows on places.k = windows.k and places.m = windows.m),
words as (select doc_id, count(distinct q) as n from (select doc_id, unnest(range(p, p + m)) as q from hits) group by doc_id),
items as (select doc_id, count(*) as n, string_agg(item_id, ',' order by item_id) as ids from (select distinct doc_id, cast(item_id as varchar) as item_id from hits) group by doc_id)
select d.doc_id, len(ws) as n_words, coalesce(words.n, 0) as n_hit, coalesce(items.n, 0) as n_items, sha256(coalesce(ids, '')) as items_sha256, coalesce(words.n, 0) > 0 as contaminated
from d left join words using (doc_id) left join items using (doc_id)
"""

#: BM25 in whole multiples of 2 ** -20, as the operator counts it; every twentieth document against all.
SEARCH = f"""
with d as (select doc_id, text is not null as known, coalesce(regexp_extract_all({AZ}, {ALNUM}), []) as ws from documents),
size as (select count(*) as n, sum(len(ws)) / count(*) as mean from d),
tf as (select doc_id, w, count(*) as tf from (select doc_id, unnest(ws) as w from d) group by all),
idf as (select w, ln(1 + (any_value(n) - count(*) + 0.5) / (count(*) + 0.5)) as idf from tf, size group by w),
weights as (select tf.doc_id, w, round(1048576 * idf * tf * 2.2 / (tf + 1.2 * (1 - 0.75 + 0.75 * len(ws) / mean))) as weight from tf join idf using (w) join d on d.doc_id = tf.doc_id, size),
points as (select q.doc_id as query_id, x.doc_id, sum(q.tf * x.weight) as points from tf q join weights x using (w) where q.doc_id % 20 = 0 group by 1, 2),
ranked as (select *, row_number() over (partition by query_id order by points desc, doc_id) as rank from points where points > 0)
select query_id, cast(rank as integer) as rank, doc_id, points / 1048576 as score from ranked where rank <= 10
"""

SQL = {
    "op4_block_max_search": SEARCH,
    "op3_temporal_url_lists": url_filter.SQL,
    "op7_fm_index": REPEATED_WORDS,
    "op8_minhash_star_components": NEAR_COPIES,
    "op10_training_suffix_arrays": CONTAMINATION,
}
