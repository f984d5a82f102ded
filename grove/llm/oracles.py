"""DuckDB SQL for the opN_ queries that SQL can express."""

from __future__ import annotations

#: Lower-cased words under the operators' word rule.
_ASCII = "translate({0}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_SPLIT = "list_filter(regexp_split_to_array({0}, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '')"

_OP8 = f"""
with recursive w as materialized (select doc_id, {_SPLIT.format(_ASCII.format("coalesce(text, '')"))} as w from documents),
s as materialized (select doc_id, case when len(w) = 0 then cast([] as varchar[]) when len(w) < 5 then [array_to_string(w, ' ')]
        else list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' '))) end as g from w),
n as materialized (select doc_id, cast(len(g) as bigint) as n_shingles from s),
u as materialized (select doc_id, hash(g) as g from (select doc_id, unnest(g) as g from s)),
e as materialized (select a.doc_id as a, b.doc_id as b from u a join u b on a.g = b.g and a.doc_id <> b.doc_id
      join n x on x.doc_id = a.doc_id join n y on y.doc_id = b.doc_id
      group by a.doc_id, b.doc_id, x.n_shingles, y.n_shingles
      having 100 * count(*) >= 85 * (x.n_shingles + y.n_shingles - count(*))),
r as (select doc_id as a, doc_id as b from n union select r.a, e.b from r join e on r.b = e.a)
select n.doc_id, n.n_shingles, min(r.b) as component_id, n.doc_id = min(r.b) as kept
from n join r on r.a = n.doc_id group by n.doc_id, n.n_shingles
"""

_OP3 = r"""
with r0 as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all values (-1, 0, 'user', '</s>[INST] ok [/INST]'), (-1, 1, 'assistant', '</s>[INST] ok [/INST]')),
r1 as (select *, row_number() over (partition by conv_id order by turn, role, text) - 1 as idx,
  len(regexp_extract_all(text, '[A-Za-z0-9]+|[^A-Za-z0-9\x20\x09-\x0D]')) + 2 as size,
  replace(replace(replace(replace(replace(text, '\', '\\'), '<s>', '<\s>'), '</s>', '<\/s>'), '[INST', '[\INST'), '[/INST', '[\/INST') as esc from r0),
r2 as (select *, sum(size) over (partition by conv_id order by idx) as upto, length(esc) + length(url_encode(role)) + 9 + 11 as chars from r1),
s as (select conv_id, size as s_size, chars as s_chars from r2 where idx = 0 and role = 'system'),
own as (select r2.*, cast(floor((upto - 1) / greatest(208, 416 - coalesce(s_size, 0) // 2)) as bigint) as win from r2 left join s using (conv_id)),
f as (select conv_id, win, min(idx) as first, min(upto - size) as base from own group by conv_id, win),
past as (select o.conv_id, f.win, o.chars from own o join f on o.conv_id = f.conv_id and o.idx in (f.first - 1, f.first - 2)
  where f.base - o.upto + o.size <= 192 and not (o.idx = 0 and o.role = 'system')),
again as (select f.conv_id, f.win, s_chars as chars from f join s using (conv_id) where first > 0),
total as (select conv_id, sum(chars) + 3 * count(distinct win) as formatted_chars from
  (select conv_id, win, chars from own union all select * from past union all select * from again) group by conv_id)
select conv_id, count(*) as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by idx)) as turns_sha256,
  coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by idx) filter (role = 'assistant'), '')) as loss_sha256,
  formatted_chars::bigint as formatted_chars
from r2 join total using (conv_id) group by conv_id, formatted_chars
"""

_OP5 = """
with p as (select page_id, coalesce(html, '') as html, sha1(coalesce(html, '')) as h, min(page_id) over (partition by coalesce(html, '')) as first from pages)
select page_id, cast(strlen(html) as bigint) as payload_bytes,
  array_to_string(list_transform(range(32), lambda j: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    cast(1 + ((cast('0x' || substr(h, cast(1 + 5 * (j // 4) as bigint), 5) as bigint) >> cast(15 - 5 * (j % 4) as bigint)) & 31) as bigint), 1)), '') as payload_digest,
  case when page_id = first then 'response' else 'revisit' end as record_type,
  case when page_id = first then null else first end as refers_to
from p
"""

_SPLIT7 = "list_filter(regexp_split_to_array(lower(text), '[^\\p{L}\\p{N}]+'), lambda x: x <> '')"
# every item of the given benchmark is longer than a span, so the rule for shorter items isn't needed here
_OP7 = f"""
with m(n, pos) as (values (0, [0, 1, 2, 4, 7, 8, 10, 11]), (1, [0, 1, 3, 4, 6, 8, 9, 11])),
d as (select doc_id, {_SPLIT7} as w from documents where text is not null),
b as (select item_id, {_SPLIT7} as v from benchmark where text is not null),
ds as (select doc_id, n, ofs, list_transform(pos, lambda p: w[ofs + p + 1]) as seed from (select *, unnest(range(0, len(w) - 11)) as ofs from d where len(w) >= 12), m),
bs as (select item_id, n, ofs, list_transform(pos, lambda p: v[ofs + p + 1]) as seed from (select *, unnest(range(0, len(v) - 11)) as ofs from b where len(v) >= 12), m),
hits as (select distinct doc_id, item_id, ds.ofs - bs.ofs as shift from ds join bs on ds.n = bs.n and ds.seed = bs.seed),
a0 as (select *, greatest(0, -shift) as lo, least(len(v), len(w) - shift) as hi, least(16, len(v)) as n_words from hits join d using (doc_id) join b using (item_id)),
a1 as (select *, list_transform(range(lo, hi), lambda j: cast(v[j + 1] = w[j + shift + 1] as int)) as same from a0 where hi - lo >= n_words),
a2 as (select *, unnest(range(0, len(same) - n_words + 1)) as ofs from a1),
a3 as (select doc_id, item_id, lo + shift + ofs as doc_word, lo + ofs as item_word, list_sum(same[ofs + 1:ofs + n_words]) as n_matched, n_words from a2)
select doc_id, item_id, cast(doc_word as bigint) as doc_word, cast(item_word as bigint) as item_word, cast(n_matched as bigint) as n_matched, cast(n_words as bigint) as n_words
from a3 where 100 * n_matched >= 80 * n_words
qualify row_number() over (partition by doc_id, item_id order by n_matched desc, doc_word, item_word) = 1
"""

_OP9 = """
with d as (select doc_id, text, md5(text) as digest, string_split(text, chr(10)) as ls from documents),
l as (select doc_id as id, digest, unnest(range(0, len(ls))) as pos, unnest(ls) as line from d where text is not null),
w as (select id, digest, pos, list_transform(list_filter(regexp_split_to_array(line, '[\\x20\\x09-\\x0D]+'), lambda x: x <> ''),
  lambda x: case when regexp_matches(x, '[0-9]') then '<*>' else x end) as w from l),
k as (select id, digest, pos, w, len(w) as n, w[1] as a, w[2] as b, w[3] as c from w where len(w) >= 3),
reached as (select n, a, b, c from k group by n, a, b, c having count(distinct digest) >= 3),
u as (select k.*, array_to_string(w, ' ') as shape from k join reached using (n, a, b, c)),
shapes as (select n, a, b, c, shape, any_value(w) as w, count(distinct digest) as texts from u group by n, a, b, c, shape),
spread as (select n, a, b, c, shape, texts, unnest(range(0, len(w))) as ofs, unnest(w) as word from shapes),
support as (select n, a, b, c, ofs, word from spread group by n, a, b, c, ofs, word having sum(texts) >= 3),
template as (select s.n, s.a, s.b, s.c, s.shape, count(p.word) as held, string_agg(coalesce(p.word, '<*>'), ' ' order by s.ofs) as template
  from spread s left join support p on s.n = p.n and s.a = p.a and s.b = p.b and s.c = p.c and s.ofs = p.ofs and s.word = p.word
  group by s.n, s.a, s.b, s.c, s.shape having 2 * count(p.word) filter (p.word <> '<*>') >= s.n and (count(p.word) = s.n or (s.n >= 8 and 4 * count(p.word) >= 3 * s.n))),
matched as (select n, a, b, c, template, digest, id, pos from u join template using (n, a, b, c, shape)),
recurs as (select n, a, b, c, template, min(struct_pack(id := id, digest := digest)) as first from matched group by n, a, b, c, template having count(distinct digest) >= 3),
drops as (select digest, list(distinct pos) as drops from matched join recurs using (n, a, b, c, template) where digest <> first.digest group by digest)
select doc_id, cast(case when length(text) > 0 then len(ls) else 0 end as bigint) as n_lines, cast(coalesce(len(drops), 0) as bigint) as n_dropped,
  md5(array_to_string(list_filter(ls, lambda x, i: not list_contains(coalesce(drops, cast([] as bigint[])), i - 1)), chr(10))) as text_md5
from d left join drops using (digest)
"""

SQL = {
    "op3_budgeted_chat_windows": _OP3,
    "op5_dictionary_warc": _OP5,
    "op7_spaced_seed_leaks": _OP7,
    "op8_minmax_near_duplicates": _OP8,
    "op9_line_templates": _OP9,
}
