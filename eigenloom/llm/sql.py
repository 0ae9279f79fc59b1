"""DuckDB SQL of the operator queries that SQL can express."""

from __future__ import annotations

from .chat import _ESCAPE
from .decontaminate import DISTANCE, RAREST, WIDTH
from .quality_rules import BOILERPLATE, LEAST_LEFT, MARKED_WORD, NAVIGATION, SHOUT, SYMBOLS


def _text(pattern: str) -> str:
    return "'" + pattern.replace("'", "''") + "'"


_GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORD = "[^\\x20\\x09-\\x0D]+"


def _words(table: str, key: str) -> str:
    return f"select {key}, list_filter(string_split_regex({_LOWER.format('coalesce(text, chr(32))')}, '{_GAP}'), lambda w: w <> '') as words from {table}"


OP1 = f"""
with d as ({_words('documents', 'doc_id')}),
b as (select * from ({_words('benchmark', 'item_id')}) where len(words) > 0),
w as (select distinct item_id, least({WIDTH}, len(words)) as n, array_to_string(words[i:i + {WIDTH - 1}], ' ') as phrase
  from b, unnest(range(1, greatest(2, len(words) - {WIDTH - 2}))) as u(i)),
spots as (select doc_id, p, n, array_to_string(words[p:p + n - 1], ' ') as phrase
  from d, unnest(range(1, len(words) + 1)) as u(p), (select distinct n from w) where p + n - 1 <= len(words)),
hit as (select a.doc_id, a.p, a.n, w.item_id from spots a join w on a.n = w.n and a.phrase = w.phrase),
covered as (select doc_id, count(distinct q) as n_hit from hit, unnest(range(p, p + n)) as u(q) group by doc_id),
named as (select doc_id, count(distinct item_id) as n_items, string_agg(distinct item_id::varchar, ',' order by item_id::varchar) as items from hit group by doc_id),
freq as (select term, count(*) as f from (select unnest(words) as term from d) group by term),
cut as (select distinct words[i:i + {WIDTH - 1}] as words from b, unnest(range(1, greatest(2, len(words) - {WIDTH - 2}))) as u(i)),
terms as (select distinct words, least({RAREST}, len(list_distinct(words))) as need, unnest(words) as term from cut),
probes as (select words, need, term, row_number() over (partition by words order by f, term) as rank from terms join freq using (term) qualify rank <= need),
asked as (select words, need, rank, term from probes qualify count(*) over (partition by words) = need),
places as (select doc_id, words[p] as term, p from d, unnest(range(1, len(words) + 1)) as u(p)),
occ as materialized (select doc_id, a.words, need, rank, p from places join asked a using (term)),
close as (select x.doc_id, x.words from occ x join occ y on x.doc_id = y.doc_id and x.words = y.words and y.p between x.p and x.p + {DISTANCE}
  group by x.doc_id, x.words, x.need, x.p having count(distinct y.rank) = x.need),
near as (select distinct doc_id, words from close),
owned as (select distinct item_id, words[i:i + {WIDTH - 1}] as words from b, unnest(range(1, greatest(2, len(words) - {WIDTH - 2}))) as u(i)),
near_named as (select doc_id, count(distinct words) as n_near, count(distinct item_id) as n_near_items, string_agg(distinct item_id::varchar, ',' order by item_id::varchar) as near_items
  from near join owned using (words) group by doc_id)
select d.doc_id, len(d.words)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items,
  sha256(coalesce(items, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated,
  coalesce(n_near, 0)::bigint as n_near, coalesce(n_near_items, 0)::bigint as n_near_items, sha256(coalesce(near_items, '')) as near_items_sha256
from d left join covered using (doc_id) left join named using (doc_id) left join near_named using (doc_id)"""

OP2 = """
with recursive crc_step(k, c, n) as (select range, range, 0 from range(256) union all
  select k, case when c & 1 = 1 then xor(c >> 1, 3988292384) else c >> 1 end, n + 1 from crc_step where n < 8),
crc_table as (select list(c order by k) as t from crc_step where n = 8),
b as (select doc_id, text, string_split(hex(encode(coalesce(text, ''))), '') as h from documents),
bytes as (select doc_id, strlen(coalesce(text, '')) + 1 as size,
  list_transform(range(0, strlen(coalesce(text, ''))), lambda i: ((strpos('0123456789ABCDEF', h[2 * i + 1]) - 1) * 16 + strpos('0123456789ABCDEF', h[2 * i + 2]) - 1)::bigint) as v from b),
crc as (select doc_id, size, case when len(v) = 0 then 0 else xor(list_reduce(list_prepend(4294967295::bigint, v), lambda c, x: xor(c >> 8, t[xor(c, x) & 255 ::bigint + 1])), 4294967295) end as text_crc32
  from bytes, crc_table),
slots as (select *, (('0x' || substr(md5(coalesce(doc_id::varchar, '')), 1, 12))::bigint % 4096)::int as vslot from crc),
owned as (select *, (vslot * 8 // 4096)::int as shard, sum(size) over (partition by vslot) as vslot_bytes from slots)
select doc_id, size::bigint as size, text_crc32::bigint as text_crc32, 'key' as law, shard,
  (row_number() over (partition by shard order by vslot, text_crc32 % 4096, doc_id, text_crc32, size) - 1)::bigint as slot,
  (case when vslot % 512 >= 512 - 57 + (shard = 7)::int then 8 else shard end)::int as grown_shard, vslot, vslot_bytes::bigint as vslot_bytes
from owned"""
OP2 = OP2.replace("t[xor(c, x) & 255 ::bigint + 1]", "t[(xor(c, x) & 255) + 1]")

_MARKS = _text(_ESCAPE.pattern)
OP6 = f"""
with c as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -1, 0, 'user', '</s>[INST] ok [/INST]' union all select -1, 1, 'assistant', '</s>[INST] ok [/INST]')
select conv_id, count(*)::bigint as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
  coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (role = 'assistant'), '')) as loss_sha256,
  sum(20 + length(role) + length(text) + len(regexp_extract_all(role, {_MARKS})) + len(regexp_extract_all(text, {_MARKS})))::bigint as formatted_chars
from c group by conv_id"""

OP10 = f"""
with d as (select doc_id, coalesce(text, '') as text from documents),
lines as (select *, string_split(text, chr(10)) as ls, regexp_extract_all(text, '{_WORD}') as ws from d),
p as (select doc_id, i, ws[i] as w from lines, unnest(range(1, len(ws) + 1)) as u(i)),
v as (select doc_id, i, case when lead(w, 4) over o is not null then w || ' ' || lead(w, 1) over o || ' ' || lead(w, 2) over o || ' ' || lead(w, 3) over o || ' ' || lead(w, 4) over o end as five
  from p window o as (partition by doc_id order by i)),
r as (select doc_id, i, five is not null and count(*) over (partition by doc_id, five) > 1 as again from v),
cov as (select doc_id, i, max(again::int) over (partition by doc_id order by i rows between 4 preceding and current row) as hit from r),
rep as (select doc_id, sum(hit) as n_repeat_words from cov group by doc_id),
base as (select doc_id, ls, len(ws)::bigint as n_words, length(translate(text, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13), ''))::bigint as word_chars,
  (length(text) - length(translate(text, '{SYMBOLS}', '')))::bigint as n_symbols, list_filter(ls, lambda l: regexp_matches(l, '{_WORD}')) as lw, coalesce(n_repeat_words, 0)::bigint as n_repeat_words
  from lines left join rep using (doc_id)),
ruled as (select *, list_filter(ls, lambda l: not (regexp_matches(l, {_text(NAVIGATION)}) or regexp_matches(l, {_text(BOILERPLATE)}) or regexp_matches(l, {_text(SHOUT)})
  or len(regexp_extract_all(l, {_text(MARKED_WORD)})) >= 3 or (length(l) - length(translate(l, '{SYMBOLS}', ''))) * 10 > length(l))) as good,
  n_words < 10 or n_repeat_words * 100 > n_words * 20 as base_failed from base),
shares as (select *, list_sum(list_transform(ls, lambda l: length(l))) as total, coalesce(list_sum(list_transform(good, lambda l: length(l))), 0) as left_over from ruled)
select doc_id, n_words, word_chars, n_symbols, (len(lw) - len(list_distinct(lw)))::bigint as n_dup_lines, n_repeat_words, base_failed,
  not base_failed and (case when total > 0 then left_over::double / total else 0 end) >= {LEAST_LEFT} as kept,
  len(ls)::bigint as n_lines, (len(ls) - len(good))::bigint as n_lines_failed, round(case when total > 0 then left_over::double / total else 0 end, 6)::double as share_left
from shares"""

ORACLES = {"op1_decontaminate": OP1, "op2_sharding": OP2, "op6_chat": OP6, "op10_quality_rules": OP10}
