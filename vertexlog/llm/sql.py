"""SQL that gives the same rows as those queries of the text operators that SQL can express."""

WORD = r"[^\x20\x09-\x0D]"

_ITEM_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_ITEM_WORDS = f"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_ITEM_WORD}')"

DECONTAMINATION = f"""
with d as (select doc_id, {_ITEM_WORDS} as ws from documents),
b as (select coalesce(item_id::varchar, 'null') as item, {_ITEM_WORDS} as ws from benchmark),
n as (select item, ws, least(13, len(ws)) as size from b where len(ws) > 0),
p as (select item, ws, size, unnest(range(1, len(ws) - size + 2)) as i from n),
w as (select distinct item, size, ws[i:i + size - 1] as part from p),
s as (select distinct size from w),
e as (select doc_id, ws, size, unnest(range(1, len(ws) - size + 2)) as i from d, s where len(ws) >= size),
h as (select doc_id, i, e.size as size, item from e join w on e.size = w.size and e.ws[e.i:e.i + e.size - 1] = w.part),
c as (select distinct doc_id, unnest(range(i, i + size)) as place from (select distinct doc_id, i, size from h)),
r as (select doc_id, place - row_number() over (partition by doc_id order by place) as run from c),
k as (select doc_id, count(*) as n_hit, count(distinct run) as n_spans from r group by doc_id),
f as (select doc_id, count(distinct item) as n_items, array_to_string(list_sort(list(distinct item)), ',') as items from h group by doc_id)
select d.doc_id, len(ws)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items,
  sha256(coalesce(items, '')) as items_sha256, coalesce(n_hit > 0 and 20 * n_hit >= len(ws), false) as contaminated,
  coalesce(n_spans, 0)::bigint as n_spans
from d left join k on d.doc_id = k.doc_id left join f on d.doc_id = f.doc_id
"""

LINE_DEDUP = rf"""
with l as (
  select doc_id, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) as i
  from documents where text is not null),
m as materialized (
  select doc_id, i, line, len(regexp_extract_all(line, '{WORD}+')) as n, ('0x' || substr(md5(line), 1, 8))::bigint as h from l),
p as (
  select *, lag(n) over d as n1, lag(h) over d as h1, lag(h, 2) over d as h2 from m window d as (partition by doc_id order by i)),
c as materialized (
  select doc_id, i, line, n,
    sum(case when i = 1 or n >= 20 or n1 >= 20 or (h1 * 31 + coalesce(h2, 0)) % 2147483647 % 4 = 0 then 1 else 0 end)
      over (partition by doc_id order by i) as no
  from p),
k as (
  select doc_id, no, count(*) as lines, sum(n) as words, string_agg(line, chr(10) order by i) as body from c group by doc_id, no),
r as (
  select *, words > 0 and (lines > 1 or words >= 20) as able from k),
g as materialized (
  select *, able and row_number() over (partition by body, able order by doc_id, no) > 1 as gone from r),
w as materialized (
  select doc_id, i, n, sum(n) over d - n as low, sum(n) over d as high, sum((n between 1 and 19)::int) over d as short
  from m window d as (partition by doc_id order by i)),
e as (
  select a.doc_id, a.i as first, b.i as last, b.short - a.short + (a.n between 1 and 19)::int as short
  from w a join w b on a.doc_id = b.doc_id and a.i < b.i and a.n > 0 and b.n > 0
    and (a.low + 49 >= b.low and a.low + 49 < b.high or b.high - 50 >= a.low and b.high - 50 < a.high)),
t as (
  select e.doc_id, first, last, array_to_string(string_split(text, chr(10))[first:last], chr(10)) as body
  from e join documents d on e.doc_id = d.doc_id where short > 0),
o as (
  select doc_id, first, last, min({{'d': doc_id, 'f': first, 'l': last}}) over (partition by body) as origin from t),
x as (
  select distinct doc_id, unnest(range(first, last + 1)) as i from o where doc_id <> origin.d or first > origin.l),
z as (
  select c.doc_id, c.i, c.line, c.n, g.gone or x.i is not null as gone
  from c join g on c.doc_id = g.doc_id and c.no = g.no left join x on c.doc_id = x.doc_id and c.i = x.i),
y as (
  select doc_id, count(*) as n_lines, count(*) filter (gone) as removed_lines, coalesce(sum(n) filter (gone), 0) as removed_words,
    coalesce(string_agg(line, chr(10) order by i) filter (not gone), '') as kept
  from z group by doc_id),
s as (
  select doc_id, count(*) as n_chunks, count(*) filter (gone) as removed_chunks from g group by doc_id)
select d.doc_id, coalesce(n_lines, 0)::bigint as n_lines, coalesce(n_chunks, 0)::bigint as n_chunks,
  coalesce(removed_chunks, 0)::bigint as removed_chunks, coalesce(removed_lines, 0)::bigint as removed_lines,
  coalesce(removed_words, 0)::bigint as removed_words, case when removed_lines > 0 then kept else d.text end as kept_text
from documents d left join s on d.doc_id = s.doc_id left join y on d.doc_id = y.doc_id
"""

QUALITY = rf"""
with w as (
  select doc_id, source, coalesce(text, '') as text, regexp_extract_all(coalesce(text, ''), '{WORD}+') as ws from documents),
u as (select doc_id, unnest(ws) as a, generate_subscripts(ws, 1) as i from w),
t as (select doc_id, i, a, lead(a) over d as b, lead(a, 2) over d as c from u window d as (partition by doc_id order by i)),
n as (select doc_id, i, count(*) over (partition by doc_id, a, b, c) as times from t where c is not null),
v as (select distinct doc_id, i + o as place from n, (values (0), (1), (2)) as x(o) where times > 1),
rep as (select doc_id, count(*) as n_repeat_words from v group by doc_id),
ln as (
  select doc_id, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '{WORD}')) as ls from w),
m as (
  select w.doc_id, w.source, len(ws)::bigint as n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::bigint as word_chars,
    (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::bigint as n_symbols,
    (len(ls) - len(list_distinct(ls)))::bigint as n_dup_lines, coalesce(n_repeat_words, 0)::bigint as n_repeat_words
  from w join ln on w.doc_id = ln.doc_id left join rep on w.doc_id = rep.doc_id),
f as (select *, n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed from m),
h as (select source, count(*) as n, count(*) filter (base_failed) as k from f group by source),
q as (select avg(k / n) as mu, coalesce(var_samp(k / n), 0) as va from h),
z as (select mu, case when va > 0 and mu * (1 - mu) > va then mu * (1 - mu) / va - 1 else 20.0 end as we from q),
y as (select source, (k + mu * we) / (n + we) as rate from h, z)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  not base_failed and not rate > 0.6 as kept, round(rate, 9) as host_rate
from f join y on f.source is not distinct from y.source
"""

_ESCAPED = "replace(replace(replace(replace(replace({0}, '\\', '\\\\'), '<s>', '<\\s>'), '</s>', '<\\/s>'), '[INST]', '[\\INST]'), '[/INST]', '[\\/INST]')"

CHAT = f"""
with r as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -1, 0, 'user', '</s>[INST] ok [/INST]' union all select -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
e as (
  select *, length('<s>' || replace({_ESCAPED.format("role")}, chr(10), '<\\n>') || chr(10) || {_ESCAPED.format("text")} || '</s>')
    + case when role = 'assistant' then 0 else length('[INST]  [/INST]') end as chars from r)
select conv_id::bigint as conv_id, count(*)::bigint as n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn)) as turns_sha256,
  coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn) filter (role = 'assistant'), '')) as loss_sha256,
  sum(chars)::bigint as formatted_chars
from e group by conv_id
"""

ORACLES = {"op1_benchmark_decontamination": DECONTAMINATION, "op2_line_dedup": LINE_DEDUP, "op6_quality_rules": QUALITY, "op10_chat_formatting": CHAT}
