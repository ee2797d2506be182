"""The operators that SQL can express, in DuckDB's SQL over the same tables."""

from __future__ import annotations

from .quality import OTHER, PUNCTUATION, SYMBOLS

_WHITE = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
_GAP = r"'[\x20\x09-\x0D]+'"


def _quoted(x: str) -> str:
    return "'" + x.replace("'", "''") + "'"


RUN_LENGTH_INDEX = """
with d as (select doc_id, hex(encode(coalesce(text, ''))) as hx from documents),
w as (select doc_id, p, substr(hx, 2 * p + 1, 200) as s from (select doc_id, hx, unnest(range(0, greatest(length(hx) // 2 - 99, 0))) as p from d)),
f as (select s, min(struct_pack(a := doc_id, b := p)) as first from w group by s having count(*) > 1),
m as (select doc_id, p from w join f using (s) where struct_pack(a := doc_id, b := p) > first),
i as (select doc_id, p, sum(new) over (partition by doc_id order by p) as k from
  (select doc_id, p, case when p <= lag(p) over (partition by doc_id order by p) + 100 then 0 else 1 end as new from m)),
r as (select doc_id, min(p) as lo, max(p) + 100 as hi from i group by doc_id, k),
g as (select doc_id, coalesce(lag(hi) over w, 0) as a, lo as b from r window w as (partition by doc_id order by lo)
  union all select doc_id, max(hi), length(any_value(hx)) // 2 from r join d using (doc_id) group by doc_id),
k as (select doc_id, string_agg(substr(hx, 2 * a + 1, 2 * (b - a)), '' order by a) as kept from g join d using (doc_id) group by doc_id),
t as (select doc_id, sum(hi - lo)::bigint as n_removed, count(*) as n_spans from r group by doc_id)
select d.doc_id, (length(hx) // 2)::bigint as n_bytes, coalesce(n_removed, 0)::bigint as n_removed, coalesce(n_spans, 0)::bigint as n_spans, sha256(unhex(coalesce(kept, hx))) as kept_sha256
from d left join t using (doc_id) left join k using (doc_id)"""


def line_suffix_array(min_lines: int = 2, min_words: int = 1) -> str:
    first = "min(struct_pack(a := doc_id, b := pos)) over (partition by name)"
    return f"""
with recursive a as (select doc_id, unnest(string_split(text, chr(10))) as raw, generate_subscripts(string_split(text, chr(10)), 1) - 1 as spot from documents),
l as (select doc_id, spot, trim(raw, {_WHITE}) as line, row_number() over (partition by doc_id order by spot) - 1 as pos, len(regexp_split_to_array(trim(raw, {_WHITE}), {_GAP})) as n_words
  from a where trim(raw, {_WHITE}) <> ''),
u as (select 1 as h, doc_id, pos, name, count(*) over (partition by name) as n, {first} as first from (select doc_id, pos, hash(line) as name from l)
  union all
  select h + 1, doc_id, pos, name, count(*) over (partition by name), {first}
  from (select u.h, u.doc_id, u.pos, hash(u.name, l.line) as name from u join l on l.doc_id = u.doc_id and l.pos = u.pos + u.h where u.n > 1)),
r as (select u.doc_id, u.pos, max(h) as run from u join l on l.doc_id = u.doc_id and l.pos = u.pos
  where struct_pack(a := u.doc_id, b := u.pos) > first and (h >= {min_lines} or n_words >= {min_words}) group by u.doc_id, u.pos),
c as (select l.doc_id, l.spot, run, coalesce(max(l.pos + run) over (partition by l.doc_id order by l.pos) > l.pos, false) as gone from l left join r on r.doc_id = l.doc_id and r.pos = l.pos),
k as (select a.doc_id, string_agg(raw, chr(10) order by a.spot) as kept from a left join c on c.doc_id = a.doc_id and c.spot = a.spot where not coalesce(gone, false) group by a.doc_id),
s as (select doc_id, count(*) as n_lines, count(*) filter (gone) as n_removed, coalesce(max(run), 0) as longest_run from c group by doc_id)
select d.doc_id, coalesce(n_lines, 0)::bigint as n_lines, coalesce(n_removed, 0)::bigint as n_removed, coalesce(longest_run, 0)::bigint as longest_run,
  case when coalesce(n_removed, 0) = 0 then text else coalesce(kept, '') end as kept_text from documents d left join s using (doc_id) left join k using (doc_id)"""


MAXSCORE = """
with v as (select vec_id, list_transform(embedding, lambda x: floor(256 * x::double)) as x from embeddings
  where embedding is not null and len(embedding) > 0 and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
p as (select q.vec_id as query_id, c.vec_id, list_inner_product(q.x, c.x)::bigint as score from v q join v c on q.vec_id % 50 = 0 and q.vec_id <> c.vec_id),
r as (select *, row_number() over (partition by query_id order by score desc, vec_id)::int as rank from p)
select query_id, rank, vec_id, score from r where rank <= 5"""


def distribution_divergence(guard_words: int = 50, class_spread: float = 4.0, word_share: float = 0.9, least_docs: int = 20, n_common: int = 12) -> str:
    without = lambda c, chars: f"(length({c}) - length(translate({c}, {_quoted(chars)}, '')))"
    jsd = lambda a, b: f"sqrt(greatest(list_sum(list_transform(list_zip({a}, {b}), lambda z: (case when z[1] > 0 then z[1] * log2(z[1] / ((z[1] + z[2]) / 2)) else 0 end) + (case when z[2] > 0 then z[2] * log2(z[2] / ((z[1] + z[2]) / 2)) else 0 end))) / 2, 0))"
    mean = lambda c: f"(select language, list(x order by k) as {c}_reference from (select language, k, avg(x) as x from (select language, unnest({c}) as x, generate_subscripts({c}, 1) as k from s where not base_failed) group by language, k) group by language)"
    none = "list_transform(common_reference, lambda x, i: case when i = len(common_reference) then 1.0::double else 0.0::double end)"
    return f"""
with own as (select lang from documents where lang is not null group by lang having count(*) >= {least_docs} order by count(*) desc, lang limit 256),
t as (select doc_id, coalesce(text, '') as text, coalesce(own.lang, '{OTHER}') as language from documents d left join own on d.lang = own.lang),
x as (select *, list_filter(regexp_split_to_array(text, {_GAP}), lambda x: x <> '') as words, translate(text, {_WHITE}, '') as solid,
  list_filter(string_split(text, chr(10)), lambda x: trim(x, {_WHITE}) <> '') as lines from t),
c as (select language, word, count(*) as n from (select language, lower(unnest(words)) as word from x) group by language, word),
li as (select language, list(word order by r) as listed from (select *, row_number() over (partition by language order by n desc, word) as r from c) where r <= {n_common} group by language),
w as (select x.*, coalesce(listed, []) as listed from x left join li using (language)),
g as (select doc_id, i, words[i] || ' ' || words[i + 1] || ' ' || words[i + 2] as s from (select doc_id, words, unnest(range(1, greatest(len(words) - 1, 1))) as i from w)),
o as (select doc_id, count(distinct j) as n from (select doc_id, unnest([i, i + 1, i + 2]) as j from (select *, count(*) over (partition by doc_id, s) as c from g) where c > 1) group by doc_id),
b as (select w.doc_id, language, len(words)::bigint as n_words, length(solid)::bigint as word_chars, length(text)::bigint as n_chars, {without('solid', SYMBOLS)}::bigint as n_symbols,
  {without('solid', '0123456789')} as digits, {without('solid', PUNCTUATION)} as marks, (len(lines) - len(list_distinct(lines)))::bigint as n_dup_lines, coalesce(o.n, 0)::bigint as n_repeat_words,
  list_transform(listed, lambda c: len(list_filter(words, lambda x: lower(x) = c))) as common from w left join o using (doc_id)),
s as (select doc_id, language, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  list_transform([word_chars - n_symbols - digits - marks, digits, marks, n_symbols, n_chars - word_chars], lambda x: case when n_chars > 0 then x / n_chars::double else 0 end) as classes,
  list_transform(list_append(common, n_words - coalesce(list_sum(common), 0)::bigint), lambda x: case when n_words > 0 then x / n_words::double else 0 end) as common,
  n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed from b),
j as (select s.*, {jsd('classes', 'classes_reference')} as class_distance, {jsd('common', 'common_reference')} as word_distance, {word_share} * {jsd(none, 'common_reference')} as word_limit
  from s left join {mean('classes')} using (language) left join {mean('common')} using (language)),
k as (select language, avg(class_distance) + {class_spread} * coalesce(stddev_pop(class_distance), 0) as class_limit from j where not base_failed group by language)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  not base_failed and not coalesce((class_distance > class_limit or word_distance > word_limit) and n_words >= {guard_words}, false) as kept,
  round(class_distance, 6) as class_distance, round(word_distance, 6) as word_distance, round(class_limit, 6) as class_limit, round(word_limit, 6) as word_limit
from j left join k using (language)"""
