"""DuckDB SQL for the training-data queries that SQL can express."""

from __future__ import annotations

from rulelattice.llm.quality_rules import ALL_LISTED, COMMON_WORDS, POOLED, Limits

#: Fixed value: the white space that separates words.
BLANK = r"[\x20\x09-\x0D]"

EXACT_DEDUP = f"""
with n as (
  select doc_id, length(coalesce(text, '')) as size, regexp_replace(coalesce(text, ''), '{BLANK}', '', 'g') as norm from documents
), r as (
  select *, row_number() over (partition by norm order by size desc, doc_id nulls first) as place, count(*) over (partition by norm) as copies,
    first_value(doc_id) over (partition by norm order by size desc, doc_id nulls first) as keeper
  from n
)
select doc_id, keeper as keep_id, copies as group_size, place = 1 as kept, sha256(norm) as text_sha256 from r
"""


def _quoted(words: list[str]) -> str:
    return "[" + ", ".join(f"'{w}'" for w in words) + "]"


def _distance(p: str, q: str) -> str:
    """Jensen-Shannon distance of two lists; null for null or empty ones."""
    share = f"list_transform(list_zip({p}, {q}), lambda z: [z[1] / list_sum({p})::double, z[2] / list_sum({q})::double])"
    half = lambda i: f"case when v[{i}] > 0 then v[{i}] * log2(v[{i}] / ((v[1] + v[2]) / 2)) else 0 end"
    return f"case when list_sum({p}) > 0 and list_sum({q}) > 0 then sqrt(greatest(list_sum(list_transform({share}, lambda v: {half(1)} + {half(2)})) / 2, 0)) end"


def quality_rules(limits: Limits = Limits()) -> str:
    lists = " ".join(f"when '{k}' then {_quoted(ws)}" for k, ws in COMMON_WORDS.items())
    count = lambda members: f"length(regexp_replace(t, '[^{members}]+', '', 'g'))"
    counted = [count(m) for m in ("A-Z", "0-9", ".,;:!?", "#*$%&|<>", r"\x{80}-\x{10FFFF}")]
    classes, word_bins = len(counted) + 2, max(map(len, COMMON_WORDS.values())) + 1
    return f"""
with d as (select doc_id, coalesce(text, '') as t, case when lang in ({", ".join(f"'{k}'" for k in COMMON_WORDS)}) then lang else '{POOLED}' end as l from documents),
w as (select *, row_number() over () as rid, list_filter(string_split_regex(t, '{BLANK}+'), lambda x: x <> '') as words, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) as lines, case l {lists} end as listed from d),
win as (select rid, i, words[i] || ' ' || words[i + 1] || ' ' || words[i + 2] as g from (select rid, words, unnest(range(1, len(words) - 1)) as i from w)),
hit as (select rid, i from (select rid, i, count(*) over (partition by rid, g) as c from win) where c > 1),
rep as (select rid, count(distinct i + k) as n from hit, (select unnest([0, 1, 2]) as k) group by rid),
b as (
  select w.rid, doc_id, l, t, len(words) as n_words, coalesce(list_sum(list_transform(words, lambda x: length(x))), 0)::bigint as word_chars, {count("#*$%&|<>")} as n_symbols,
    len(lines) - len(list_distinct(lines)) as n_dup_lines, coalesce(rep.n, 0) as n_repeat_words,
    [{", ".join(counted)}] as counted, list_filter(words, lambda x: list_contains({_quoted(ALL_LISTED)}, x)) as found, listed
  from w left join rep using (rid)
), h as (
  select *, n_words < {limits.min_words} or 100 * n_repeat_words > {limits.max_repeat_percent} * n_words as base_failed,
    list_concat(counted, [length(t) - word_chars, word_chars - list_sum(counted)]) as cs,
    list_transform(listed, lambda x: len(list_filter(found, lambda y: y = x))) as ws
  from b
), f as (select *, list_concat(ws, [n_words - list_sum(ws)]) as wh from h),
ref as (
  select l, [{", ".join(f"sum(cs[{i + 1}])" for i in range(classes))}] as rc, case when l <> '{POOLED}' then [{", ".join(f"sum(wh[{i + 1}])" for i in range(word_bins))}] end as rw from f group by l
), j as (
  select f.*, case when length(t) >= {limits.guard_chars} then {_distance("cs", "rc")} end as jc, case when n_words >= {limits.guard_words} and ws is not null then {_distance("wh", "rw")} end as jw
  from f join ref using (l)
)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, round(jc * 1000000)::bigint as class_distance_ppm, round(jw * 1000000)::bigint as word_distance_ppm,
  not base_failed and not coalesce(jc > {limits.max_class_distance}, false) and not coalesce(jw > {limits.max_word_distance}, false) as kept
from j
"""


REVISITS = """
with u as (select page_id, html, regexp_replace(url, '^[\\x20\\x09-\\x0D]+|[\\x20\\x09-\\x0D]+$', '', 'g') as url from pages),
p as (
  select page_id, md5(coalesce(html, '')) as d, url,
    regexp_replace(regexp_replace(lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)', 1)), '^www\\.', ''), ':(80|443)$', '') as host,
    regexp_replace(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)', 1), '/+$', '') as path,
    list_sort(list_filter(string_split(regexp_extract(url, '^[^?#]*\\?([^#]*)', 1), '&'), lambda x: x <> '' and not regexp_matches(x, '^(utm_[a-z]+|ref|fbclid|gclid|sessionid)(=|$)'))) as asked
  from u
), k as (
  select page_id, d, case when host <> '' then host || path || case when len(asked) > 0 then '?' || array_to_string(asked, '&') else '' end when url <> '' then ':' || regexp_extract(url, '^[^#]*') end as url_key from p
), full_ as (select page_id * 2 as id, page_id * 60 as ts, d, url_key from k),
again as (select page_id * 2 + 1 as id, (page_id + 1000) * 60 + 30 as ts, d, url_key from k),
best as (
  select a.id, a.ts, a.d, a.url_key, max_by(f.id, f.ts) as rid, max_by(f.d, f.ts) as rd, max_by(f.ts, f.ts) as rts
  from again a left join full_ f on a.url_key = f.url_key and f.ts < a.ts group by all
)
select id as record_id, url_key, case when rid is null then 'no_response' when rd = d then 'resolved' else 'changed' end as status, rid as response_id,
  case when rd = d then rd end as payload_digest,
  case when rd = d then 'content-type=text/html;date=' || ts || ';etag="' || rd || '"' end as headers
from best
"""


def sentence_spans(span: int = 3) -> str:
    trimmed = lambda x: f"regexp_replace({x}, '^{BLANK}+|{BLANK}+$', '', 'g')"
    ends = lambda x: f"regexp_replace({x}, '([.!?]{BLANK})([^\\x01\\x20\\x09-\\x0D])', '\\1' || chr(1) || '\\2', 'g')"
    run = " || chr(10) || ".join(f"lead(s, {k}) over w" if k else "s" for k in range(span))
    return f"""
with t as (select doc_id, regexp_replace(coalesce(text, ''), '(\\n)([^\\n])', '\\1' || chr(1) || '\\2', 'g') as a from documents),
ps as (select doc_id, string_split({ends(ends("a"))}, chr(1)) as ps from t),
p as (select doc_id, unnest(ps) as p, unnest(range(1, len(ps) + 1)) as i from ps),
s as (select doc_id, p, i, {trimmed("p")} as s from p),
f as (select * from s where s <> ''),
r as (select doc_id, i as a, lead(i, {span - 1}) over w as b, {run} as h from f window w as (partition by doc_id order by i)),
g as (select *, row_number() over (partition by h order by doc_id, a) as place from r where b is not null),
gone as (select distinct g.doc_id, f.i from g join f on f.doc_id = g.doc_id and f.i between g.a and g.b where g.place > 1),
m as (select s.*, gone.i is not null as gone from s left join gone using (doc_id, i)),
c as (select doc_id, i, gone and not coalesce(lag(gone) over (partition by doc_id order by i), false) as starts from m where s <> ''),
n as (select doc_id, count(*) as n_sentences, sum(case when gone then 1 else 0 end)::bigint as n_removed from m where s <> '' group by 1),
v as (select doc_id, sum(case when starts then 1 else 0 end)::bigint as n_spans from c group by 1),
k as (select doc_id, coalesce(string_agg(case when not gone then p end, '' order by i), '') as kept from m group by 1)
select k.doc_id, coalesce(n_sentences, 0) as n_sentences, coalesce(n_removed, 0) as n_removed, coalesce(n_spans, 0) as n_spans, sha256(kept) as kept_sha256
from k left join n using (doc_id) left join v using (doc_id)
"""


ORACLES = {
    "op3_revisit_resolution": REVISITS,
    "op4_exact_dedup": EXACT_DEDUP,
    "op5_quality_rules": quality_rules(),
    "op7_sentence_spans": sentence_spans(),
}
