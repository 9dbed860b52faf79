r"""SQL counterparts of the corpus queries, for an engine with lists and lambdas."""

from __future__ import annotations

from . import pii
from .rules import RULES, mask

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: A word of any characters but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"


def _low(column: str) -> str:
    return f"translate(coalesce({column}, ''), '{UPPER}', '{LOWER}')"


_ALNUM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

DECONTAMINATION = f"""
with b as (select item_id, regexp_extract_all({_low('text')}, '{_ALNUM}') as w from benchmark),
bw as (select distinct item_id, array_to_string(w[i:i + 12], ' ') as g, least(13, len(w)) as l from (select *, unnest(range(1, greatest(1, len(w) - 12) + 1)) as i from b where len(w) > 0)),
d as (select doc_id, regexp_extract_all({_low('text')}, '{_ALNUM}') as w from documents),
dw as (select doc_id, i, l, array_to_string(w[i:i + l - 1], ' ') as g from (select doc_id, w, l, unnest(range(1, len(w) - l + 2)) as i from d cross join (select distinct l from bw))),
hit as (select doc_id, i, l, item_id from dw join bw using (g, l)),
words as (select doc_id, count(distinct p) as n_hit from (select doc_id, unnest(range(i, i + l)) as p from hit) group by doc_id),
items as (select doc_id, count(distinct item_id) as n_items, string_agg(distinct item_id::varchar, ',' order by item_id::varchar) as names from hit group by doc_id)
select doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items, sha256(coalesce(names, '')) as items_sha256,
  coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= len(w) as contaminated
from d left join words using (doc_id) left join items using (doc_id)"""

_KINDS = {
    "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", "true"),
    "ip": (r"[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+", "list_max(list_transform(string_split(m, '.'), lambda x: x::hugeint)) <= 255"),
    "card": (r"[0-9](?:[\x20-]?[0-9])+", "length(g) between 13 and 19 and list_sum(list_transform(range(0, length(g)), lambda i: case when i % 2 = 0 then g[length(g) - i]::int else 2 * g[length(g) - i]::int - 9 * (g[length(g) - i]::int > 4)::int end)) % 10 = 0"),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", "length(g) between 9 and 15"),
}


#: Characters between words, and between tokens that could be identifiers.
_SPACE = r"\t\n\x0B\f\r\x20\x22\x27()"
_EDGE = _SPACE + ",;:="
_FREE = rf"[^{_EDGE}0-9]*(?:[0-9][^{_EDGE}0-9]*){{3,}}|[^{_EDGE}]*?(?:@|\[at\])[^{_EDGE}]+"
_TRIMMED = f"rtrim(m, '{pii.TRAILING}')"


def _words(x: str) -> str:
    return f"list_transform(list_filter(string_split_regex(lower({x}), '[{_SPACE}]+'), lambda t: t <> ''), lambda t: case when regexp_matches(t, '[0-9@]') then '#' else t end)"


def _matched(order: int, pattern: str, valid: str) -> str:
    """All valid matches of a shape: where, the value, and the words before and after it."""
    return f"""select doc_id, {order} as k, m, a as s, a + length(m) as e, i = 1 as is_first, {_words('between_[i]')} as l, {_words('between_[i + 1]')} as r from (
  select *, regexp_replace(m, '[^0-9]', '', 'g') as g, coalesce(list_sum(list_transform(between_[1:i], lambda x: length(x))), 0)::bigint + coalesce(list_sum(list_transform(ms[1:i - 1], lambda x: length(x))), 0)::bigint as a
  from (select doc_id, between_, ms, i, ms[i] as m from (select *, unnest(range(1, len(ms) + 1)) as i from (select doc_id, string_split_regex(text, '{pattern}') as between_, regexp_extract_all(text, '{pattern}') as ms from t)))) where {valid}"""


def _round(n: int) -> str:
    """One round of scores: patterns by their sure instances, then unknown instances by their patterns."""
    return f"""score{n} as materialized (select pattern, y.kind, sum(y.sure) / any_value(instances) * any_value(special) as sure from pairs join sure{n - 1} y using (value) join totals using (pattern) join special using (pattern) group by pattern, y.kind),
sure{n} as materialized (select value, kind, 1.0::double as sure from seeds union all (select value, s.kind, 1 - exp(sum(ln(greatest(1e-6, 1 - s.sure)))) as sure from pairs join score{n} s using (pattern) where value not in (select value from seeds) group by value, s.kind having 1 - exp(sum(ln(greatest(1e-6, 1 - s.sure)))) >= {pii.SURE}))"""


def _list(condition: str) -> str:
    return f"string_agg(['email', 'ip', 'card', 'phone', 'secret'][k + 1] || ':' || s || ':' || e, ',' order by k, s, e) filter ({condition})"


#: Base spans, the pattern graph over them and the free tokens, its rounds, and the spans that sure patterns add.
PII = f"""
with t as materialized (select doc_id, coalesce(text, '') as text from documents),
b as materialized ({' union all '.join(_matched(k, *v) for k, v in enumerate(_KINDS.values()))}),
loose as ({_matched(-1, _FREE, 'true')}),
free as materialized (select doc_id, s, s + length(v) as e, regexp_matches(v, '@|\\[at\\]') as is_at, case when regexp_matches(v, '^[A-Za-z0-9_-]{{32,}}$') and regexp_matches(v, '[0-9]') and regexp_matches(v, '[A-Za-z]') then 4 else -1 end as k, v as m, is_first, l, r
  from (select *, case when {_TRIMMED} = '' then m else {_TRIMMED} end as v from loose where not exists (select 1 from b where b.doc_id = loose.doc_id and b.s < loose.e and loose.s < b.e))),
seen as (select doc_id, s, e, null as is_at, k as kind, m as value, is_first, l, r from b union all select doc_id, s, e, is_at, k, m, is_first, l, r from free),
slot as materialized (select doc_id, s, e, is_at, kind, value, unnest([1, 2, 3]) as turn, unnest([case when len(r) > 0 then l[-1] || ' _ ' || r[1] end, case when len(l) > 1 then l[-2] || ' ' || l[-1] when not is_first then '# ' || l[-1] end, l[-1]]) as pattern from seen where len(l) > 0),
edge as materialized (select pattern, value, kind, count(*) as n from slot where pattern is not null group by all),
likely as materialized (select pattern, sum(n) as n_seen from edge group by pattern having count(*) filter (kind >= 0) >= {pii.SEEDS}),
w as (select {_words('text')} as w from t),
gram as (select unnest([w[i], w[i] || ' ' || w[i + 1], w[i] || ' _ ' || w[i + 2]]) as pattern from (select w, unnest(range(1, len(w) + 1)) as i from w)),
place as (select pattern, count(*) as places from gram join likely using (pattern) group by pattern),
special as materialized (select pattern, n_seen / greatest(n_seen, coalesce(places, 0)) as special from likely left join place using (pattern) where n_seen / greatest(n_seen, coalesce(places, 0)) >= {pii.SURE}),
graph as materialized (select edge.* from edge join special using (pattern)),
seeds as materialized (select value, max(kind) as kind from graph group by value having max(kind) >= 0),
pairs as materialized (select distinct pattern, value from graph),
totals as materialized (select pattern, count(*) as instances from pairs group by pattern),
sure0 as materialized (select value, kind, 1.0::double as sure from seeds),
{', '.join(_round(n) for n in range(1, pii.ROUNDS + 1))},
best as (select pattern, arg_max(kind, (sure, -kind)) as kind from score{pii.ROUNDS} where sure >= {pii.SURE} group by pattern),
met as (select doc_id, s, e, arg_min(best.kind, turn) as k from slot join best using (pattern) where is_at = (best.kind = 0) group by doc_id, s, e),
every as (select doc_id, s, e, k, true as is_base from b union all select doc_id, s, e, k, false from met),
a as (select doc_id, {', '.join(f"count(*) filter (is_base and k = {k}) as n_{n}" for k, n in enumerate(_KINDS))}, {_list('is_base')} as base, {_list('k < 4')} as spans, count(*) filter (k = 4) as n_secret, {_list('k = 4')} as secrets, count(*) as n_spans from every group by doc_id)
select t.doc_id, {', '.join(f'coalesce(n_{n}, 0)::bigint as n_{n}' for n in _KINDS)}, sha256(coalesce(base, '')) as base_sha256, coalesce(spans, '') as spans, coalesce(n_secret, 0)::bigint as n_secret, coalesce(secrets, '') as secrets, coalesce(n_spans, 0)::bigint as n_spans
from t left join a using (doc_id)"""

NEAR_DUPLICATES = f"""
with recursive w as (select doc_id, regexp_extract_all({_low('text')}, '{WORD}') as w from documents),
sh as materialized (select distinct doc_id, array_to_string(w[i:i + 3], ' ') as g from (select *, unnest(range(1, greatest(1, len(w) - 3) + 1)) as i from w where len(w) > 0)),
n as materialized (select doc_id, count(*) as n from sh group by doc_id),
pairs as (select a.doc_id as x, b.doc_id as y, count(*) as c from sh a join sh b on a.g = b.g and a.doc_id < b.doc_id group by 1, 2),
link as materialized (select x, y from pairs join n nx on nx.doc_id = x join n ny on ny.doc_id = y where 100 * c >= 80 * (nx.n + ny.n - c)),
reach as (select doc_id, doc_id as other from w union select r.doc_id, case when l.x = r.other then l.y else l.x end from reach r join link l on l.x = r.other or l.y = r.other),
comp as (select doc_id, min(other) as component_id from reach group by doc_id)
select doc_id, coalesce(n.n, 0)::bigint as n_shingles, component_id, doc_id = component_id as kept from comp left join n using (doc_id)"""

_EOL = "chr(13) || chr(10)"
FIXITY = f"""
with r as (select page_id, page_id // 256 as segment, 'WARC/1.1' || {_EOL} || 'WARC-Type: response' || {_EOL} || 'WARC-Record-ID: <urn:page:' || page_id || '>' || {_EOL} || 'WARC-Target-URI: ' || coalesce(url, '') || {_EOL} || 'Content-Length: ' || strlen(coalesce(html, '')) || {_EOL} || {_EOL} || coalesce(html, '') || {_EOL} || {_EOL} as body from pages)
select page_id, segment, (sum(strlen(body)) over (partition by segment order by page_id) - strlen(body))::bigint as start, strlen(body)::bigint as length, sha256(body) as digest,
  case when page_id % 211 = 5 then 'missing' when page_id % 101 = 13 then 'altered' else 'ok' end as status from r"""


def _rules_sql() -> str:
    bits = " + ".join(f"({t})::bigint * {1 << i}" for i, t in enumerate(RULES.values()))
    return f"""
with w as (select doc_id, coalesce(text, '') as text, regexp_extract_all(coalesce(text, ''), '{WORD}') as w from documents),
g as (select doc_id, i, array_to_string(w[i:i + 4], chr(1)) as g from (select doc_id, w, unnest(range(1, len(w) - 3)) as i from w)),
twice as (select doc_id, i from (select *, count(*) over (partition by doc_id, g) as c from g) where c > 1),
rep as (select doc_id, count(distinct p) as n from (select doc_id, unnest(range(i, i + 5)) as p from twice) group by doc_id),
l as (select *, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '{WORD}')) as lines from w),
m as (select doc_id, len(w)::bigint as n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::bigint as word_chars, length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::bigint as n_symbols,
  len(lines)::bigint as n_lines, (len(lines) - len(list_distinct(lines)))::bigint as n_dup_lines, coalesce(rep.n, 0)::bigint as n_repeat_words, length(regexp_replace(text, '[^A-Z]', '', 'g')) as n_upper,
  length(regexp_replace(text, '[^A-Za-z]', '', 'g')) as n_letters, len(list_filter(range(1, len(w)), lambda i: w[i] = w[i + 1])) as n_same_next from l left join rep using (doc_id)),
f as (select *, ({bits})::bigint as failed from m)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (failed & {mask('base')}) <> 0 as base_failed, (failed & {mask('v2')}) = 0 as kept, failed from f"""


ORACLE_SQL = {"op1_decontamination": DECONTAMINATION, "op2_pii": PII, "op3_near_duplicates": NEAR_DUPLICATES, "op9_warc_fixity": FIXITY, "op10_quality_rules": _rules_sql()}
