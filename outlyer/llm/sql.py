"""DuckDB SQL with the same rows as the queries that SQL can express."""

from __future__ import annotations

from .pii import BASE_SCORE, CONTEXT, RAISE, SURE

# The contract's patterns, as they stand there.
_EMAIL = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"
_IP = r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"
_CARD = r"[0-9]([\x20-]?[0-9])+"
_PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
_IBAN = r"\b[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}(?:\x20?[A-Z0-9]{1,3})?\b"

_LUHN = """(length(d) between 12 and 19 and list_sum(list_transform(range(1, length(d) + 1), lambda i:
    case when (length(d) - i) % 2 = 1 then (case when 2 * d[i]::int > 9 then 2 * d[i]::int - 9 else 2 * d[i]::int end) else d[i]::int end)) % 10 = 0)"""
_MOD = """(length(p) between 15 and 34 and list_reduce(list_prepend(0::bigint, list_transform(range(1, length(p) + 1), lambda i:
    case when ascii((p[5:] || p[:4])[i]) >= 65 then ascii((p[5:] || p[:4])[i])::bigint + 945 else ascii((p[5:] || p[:4])[i])::bigint - 48 end)),
    lambda a, c: case when c >= 1000 then (a * 100 + c - 1000) % 97 else (a * 10 + c) % 97 end) = 1)"""


def _kind(n: int, name: str, pattern: str) -> str:
    score = BASE_SCORE[name]
    return f"""select doc_id, {n} as ord, '{name}' as kind, unnest(m) as m, unnest(list_transform(range(1, len(m) + 1), lambda i: ends[i] - length(m[i]))) as s, unnest(ends) as e,
  unnest(list_transform(range(1, len(m) + 1), lambda i: {score} + case when regexp_matches(lower(right(g[i], 40)), '(?:^|[^a-z])(?:{CONTEXT[name]})') then {RAISE} else 0 end)) as score
  from (select doc_id, m, g, list_transform(range(1, len(m) + 1), lambda i: list_sum(list_transform(g[:i], lambda x: length(x))) + list_sum(list_transform(m[:i], lambda x: length(x))))::bigint[] as ends
  from (select doc_id, regexp_extract_all(text, '{pattern}') as m, regexp_split_to_array(text, '{pattern}') as g from t) where len(m) > 0)"""


OP5 = f"""with t as (select doc_id, coalesce(text, '') as text from documents),
raw as ({' union all '.join(_kind(n, k, p) for n, (k, p) in enumerate((("email", _EMAIL), ("ip", _IP), ("card", _CARD), ("phone", _PHONE), ("iban", _IBAN))))}),
plain as (select *, regexp_replace(m, '[^0-9]', '', 'g') as d, regexp_replace(m, ' ', '', 'g') as p from raw),
good as (select * from plain where case kind when 'email' then true
  when 'ip' then list_bool_and(list_transform(string_split(m, '.'), lambda x: coalesce(try_cast(x as bigint), 256) <= 255))
  when 'card' then {_LUHN}
  when 'phone' then length(d) between 9 and 15
  else {_MOD} end),
agg as (select doc_id, count(*) filter (ord = 0) as n_email, count(*) filter (ord = 1) as n_ip, count(*) filter (ord = 2) as n_card, count(*) filter (ord = 3) as n_phone, count(*) filter (score >= {SURE}) as n_sure,
  string_agg(kind || ':' || s || ':' || e, ',' order by s, ord) filter (ord < 4) as base, string_agg(kind || ':' || s || ':' || e, ',' order by s, ord) as spans from good group by doc_id)
select t.doc_id, coalesce(n_email, 0) as n_email, coalesce(n_ip, 0) as n_ip, coalesce(n_card, 0) as n_card, coalesce(n_phone, 0) as n_phone,
  sha256(coalesce(base, '')) as base_sha256, coalesce(spans, '') as spans, coalesce(n_sure, 0) as n_sure from t left join agg using (doc_id)"""

# Windows of whole lines: the shortest of at least 50 words from each line and to each line; the first copy of each stays.
OP7 = r"""with raw as (select doc_id, text, string_split(text, chr(10)) as ls from documents),
lines as (select doc_id, unnest(range(len(ls))) as place, regexp_replace(unnest(ls), '^[\s\p{Z}]+|[\s\p{Z}]+$', '', 'g') as line from raw),
full_lines as (select doc_id, place, line, len(regexp_split_to_array(line, '[\s\p{Z}]+')) as words, row_number() over (partition by doc_id order by place) as seq from lines where line <> ''),
docs as (select doc_id, list(line order by seq) as ls, list(words order by seq) as ws, list(place order by seq) as ps from full_lines group by doc_id),
sums as (select doc_id, seq, sum(words) over (partition by doc_id order by seq) as upto, words from full_lines),
fore as (select a.doc_id, a.seq as s, min(b.seq) as e from sums a join sums b on a.doc_id = b.doc_id and b.seq between a.seq and a.seq + 50 and b.upto - a.upto + a.words >= 50 group by 1, 2),
hind as (select b.doc_id, max(a.seq) as s, b.seq as e from sums b join sums a on a.doc_id = b.doc_id and a.seq between b.seq - 50 and b.seq and b.upto - a.upto + a.words >= 50 group by b.doc_id, b.seq),
win as (select distinct doc_id, s, e from (select doc_id, s, e from fore union all select doc_id, s, e from hind)),
named as (select doc_id, s, e, e - s as n_win, md5(array_to_string(ls[s:e], chr(10))) as k from win join docs using (doc_id)),
ranked as (select *, row_number() over (partition by n_win, k order by doc_id, s) as copy from named),
gone as (select distinct doc_id, unnest(range(s, e + 1)) as seq from ranked where copy > 1),
places as (select doc_id, place from gone join full_lines using (doc_id, seq)),
kept as (select l.doc_id, string_agg(l.line, chr(10) order by l.place) as text
  from (select doc_id, unnest(range(len(ls))) as place, unnest(ls) as line from raw) l left join places p on l.doc_id = p.doc_id and l.place = p.place where p.place is null group by l.doc_id),
lost as (select doc_id, count(*) as n_removed from places group by doc_id)
select d.doc_id, (case when d.text is null then 0 else len(d.ls) end)::bigint as n_lines, coalesce(n_removed, 0)::bigint as n_removed, md5(coalesce(kept.text, '')) as text_md5
from raw d left join kept using (doc_id) left join lost using (doc_id)"""

ORACLES: dict[str, str] = {"op5_personal_data": OP5, "op7_line_dedup": OP7}
