"""DuckDB oracles of the queries that SQL can express."""

_WORD = r"[^\x20\x09-\x0D]+"
_FOLD = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _count(pattern: str) -> str:
    return f"length(regexp_extract_all(t, '{pattern}'))"


_RULES = rf"""
with d as (select doc_id, coalesce(text, '') as t from documents),
base as (
  select doc_id, t, regexp_extract_all(t, '{_WORD}') as w,
         list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '{_WORD}')) as lines
  from d
),
wins as (
  select doc_id, i, array_to_string(w[i : i + 4], ' ') as win
  from (select doc_id, w, unnest(range(1, greatest(1, len(w) - 3))) as i from base)
),
covered as (
  select doc_id, count(distinct i + j) as n_repeat_words
  from (select doc_id, i, count(*) over (partition by doc_id, win) as c from wins) cross join range(5) r(j)
  where c > 1 group by doc_id
),
counts as (
  select b.doc_id, cast(len(w) as bigint) as n_words, cast(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) as bigint) as word_chars,
         cast({_count('[#*$%&|<>]')} as bigint) as n_symbols, cast(len(lines) - len(list_distinct(lines)) as bigint) as n_dup_lines, len(lines) as n_lines,
         cast(coalesce(n_repeat_words, 0) as bigint) as n_repeat_words,
         {_count('[A-Za-z]')} + {_count('[^\\x00-\\x7F]')} as letters, {_count('[A-Z]')} as capitals
  from base b left join covered c on b.doc_id = c.doc_id
),
judged as (select *, n_words < 10 or 100 * n_repeat_words > 20 * n_words as base_failed from counts)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       not (base_failed or 10 * n_symbols > n_words or (n_lines > 1 and 100 * n_dup_lines > 60 * n_lines)
            or not (2 * n_words <= word_chars and word_chars <= 20 * n_words) or 4 * letters < word_chars or 2 * capitals > letters) as kept
from judged
"""

_REACH = "reach(a, b) as (select id, id from nodes union select r.a, l.b from reach r join links l on r.b = l.a)"

_VECTORS = f"""
with recursive nodes as (select vec_id as id from embeddings),
sound as (
  select vec_id, label, cast(embedding as double[]) as e from embeddings
  where label is not null and embedding is not null and len(embedding) > 0
    and len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0
),
links as (
  select a.vec_id as a, b.vec_id as b from sound a join sound b on a.label = b.label and a.vec_id <> b.vec_id and len(a.e) = len(b.e)
  where list_cosine_similarity(a.e, b.e) >= 0.93
),
{_REACH}
select id as vec_id, cast(coalesce(n, 0) as bigint) as n_links, component_id, id = component_id as kept
from (select a as id, min(b) as component_id from reach group by a) left join (select a, count(*) as n from links group by a) using (id)
""".replace("(select a, count(*) as n from links group by a) using (id)", "(select a as id, count(*) as n from links group by a) using (id)")

_NEAR = rf"""
with recursive nodes as (select doc_id as id from documents),
words as (select doc_id, regexp_extract_all({_FOLD}, '{_WORD}') as w from documents),
sets as (
  select doc_id, case when len(w) = 1 then w else list_distinct(list_transform(range(1, greatest(1, len(w))), lambda i: w[i] || ' ' || w[i + 1])) end as s from words
),
sizes as (select doc_id, cast(len(s) as bigint) as n from sets),
each as (select doc_id, unnest(s) as g from sets),
pairs as (select a.doc_id as a, b.doc_id as b, count(*) as i from each a join each b on a.g = b.g and a.doc_id <> b.doc_id group by all),
links as (select a, b from pairs join sizes x on a = x.doc_id join sizes y on b = y.doc_id where 100 * i >= 80 * (x.n + y.n - i)),
{_REACH}
select id as doc_id, n as n_shingles, component_id, id = component_id as kept
from (select a as id, min(b) as component_id from reach group by a) r join sizes on id = doc_id
"""

_REPEATS = """
with d as (select doc_id, hex(encode(coalesce(text, ''))) as h from documents),
parts as (select doc_id, s, substr(h, 2 * s + 1, 2 * (512 + 49)) as part from (select doc_id, h, unnest(range(0, len(h) // 2, 512)) as s from d)),
wins as (
  select doc_id, s + i as p, substr(part, 2 * i + 1, 100) as win
  from (select doc_id, s, part, unnest(range(0, greatest(0, least(512, len(part) // 2 - 49)))) as i from parts)
),
shared as (select win, min(doc_id) as first from wins group by win having min(doc_id) < max(doc_id)),
hits as (select doc_id, p from wins join shared using (win) where first < doc_id),
marked as (select doc_id, p, case when p - lag(p) over w <= 50 then 0 else 1 end as opens from hits window w as (partition by doc_id order by p)),
numbered as (select doc_id, p, sum(opens) over (partition by doc_id order by p) as run from marked),
runs as (select doc_id, min(p) as a, max(p) + 50 as b from numbered group by doc_id, run),
gaps as (select doc_id, a, b, coalesce(lag(b) over (partition by doc_id order by a), 0) as since from runs),
cut as (
  select g.doc_id, sum(b - a) as n_removed, count(*) as n_spans,
         string_agg(substr(h, 2 * since + 1, 2 * (a - since)), '' order by a) || substr(any_value(h), 2 * max(b) + 1) as kept
  from gaps g join d on g.doc_id = d.doc_id group by g.doc_id
)
select d.doc_id, cast(len(h) // 2 as bigint) as n_bytes, cast(coalesce(n_removed, 0) as bigint) as n_removed,
       cast(coalesce(n_spans, 0) as bigint) as n_spans, sha256(unhex(coalesce(kept, h))) as kept_sha256
from d left join cut on d.doc_id = cut.doc_id
"""

_UP, _LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_PARTS = "(?s)^.*?://([^/?#]*)([^?#]*)"

#: Holds while no more rows are labelled than the method mines (100,000).
_URLS = rf"""
with stated(rule, verdict, on_host, on_path) as (
  values ('org/', 'allow', 'org', '/'), ('example.org/es/', 'block', 'example.org', '/es/'), ('example.org/en/1', 'block', 'example.org', '/en/1'),
         ('com/fr/', 'allow', 'com', '/fr/'), ('com/de/', 'block', 'com', '/de/')
),
read as (
  select page_id, translate(coalesce(regexp_extract(url, '{_PARTS}', 1), ''), '{_UP}', '{_LOW}') as host, coalesce(regexp_extract(url, '{_PARTS}', 2), '') as path,
         coalesce(regexp_extract(url, '(?s)\?([^#]*)', 1), '') as query, row_number() over () as row
  from pages
),
fitting as (
  select row, arg_max(struct_pack(r := rule, v := verdict), length(rule)) as best
  from read join stated on (host = on_host or ends_with(host, '.' || on_host)) and starts_with(path, on_path) group by row
),
tokens as (
  select row, unnest(list_distinct(list_concat(
    list_transform(string_split(host, '.'), lambda x: 'h:' || x), list_transform(string_split(path, '/'), lambda x: 'p:' || x),
    list_transform(string_split(query, '&'), lambda x: 'q:' || split_part(x, '=', 1))))) as token
  from read
),
least as (select greatest(1, ceil(cast(0.005 as double) * count(*))) as n from fitting),
frequent as (select token from tokens join fitting using (row) where length(token) > 2 group by token having count(*) >= (select n from least)),
baskets as (select row, list_sort(list(token)) as items from tokens join frequent using (token) group by row),
masks as (select row, items, unnest(range(1, 1 << len(items))) as mask from baskets),
subsets as (select row, list_filter(items, lambda x, i: (mask >> (i - 1)) & 1 = 1) as items from masks),
counted as (select items, best.v as verdict, count(*) as n from subsets join fitting using (row) group by all),
rules as (
  select items, verdict, n, n / sum(n) over (partition by items) as confidence from counted
  qualify n >= (select n from least) and confidence >= cast(0.9 as double)
),
mined as (select row, max(struct_pack(c := confidence, s := n, v := verdict)) as top from subsets join rules using (items) group by row)
select page_id, host, path, best.r as rule, coalesce(best.v, top.v, 'allow') as verdict
from read left join fitting using (row) left join mined using (row)
"""

_PERSONAL_KINDS = (
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", "true"),
    ("ip", r"[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)", "len(list_filter(string_split(m, '.'), lambda x: length(ltrim(x, '0')) > 3 or cast('0' || right(x, 3) as integer) > 255)) = 0"),
    ("card", r"[0-9](?:[\x20-]?[0-9])+", "length(digits) between 16 and 19 and list_sum(list_transform(string_split(reverse(digits), ''), lambda x, i: case when i % 2 = 1 then cast(x as integer) when x > '4' then 2 * cast(x as integer) - 9 else 2 * cast(x as integer) end)) % 10 = 0"),
    ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", "length(digits) between 8 and 15"),
    ("secret", r"""(?i)(?:token|secret|passw(?:or)?d|(?:api|access|private)[_-]?key)\b["'']?[ \t]{0,4}[:=][ \t]{0,4}["'']?(?:[^\s"'',;]{8,})""", "regexp_matches(value, '[0-9]')"),
)
_VALUE = r"""[^\s"'',;]{8,}$"""
_LETTERS = r"[\pL\p{Nl}\p{No}]{4,}"


def _placed(pattern: str, source: str) -> str:
    """(row, m, a, b): the matches of a pattern in each text and their places."""
    return rf"""
  select row, m, a, a + length(m) as b from (
    select row, m, sum(length(gap)) over before_it + sum(length(m)) over before_it - length(m) as a
    from (select row, unnest(regexp_extract_all(t, '{pattern}')) as m, unnest(list_slice(string_split_regex(t, '{pattern}'), 1, length(regexp_extract_all(t, '{pattern}')))) as gap,
                 unnest(range(length(regexp_extract_all(t, '{pattern}')))) as i from {source})
    window before_it as (partition by row order by i))"""


_FOUND = " union all ".join(
    f"select row, '{kind}' as kind, {i} as nth, cast(a as bigint) as a, cast(b as bigint) as b, value, digits from (select row, case when '{kind}' = 'secret' then b - length(value) else a end as a, b, m, value, digits "
    f"from (select *, case when '{kind}' = 'secret' then regexp_extract(m, '{_VALUE}') else m end as value, regexp_replace(m, '[^0-9]', '', 'g') as digits from ({_placed(pattern, 'd')}))) where {holds}"
    for i, (kind, pattern, holds) in enumerate(_PERSONAL_KINDS)
)

_PERSONAL = rf"""
with d as (select doc_id, row_number() over () as row, coalesce(text, '') as t from documents),
found as ({_FOUND}),
named as (select row, a, b, kind, case when kind in ('card', 'phone') then digits else lower(value) end as v from found),
faces as (
  select row, a, b, kind || ':' || v as face from named
  union select row, a, b, 'domain:' || split_part(v, '@', 2) from named where kind = 'email'
  union select row, a, b, 'name:' || unnest(regexp_extract_all(split_part(v, '@', 1), '{_LETTERS}')) from named where kind = 'email'
  union select row, a, b, 'net:' || regexp_extract(v, '^[0-9]+\.[0-9]+') from named where kind = 'ip'
  union select row, a, b, kind || 's:' || left(v, 6) from named where kind in ('card', 'phone')
),
touched as (select row, t from d where row in (select row from found)),
terms as (select row, lower(m) as term, cast(a as bigint) as s, cast(b as bigint) as f from ({_placed(_LETTERS, 'touched')})),
outside as (select * from terms x where not exists (select 1 from found y where x.row = y.row and y.a < x.f and y.b > x.s)),
near as (select distinct x.row, face, term, s, f from faces x join outside y on x.row = y.row and y.s >= x.a - 80 and y.f <= x.b + 80),
pairs as (select face, term, count(distinct row) as both_ from near group by all),
of_face as (select face, count(distinct row) as of_e from faces group by face),
of_term as (select term, count(distinct row) as of_t from (select row, unnest(regexp_extract_all(lower(t), '{_LETTERS}')) as term from d) group by term),
size as (select cast(greatest(2, count(*)) as double) as n from d),
told as (
  select face, term, ln((both_ + cast(1 as double) * of_t / n) / (of_e + cast(1 as double)) * n / of_t) as tells, ln(n / of_e) as content
  from pairs join of_face using (face) join of_term using (term), size
),
bad as (select face, term from told where tells >= cast(0.9 as double) * content and tells >= ln(cast(20 as double))),
spots as (select distinct row, s, f from near join bad using (face, term)),
listed as (
  select row, string_agg(kind || ':' || a || ':' || b, ',' order by nth, a) filter (where kind <> 'secret') as base,
         string_agg(kind || ':' || a || ':' || b, ',' order by a) filter (where kind = 'secret') as more, count(*) as n,
         count(*) filter (where kind = 'email') as n_email, count(*) filter (where kind = 'ip') as n_ip,
         count(*) filter (where kind = 'card') as n_card, count(*) filter (where kind = 'phone') as n_phone
  from found group by row
),
added as (select row, string_agg('term:' || s || ':' || f, ',' order by s, f) as terms, count(*) as n_terms from spots group by row)
select doc_id, coalesce(n_email, 0) as n_email, coalesce(n_ip, 0) as n_ip, coalesce(n_card, 0) as n_card, coalesce(n_phone, 0) as n_phone,
       sha256(coalesce(base, '')) as base_sha256, concat_ws(',', base, more, terms) as spans, coalesce(n, 0) + coalesce(n_terms, 0) as n_spans
from d left join listed using (row) left join added using (row)
"""

ORACLES: dict[str, str] = {"op1_pii": _PERSONAL, "op4_quality_rules": _RULES, "op5_embedding_dedup": _VECTORS, "op7_url_filter": _URLS, "op9_near_dedup": _NEAR, "op10_suffix_dedup": _REPEATS}
