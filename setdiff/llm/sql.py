"""DuckDB twins of the corpus queries that SQL can express."""

from __future__ import annotations

from .line_rules import LEAST_WORDS, MOST_LOST, MOST_REPEATED, NOTICE, SEPARATORS, WINDOW

_WORD = r"[^\x20\x09-\x0D]+"
_SEPARATORS = ", ".join(f"'{s.decode()}'" for s in SEPARATORS)

LINE_RULES = f"""
with docs as (select row_number() over () as rid, doc_id, coalesce(text, '') as text from documents),
base as (select rid, doc_id, text, regexp_extract_all(text, '{_WORD}') as w from docs),
parts as (select rid, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) as pos from docs),
lines as (
  select rid, line, regexp_extract_all(line, '{_WORD}') as w, row_number() over (partition by rid, line order by pos) as nth
  from parts where regexp_matches(line, '{_WORD}')),
judged as (
  select rid, nth, len(w) as k,
    (10 * len([x for x in w if ends_with(x, '!!')]) >= 3 * len(w) and contains(line, '!!'))
    or 2 * length(regexp_replace(line, '[^#*$%&|<>]', '', 'g')) >= len(w)
    or (len(w) >= 8 and not regexp_matches(line, '[.!?:;]'))
    or 4 * len([x for x in w if x in ({_SEPARATORS})]) >= len(w)
    or regexp_matches(line, '(?i){NOTICE}') or (len(w) >= 4 and nth > 1) as fails
  from lines),
by_line as (
  select rid, count(*) as n_lines, count(*) filter (fails) as n_lines_removed, coalesce(sum(k) filter (fails), 0)::bigint as n_words_removed, count(*) filter (nth > 1) as n_dup_lines
  from judged group by rid),
windows as (
  select rid, i, array_to_string(w[i:i + {WINDOW - 1}], ' ') as v from (select rid, w, unnest(range(1, len(w) - {WINDOW - 2})) as i from base where len(w) >= {WINDOW})),
again as (select rid, i from (select rid, i, count(*) over (partition by rid, v) as n from windows) where n > 1),
covered as (select rid, count(distinct i + o) as n from again, range({WINDOW}) r(o) group by rid),
counts as (
  select b.doc_id, len(b.w)::bigint as n_words, length(regexp_replace(b.text, '[\\x20\\x09-\\x0D]', '', 'g'))::bigint as word_chars,
    length(regexp_replace(b.text, '[^#*$%&|<>]', '', 'g'))::bigint as n_symbols, coalesce(l.n_dup_lines, 0)::bigint as n_dup_lines, coalesce(c.n, 0)::bigint as n_repeat_words,
    coalesce(l.n_lines, 0)::bigint as n_lines, coalesce(l.n_lines_removed, 0)::bigint as n_lines_removed, coalesce(l.n_words_removed, 0)::bigint as n_words_removed
  from base b left join by_line l using (rid) left join covered c using (rid))
select *, n_words < {LEAST_WORDS} or 100 * n_repeat_words > {MOST_REPEATED} * n_words as base_failed,
  not (n_words < {LEAST_WORDS} or 100 * n_repeat_words > {MOST_REPEATED} * n_words) and 100 * n_words_removed <= {MOST_LOST} * n_words as kept
from counts
"""

_BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"

WARC = f"""
with p as (select page_id, coalesce(html, '') as html, sha1(coalesce(html, '')) as h from pages),
best as (select h, max(page_id) as best from p group by h)
select page_id, strlen(html)::bigint as payload_bytes,
  array_to_string([substr('{_BASE32}', (((('0x' || substr(h, (i // 4)::int * 5 + 1, 5))::int >> (15 - 5 * (i % 4))::int) & 31) + 1)::int, 1) for i in range(32)], '') as payload_digest,
  case when page_id = best then 'response' else 'revisit' end as record_type, case when page_id <> best then best end as refers_to
from p join best using (h)
"""

ORACLES: dict[str, str] = {"op3_line_rules": LINE_RULES, "op5_warc_salvage": WARC}
