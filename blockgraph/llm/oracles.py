"""DuckDB SQL of the corpus queries that SQL can express."""

from __future__ import annotations

WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

QUALITY_BASE = rf"""
words as (select doc_id, coalesce(text, '') as text, {WORDS} as w from documents),
wins as (
  select doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] as win
  from (select doc_id, w, unnest(range(1, len(w) - 1)) as i from words where len(w) > 2)
),
twice as (select doc_id, win from wins group by doc_id, win having count(*) > 1),
cover as (
  select doc_id, count(distinct p) as n from (
    select wins.doc_id, unnest([i, i + 1, i + 2]) as p from wins join twice using (doc_id, win)
  ) group by doc_id
),
stats as (
  select words.doc_id, text,
    len(w)::bigint as n_words,
    coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::bigint as word_chars,
    (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::bigint as n_symbols,
    (len(list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))
      - len(list_distinct(list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))))::bigint as n_dup_lines,
    coalesce(cover.n, 0)::bigint as n_repeat_words,
    length(regexp_replace(text, '[^A-Z]', '', 'g')) as up,
    length(regexp_replace(text, '[^a-z]', '', 'g')) as low,
    len(string_split(text, chr(10))) as n_lines
  from words left join cover using (doc_id)
)"""

QUALITY_KEPT = """
  not (n_words < 50 or 100 * n_repeat_words > 50 * n_words)
  and not (n_symbols > 0.25 * n_words)
  and not (up > 0.5 * (up + low))
  and not (word_chars < 2.0 * n_words or word_chars > 20.0 * n_words)
  and not (n_dup_lines > 0.5 * n_lines)"""

OP4 = f"""
with {QUALITY_BASE}
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  (n_words < 50 or 100 * n_repeat_words > 50 * n_words) as base_failed, ({QUALITY_KEPT}) as kept
from stats
"""

TRIM = "' ' || chr(9) || chr(13)"


def lines_dropped(table: str) -> str:
    """Common table expressions that give host, line and whether it goes."""
    return f"""
line_of as (
  select doc_id, coalesce('h' || source, 'n') as host, i, l, trim(l, {TRIM}) as k
  from (select doc_id, source, unnest(string_split(text, chr(10))) as l, unnest(range(1, len(string_split(text, chr(10))) + 1)) as i from {table} where text is not null)
),
pages_of as (select coalesce('h' || source, 'n') as host, count(*) as pages from {table} group by 1),
common as (
  select host, k from (select host, k, count(distinct doc_id) as n from line_of where k <> '' group by host, k)
  join pages_of using (host) where n >= 3 and n > 0.05 * pages
),
kept_lines as (
  select doc_id, i, l, common.k is not null as gone from line_of left join common on line_of.host = common.host and line_of.k = common.k
),
cleaned as (
  select doc_id, count(*)::bigint as n_lines, (count(*) filter (where gone))::bigint as n_dropped,
    coalesce(string_agg(l, chr(10) order by i) filter (where not gone), '') as text
  from kept_lines group by doc_id
)"""


OP5 = f"""
with {lines_dropped('documents')}
select d.doc_id, d.source, coalesce(c.n_lines, 0)::bigint as n_lines, coalesce(c.n_dropped, 0)::bigint as n_dropped,
  sha256(coalesce(c.text, '')) as kept_sha256
from documents d left join cleaned c using (doc_id)
"""

WORD_ROLLUP = f"""
with counts as (select doc_id, source, lang, len({WORDS})::bigint as n from documents),
lab as (select doc_id, max(toxic) as t, max(case when quality = 1 then 1 else 0 end) as q from labels where doc_id is not null group by doc_id)
select source, lang, 'ws-words@1' as tokenizer, count(*)::bigint as n_docs,
  sum(n + case when lab.t = 0 and lab.q = 1 then 1 else 0 end)::bigint as n_tokens
from counts left join lab using (doc_id) where coalesce(lab.t, 0) <> 1
group by source, lang
"""


def oracle_sql() -> dict[str, str]:
    return {"op4_quality_rules": OP4, "op5_line_dedup": OP5, "llm_word_rollup": WORD_ROLLUP}
