"""SQL twins, for DuckDB, of those operators that SQL can express."""

from __future__ import annotations

from warpspan.llm import quality

_BLANKS = r"[ \t-\r]"
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def _broken(limit: quality.Limit) -> str:
    sides = []
    if limit.low is not None:
        sides.append(f"{limit.metric} < {limit.low}::DOUBLE")
    if limit.high is not None:
        sides.append(f"{limit.metric} > {limit.high}::DOUBLE")
    return f"({' OR '.join(sides)})"


def quality_rules() -> str:
    stop = ", ".join(f"'{w}'" for w in quality.STOP_WORDS)
    rules = (*quality.BASE, *quality.STANDARD)
    base = " OR ".join(map(_broken, quality.BASE))
    reasons = ", ".join(f"CASE WHEN {_broken(r)} THEN '{r.name}' END" for r in rules)
    return rf"""WITH parts AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t,
  list_filter(string_split_regex(coalesce(text, ''), '{_BLANKS}+'), lambda x: x <> '') AS ws,
  list_filter(string_split(coalesce(text, ''), chr(10)), lambda s: regexp_matches(s, '[^ \t-\r]')) AS ls FROM documents),
windows AS (SELECT rid, i, ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2] AS g FROM (SELECT rid, ws, unnest(range(1, len(ws) - 1)) AS i FROM parts)),
again AS (SELECT rid, i FROM windows QUALIFY count(*) OVER (PARTITION BY rid, g) > 1),
covered AS (SELECT rid, count(DISTINCT p) AS n FROM (SELECT rid, unnest([i, i + 1, i + 2]) AS p FROM again) GROUP BY rid),
counts AS (SELECT doc_id, len(ws) AS n_words, length(array_to_string(ws, '')) AS word_chars,
  length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS n_symbols, len(ls) AS n_lines, len(ls) - len(list_distinct(ls)) AS n_dup_lines,
  coalesce(n, 0) AS n_repeat_words, len(list_filter(ws, lambda x: lower(x) IN ({stop}))) AS n_stop_words,
  length(t) - length(regexp_replace(t, '\p{{L}}+', '', 'g')) AS n_letters, length(t) - length(regexp_replace(t, '\p{{Lu}}+', '', 'g')) AS n_capitals
  FROM parts LEFT JOIN covered USING (rid)),
ratios AS (SELECT *, coalesce(n_repeat_words / nullif(n_words, 0), 0) AS repeat_word_ratio, coalesce(n_symbols / nullif(word_chars, 0), 0) AS symbol_ratio,
  coalesce(word_chars / nullif(n_words, 0), 0) AS mean_word_length, coalesce(n_dup_lines / nullif(n_lines, 0), 0) AS dup_line_ratio,
  coalesce(n_letters / nullif(word_chars, 0), 0) AS letter_ratio, coalesce(n_stop_words / nullif(n_words, 0), 0) AS stop_word_ratio,
  coalesce(n_capitals / nullif(n_letters, 0), 0) AS capital_ratio FROM counts)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols, n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words::BIGINT AS n_repeat_words,
  ({base}) AS base_failed, NOT ({' OR '.join(map(_broken, rules))}) AS kept, concat_ws(',', {reasons}) AS reasons FROM ratios"""


def decontamination(width: int = 13) -> str:
    words = lambda t: rf"regexp_extract_all(translate(coalesce({t}, ''), '{_UPPER}', '{_UPPER.lower()}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
    return f"""WITH items AS (SELECT item_id, {words('text')} AS ws FROM benchmark),
marks AS (SELECT DISTINCT item_id::VARCHAR AS item, n, array_to_string(ws[i:i + n - 1], ' ') AS g
  FROM (SELECT item_id, ws, least(len(ws), {width}) AS n, unnest(range(1, greatest(len(ws) - {width - 1}, 1) + 1)) AS i FROM items WHERE len(ws) > 0)),
docs AS (SELECT row_number() OVER () AS rid, doc_id, {words('text')} AS ws FROM documents),
places AS (SELECT rid, i, n, array_to_string(ws[i:i + n - 1], ' ') AS g FROM (SELECT rid, ws, n, unnest(range(1, len(ws) - n + 2)) AS i FROM docs CROSS JOIN (SELECT DISTINCT n FROM marks))),
found AS (SELECT rid, i, m.n, item FROM places p JOIN marks m ON p.n = m.n AND p.g = m.g),
hits AS (SELECT rid, count(DISTINCT w) AS n_hit FROM (SELECT rid, unnest(range(i, i + n)) AS w FROM found) GROUP BY rid),
owners AS (SELECT rid, count(item) AS n_items, string_agg(item, ',' ORDER BY item) AS listed FROM (SELECT DISTINCT rid, item FROM found) GROUP BY rid)
SELECT doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(listed, '')) AS items_sha256,
  coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated FROM docs LEFT JOIN hits USING (rid) LEFT JOIN owners USING (rid)"""
