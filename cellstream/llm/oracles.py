"""DuckDB SQL of the operators that SQL can express, written from their contracts and not from the Spark expressions.

Token ids, XXH64, CRC-32, keyed surrogates and compression have no SQL form; tests hold those operators against
brute-force versions.
"""

from .quality import ENDS, NAVIGATION, PHRASES, SYMBOLS


def _text(value: str) -> str:
    return "'" + value.replace("'", "''") + "'"


_PLAIN = "' ' || trim(regexp_replace(lower(line), '[^\\p{L}\\p{N}]+', ' ', 'g'), ' ') || ' '"
_FURNITURE = " + ".join(f"(length({_PLAIN}) - length(replace({_PLAIN}, {_text(f' {p} ')}, ' ')))" for p in PHRASES)
_BARS = " + ".join(f"(length(line) - length(replace(line, {_text(p)}, ''))) // {len(p)}" for p in NAVIGATION)
_ENDS = f"right(rtrim(line, ' ' || chr(9) || chr(13)), 1) IN ({', '.join(map(_text, ENDS))})"
_MARKS = f"length(regexp_replace({{0}}, '[^{SYMBOLS}]', '', 'g'))"

_QUALITY = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, list_filter(regexp_split_to_array(t, '[ \\t-\\r]+'), lambda x: x <> '') AS ws FROM d),
g AS (SELECT doc_id, i, array_to_string(ws[i:i + 4], ' ') AS s FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 3)) AS i FROM w)),
twice AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, s) AS n FROM g),
steps AS (SELECT doc_id, i - lag(i) OVER (PARTITION BY doc_id ORDER BY i) AS gap FROM twice WHERE n > 1),
rep AS (SELECT doc_id, CAST(sum(least(5, coalesce(gap, 5))) AS BIGINT) AS n_repeat_words FROM steps GROUP BY doc_id),
ln AS (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM d),
judged AS (SELECT doc_id, line, CASE WHEN 3 * ({_FURNITURE}) >= length({_PLAIN}) THEN 1 WHEN ({_BARS}) >= 2 AND (NOT {_ENDS} OR 16 * ({_BARS}) >= length(line)) THEN 2
  WHEN 5 * {_MARKS.format('line')} > length(line) THEN 3 WHEN NOT {_ENDS} AND len(list_filter(regexp_split_to_array(line, '[ \\t-\\r]+'), lambda x: x <> '')) < 12 THEN 4 ELSE 0 END AS rule FROM ln WHERE regexp_matches(line, '[^ \\t-\\r]')),
per AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n_dup_lines, CAST(coalesce(sum(length(line)) FILTER (rule > 0), 0) AS BIGINT) AS chars_lost, count(*) FILTER (rule = 1) AS lines_boilerplate, count(*) FILTER (rule = 2) AS lines_navigation, count(*) FILTER (rule = 3) AS lines_symbols, count(*) FILTER (rule = 4) AS lines_punctuation FROM judged GROUP BY doc_id),
m AS (SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars, CAST({_MARKS.format('t')} AS BIGINT) AS n_symbols,
  coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(chars_lost, 0) AS chars_lost, length(t) AS n_chars, coalesce(lines_boilerplate, 0) AS lines_boilerplate, coalesce(lines_navigation, 0) AS lines_navigation, coalesce(lines_symbols, 0) AS lines_symbols, coalesce(lines_punctuation, 0) AS lines_punctuation
  FROM w LEFT JOIN rep ON rep.doc_id = w.doc_id LEFT JOIN per ON per.doc_id = w.doc_id)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, chars_lost, lines_boilerplate, lines_navigation, lines_symbols, lines_punctuation, (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed,
  NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AND 2 * chars_lost <= n_chars AS kept FROM m
"""


def _words_of(table: str, key: str) -> str:
    return f"{key}_w AS (SELECT {key}, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '') AS ws FROM {table} WHERE {key} IS NOT NULL)"


_DECONTAMINATION = f"""
WITH {_words_of('documents', 'doc_id')}, {_words_of('benchmark', 'item_id')},
item AS (SELECT DISTINCT item_id, k, array_to_string(ws[i:i + k - 1], ' ') AS s FROM (SELECT item_id, ws, k, unnest(range(1, len(ws) - k + 2)) AS i FROM (SELECT item_id, ws, least(len(ws), 5) AS k FROM item_id_w WHERE len(ws) > 0))),
doc AS (SELECT DISTINCT doc_id, array_to_string(ws[i:i + k - 1], ' ') AS s FROM (SELECT doc_id, ws, k, unnest(range(1, len(ws) - k + 2)) AS i FROM doc_id_w CROSS JOIN (SELECT DISTINCT k FROM item) WHERE len(ws) >= k)),
q AS (SELECT item_id, count(DISTINCT s) AS n_item FROM item GROUP BY item_id),
hit AS (SELECT doc_id, item_id, count(DISTINCT s) AS n_shared FROM doc JOIN item USING (s) GROUP BY doc_id, item_id)
SELECT doc_id, item_id, n_shared, n_item, n_shared / n_item AS containment FROM hit JOIN q USING (item_id) WHERE 10 * n_shared >= 8 * n_item
"""

_SUFFIX = """
WITH d AS (SELECT doc_id, encode(coalesce(text, '')) AS raw FROM documents),
win AS (SELECT doc_id, i, raw[i:i + 99] AS s FROM (SELECT doc_id, raw, unnest(range(1, octet_length(raw) - 98)) AS i FROM d)),
again AS (SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY s ORDER BY doc_id, i) AS k FROM win) WHERE k > 1),
steps AS (SELECT doc_id, i, coalesce(i > lag(i) OVER (PARTITION BY doc_id ORDER BY i) + 100, TRUE) AS fresh FROM again),
runs AS (SELECT doc_id, i, sum(CAST(fresh AS INT)) OVER (PARTITION BY doc_id ORDER BY i) AS r FROM steps),
spans AS (SELECT doc_id, r, min(i) AS a, max(i) + 99 AS b FROM runs GROUP BY doc_id, r),
sums AS (SELECT doc_id, CAST(sum(b - a + 1) AS BIGINT) AS n_removed, count(*) AS n_spans, max(b) AS last_b FROM spans GROUP BY doc_id),
cuts AS (SELECT doc_id, r, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY r), 0) + 1 AS x, a - 1 AS y FROM spans),
heads AS (SELECT doc_id, string_agg(hex(raw[x:y]), '' ORDER BY r) AS h FROM cuts JOIN d USING (doc_id) WHERE y >= x GROUP BY doc_id)
SELECT doc_id, octet_length(raw) AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans,
  sha256(unhex(coalesce(h, '') || CASE WHEN coalesce(last_b, 0) < octet_length(raw) THEN hex(raw[coalesce(last_b, 0) + 1:octet_length(raw)]) ELSE '' END)) AS kept_sha256
FROM d LEFT JOIN sums USING (doc_id) LEFT JOIN heads USING (doc_id)
"""

ORACLES: dict[str, str] = {"op3_quality": _QUALITY, "op4_decontamination": _DECONTAMINATION, "op7_suffix_dedup": _SUFFIX}
