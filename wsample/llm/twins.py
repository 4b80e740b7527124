"""DuckDB twins of the corpus queries that SQL can state."""

from __future__ import annotations

SQL: dict[str, str] = {}

#: Lines as their words with one space between; a unit is a word from three words on, else a character of five or more.
#: A line without its i-th unit meets lines of its size without theirs, and whole lines of one unit less.
SQL["op1_line_dedup"] = r"""
WITH pieces AS (
  SELECT doc_id, text, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents
), lines AS (
  SELECT doc_id, line_no, line, array_to_string(words, ' ') AS whole, words
  FROM (SELECT doc_id, line_no, line, regexp_extract_all(line, '[^\x20\x09-\x0D]+') AS words
        FROM (SELECT doc_id, unnest(parts) AS line, unnest(range(len(parts))) AS line_no FROM pieces))
), firsts AS (
  SELECT whole, any_value(words) AS words, min((doc_id IS NULL, doc_id, line_no)) AS place FROM lines WHERE len(words) > 0 GROUP BY whole
), units AS (
  SELECT whole, place, len(words) >= 3 AS by_word, CASE WHEN len(words) >= 3 THEN words ELSE regexp_extract_all(whole, '(?s).') END AS u
  FROM firsts WHERE len(words) >= 3 OR length(whole) >= 5
), rests AS (
  SELECT whole, place, by_word, n, i,
    CASE WHEN by_word THEN array_to_string(u[:i - 1] || u[i + 1:], ' ') ELSE array_to_string(u[:i - 1] || u[i + 1:], '') END AS rest
  FROM (SELECT whole, place, by_word, u, len(u) AS n, unnest(range(1, len(u) + 1)) AS i FROM units)
), replaced AS (
  SELECT by_word, n, i, rest, min(place) AS least FROM rests GROUP BY ALL
), dropped AS (
  SELECT by_word, rest, min(place) AS least FROM rests GROUP BY ALL
), near AS (
  SELECT r.whole FROM rests r JOIN replaced x ON x.by_word = r.by_word AND x.n = r.n AND x.i = r.i AND x.rest = r.rest AND x.least < r.place
  UNION SELECT w.whole FROM units w JOIN dropped x ON x.by_word = w.by_word AND x.rest = w.whole AND x.least < w.place
  UNION SELECT r.whole FROM rests r JOIN units w ON w.by_word = r.by_word AND w.whole = r.rest AND w.place < r.place
), judged AS (
  SELECT l.doc_id, l.line_no, l.line, len(l.words) > 0 AS has_words, n.whole IS NOT NULL AS is_near,
    n.whole IS NULL AND f.place IS NOT NULL AND (l.doc_id IS NULL, l.doc_id, l.line_no) > f.place AS is_exact
  FROM lines l LEFT JOIN firsts f ON f.whole = l.whole LEFT JOIN near n ON n.whole = l.whole
)
SELECT doc_id, CAST(count(*) FILTER (WHERE has_words) AS INTEGER) AS n_lines, CAST(count(*) FILTER (WHERE is_exact) AS INTEGER) AS n_exact,
  CAST(count(*) FILTER (WHERE is_near) AS INTEGER) AS n_near,
  md5(coalesce(string_agg(line, chr(10) ORDER BY line_no) FILTER (WHERE NOT is_near AND NOT is_exact), '')) AS text_md5
FROM judged GROUP BY doc_id
"""

#: Every window of every item against every run of as many words of every document.
SQL["op6_decontamination"] = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), b AS (
  SELECT CAST(item_id AS VARCHAR) AS item, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark WHERE item_id IS NOT NULL
), windows AS (
  SELECT DISTINCT item, n, array_to_string(w[p:p + n - 1], ' ') AS g
  FROM (SELECT item, w, least(len(w), 10) AS n, unnest(range(1, len(w) - least(len(w), 10) + 2)) AS p FROM b WHERE len(w) > 0)
), runs AS (
  SELECT doc_id, n, p, array_to_string(w[p:p + n - 1], ' ') AS g
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d JOIN (SELECT DISTINCT n FROM windows) ON len(w) >= n)
), met AS (
  SELECT doc_id, n, p, item FROM runs JOIN windows USING (n, g)
), words AS (
  SELECT doc_id, count(DISTINCT word_no) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS word_no FROM met) GROUP BY doc_id
), items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT doc_id, item FROM met) GROUP BY doc_id
)
SELECT doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
  sha256(coalesce(names, '')) AS items_sha256, n_hit IS NOT NULL AS contaminated
FROM d LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)
"""
