"""SQL of the queries, for DuckDB, written from their contracts."""

from __future__ import annotations

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _low(e: str) -> str:
    return f"translate({e}, '{_UPPER}', '{_LOWER}')"


_BLANK_WORDS = r"[^\x20\x09-\x0D]+"
_ALNUM_WORDS = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

#: Each measure's value, quartile distances of its fence, and the least distance in buckets.
_MEASURES = {
    "symbols": ("(n_symbols + 0.5::DOUBLE) / (word_chars + 1)", 3, 35), "repeats": ("(n_repeat_words + 0.5::DOUBLE) / (n_words + 1)", 3, 35),
    "dup_lines": ("(n_dup_lines + 0.5::DOUBLE) / (n_words + 1)", 3, 35), "word_length": ("word_chars / greatest(n_words, 1)::DOUBLE", 6, 2),
}


def _bucket(v: str) -> str:
    return f"CASE WHEN ({v}) * 10000 < 1 THEN 0 ELSE floor(ln(({v}) * 10000) / ln(1.02::DOUBLE))::INT + 1 END"


def _level(name: str, keys: str) -> str:
    """Fences of a level, in buckets of a growth of 1.02 from 1/10000."""
    by = f"{keys}, " if keys else ""
    return f"""{name}_n AS (SELECT {by}m, b, count(*) AS n FROM e GROUP BY {by}m, b),
    {name}_u AS (SELECT *, sum(n) OVER (PARTITION BY {by}m ORDER BY b) AS upto, sum(n) OVER (PARTITION BY {by}m) AS docs FROM {name}_n),
    {name}_q AS (SELECT {by}m, docs, min(b) FILTER (upto >= 0.25 * docs) AS q1, min(b) FILTER (upto >= 0.75 * docs) AS q3 FROM {name}_u GROUP BY {by}m, docs),
    {name} AS (SELECT {by}m, docs, q3 + reach * greatest(q3 - q1, least_width) AS high, q1 - reach * greatest(q3 - q1, least_width) AS low FROM {name}_q JOIN ru USING (m))"""


OP1 = f"""
WITH w AS (SELECT doc_id, lang, source, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '{_BLANK_WORDS}') AS ws FROM documents),
    g AS (SELECT doc_id, unnest(range(1, len(ws) - 3)) AS p, ws FROM w WHERE len(ws) >= 5),
    g5 AS (SELECT doc_id, p, array_to_string(ws[p:p + 4], ' ') AS s FROM g),
    rep AS (SELECT doc_id, p FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, s) AS c FROM g5) WHERE c > 1),
    cov AS (SELECT doc_id, count(DISTINCT p + k) AS n_repeat_words FROM rep, (SELECT unnest(range(0, 5)) AS k) GROUP BY doc_id),
    ln AS (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM w),
    dup AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n_dup_lines FROM ln WHERE regexp_matches(line, '{_BLANK_WORDS}') GROUP BY doc_id),
    c AS (SELECT w.doc_id, lang, source, len(ws)::BIGINT AS n_words, length(array_to_string(ws, ''))::BIGINT AS word_chars,
                 (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
                 coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words
          FROM w LEFT JOIN cov USING (doc_id) LEFT JOIN dup USING (doc_id)),
    e AS ({' UNION ALL '.join(f"SELECT lang, source, '{m}' AS m, {_bucket(v)} AS b FROM c WHERE n_words > 0" for m, (v, _, _) in _MEASURES.items())}),
    ru AS (SELECT * FROM (VALUES {', '.join(f"('{m}', {r}, {w})" for m, (_, r, w) in _MEASURES.items())}) AS t(m, reach, least_width)),
    {_level('own', 'lang, source')}, {_level('bylang', 'lang')}, {_level('whole', '')},
    wi AS (SELECT o.lang, o.source, o.m, o.docs, o.high, o.low, CASE WHEN l.docs >= 50 THEN l.high ELSE a.high END AS wide_high, CASE WHEN l.docs >= 50 THEN l.low ELSE a.low END AS wide_low
           FROM own o JOIN bylang l ON o.lang IS NOT DISTINCT FROM l.lang AND o.m = l.m JOIN whole a ON o.m = a.m),
    f AS (SELECT lang, source, m, CASE WHEN docs >= 50 THEN least(high, wide_high) ELSE wide_high END AS high, CASE WHEN docs >= 50 THEN greatest(low, wide_low) ELSE wide_low END AS low FROM wi),
    h AS (SELECT lang, source, {', '.join(f"max(high) FILTER (m = '{m}') AS {m}_high" for m in _MEASURES)}, max(low) FILTER (m = 'word_length') AS low FROM f GROUP BY lang, source),
    j AS (SELECT c.*, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed, {', '.join(f'h.{m}_high' for m in _MEASURES)}, h.low
          FROM c LEFT JOIN h ON c.lang IS NOT DISTINCT FROM h.lang AND c.source IS NOT DISTINCT FROM h.source)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       coalesce(NOT base_failed AND {' AND '.join(f'{_bucket(v)} <= {m}_high' for m, (v, _, _) in _MEASURES.items())}
       AND {_bucket(_MEASURES['word_length'][0])} >= low, FALSE) AS kept
FROM j
"""

OP2 = f"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all({_low("coalesce(text, '')")}, '{_BLANK_WORDS}') AS ws FROM documents),
    s AS (SELECT DISTINCT doc_id, array_to_string(ws[p:p + 4], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 2))) AS p FROM w WHERE len(ws) > 0)),
    n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
    p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
    l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 80 * (x.n + y.n - i)),
    d AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
    r AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, d.b FROM r JOIN d ON r.b = d.a)
SELECT doc_id, coalesce(n, 0) AS n_shingles, (SELECT min(b) FROM r WHERE r.a = documents.doc_id) AS component_id FROM documents LEFT JOIN n USING (doc_id)
"""

OP3 = f"""
WITH i AS (SELECT item_id::VARCHAR AS item, regexp_extract_all({_low("coalesce(text, '')")}, '{_ALNUM_WORDS}') AS ws FROM benchmark),
    q AS (SELECT item, ws, least(13, len(ws)) AS m FROM i WHERE len(ws) > 0),
    pat AS (SELECT DISTINCT item, m, array_to_string(ws[p:p + m - 1], ' ') AS s FROM (SELECT item, ws, m, unnest(range(1, len(ws) - m + 2)) AS p FROM q)),
    d AS (SELECT doc_id, regexp_extract_all({_low("coalesce(text, '')")}, '{_ALNUM_WORDS}') AS ws FROM documents),
    win AS (SELECT doc_id, m, p, array_to_string(ws[p:p + m - 1], ' ') AS s FROM (SELECT doc_id, ws, m, unnest(range(1, len(ws) - m + 2)) AS p FROM d, (SELECT DISTINCT m FROM pat) WHERE len(ws) >= m)),
    hit AS (SELECT doc_id, win.m, p, item FROM win JOIN pat USING (m, s)),
    pos AS (SELECT doc_id, count(DISTINCT x) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + m)) AS x FROM hit) GROUP BY doc_id),
    own AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, item FROM hit) GROUP BY doc_id)
SELECT doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated
FROM d LEFT JOIN pos USING (doc_id) LEFT JOIN own USING (doc_id)
"""
