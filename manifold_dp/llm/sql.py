"""DuckDB SQL of the text operators whose results plain SQL can state."""

from __future__ import annotations

from . import chat, linededup, topk

_WORDS = "SELECT doc_id, list_filter(string_split_regex({text}, '[\\x20\\x09-\\x0D]+'), lambda z: z <> '') AS ws FROM documents"

SUBSTRING = f"""
WITH w AS ({_WORDS.format(text="coalesce(text, '')")}),
tok AS (SELECT doc_id, generate_subscripts(ws, 1) AS p, unnest(ws) AS x FROM w),
win AS (
  SELECT doc_id, p, string_agg(x, ' ') OVER f AS k, count(*) OVER f AS n FROM tok
  WINDOW f AS (PARTITION BY doc_id ORDER BY p ROWS BETWEEN CURRENT ROW AND 12 FOLLOWING)
),
first AS (SELECT k, min(doc_id) AS d FROM win WHERE n = 13 GROUP BY k),
gone AS (SELECT DISTINCT doc_id, unnest(generate_series(p, p + 12)) AS p FROM win JOIN first USING (k) WHERE n = 13 AND doc_id > d),
kept AS (
  SELECT doc_id, count(*) AS n_words, count(g.p) AS n_removed, string_agg(x, ' ' ORDER BY tok.p) FILTER (g.p IS NULL) AS t
  FROM tok LEFT JOIN gone g USING (doc_id, p) GROUP BY doc_id
)
SELECT d.doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM documents d LEFT JOIN kept USING (doc_id)
"""

JACCARD = f"""
WITH RECURSIVE w AS ({_WORDS.format(text="translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')")}),
tok AS (SELECT doc_id, generate_subscripts(ws, 1) AS p, unnest(ws) AS x, len(ws) AS n FROM w),
win AS (
  SELECT doc_id, p, n, string_agg(x, ' ') OVER f AS k, count(*) OVER f AS m FROM tok
  WINDOW f AS (PARTITION BY doc_id ORDER BY p ROWS BETWEEN CURRENT ROW AND 4 FOLLOWING)
),
s AS (SELECT DISTINCT doc_id, k FROM win WHERE m = 5 OR (n < 5 AND p = 1)),
size AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
shared AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.k = b.k AND a.doc_id <> b.doc_id GROUP BY ALL),
link AS (SELECT a, b FROM shared JOIN size x ON x.doc_id = a JOIN size y ON y.doc_id = b WHERE 100 * c >= 80 * (x.n + y.n - c)),
reach AS (SELECT doc_id AS a, doc_id AS b FROM size UNION SELECT r.a, l.b FROM reach r JOIN link l ON l.a = r.b),
least AS (SELECT a, min(b) AS c FROM reach GROUP BY a)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, coalesce(c, d.doc_id) AS component_id
FROM documents d LEFT JOIN size USING (doc_id) LEFT JOIN least ON a = d.doc_id
"""

_NORMAL = "list_filter(string_split_regex(lower(coalesce(text, '')), '[^a-z0-9\\x{80}-\\x{10FFFF}]+'), lambda z: z <> '')"

#: Windows of a document and of an item (13 words, or all of a shorter item) meet on one of
#: three stretches that at least one must be free of the two substitutions; items under 5
#: words meet whole lines (``st``, ``en``: a line of words begins, ends here).
CONTAMINATION = f"""
WITH dl AS (SELECT doc_id, generate_subscripts(ls, 1) AS ln, unnest(ls) AS text FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents)),
dn AS (SELECT doc_id, row_number() OVER (PARTITION BY doc_id ORDER BY ln, k) - 1 AS p, x, ln FROM (SELECT doc_id, ln, generate_subscripts(ws, 1) AS k, unnest(ws) AS x FROM (SELECT doc_id, ln, {_NORMAL} AS ws FROM dl))),
dt AS (SELECT doc_id, p, x, coalesce(lag(ln) OVER o <> ln, true) AS st, coalesce(lead(ln) OVER o <> ln, true) AS en FROM dn WINDOW o AS (PARTITION BY doc_id ORDER BY p)),
it AS (SELECT item_id, len(ws) AS n, generate_subscripts(ws, 1) - 1 AS a, unnest(ws) AS y FROM (SELECT item_id, {_NORMAL} AS ws FROM benchmark)),
dp AS (SELECT doc_id, p, string_agg(x, ' ') OVER f4 AS k4, count(*) OVER f4 AS c4, string_agg(x, ' ') OVER f2 AS k2, count(*) OVER f2 AS c2 FROM dt
  WINDOW f4 AS (PARTITION BY doc_id ORDER BY p ROWS BETWEEN CURRENT ROW AND 3 FOLLOWING), f2 AS (PARTITION BY doc_id ORDER BY p ROWS BETWEEN CURRENT ROW AND 1 FOLLOWING)),
ip AS (SELECT item_id, n, a, string_agg(y, ' ') OVER f4 AS k4, count(*) OVER f4 AS c4, string_agg(y, ' ') OVER f2 AS k2, count(*) OVER f2 AS c2 FROM it
  WINDOW f4 AS (PARTITION BY item_id ORDER BY a ROWS BETWEEN CURRENT ROW AND 3 FOLLOWING), f2 AS (PARTITION BY item_id ORDER BY a ROWS BETWEEN CURRENT ROW AND 1 FOLLOWING)),
diag AS (SELECT DISTINCT doc_id, item_id, n, p - a AS shift FROM dp JOIN ip ON dp.k4 = ip.k4 AND dp.c4 = 4 AND ip.c4 = 4 AND n >= 13
  UNION SELECT DISTINCT doc_id, item_id, n, p - a FROM dp JOIN ip ON dp.k2 = ip.k2 AND dp.c2 = 2 AND ip.c2 = 2 AND n < 13 AND n >= 5
  UNION SELECT d.doc_id, item_id, n, d.p FROM dt d JOIN it ON a = 0 AND n < 5 AND x = y AND st JOIN dt e ON e.doc_id = d.doc_id AND e.p = d.p + n - 1 AND e.en),
cell AS (SELECT g.doc_id, g.item_id, g.n, shift, a, CASE WHEN x = y THEN 1 ELSE 0 END AS same FROM diag g JOIN it USING (item_id) JOIN dt ON dt.doc_id = g.doc_id AND dt.p = it.a + shift),
win AS (SELECT *, least(13, n) AS span, sum(same) OVER f AS hits, count(*) OVER f AS c FROM cell
  WINDOW f AS (PARTITION BY doc_id, item_id, n, shift ORDER BY a ROWS BETWEEN CURRENT ROW AND 12 FOLLOWING)),
good AS (SELECT doc_id, item_id, n, shift, a, span FROM win WHERE c = span AND hits >= span - CASE WHEN n >= 13 THEN 2 ELSE n * 2 // 13 END),
cover AS (SELECT DISTINCT doc_id, item_id, n, shift, unnest(generate_series(a, a + span - 1)) AS a FROM good),
per AS (SELECT doc_id, item_id, n, shift, CAST(sum(same) AS BIGINT) AS matched, count(*) AS overlap, min(a) + shift AS doc_from FROM cover JOIN cell USING (doc_id, item_id, n, shift, a) GROUP BY doc_id, item_id, n, shift)
SELECT doc_id, item_id, n AS item_words, matched, overlap, doc_from
FROM (SELECT *, row_number() OVER (PARTITION BY doc_id, item_id ORDER BY matched DESC, overlap DESC, doc_from DESC) AS r FROM per) WHERE r = 1
"""

ORACLES = {
    "op1_decontaminate": CONTAMINATION,
    "op2_line_dedup": linededup.ORACLE,
    "op4_chat_format": chat.ORACLE,
    "op7_substring_dedup": SUBSTRING,
    "op8_jaccard_join": JACCARD,
    "op9_topk": topk.ORACLE,
}
