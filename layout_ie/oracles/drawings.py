"""DuckDB SQL that draws the three corpora from the raw tables, apart from the engine's code.

Each constant is a list of common table expressions; ``q(...)`` puts them in front of a query.
"""

from __future__ import annotations

SHEETS = """
ln AS (
  SELECT l.l_orderkey AS p, row_number() OVER (PARTITION BY l.l_orderkey ORDER BY l.l_linenumber, l.l_partkey, l.l_suppkey) AS r,
         count(*) OVER (PARTITION BY l.l_orderkey) AS n, l.l_returnflag AS flag, strftime(l.l_shipdate, '%Y-%m-%d') AS dy,
         CAST(CAST(l.l_quantity AS BIGINT) AS VARCHAR) AS qty, pt.p_name AS nm, o.o_orderstatus AS st
  FROM lineitem l, part pt, orders o WHERE l.l_partkey = pt.p_partkey AND l.l_orderkey = o.o_orderkey),
pg AS (SELECT p, max(n) AS n, max(st) AS st FROM ln GROUP BY p),
cells AS (
  SELECT p, r, 1 AS k, 'value' AS kind, CASE flag WHEN 'R' THEN 'Returned' WHEN 'A' THEN 'Accepted' ELSE 'None' END AS text FROM ln
  UNION ALL SELECT p, r, 2, 'value', dy FROM ln UNION ALL SELECT p, r, 3, 'value', qty FROM ln UNION ALL SELECT p, r, 4, 'value', nm FROM ln
  UNION ALL SELECT p, 0, h.k, 'head', h.t FROM pg, (VALUES (1,'Return Flag'),(2,'Ship Date'),(3,'Quantity'),(4,'Part')) h(k, t)
  UNION ALL SELECT p, n + 1, 1, 'note', 'Returned items: see policy' FROM pg WHERE p % 2 = 0 AND p % 11 = 5),
grid AS (
  SELECT p, kind, text, CASE WHEN p % 2 = 0 THEN 200 + 160 * (k - 1) ELSE 200 + 160 * r END AS x,
         CASE WHEN p % 2 = 0 THEN 100 + 20 * r ELSE 100 + 20 * (k - 1) END AS y,
         CASE WHEN p % 2 = 0 THEN r ELSE k - 1 END AS vr, CASE WHEN p % 2 = 0 THEN k - 1 ELSE r END AS vc,
         CASE WHEN kind = 'head' AND p % 7 = 3 THEN 20 ELSE 0 END AS ins FROM cells),
gb AS (SELECT *, CASE WHEN p % 3 = 2 THEN vc ELSE vr END + 1 AS i, CASE WHEN p % 3 = 2 THEN vr ELSE vc END + 1 AS j FROM grid),
drawn AS (
  SELECT p, kind, '1.3.' || i || '.' || j || CASE WHEN kind = 'head' THEN '.1' ELSE '' END AS region_id, x + ins AS x_l, y AS y_l, x + 160 - ins AS x_h, y + 20 AS y_h, text,
         CASE WHEN kind = 'head' THEN 'span' WHEN p % 3 = 0 THEN 'td' WHEN p % 3 = 1 THEN 'div' ELSE 'li' END AS html_tag, 3 AS s1, i AS s2, j AS s3 FROM gb
  UNION ALL
  SELECT p, 'bar', '1.1.' || b.k, 0, 80 + 20 * b.k, 180, 100 + 20 * b.k, b.t, 'li', 1, b.k, 0 FROM pg, (VALUES (1,'Home'),(2,'Orders'),(3,'Returned'),(4,'Parts'),(5,'Help')) b(k, t)
  UNION ALL
  SELECT p, 'title', '1.2', 200, CASE WHEN p % 17 = 2 THEN 80 ELSE 0 END, 1000, CASE WHEN p % 17 = 2 THEN 120 ELSE 40 END,
         CASE WHEN st <> 'P' THEN 'Order Summary' WHEN p % 13 = 1 THEN 'Order Draft, not an Order Summary' ELSE 'Order Draft' END, 'h1', 2, 0, 0 FROM pg
  UNION ALL
  SELECT p, 'footer', '1.4', CASE WHEN p % 5 = 0 THEN 0 ELSE 200 END, 240 + 20 * n, 1000, 260 + 20 * n, 'See Order Summary. Returned goods policy.', 'footer', 4, 0, 0 FROM pg),
vis AS (
  SELECT CAST(p AS BIGINT) AS page_id, region_id, CAST(x_l AS BIGINT) AS x_l, CAST(y_l AS BIGINT) AS y_l, CAST(x_h AS BIGINT) AS x_h, CAST(y_h AS BIGINT) AS y_h,
         CAST(coalesce(sum(length(text) + 1) OVER (PARTITION BY p ORDER BY s1, s2, s3 ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS text_start,
         CAST(sum(length(text) + 1) OVER (PARTITION BY p ORDER BY s1, s2, s3) - 1 AS BIGINT) AS text_end, text, html_tag, kind,
         CAST(row_number() OVER (PARTITION BY p ORDER BY s1, s2, s3) AS BIGINT) AS ord, CAST(p % 3 AS BIGINT) AS template FROM drawn)
"""

#: Heading label -> the box of its cell.
HEAD_CELLS = """
headcell AS (
  SELECT page_id, substr(region_id, 1, length(region_id) - 2) AS region_id, x_l - CASE WHEN page_id % 7 = 3 THEN 20 ELSE 0 END AS x_l, y_l,
         x_h + CASE WHEN page_id % 7 = 3 THEN 20 ELSE 0 END AS x_h, y_h, text FROM vis WHERE kind = 'head')
"""

PAGES = r"""
src AS (
  SELECT page_id, CASE WHEN position('</body>' IN html) = 0 THEN body || '</body>' ELSE body END AS h FROM (
    SELECT page_id, html, regexp_replace(regexp_replace(substr(html, position('<body>' IN html)), '(?s)<!--.*?-->', '', 'g'), '(?s)<p><b>([^<]*)<br>', '<p><b>\1</b></p>', 'g') AS body FROM pages)),
tk AS (SELECT page_id, unnest(t) AS t, CAST(unnest(range(1, len(t) + 1)) AS BIGINT) AS o FROM (SELECT page_id, regexp_extract_all(h, '<[^>]*>|[^<]+') AS t FROM src)),
kd AS (
  SELECT page_id, o, t, CASE WHEN t LIKE '</%' THEN -1 WHEN t LIKE '<%' AND t NOT LIKE '<br%' THEN 1 ELSE 0 END AS d, CASE WHEN t LIKE '<%' THEN NULL ELSE
    trim(regexp_replace(replace(replace(replace(replace(replace(replace(replace(t, '&copy;', '©'), '&middot;', '·'), '&quot;', '"'), '&lt;', '<'), '&gt;', '>'), '&#39;', ''''), '&amp;', '&'), '[ \t\n\r\f]+', ' ', 'g')) END AS said FROM tk),
dp AS (SELECT *, CAST(sum(d) OVER (PARTITION BY page_id ORDER BY o) AS BIGINT) AS dep FROM kd),
el AS (
  SELECT s.page_id, s.o, s.dep AS depth, regexp_extract(s.t, '<([a-z0-9]+)', 1) AS html_tag, min(e.o) AS stop
  FROM dp s JOIN dp e ON e.page_id = s.page_id AND e.o > s.o AND e.d = -1 AND e.dep = s.dep - 1 WHERE s.d = 1 GROUP BY ALL),
up AS (SELECT c.page_id, c.o, max(p.o) AS po FROM el c JOIN el p ON p.page_id = c.page_id AND p.depth = c.depth - 1 AND p.o < c.o GROUP BY ALL),
nth AS (SELECT page_id, o, po, row_number() OVER (PARTITION BY page_id, po ORDER BY o) AS i FROM up),
pt AS (
  WITH RECURSIVE w AS (
    SELECT page_id, o, '1' AS region_id FROM el WHERE depth = 1
    UNION ALL SELECT n.page_id, n.o, w.region_id || '.' || n.i FROM nth n JOIN w ON w.page_id = n.page_id AND w.o = n.po)
  SELECT * FROM w),
rn AS (
  SELECT page_id, o, said, CAST(coalesce(sum(length(said) + 1) OVER (PARTITION BY page_id ORDER BY o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS a, length(said) AS n
  FROM kd WHERE said IS NOT NULL AND said <> ''),
ow AS (SELECT r.page_id, r.o, r.said, max(e.o) AS eo FROM rn r JOIN el e ON e.page_id = r.page_id AND e.o < r.o AND e.stop > r.o GROUP BY ALL),
tx AS (
  SELECT e.page_id, e.o, e.depth, e.html_tag, p.region_id, min(r.a) AS text_start, max(r.a + r.n) AS text_end
  FROM el e JOIN pt p ON p.page_id = e.page_id AND p.o = e.o LEFT JOIN rn r ON r.page_id = e.page_id AND r.o > e.o AND r.o < e.stop GROUP BY ALL),
sz AS (
  SELECT *, page_id % 3 AS tm, text_end - text_start AS len, row_number() OVER (PARTITION BY page_id ORDER BY o) AS ord,
         CASE WHEN html_tag = 'li' THEN 'nav' WHEN html_tag IN ('h1','p','div','footer') THEN 'content' END AS col FROM tx),
wd AS (
  SELECT *, CASE WHEN col = 'nav' THEN CASE tm WHEN 0 THEN 0 WHEN 1 THEN 824 ELSE 0 END WHEN col = 'content' THEN CASE tm WHEN 0 THEN 220 ELSE 0 END END AS cx,
         CASE WHEN col = 'nav' THEN CASE tm WHEN 0 THEN 200 WHEN 1 THEN 1024 ELSE 1024 END WHEN col = 'content' THEN CASE tm WHEN 1 THEN 804 ELSE 1024 END END AS ch FROM sz),
ht AS (SELECT *, 20 * greatest(1, (8 * len + (ch - cx) - 1) // (ch - cx)) AS hh, row_number() OVER (PARTITION BY page_id, col ORDER BY o) AS ci FROM wd),
lf AS (
  SELECT page_id, o, CASE WHEN tm = 2 AND col = 'nav' THEN 160 * (ci - 1) ELSE cx END AS x_l, CASE WHEN tm = 2 AND col = 'nav' THEN 160 * ci ELSE ch END AS x_h,
         CASE WHEN tm = 2 AND col = 'nav' THEN 100 ELSE 100 + CASE WHEN tm = 2 THEN 20 ELSE 0 END + sum(hh) OVER (PARTITION BY page_id, col ORDER BY o) - hh END AS y_l,
         CASE WHEN tm = 2 AND col = 'nav' THEN 120 ELSE 100 + CASE WHEN tm = 2 THEN 20 ELSE 0 END + sum(hh) OVER (PARTITION BY page_id, col ORDER BY o) END AS y_h FROM ht WHERE col IS NOT NULL),
inl AS (
  SELECT z.page_id, z.o, l.x_l, l.x_l + least(8 * z.len, l.x_h - l.x_l) AS x_h, l.y_l, l.y_h
  FROM sz z JOIN up u ON u.page_id = z.page_id AND u.o = z.o JOIN lf l ON l.page_id = u.page_id AND l.o = u.po WHERE z.html_tag IN ('a', 'b')),
con AS (
  SELECT e.page_id, e.o, min(l.x_l) AS x_l, max(l.x_h) AS x_h, min(l.y_l) AS y_l, max(l.y_h) AS y_h
  FROM el e JOIN el f ON f.page_id = e.page_id AND f.o > e.o AND f.o < e.stop JOIN lf l ON l.page_id = f.page_id AND l.o = f.o WHERE e.html_tag IN ('body','nav','ul','article') GROUP BY ALL),
bx AS (SELECT page_id, o, x_l, x_h, y_l, y_h FROM lf UNION ALL SELECT page_id, o, x_l, x_h, y_l, y_h FROM inl UNION ALL SELECT page_id, o, x_l, x_h, y_l, y_h FROM con),
own AS (SELECT page_id, eo AS o, string_agg(said, chr(10) ORDER BY o) AS text FROM ow GROUP BY ALL),
reg AS (
  SELECT s.page_id, s.region_id, CAST(b.x_l AS BIGINT) AS x_l, CAST(b.y_l AS BIGINT) AS y_l, CAST(b.x_h AS BIGINT) AS x_h, CAST(b.y_h AS BIGINT) AS y_h,
         CAST(s.text_start AS BIGINT) AS text_start, CAST(s.text_end AS BIGINT) AS text_end, w.text, s.html_tag,
         CASE WHEN s.len > 0 THEN arg_max(s.region_id, s.depth) OVER (PARTITION BY s.page_id, s.text_start, s.text_end) ELSE s.region_id END AS minimal_region,
         CASE WHEN s.len > 0 THEN arg_min(s.region_id, s.depth) OVER (PARTITION BY s.page_id, s.text_start, s.text_end) ELSE s.region_id END AS maximal_region,
         CAST(s.depth AS BIGINT) AS depth, CAST(s.ord AS BIGINT) AS ord, CAST(s.tm AS BIGINT) AS template
  FROM sz s JOIN bx b ON b.page_id = s.page_id AND b.o = s.o LEFT JOIN own w ON w.page_id = s.page_id AND w.o = s.o)
"""

GRID = r"""
gl AS (SELECT doc_id, text, unnest(string_split(text, chr(10))) AS line, CAST(unnest(range(1, len(string_split(text, chr(10))) + 1)) AS BIGINT) AS l FROM documents),
go AS (SELECT *, CAST(coalesce(sum(length(line) + 1) OVER (PARTITION BY doc_id ORDER BY l ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS pos0 FROM gl),
gm AS (SELECT doc_id, l, pos0, regexp_extract_all(line, '[^ \t\r\f]+') AS m, regexp_split_to_array(line, '[^ \t\r\f]+') AS g FROM go),
gu AS (SELECT doc_id, l, pos0, unnest(m) AS w, unnest(g[1:len(m)]) AS gap, CAST(unnest(range(1, len(m) + 1)) AS BIGINT) AS i FROM gm WHERE len(m) > 0),
gc AS (SELECT *, CAST(sum(length(gap) + length(w)) OVER (PARTITION BY doc_id, l ORDER BY i) AS BIGINT) - length(w) AS c FROM gu),
grid_words AS (
  SELECT doc_id AS page_id, '1.' || l || '.' || i AS region_id, CAST(8 * c AS BIGINT) AS x_l, CAST(20 * (l - 1) AS BIGINT) AS y_l, CAST(8 * (c + length(w)) AS BIGINT) AS x_h, CAST(20 * l AS BIGINT) AS y_h,
         CAST(pos0 + c AS BIGINT) AS text_start, CAST(pos0 + c + length(w) AS BIGINT) AS text_end, w AS text FROM gc),
grid_lines AS (
  SELECT doc_id AS page_id, '1.' || l AS region_id, CAST(0 AS BIGINT) AS x_l, CAST(20 * (l - 1) AS BIGINT) AS y_l, CAST(8 * length(line) AS BIGINT) AS x_h, CAST(20 * l AS BIGINT) AS y_h,
         pos0 AS text_start, CAST(pos0 + length(line) AS BIGINT) AS text_end, CAST(2 AS BIGINT) AS depth FROM go)
"""


def q(body: str, *parts: str) -> str:
    """A query with common table expressions in front."""
    return f"WITH RECURSIVE {', '.join(p.strip() for p in parts)} {body}" if parts else body


def spans(pattern: str, table: str = "documents", key: str = "doc_id", text: str = "text", name: str = "sp") -> str:
    """Expression ``name(key, begin, end, matched)``: offsets as running lengths of gaps and matches."""
    return rf"""
{name}_m AS (SELECT {key}, regexp_extract_all({text}, '{pattern}') AS m, regexp_split_to_array({text}, '{pattern}') AS g, row_number() OVER () AS rid FROM {table}),
{name}_u AS (SELECT {key}, rid, unnest(m) AS w, unnest(g[1:len(m)]) AS gap, unnest(range(1, len(m) + 1)) AS i FROM {name}_m WHERE len(m) > 0),
{name} AS (SELECT {key}, CAST(sum(length(gap) + length(w)) OVER (PARTITION BY rid ORDER BY i) AS BIGINT) - length(w) AS "begin", CAST(sum(length(gap) + length(w)) OVER (PARTITION BY rid ORDER BY i) AS BIGINT) AS "end", w AS matched FROM {name}_u)
"""
