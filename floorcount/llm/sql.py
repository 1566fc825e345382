"""DuckDB SQL for the results of the operators that SQL can express."""

WORDS = r"regexp_extract_all(text, '[^\x20\x09-\x0D]+')"

OP2 = rf"""
WITH d AS (SELECT doc_id, lang, source, coalesce(text, '') AS text, {WORDS.replace("text,", "coalesce(text, ''),")} AS ws FROM documents),
pos AS (SELECT doc_id, i, array_to_string(ws[i:i + 7], ' ') AS w FROM (SELECT doc_id, ws, unnest(generate_series(1, len(ws) - 7)) AS i FROM d WHERE len(ws) >= 8)),
twice AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, w) AS n FROM pos) WHERE n > 1),
rep AS (SELECT doc_id, count(DISTINCT i + k) AS n_repeat_words FROM twice, generate_series(0, 7) AS g(k) GROUP BY doc_id),
ln AS (SELECT doc_id, count(*) AS n_lines, count(DISTINCT l) AS n_distinct FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM d) WHERE regexp_matches(l, '[^\x20\x09-\x0D]') GROUP BY doc_id),
m AS (SELECT d.doc_id, lang, source, len(ws) AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g')) AS word_chars,
  length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS n_symbols, coalesce(n_lines - n_distinct, 0) AS n_dup_lines,
  coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(n_lines, 0) AS n_lines FROM d LEFT JOIN rep USING (doc_id) LEFT JOIN ln USING (doc_id)),
f AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM m),
r AS (SELECT doc_id, lang, source, base_failed, ratio, CASE WHEN den > 0 THEN floor(num * 1000 / den)::BIGINT ELSE 0 END AS v FROM
  (SELECT doc_id, lang, source, base_failed, unnest(['symbols', 'dup_lines', 'repeats', 'word_length']) AS ratio, unnest([n_symbols, n_dup_lines, n_repeat_words, word_chars]) AS num,
   unnest([word_chars, n_lines, n_words, n_words]) AS den FROM f)),
b AS (SELECT *, CASE WHEN v < 256 THEN v ELSE (length(bin(v)) - 8) * 128 + (v >> (length(bin(v)) - 8)) END AS bucket FROM r),
s AS (SELECT lang, source, ratio, bucket, count(*) * 1000000 AS w FROM b WHERE NOT base_failed AND (bucket > 0 OR ratio IN ('symbols', 'word_length')) GROUP BY ALL),
-- ten documents' weight of all in each language, thirty of the language in each group
a0 AS (SELECT ratio, bucket, sum(w)::BIGINT AS w FROM s GROUP BY ALL),
a1 AS (SELECT ratio, bucket, floor(10000000.0::DOUBLE * (w::DOUBLE / sum(w) OVER (PARTITION BY ratio)))::BIGINT AS w FROM a0),
l0 AS (SELECT lang, ratio, bucket, sum(w)::BIGINT AS w FROM (SELECT lang, ratio, bucket, w FROM s UNION ALL SELECT lang, ratio, bucket, w FROM a1, (SELECT DISTINCT lang FROM s)) GROUP BY ALL),
l1 AS (SELECT lang, ratio, bucket, floor(30000000.0::DOUBLE * (w::DOUBLE / sum(w) OVER (PARTITION BY lang, ratio)))::BIGINT AS w FROM l0),
g AS (SELECT lang, source, ratio, bucket, sum(w)::BIGINT AS w FROM (FROM s UNION ALL SELECT k.lang, source, ratio, bucket, w FROM l1 JOIN (SELECT DISTINCT lang, source FROM s) k ON k.lang IS NOT DISTINCT FROM l1.lang) GROUP BY ALL),
o AS (SELECT *, sum(w) OVER (PARTITION BY lang, source, ratio ORDER BY bucket) AS upto, sum(w) OVER (PARTITION BY lang, source, ratio) AS total FROM g),
q AS (SELECT lang, source, ratio, min(CASE WHEN upto * 100 >= total * 50 THEN bucket END) AS low, min(CASE WHEN upto * 100 >= total * 90 THEN bucket END) AS high FROM o GROUP BY ALL),
raw AS (SELECT *, high + 4 * (high - low) AS raw FROM q),
half AS (SELECT lang, ratio, quantile_disc(raw, 0.5) AS half FROM raw GROUP BY ALL HAVING count(*) >= 3),
fence AS (SELECT raw.lang, source, raw.ratio, greatest(least(raw, coalesce(half, every)), CASE WHEN raw.ratio = 'symbols' THEN 10 ELSE 0 END) AS fence FROM raw
  JOIN (SELECT ratio, quantile_disc(raw, 0.5) AS every FROM raw GROUP BY ratio) x USING (ratio) LEFT JOIN half ON half.lang IS NOT DISTINCT FROM raw.lang AND half.ratio = raw.ratio),
j AS (SELECT b.doc_id, b.ratio, b.bucket > fence AS over_it FROM b LEFT JOIN fence f ON f.ratio = b.ratio AND f.lang IS NOT DISTINCT FROM b.lang AND f.source IS NOT DISTINCT FROM b.source WHERE NOT b.base_failed),
over_ AS (SELECT doc_id, list_filter([CASE WHEN bool_or(over_it AND ratio = 'symbols') THEN 'symbols' END, CASE WHEN bool_or(over_it AND ratio = 'dup_lines') THEN 'dup_lines' END,
  CASE WHEN bool_or(over_it AND ratio = 'repeats') THEN 'repeats' END, CASE WHEN bool_or(over_it AND ratio = 'word_length') THEN 'word_length' END], lambda x: x IS NOT NULL) AS beyond FROM j GROUP BY doc_id)
SELECT f.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND len(coalesce(beyond, [])) = 0 AS kept,
  array_to_string(coalesce(beyond, []), ',') AS beyond FROM f LEFT JOIN over_ USING (doc_id)
"""

BARE = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
FORM = "translate({0}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
OP3 = rf"""
WITH d AS (SELECT doc_id, regexp_extract_all({FORM.format("coalesce(text, '')")}, '{BARE}') AS ws FROM documents),
i AS (SELECT item_id::VARCHAR AS item, regexp_extract_all({FORM.format("text")}, '{BARE}') AS ws FROM benchmark WHERE text IS NOT NULL AND item_id IS NOT NULL),
p AS (SELECT DISTINCT item, least(13, len(ws)) AS n, array_to_string(ws[k:k + 12], ' ') AS w FROM (SELECT item, ws, unnest(generate_series(1, greatest(1, len(ws) - 12))) AS k FROM i WHERE len(ws) > 0)),
n AS (SELECT DISTINCT n FROM p),
x AS (SELECT doc_id, n, k, array_to_string(ws[k:k + n - 1], ' ') AS w FROM (SELECT doc_id, ws, n, unnest(generate_series(1, len(ws) - n + 1)) AS k FROM d, n WHERE len(ws) >= n)),
h AS (SELECT x.doc_id, x.k, x.n, p.item FROM x JOIN p ON x.w = p.w AND x.n = p.n),
t AS (SELECT doc_id, count(DISTINCT w) AS n_hit FROM (SELECT doc_id, unnest(generate_series(k, k + n - 1)) AS w FROM h) GROUP BY doc_id),
s AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, item FROM h) GROUP BY doc_id)
SELECT d.doc_id, len(ws) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256,
  coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated FROM d LEFT JOIN t USING (doc_id) LEFT JOIN s USING (doc_id)
"""

OP4 = """
WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first FROM p)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN payload_bytes >= 100 AND first < page_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN payload_bytes >= 100 AND first < page_id THEN first END AS refers_to FROM f
"""

OP7 = r"""
WITH l AS (SELECT doc_id, k, line, ls[line + 1] AS t FROM (SELECT doc_id, k, ls, unnest(generate_series(0, len(ls) - 1)) AS line
  FROM (SELECT DISTINCT doc_id, md5(text) AS k, string_split(text, chr(10)) AS ls FROM documents WHERE text IS NOT NULL))),
w AS (SELECT *, len(regexp_extract_all(t, '[^\x20\x09-\x0D]+')) AS n FROM l),
b AS (SELECT *, sum(n) OVER (PARTITION BY doc_id, k ORDER BY line) AS upto, sum(n) OVER (PARTITION BY doc_id, k) AS total FROM w WHERE n > 0),
-- the shortest run of 25 words or more that starts at each line, and the shortest that ends at each
f AS (SELECT doc_id, k, line AS a, max(line) OVER s AS z, list(t) OVER s AS run, total - upto + n AS held FROM b WINDOW s AS (PARTITION BY doc_id, k ORDER BY upto - n RANGE BETWEEN CURRENT ROW AND 24 FOLLOWING)),
e AS (SELECT doc_id, k, min(line) OVER s AS a, line AS z, list(t) OVER s AS run, upto AS held FROM b WINDOW s AS (PARTITION BY doc_id, k ORDER BY upto RANGE BETWEEN 24 PRECEDING AND CURRENT ROW)),
r AS (SELECT doc_id, k, a, z, run FROM f WHERE held >= 25 UNION SELECT doc_id, k, a, z, run FROM e WHERE held >= 25),
o AS (SELECT *, row_number() OVER (PARTITION BY run ORDER BY doc_id NULLS LAST, k, a) AS place FROM r),
hit AS (SELECT DISTINCT doc_id, k, unnest(generate_series(a, z)) AS line FROM o WHERE place > 1),
m AS (SELECT w.doc_id, w.k, w.line, CASE WHEN n > 0 THEN hit.line IS NOT NULL END AS goes FROM w LEFT JOIN hit ON w.doc_id IS NOT DISTINCT FROM hit.doc_id AND w.k = hit.k AND w.line = hit.line),
-- a line without words goes where the lines with words before and after it go
gone AS (SELECT doc_id, k, line FROM (SELECT *, last_value(goes IGNORE NULLS) OVER (PARTITION BY doc_id, k ORDER BY line ROWS UNBOUNDED PRECEDING) AS up,
  first_value(goes IGNORE NULLS) OVER (PARTITION BY doc_id, k ORDER BY line ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS down FROM m) WHERE up AND down),
runs AS (SELECT doc_id, k, count(*) AS n_removed, count(DISTINCT line - rn) AS n_runs FROM (SELECT *, row_number() OVER (PARTITION BY doc_id, k ORDER BY line) AS rn FROM gone) GROUP BY ALL),
kept AS (SELECT l.doc_id, l.k, string_agg(t, chr(10) ORDER BY l.line) AS body FROM l ANTI JOIN gone ON l.doc_id IS NOT DISTINCT FROM gone.doc_id AND l.k = gone.k AND l.line = gone.line GROUP BY ALL)
SELECT x.doc_id, coalesce(n_runs, 0) AS n_runs, coalesce(n_removed, 0) AS n_removed, CASE WHEN x.text IS NOT NULL THEN length(coalesce(body, '')) END AS kept_chars,
  CASE WHEN x.text IS NOT NULL THEN sha256(coalesce(body, '')) END AS kept_sha256
FROM documents x LEFT JOIN runs r ON r.doc_id IS NOT DISTINCT FROM x.doc_id AND r.k = md5(x.text) LEFT JOIN kept y ON y.doc_id IS NOT DISTINCT FROM x.doc_id AND y.k = md5(x.text)
"""

OP8 = rf"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents WHERE text IS NOT NULL),
s AS (SELECT DISTINCT doc_id, array_to_string(ws[i:i + 4], ' ') AS w FROM (SELECT doc_id, ws, unnest(generate_series(1, greatest(1, len(ws) - 4))) AS i FROM d WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS k FROM s x JOIN s y ON x.w = y.w AND x.doc_id < y.doc_id GROUP BY ALL),
e AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * k >= 75 * (x.n + y.n - k)),
z AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
r AS (SELECT doc_id AS a, doc_id AS c FROM documents UNION SELECT z.b, r.c FROM r JOIN z ON z.a = r.a)
SELECT doc_id, coalesce(n, 0) AS n_shingles, component_id FROM (SELECT a AS doc_id, min(c) AS component_id FROM r GROUP BY a) LEFT JOIN n USING (doc_id)
"""

_HOST = r"CASE WHEN contains({0}, '://') THEN translate(regexp_extract({0}, '(?s)^.*?://([^/?#]*)([^?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') ELSE '' END"
_PATH = r"CASE WHEN contains({0}, '://') THEN regexp_extract({0}, '(?s)^.*?://([^/?#]*)([^?#]*)', 2) ELSE '' END"
_FORM = r"""CASE WHEN contains({0}, '://') THEN '//' || regexp_replace(regexp_replace(""" + _HOST + r""", '^www\.', ''), ':(80|443)$', '') || regexp_replace(""" + _PATH + r""", '/$', '') ||
  coalesce('?' || nullif(array_to_string(list_filter(string_split(regexp_extract({0}, '(?s)^.*?://[^?#]*\?([^#]*)', 1), '&'), lambda x: NOT regexp_matches(x, '^(utm_[a-z]+|gclid|fbclid)=')), '&'), ''), '') END"""
OP9 = rf"""
WITH RECURSIVE rules(verdict, host, path) AS (VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/')),
tags AS (SELECT url, unnest(regexp_extract_all(html, '(?is)<(?:link|meta)\b[^>]*>')) AS t FROM pages WHERE url IS NOT NULL),
said AS (SELECT url, CASE WHEN regexp_matches(t, '(?is)\brel\s*=\s*["'']?canonical\b') THEN regexp_extract(t, '(?is)\bhref\s*=\s*["'']?([^"''\s>]+)', 1) END AS target FROM tags
  UNION ALL SELECT url, CASE WHEN regexp_matches(t, '(?is)\bhttp-equiv\s*=\s*["'']?refresh\b') THEN regexp_extract(t, '(?is)\bcontent\s*=\s*["''][^"'']*?url\s*=\s*([^"''\s>;]+)', 1) END FROM tags),
e AS (SELECT url AS a, {_FORM.format("url")} AS b FROM pages UNION SELECT url, {_FORM.format("target")} FROM said WHERE contains(target, '://') UNION SELECT target, {_FORM.format("target")} FROM said WHERE contains(target, '://')),
z AS (SELECT a, b FROM e WHERE a IS NOT NULL AND b IS NOT NULL AND a <> b UNION SELECT b, a FROM e WHERE a IS NOT NULL AND b IS NOT NULL AND a <> b),
r AS (SELECT a AS x, a AS y FROM z UNION SELECT r.x, z.b FROM r JOIN z ON z.a = r.y),
u AS (SELECT x AS url FROM r UNION SELECT url FROM pages),
h AS (SELECT url, {_HOST.format("coalesce(url, '')")} AS host, {_PATH.format("coalesce(url, '')")} AS path FROM u),
own AS (SELECT h.url, h.host, h.path, arg_max(rules.host || rules.path, length(rules.host || rules.path)) AS rule, arg_max(verdict, length(rules.host || rules.path)) AS verdict
  FROM h LEFT JOIN rules ON (h.host = rules.host OR ends_with(h.host, '.' || rules.host)) AND starts_with(h.path, rules.path) GROUP BY ALL),
passed AS (SELECT r.x AS url, min(own.verdict) AS verdict FROM r JOIN own ON own.url = r.y GROUP BY r.x)
SELECT page_id, own.host, own.path, own.rule, coalesce(own.verdict, passed.verdict, 'allow') AS verdict FROM pages LEFT JOIN own ON own.url IS NOT DISTINCT FROM pages.url LEFT JOIN passed ON passed.url = pages.url
"""

OP10 = rf"""
WITH d AS (SELECT doc_id, source, lang, text, min(doc_id) OVER (PARTITION BY text) AS first FROM documents),
k AS (SELECT * FROM d WHERE text IS NULL OR doc_id = first),
t AS (SELECT source, lang, 'words-1' AS tokenizer, coalesce(len(regexp_extract_all(array_to_string(list_distinct(string_split(text, chr(10))), chr(10)), '[^\x20\x09-\x0D]+')), 0) AS n FROM k
  UNION ALL SELECT source, lang, 'words-2', coalesce(len(regexp_extract_all(text, '[A-Za-z0-9\x{{80}}-\x{{10FFFF}}]+|[!-/:-@\[-`{{-~]')), 0) FROM k)
SELECT source, lang, tokenizer, count(*)::BIGINT AS n_docs, sum(n)::BIGINT AS n_tokens FROM t GROUP BY ALL
"""
