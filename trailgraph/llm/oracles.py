"""DuckDB SQL for the operators that it can express."""

from __future__ import annotations

_BITS = "CAST(concat('0x', substr(md5({}), 1, 15)) AS BIGINT)"

OP1 = f"""WITH d AS (SELECT doc_id, CAST(coalesce(strlen(text), 0) AS BIGINT) AS n_bytes, {_BITS.format("coalesce(CAST(doc_id AS VARCHAR), '')")} AS h FROM documents),
l AS (SELECT *, unnest(generate_series(0, 24)) AS depth FROM d),
s AS (SELECT depth, h >> (60 - depth) AS p, CAST(sum(n_bytes) AS BIGINT) AS b FROM l GROUP BY ALL),
f AS (SELECT doc_id, l.h, n_bytes, min(l.depth) AS local_depth FROM l JOIN s ON l.depth = s.depth AND l.h >> (60 - l.depth) = s.p WHERE s.b <= {64 << 20} GROUP BY ALL)
SELECT doc_id, n_bytes, concat('s', CASE WHEN local_depth = 0 THEN '' ELSE substr(lpad(bin(f.h), 60, '0'), 1, local_depth) END) AS shard, CAST(local_depth AS INTEGER) AS local_depth, s.b AS shard_bytes
FROM f JOIN s ON s.depth = f.local_depth AND s.p = f.h >> (60 - f.local_depth)"""

_W = r"[^\x20\x09-\x0D]+"

OP2 = rf"""WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{_W}') AS ws FROM documents),
s AS (SELECT doc_id, ws, unnest(generate_series(1, len(ws) - 49)) AS i FROM w WHERE len(ws) >= 50),
k AS (SELECT doc_id, i, md5(array_to_string(ws[i:i + 49], ' ')) AS g FROM s),
m AS (SELECT g, min(doc_id) AS first FROM k GROUP BY g),
hit AS (SELECT doc_id, i FROM k JOIN m USING (g) WHERE first < doc_id),
p AS (SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS i FROM w),
c AS (SELECT p.doc_id, p.i, word, max(CASE WHEN hit.i IS NULL THEN 0 ELSE 1 END) OVER (PARTITION BY p.doc_id ORDER BY p.i ROWS BETWEEN 49 PRECEDING AND CURRENT ROW) AS gone FROM p LEFT JOIN hit ON hit.doc_id = p.doc_id AND hit.i = p.i),
r AS (SELECT doc_id, CAST(sum(gone) AS BIGINT) AS n_removed, string_agg(word, ' ' ORDER BY i) FILTER (gone = 0) AS kept FROM c GROUP BY doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM w LEFT JOIN r USING (doc_id)"""

_HOST = r"translate(regexp_extract({u}, '^.*?://([^/?#]*)', 1, 's'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_PATH = r"regexp_extract({u}, '^.*?://[^/?#]*([^?#]*)', 1, 's')"
_NODE = rf"CASE WHEN {_HOST} <> '' THEN concat({_HOST}, CASE WHEN {_PATH} = '' THEN '/' ELSE {_PATH} END, regexp_extract({{u}}, '^.*?://[^?#]*(\?[^#]*)?', 1, 's')) END"
_RULES = "r(verdict, h, p) AS (VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/'))"
_FITS = "(host = h OR ends_with(host, concat('.', h))) AND starts_with(path, p)"

OP6 = rf"""WITH RECURSIVE {_RULES},
g AS (SELECT row_number() OVER () AS k, page_id, coalesce(url, '') AS u, coalesce(html, '') AS t FROM pages),
x AS (SELECT k, page_id, u, {_HOST.format(u="u")} AS host, {_PATH.format(u="u")} AS path, {_NODE.format(u="u")} AS node,
  regexp_extract(t, '(?is)<link\b[^>]*\brel\s*=\s*["'']?\s*canonical\b[^>]*>') AS tag1, regexp_extract(t, '(?is)<meta\b[^>]*\bhttp-equiv\s*=\s*["'']?\s*refresh\b[^>]*>') AS tag2 FROM g),
own AS (SELECT x.k, max_by(concat(h, p), length(concat(h, p))) AS rule, max_by(verdict, length(concat(h, p))) AS v FROM x JOIN r ON {_FITS} GROUP BY x.k),
links AS (SELECT u, host, path, node, unnest([regexp_extract(tag1, '(?is)\bhref\s*=\s*["'']?([^"''\s>]+)', 1), regexp_extract(tag2, '(?is)url\s*=\s*["'']?([^"''\s>]+)', 1)]) AS raw FROM x),
abs AS (SELECT node, replace(CASE WHEN contains(raw, '://') THEN raw WHEN starts_with(raw, '//') THEN concat(split_part(u, ':', 1), ':', raw) WHEN starts_with(raw, '/') THEN concat(split_part(u, ':', 1), '://', host, raw)
  ELSE concat(split_part(u, ':', 1), '://', host, CASE WHEN regexp_extract(path, '^.*/') = '' THEN '/' ELSE regexp_extract(path, '^.*/') END, raw) END, '&amp;', '&') AS l FROM links WHERE raw <> '' AND node IS NOT NULL),
e AS (SELECT DISTINCT node AS a, {_NODE.format(u="l")} AS b FROM abs), s AS (SELECT a, b FROM e WHERE a <> b UNION SELECT b, a FROM e WHERE a <> b),
nodes AS (SELECT node FROM x WHERE node IS NOT NULL UNION SELECT a FROM s), reach AS (SELECT node, node AS c FROM nodes UNION SELECT s.b, reach.c FROM reach JOIN s ON s.a = reach.node),
comp AS (SELECT node, min(c) AS c FROM reach GROUP BY node),
aim AS (SELECT a AS node, regexp_extract(a, '^[^/?]*') AS host, regexp_extract(a, '^[^/?]*([^?]*)', 1) AS path FROM (SELECT DISTINCT a FROM s)),
said AS (SELECT node, v FROM x JOIN own USING (k) WHERE node IS NOT NULL UNION ALL SELECT aim.node, max_by(verdict, length(concat(h, p))) FROM aim JOIN r ON {_FITS} GROUP BY aim.node),
cv AS (SELECT c, min(v) AS v FROM said JOIN comp USING (node) GROUP BY c)
SELECT page_id, host, path, own.rule, coalesce(own.v, cv.v, 'allow') AS verdict FROM x LEFT JOIN own USING (k) LEFT JOIN comp ON comp.node = x.node LEFT JOIN cv ON cv.c = comp.c"""

_FOLD = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

OP7 = rf"""WITH d AS (SELECT doc_id, {_FOLD} AS ws FROM documents), b AS (SELECT CAST(item_id AS VARCHAR) AS item, {_FOLD} AS ws FROM benchmark),
bw AS (SELECT item, ws, least(13, len(ws)) AS m FROM b WHERE len(ws) > 0),
pat AS (SELECT DISTINCT item, m, array_to_string(ws[i:i + m - 1], ' ') AS g FROM (SELECT *, unnest(generate_series(1, len(ws) - m + 1)) AS i FROM bw)),
sizes AS (SELECT DISTINCT m FROM pat),
win AS (SELECT doc_id, m, i, array_to_string(ws[i:i + m - 1], ' ') AS g FROM (SELECT doc_id, ws, m, unnest(generate_series(1, len(ws) - m + 1)) AS i FROM d, sizes WHERE len(ws) >= m)),
hit AS (SELECT win.doc_id, win.i, win.m, pat.item FROM win JOIN pat USING (m, g)),
pos AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest(generate_series(i, i + m - 1)) AS j FROM hit) GROUP BY doc_id),
it AS (SELECT doc_id, count(*) AS n, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT doc_id, item FROM hit) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(pos.n, 0) AS n_hit, coalesce(it.n, 0) AS n_items, sha256(coalesce(names, '')) AS items_sha256, coalesce(pos.n, 0) > 0 AND 20 * coalesce(pos.n, 0) >= len(ws) AS contaminated
FROM d LEFT JOIN pos USING (doc_id) LEFT JOIN it USING (doc_id)"""

OP9 = rf"""WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '{_W}')) AS BIGINT) AS size, {_BITS.format("concat('9:', doc_id)")} AS key FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
n AS (SELECT *, [5, 2, 1][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3] AS w, source_size * 2.0 AS cap FROM s),
o AS (SELECT *, sum(cap) OVER u - cap AS full_, sum(w) OVER u - w AS gone, (SELECT sum(w) FROM n) AS all_w, (SELECT sum(source_size) * 1.5 FROM n) AS total FROM n WINDOW u AS (ORDER BY cap / w, source NULLS LAST)),
l AS (SELECT min_by(level, ratio) AS level FROM (SELECT (total - full_) / (all_w - gone) AS level, cap / w AS ratio FROM o) WHERE level <= ratio),
t AS (SELECT source, source_size, CAST(coalesce(least(cap, w * level), cap) AS DOUBLE) AS target FROM n, l),
x AS (SELECT d.*, source_size, target, coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS run FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
y AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS epochs FROM x)
SELECT doc_id, size, source_size, target, CAST(epochs * size + least(size, greatest(0, CAST(floor(target) AS BIGINT) - epochs * source_size - run)) AS BIGINT) AS taken FROM y"""

ALL = {"op1_extendible_sharding": OP1, "op2_fixed_block_anchors": OP2, "op6_redirect_url_filter": OP6, "op7_wu_manber_decontamination": OP7, "op9_prefix_sum_mixing": OP9}
