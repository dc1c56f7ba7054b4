"""DuckDB SQL for the corpus queries that SQL expresses on whole tables.

Tokenising, trained models, byte matches, bootstrapped patterns and alignment are beyond it; their tests use brute force.
"""

from __future__ import annotations

from propalign.llm import quality_rules as qr
from propalign.llm.mixing import MOST, SALTS, TRIES, WEIGHTS
from propalign.llm.url_filter import RULES

_SPLIT = "list_filter(regexp_split_to_array(coalesce({0}, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '')"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

OP4 = f"""
WITH r(h, p, v) AS (VALUES {", ".join(str(r) for r in RULES)}),
u AS (SELECT row_number() OVER () AS n, page_id, translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), ''), '{_UPPER}', '{_LOWER}') AS host,
 coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*(/[^?#]*)', 1), '') AS path FROM pages),
hit AS (SELECT n, h || p AS rule, v, row_number() OVER (PARTITION BY n ORDER BY length(h || p) DESC, length(h) DESC, v DESC) AS k
 FROM u JOIN r ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p))
SELECT page_id, host, path, rule, coalesce(v, 'allow') AS verdict FROM u LEFT JOIN (SELECT * FROM hit WHERE k = 1) USING (n)
"""

OP5 = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS e FROM embeddings
 WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda z: coalesce(z[1] * z[2], 0))) AS BIGINT) AS score FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id),
k AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INT) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM k WHERE rank <= 5
"""

_CUTS = ", ".join(f"('{m}', {i}, CAST({c} AS DOUBLE))" for m, cs in qr.CUTOFFS.items() for i, c in enumerate(cs))
_MEASURES = ", ".join(f"('{m}', {m})" for m in qr.CUTOFFS)
OP2 = f"""
WITH d AS (SELECT row_number() OVER () AS n, doc_id, lang, coalesce(text, '') AS text, {_SPLIT.format('text')} AS w FROM documents),
tri AS (SELECT n, i, [w[i], w[i + 1], w[i + 2]] AS g FROM (SELECT n, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) >= 3)),
often AS (SELECT n, g FROM tri GROUP BY n, g HAVING count(*) > 1),
rep AS (SELECT n, count(DISTINCT i + j) AS c FROM tri JOIN often USING (n, g), (VALUES (0), (1), (2)) o(j) GROUP BY n),
ln AS (SELECT n, count(*) AS n_lines, count(DISTINCT l) AS kinds FROM (SELECT n, unnest(string_split(text, chr(10))) AS l FROM d) WHERE regexp_matches(l, '[^\\x20\\x09-\\x0D]') GROUP BY n),
b AS (SELECT n, doc_id, lang, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars, CAST(len(regexp_extract_all(text, '[#*$%&|<>]')) AS BIGINT) AS n_symbols,
 CAST(coalesce(n_lines - kinds, 0) AS BIGINT) AS n_dup_lines, coalesce(n_lines, 0) AS n_lines, CAST(coalesce(c, 0) AS BIGINT) AS n_repeat_words, len(regexp_extract_all(text, '\\p{{Lu}}')) AS capitals
 FROM d LEFT JOIN rep USING (n) LEFT JOIN ln USING (n)),
m AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed, CASE WHEN n_words > 0 THEN CAST(n_symbols AS DOUBLE) / n_words ELSE 0 END AS symbol_share,
 CASE WHEN n_lines > 0 THEN CAST(n_dup_lines AS DOUBLE) / n_lines ELSE 0 END AS dup_line_share, CASE WHEN n_words > 0 THEN CAST(n_repeat_words AS DOUBLE) / n_words ELSE 0 END AS repeat_share,
 CASE WHEN n_words > 0 THEN CAST(word_chars AS DOUBLE) / n_words ELSE 0 END AS word_length, CASE WHEN word_chars > 0 THEN CAST(capitals AS DOUBLE) / word_chars ELSE 0 END AS capital_share FROM b),
long AS (SELECT n, doc_id, lang, base_failed, x.measure, x.v FROM m, LATERAL (VALUES {_MEASURES}) x(measure, v)),
known AS (SELECT coalesce(d.lang, chr(1)) AS s, measure, v, quality = 1 AS good FROM long d JOIN labels l ON l.doc_id = d.doc_id WHERE quality IS NOT NULL AND NOT base_failed),
cut(measure, step, cutoff) AS (VALUES {_CUTS}),
cell AS (SELECT s, measure, step, cutoff, count(*) FILTER (good) AS n, count(*) FILTER (NOT good) AS nb, count(*) FILTER (good AND v > cutoff) AS k, count(*) FILTER (NOT good AND v > cutoff) AS kb
 FROM known JOIN cut USING (measure) GROUP BY ALL HAVING n > 0),
lev AS (SELECT {qr.DELTA} / (count(DISTINCT s) * {len(qr.CUTOFFS)}) AS level FROM cell),
few AS (SELECT s, n AS m, pow({1 - qr.ALPHA}, n) > level AS few FROM (SELECT DISTINCT s, n FROM cell), lev),
too AS (SELECT pow({1 - qr.ALPHA}, coalesce(sum(m) FILTER (few), 0)) > any_value(level) AS too FROM few, lev),
pool AS (SELECT measure, step, sum(n) AS n, sum(nb) AS nb, sum(k) AS k, sum(kb) AS kb FROM cell JOIN few f USING (s), too WHERE f.few OR too GROUP BY ALL),
used AS (SELECT s, c.measure, c.step, cutoff, CAST(if(few, p.n, c.n) AS BIGINT) AS n, CAST(if(few, p.nb, c.nb) AS BIGINT) AS nb, CAST(if(few, p.k, c.k) AS BIGINT) AS k, CAST(if(few, p.kb, c.kb) AS BIGINT) AS kb
 FROM cell c JOIN few USING (s) LEFT JOIN pool p ON p.measure = c.measure AND p.step = c.step),
test AS (SELECT *, CASE WHEN k >= n * {qr.ALPHA} THEN 1.0 ELSE
 list_sum(list_transform(range(0, k + 1), lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln({qr.ALPHA}) + (n - i) * ln({1 - qr.ALPHA})))) END AS p FROM used),
seq AS (SELECT *, kb * n - k * nb AS lead, min(CASE WHEN p <= level THEN 1 ELSE 0 END) OVER (PARTITION BY s, measure ORDER BY step) AS ok FROM test, lev),
taken AS (SELECT s, measure, cutoff FROM seq WHERE ok = 1 AND lead > 0 QUALIFY row_number() OVER (PARTITION BY s, measure ORDER BY lead DESC, step) = 1),
bad AS (SELECT DISTINCT n FROM long JOIN taken t ON t.s = coalesce(lang, chr(1)) AND t.measure = long.measure WHERE v > t.cutoff)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND bad.n IS NULL AS kept FROM m LEFT JOIN bad ON bad.n = m.n
"""

_WEIGHT = f"[{', '.join(map(str, map(float, WEIGHTS)))}]"
OP10 = f"""
WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS BIGINT) AS size, CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 4) AS INT) % {SALTS} AS salt FROM documents),
b AS (SELECT *, CASE WHEN size < 64 THEN size ELSE length(bin(size)) * 16 + (size >> CAST(length(bin(size)) - 5 AS INT)) END AS band FROM d),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, {_WEIGHT}[(row_number() OVER (ORDER BY source NULLS LAST) - 1) % {len(WEIGHTS)} + 1] AS w FROM d GROUP BY source),
c AS (SELECT *, source_size * {float(MOST)} AS cap, source_size * {float(MOST)} / w AS ratio, CAST(sum(source_size) OVER () AS DOUBLE) AS total FROM s),
l AS (SELECT *, (total - coalesce(sum(cap) OVER (ORDER BY ratio, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(w) OVER (ORDER BY ratio, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM c),
t AS (SELECT source, source_size, least(cap, coalesce((SELECT level FROM l WHERE level <= ratio ORDER BY ratio LIMIT 1), 0) * w) AS target FROM l),
r AS (SELECT b.*, source_size, target, row_number() OVER (PARTITION BY b.source ORDER BY band, salt, size, doc_id) AS k, CASE WHEN source_size > 0 THEN target / source_size ELSE 0.0 END AS rate
 FROM b JOIN t ON b.source IS NOT DISTINCT FROM t.source),
o AS (SELECT source, j, CAST('0x' || substr(md5('7:' || j || ':' || coalesce(source, chr(1) || 'null')), 1, 8) AS BIGINT) / 4294967296.0 AS o FROM t, range({TRIES}) x(j)),
w AS (SELECT o.source, j, o, sum(size * CAST(floor(k * rate + o) - floor((k - 1) * rate + o) AS BIGINT)) AS words, any_value(target) AS target FROM r JOIN o ON r.source IS NOT DISTINCT FROM o.source GROUP BY ALL),
best AS (SELECT source, arg_min(o, (abs(words - target), j)) AS o FROM w GROUP BY source)
SELECT doc_id, size, source_size, target, size * CAST(floor(k * rate + o) - floor((k - 1) * rate + o) AS BIGINT) AS taken FROM r JOIN best ON r.source IS NOT DISTINCT FROM best.source
"""

OP9 = f"""
WITH RECURSIVE d AS MATERIALIZED (SELECT doc_id, {_SPLIT.format(f"translate(text, '{_UPPER}', '{_LOWER}')")} AS w FROM documents),
sh AS MATERIALIZED (SELECT DISTINCT doc_id, CASE WHEN len(w) < 5 THEN array_to_string(w, ' ') || '|' || len(w) ELSE array_to_string(w[i:i + 4], ' ') END AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 2))) AS i FROM d WHERE len(w) > 0)),
n AS MATERIALIZED (SELECT doc_id, count(*) AS k FROM sh GROUP BY doc_id),
both_ AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM sh a JOIN sh b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
e AS MATERIALIZED (SELECT x, y FROM both_ JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * c >= 75 * (p.k + q.k - c)),
r AS (SELECT doc_id AS v, doc_id AS l FROM n UNION SELECT e.y, r.l FROM r JOIN e ON e.x = r.v WHERE r.l < e.y)
SELECT d.doc_id, CAST(coalesce(n.k, 0) AS BIGINT) AS n_shingles, coalesce(m.l, d.doc_id) AS component_id, coalesce(m.l, d.doc_id) = d.doc_id AS kept
FROM d LEFT JOIN n USING (doc_id) LEFT JOIN (SELECT v AS doc_id, min(l) AS l FROM r GROUP BY v) m USING (doc_id)
"""

ORACLE = {"op2_quality_rules": OP2, "op4_url_filter": OP4, "op5_exact_topk": OP5, "op9_minhash_neardup": OP9, "op10_systematic_mix": OP10}
