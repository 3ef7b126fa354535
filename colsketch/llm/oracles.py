"""DuckDB SQL with the rows of the corpus queries that SQL can express."""

_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_ITEM = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

OP1 = f"""
WITH d AS (SELECT doc_id, source, CAST(len({_WORDS}) AS BIGINT) AS size, md5('7:' || coalesce(CAST(doc_id AS VARCHAR), '')) AS key FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS n, [5, 2, 1][CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS INTEGER) + 1] AS w, row_number() OVER (ORDER BY source NULLS LAST) AS rank FROM d GROUP BY source),
o AS (SELECT *, sum(3 * n) OVER q - 3 * n AS capped, sum(w) OVER q - w AS used, sum(n) OVER () AS total, sum(w) OVER () AS weights FROM s WINDOW q AS (ORDER BY 3 * n / w, rank ROWS UNBOUNDED PRECEDING)),
f AS (SELECT *, 3 * n * (weights - used) > (total - capped) * w AS open FROM o),
l AS (SELECT min_by(CAST(total - capped AS BIGINT), capped) AS left_, min_by(CAST(weights - used AS BIGINT), capped) AS share FROM f WHERE open),
t AS (SELECT rank, source, n, CASE WHEN open THEN CAST(w * left_ AS DOUBLE) / share ELSE CAST(3 * n AS DOUBLE) END AS target FROM f LEFT JOIN l ON true),
p AS (SELECT doc_id, size, n AS source_size, target, CAST(sum(size) OVER (PARTITION BY rank ORDER BY key, doc_id ROWS UNBOUNDED PRECEDING) - size AS BIGINT) AS before, CASE WHEN n > 0 THEN CAST(floor(target) AS BIGINT) // n ELSE 0 END AS whole FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target, whole * size + greatest(0, least(size, CAST(floor(target) AS BIGINT) - whole * source_size - before)) AS taken FROM p
"""

_LOWER = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+')"

OP3 = f"""
WITH RECURSIVE d AS (SELECT doc_id, {_LOWER} AS w FROM documents),
s AS (SELECT DISTINCT doc_id, md5(array_to_string(w[k : k + 4], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, greatest(1, len(w) - 4) + 1)) AS k FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS m FROM s x JOIN s y ON x.h = y.h AND x.doc_id < y.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * m >= 75 * (x.n + y.n - m)),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
r AS (SELECT DISTINCT a AS id, a AS c FROM e UNION SELECT r.id, e.b FROM r JOIN e ON e.a = r.c)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(t.c, d.doc_id) AS component_id FROM d LEFT JOIN n USING (doc_id) LEFT JOIN (SELECT id AS doc_id, min(c) AS c FROM r GROUP BY 1) t USING (doc_id)
"""

OP4 = f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
p AS (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS k FROM d),
g AS (SELECT doc_id, k, md5(array_to_string(w[k : k + 19], ' ')) AS h FROM p WHERE k + 19 <= len(w)),
later AS (SELECT doc_id, k FROM (SELECT doc_id, k, row_number() OVER (PARTITION BY h ORDER BY doc_id, k) AS r FROM g) WHERE r > 1),
gone AS (SELECT DISTINCT doc_id, k + o AS k FROM later, range(0, 20) t(o)),
kept AS (SELECT p.doc_id, count(g2.k) AS n_removed, string_agg(w[p.k], ' ' ORDER BY p.k) FILTER (WHERE g2.k IS NULL) AS t FROM p LEFT JOIN gone g2 ON g2.doc_id = p.doc_id AND g2.k = p.k GROUP BY p.doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM d LEFT JOIN kept USING (doc_id)
"""

OP5 = f"""
WITH i AS (SELECT DISTINCT item_id, {_ITEM} AS w FROM benchmark),
v AS (SELECT item_id, w, unnest(range(1, greatest(1, len(w) - 12) + 1)) AS k FROM i WHERE len(w) > 0),
x AS (SELECT DISTINCT item_id, array_to_string(w[k : k + 12], ' ') AS win, least(13, len(w)) AS n FROM v),
d AS (SELECT doc_id, {_ITEM} AS w FROM documents),
z AS (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS k FROM d, (SELECT DISTINCT n FROM x) WHERE len(w) >= n),
hit AS (SELECT doc_id, k, x.n, item_id FROM (SELECT doc_id, k, n, array_to_string(w[k : k + n - 1], ' ') AS win FROM z) y JOIN x ON y.win = x.win AND y.n = x.n),
words AS (SELECT doc_id, count(DISTINCT k + o) AS n_hit FROM hit, range(0, 13) t(o) WHERE o < n GROUP BY 1),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM hit) GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated FROM d LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)
"""

OP6 = """
WITH d AS (SELECT doc_id, coalesce(strlen(text), 0) AS bytes, md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS h FROM documents),
b AS (SELECT doc_id, bytes, lpad(bin(('0x' || substr(h, 1, 15))::BIGINT), 60, '0') AS bits FROM d),
p AS (SELECT doc_id, bytes, k, substr(bits, 1, k) AS shard FROM b, range(0, 61) t(k)),
s AS (SELECT *, sum(bytes) OVER (PARTITION BY shard) AS total FROM p),
c AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY CASE WHEN total <= 1048576 THEN k ELSE 100 - k END) AS r FROM s)
SELECT doc_id, bytes, shard, CAST(k AS INTEGER) AS depth, CAST(total AS BIGINT) AS shard_bytes, total > 1048576 AS oversize FROM c WHERE r = 1
"""

BASE_FIGURES = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, {_WORDS} AS w FROM documents),
g AS (SELECT doc_id, k, md5(array_to_string(w[k : k + 7], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS k FROM d WHERE len(w) >= 8)),
c AS (SELECT doc_id, count(DISTINCT k + o) AS n FROM (SELECT doc_id, k FROM (SELECT doc_id, k, count(*) OVER (PARTITION BY doc_id, h) AS m FROM g) WHERE m > 1), range(0, 8) z(o) GROUP BY 1),
l AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM d) WHERE regexp_matches(line, '[^\\x20\\x09-\\x0D]') GROUP BY 1)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars, CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, coalesce(l.n, 0) AS n_dup_lines, coalesce(c.n, 0) AS n_repeat_words, len(w) < 20 OR 100 * coalesce(c.n, 0) > 30 * len(w) AS base_failed FROM d LEFT JOIN c USING (doc_id) LEFT JOIN l USING (doc_id)
"""

SQL: dict[str, str] = {"op3_jaccard_join": OP3, "quality_base_figures": BASE_FIGURES, "op1_mixing": OP1, "op4_substring_dedup": OP4, "op5_decontamination": OP5, "op6_sharding": OP6}
