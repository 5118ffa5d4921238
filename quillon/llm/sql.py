"""DuckDB SQL of the queries that SQL can express over whole tables."""

_OP1 = """
WITH RECURSIVE v AS (
  SELECT row_number() OVER () AS r, vec_id, label, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings
), ok AS (
  SELECT *, sqrt(list_sum(list_transform(e, lambda x: x * x))) AS norm FROM v
  WHERE label IS NOT NULL AND e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0
), pairs AS (
  SELECT a.r AS a, b.r AS b, a.vec_id AS ai, b.vec_id AS bi FROM ok a JOIN ok b ON a.label = b.label AND a.r < b.r AND len(a.e) = len(b.e)
  WHERE list_dot_product(a.e, b.e) / (a.norm * b.norm) >= 0.93
), both_ways AS (
  SELECT a, b, ai, bi FROM pairs UNION ALL SELECT b, a, bi, ai FROM pairs
), reach AS (
  SELECT DISTINCT ai AS id, ai AS other FROM both_ways
  UNION
  SELECT reach.id, w.bi FROM reach JOIN both_ways w ON reach.other = w.ai
), comp AS (SELECT id, min(other) AS c FROM reach GROUP BY id),
links AS (SELECT a AS r, count(*) AS n FROM both_ways GROUP BY a)
SELECT v.vec_id, coalesce(links.n, 0)::BIGINT AS n_links, coalesce(comp.c, v.vec_id)::BIGINT AS component_id, v.vec_id = coalesce(comp.c, v.vec_id) AS kept
FROM v LEFT JOIN links ON v.r = links.r LEFT JOIN comp ON v.vec_id = comp.id
"""

_OP2 = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i : i + 4], ' '))) END AS s FROM words
), grams AS (
  SELECT doc_id, unnest(s) AS g FROM sets
), sizes AS (SELECT doc_id, len(s) AS n FROM sets),
common AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM grams a JOIN grams b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL
), pairs AS (
  SELECT a, b FROM common JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b WHERE 100 * k >= 80 * (x.n + y.n - k)
), both_ways AS (
  SELECT a, b FROM pairs UNION ALL SELECT b, a FROM pairs
), reach AS (
  SELECT DISTINCT a AS id, a AS other FROM both_ways
  UNION
  SELECT reach.id, w.b FROM reach JOIN both_ways w ON reach.other = w.a
), comp AS (SELECT id, min(other) AS c FROM reach GROUP BY id)
SELECT sizes.doc_id, sizes.n::BIGINT AS n_shingles, coalesce(comp.c, sizes.doc_id)::BIGINT AS component_id
FROM sizes LEFT JOIN comp ON sizes.doc_id = comp.id
"""

_OP10 = r"""
WITH cut AS (
  SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages
), parts AS (
  SELECT page_id, translate(coalesce(rest, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS whole, translate(regexp_extract(coalesce(rest, ''), '(?s)\A([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(coalesce(rest, ''), '(?s)\A[^/?#]*([^?#]*)', 1) AS path FROM cut
), rules(host, path, verdict) AS (
  VALUES ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'), ('com', '/fr/', 'allow'), ('com', '/de/', 'block')
), fits AS (
  SELECT p.page_id, r.host || r.path AS rule, r.verdict, row_number() OVER (PARTITION BY p.page_id ORDER BY length(r.host || r.path) DESC, r.verdict DESC) AS k
  FROM (SELECT DISTINCT * FROM parts) p JOIN rules r ON (p.host = r.host OR ends_with(p.host, '.' || r.host)) AND starts_with(p.path, r.path)
)
SELECT parts.page_id, parts.host, parts.path, fits.rule,
  coalesce(fits.verdict, CASE WHEN regexp_matches(parts.whole, 'spam|cheap-pills|casino|porn|malware') THEN 'block' ELSE 'allow' END) AS verdict
FROM parts LEFT JOIN fits ON parts.page_id = fits.page_id AND fits.k = 1
"""

_TARGETS = r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size, ([3, 1, 2])[(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1] AS weight FROM d GROUP BY source),
a AS (SELECT 1.5 * sum(source_size)::DOUBLE AS whole, sum(weight) AS weights FROM s),
l AS (SELECT (whole - coalesce((SELECT sum(2 * source_size) FROM s t WHERE 2.0 * t.source_size / t.weight <= r), 0)) / nullif(weights - coalesce((SELECT sum(weight) FROM s t WHERE 2.0 * t.source_size / t.weight <= r), 0), 0) AS level
  FROM (SELECT -1.0::DOUBLE AS r UNION SELECT 2.0::DOUBLE * source_size / weight FROM s), a),
f AS (SELECT level FROM l, a WHERE level IS NOT NULL ORDER BY abs((SELECT sum(least(2.0 * source_size, level * weight)) FROM s) - whole) LIMIT 1)
SELECT doc_id, size, source_size, round(least(2.0 * source_size, (SELECT level FROM f) * weight)::DOUBLE, 6) AS target FROM d JOIN s ON d.source IS NOT DISTINCT FROM s.source
"""

SQL: dict[str, str] = {"mixing_targets": _TARGETS, "op1_embedding_near_dedup": _OP1, "op2_ngram_jaccard_join": _OP2, "op10_url_filters": _OP10}
