"""DuckDB SQL for the operators, or parts of them, that SQL can express."""

from __future__ import annotations

_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+')"

#: (node, component) of the links in ``links(a, b)``, both ways, and of nodes without any.
_CLOSURE = """reach AS (SELECT id AS a, id AS b FROM nodes UNION SELECT reach.a, links.b FROM reach JOIN links ON reach.b = links.a),
    parts AS (SELECT a AS id, min(b) AS component FROM reach GROUP BY 1)"""

TOP_K = """WITH v AS (SELECT vec_id, [floor(1024 * CAST(x AS DOUBLE)) for x in embedding] AS e FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL),
    s AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_dot_product(q.e, c.e) AS BIGINT) AS score FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 100 = 0),
    r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
    SELECT * FROM r WHERE rank <= 10"""

NEAR_VECTORS = f"""WITH RECURSIVE nodes AS (SELECT vec_id AS id, [CAST(x AS DOUBLE) for x in embedding] AS e FROM embeddings),
    links AS MATERIALIZED (SELECT x.id AS a, y.id AS b FROM nodes x JOIN nodes y ON x.id <> y.id WHERE list_cosine_similarity(x.e, y.e) >= 0.95), {_CLOSURE}
    SELECT parts.id AS vec_id, (SELECT count(*) FROM links WHERE links.a = parts.id) AS n_links, component AS component_id, parts.id = component AS kept FROM parts"""

NEAR_DUP = f"""WITH RECURSIVE w AS (SELECT doc_id, {_WORDS} AS w FROM documents),
    sets AS MATERIALIZED (SELECT doc_id AS id, list_distinct(CASE WHEN len(w) >= 5 THEN [array_to_string(w[i:i + 4], ' ') for i in range(1, len(w) - 3)] WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS s FROM w),
    nodes AS (SELECT id FROM sets), sizes AS MATERIALIZED (SELECT id, len(s) AS n FROM sets), one AS MATERIALIZED (SELECT id, unnest(s) AS x FROM sets),
    common AS (SELECT p.id AS a, q.id AS b, count(*) AS shared FROM one p JOIN one q ON p.x = q.x AND p.id <> q.id GROUP BY 1, 2),
    links AS MATERIALIZED (SELECT a, b FROM common JOIN sizes m ON m.id = a JOIN sizes n ON n.id = b WHERE 100 * shared >= 75 * (m.n + n.n - shared)), {_CLOSURE}
    SELECT parts.id AS doc_id, n AS n_shingles, component AS component_id, parts.id = component AS kept FROM parts JOIN sizes ON sizes.id = parts.id"""

MIX_TARGETS = f"""WITH d AS (SELECT doc_id, source, CAST(len({_WORDS}) AS BIGINT) AS size FROM documents),
    p AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, [5.0, 2.0, 1.0][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3]::DOUBLE AS weight FROM d GROUP BY source),
    l AS (SELECT *, 2.0::DOUBLE * source_size AS cap, 2.0::DOUBLE * source_size / weight AS level, sum(source_size) OVER () * 1.5::DOUBLE AS wanted FROM p),
    c AS (SELECT *, (wanted - coalesce(sum(cap) OVER (ORDER BY level, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(weight) OVER (ORDER BY level, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS common FROM l),
    t AS (SELECT *, (SELECT arg_min(common, level) FROM c WHERE level > common) AS open FROM c)
    SELECT doc_id, size, source_size, CASE WHEN open IS NULL OR level <= open THEN cap ELSE weight * open END AS target FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source"""

_RULES = (("com/en/", "block"), ("example.com/en/7", "allow"), ("net/de/", "allow"), ("example.net/de/8", "block"), ("org/es/", "block"))
_RULE_ROWS = ", ".join(f"('{r}', '{r.partition('/')[0]}', '/{r.partition('/')[2]}')" for r, _ in _RULES)

URL_RULES = f"""WITH r(rule, domain, start) AS (VALUES {_RULE_ROWS}),
    u AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
    h AS (SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u)
    SELECT page_id, host, path, (SELECT arg_max(rule, length(rule)) FROM r WHERE (host = domain OR ends_with(host, '.' || domain)) AND starts_with(path, start)) AS rule FROM h"""
