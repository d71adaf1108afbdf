"""SQL of the same meaning as the queries of four operators, for another engine: all pairs, all windows, plain joins."""

from __future__ import annotations

#: Letters A-Z, and the characters between words.
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
WORDS = r"[^\x20\x09-\x0D]+"


def components(links: str, nodes: str) -> str:
    """cc(node, c): the least node reached over links(u, v), in rounds that keep one row a node."""
    both = f"bl AS (SELECT u, v FROM {links} UNION ALL SELECT v, u FROM {links})"
    return f"{both}, cc(node, c) USING KEY (node) AS (SELECT node, node AS c FROM {nodes} UNION SELECT b.v AS node, min(cc.c) AS c FROM cc JOIN bl b ON b.u = cc.node JOIN recurring.cc r ON r.node = b.v WHERE cc.c < r.c GROUP BY b.v)"


def near_duplicates(width: int = 4, percent: int = 80) -> str:
    return f"""WITH RECURSIVE wd AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '{WORDS}') AS w FROM documents),
 sh AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < {width} THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - {width - 2}), lambda i: array_to_string(w[i:i + {width - 1}], ' ')) END) AS s FROM wd),
 sz AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id), both_sizes AS (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS k FROM sh a JOIN sh b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY ALL),
 links AS (SELECT u, v FROM both_sizes JOIN sz x ON x.doc_id = u JOIN sz y ON y.doc_id = v WHERE 100 * k >= {percent} * (x.n + y.n - k)), nodes AS (SELECT DISTINCT doc_id AS node FROM documents), {components('links', 'nodes')}
 SELECT node AS doc_id, coalesce(n, 0) AS n_shingles, c AS component_id, node = c AS kept FROM cc LEFT JOIN sz ON sz.doc_id = node"""


def near_vectors(cosine: float = 0.95) -> str:
    return f"""WITH RECURSIVE vc AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
 good AS (SELECT vec_id, e, sqrt(list_dot_product(e, e)) AS norm FROM vc WHERE e IS NOT NULL AND len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
 links AS (SELECT a.vec_id AS u, b.vec_id AS v FROM good a JOIN good b ON a.vec_id < b.vec_id AND len(a.e) = len(b.e) AND list_dot_product(a.e, b.e) / (a.norm * b.norm) >= {cosine}),
 nodes AS (SELECT vec_id AS node FROM embeddings), {components('links', 'nodes')}, per AS (SELECT u, count(*) AS n FROM bl GROUP BY u)
 SELECT node AS vec_id, coalesce(n, 0) AS n_links, c AS component_id, node = c AS kept FROM cc LEFT JOIN per ON u = node"""


def without_repeated_words(width: int = 50) -> str:
    return f"""WITH wd AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{WORDS}') AS w FROM documents),
 win AS (SELECT doc_id, i, md5(array_to_string(w[i:i + {width - 1}], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - {width - 2})) AS i FROM wd WHERE len(w) >= {width})),
 own AS (SELECT h, min(doc_id) AS least FROM win GROUP BY h), gone AS (SELECT doc_id, i FROM win JOIN own USING (h) WHERE least < doc_id),
 cov AS (SELECT DISTINCT doc_id, i + j AS place FROM gone, (SELECT unnest(range(0, {width})) AS j)), lost AS (SELECT doc_id, count(*) AS n FROM cov GROUP BY doc_id),
 pos AS (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS place FROM wd), kept AS (SELECT p.doc_id, string_agg(word, ' ' ORDER BY p.place) AS t FROM pos p ANTI JOIN cov c ON c.doc_id = p.doc_id AND c.place = p.place GROUP BY p.doc_id)
 SELECT wd.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM wd LEFT JOIN lost USING (doc_id) LEFT JOIN kept USING (doc_id)"""


def without_repeated_bytes(width: int = 50) -> str:
    two = 2 * width
    return f"""WITH hx AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents), sz AS (SELECT doc_id, x, length(x) // 2 AS n FROM hx),
 win AS (SELECT doc_id, i, hash(substr(x, 2 * i + 1, {two})) AS h, md5_number_lower(substr(x, 2 * i + 1, {two})) AS h2 FROM (SELECT doc_id, x, unnest(range(0, n - {width - 1})) AS i FROM sz WHERE n >= {width})),
 own AS (SELECT h, h2, min(doc_id) AS least FROM win GROUP BY ALL), gone AS (SELECT doc_id, i FROM win JOIN own USING (h, h2) WHERE least < doc_id),
 isl AS (SELECT doc_id, i, i - lag(i, 1, -{two}) OVER (PARTITION BY doc_id ORDER BY i) > {width} AS fresh FROM gone), num AS (SELECT doc_id, i, sum(fresh::INT) OVER (PARTITION BY doc_id ORDER BY i) AS k FROM isl),
 span AS (SELECT doc_id, k, min(i) AS a, max(i) + {width} AS b FROM num GROUP BY ALL), per AS (SELECT doc_id, CAST(sum(b - a) AS BIGINT) AS n_removed, count(*) AS n_spans FROM span GROUP BY doc_id),
 gaps AS (SELECT doc_id, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS f, a AS t FROM span UNION ALL SELECT doc_id, max(b), NULL FROM span GROUP BY doc_id),
 rest AS (SELECT g.doc_id, string_agg(substr(x, CAST(2 * f + 1 AS BIGINT), CAST(2 * (coalesce(t, n) - f) AS BIGINT)), '' ORDER BY f) AS kept FROM gaps g JOIN sz USING (doc_id) GROUP BY g.doc_id)
 SELECT doc_id, CAST(n AS BIGINT) AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept, x))) AS kept_sha256 FROM sz LEFT JOIN per USING (doc_id) LEFT JOIN rest USING (doc_id)"""
