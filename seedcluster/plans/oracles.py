"""SQL of the same meaning as the queries, for another engine. Common table expressions are put together by need."""

from __future__ import annotations

from ..functions.hashing import PRIME, mix_sql
from ..sources.graphs import NODES, SQL

GOLDEN = (0, 7, 42, 99, 149)
ADJ = "adj AS (SELECT src AS node, dst AS nbr FROM edges UNION ALL SELECT dst, src FROM edges), deg AS (SELECT node, count(*) AS d FROM adj GROUP BY node)"
TRI = "tri AS (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM edges x JOIN edges y ON x.dst = y.src JOIN edges z ON z.src = x.src AND z.dst = y.dst)"
DMU = "dmu AS (SELECT node, count(*) AS dmu FROM (SELECT a AS node FROM tri UNION ALL SELECT b FROM tri UNION ALL SELECT c FROM tri) GROUP BY node)"
#: cc(node, c): the least node that each node reaches, by rounds that keep one row a node.
COMPONENTS = "cc(node, c) USING KEY (node) AS (SELECT node, node AS c FROM deg UNION SELECT a.node, min(cc.c) AS c FROM cc JOIN adj a ON a.nbr = cc.node JOIN recurring.cc r ON r.node = a.node WHERE cc.c < r.c GROUP BY a.node)"
TOTAL = "total AS (SELECT 3 * count(*) AS total FROM tri)"


def base(graph: str = "affinity", *parts: str) -> str:
    return ", ".join(["WITH RECURSIVE " + SQL[graph], ADJ, *parts])


def seeds(values: tuple[int, ...] = GOLDEN) -> str:
    return "seeds AS (SELECT * FROM (VALUES " + ", ".join(f"(CAST({v} AS BIGINT))" for v in values) + ") t(seed))"


def ball(layers: int, values: tuple[int, ...] = GOLDEN) -> str:
    out = [seeds(values), "b0 AS (SELECT seed, seed AS node, 0 AS depth FROM seeds)"]
    for i in range(1, layers + 1):
        out.append(f"b{i} AS (SELECT * FROM b{i - 1} UNION ALL SELECT DISTINCT f.seed, a.nbr, {i} FROM b{i - 1} f JOIN adj a ON f.node = a.node WHERE f.depth = {i - 1} AND NOT EXISTS (SELECT 1 FROM b{i - 1} v WHERE v.seed = f.seed AND v.node = a.nbr))")
    out.append(f"ball AS (SELECT * FROM b{layers})")
    return ", ".join(out)


OCC = """tn AS (SELECT a, b, c, a AS node FROM tri UNION ALL SELECT a, b, c, b FROM tri UNION ALL SELECT a, b, c, c FROM tri), th3 AS MATERIALIZED (SELECT l.seed, t.a, t.b, t.c, l.depth FROM tn t JOIN ball l USING (node)),
 occ AS MATERIALIZED (SELECT seed, a, b, c, min(depth) AS min_depth FROM th3 GROUP BY ALL)"""


def placed(layers: tuple[int, ...]) -> str:
    """balls(seed, ball_no, node, depth) and placed(seed, ball_no, x, y, z) with outside ends as -1."""
    plan = "plan AS (SELECT * FROM (VALUES " + ", ".join(f"({i}, {n})" for i, n in enumerate(layers)) + ") t(ball_no, layers))"
    side = lambda c: f"coalesce((SELECT l.node FROM balls l WHERE l.seed = o.seed AND l.ball_no = p.ball_no AND l.node = o.{c}), -1)"
    return f"""{plan}, balls AS (SELECT seed, ball_no, node, depth FROM ball JOIN plan ON depth <= layers),
 placed AS (SELECT o.seed, p.ball_no, coalesce(ba.node, -1) AS x, coalesce(bb.node, -1) AS y, coalesce(bc.node, -1) AS z FROM occ o JOIN plan p ON o.min_depth <= p.layers
 LEFT JOIN balls ba ON ba.seed = o.seed AND ba.ball_no = p.ball_no AND ba.node = o.a LEFT JOIN balls bb ON bb.seed = o.seed AND bb.ball_no = p.ball_no AND bb.node = o.b
 LEFT JOIN balls bc ON bc.seed = o.seed AND bc.ball_no = p.ball_no AND bc.node = o.c)"""


NETS = "nets AS (SELECT seed, ball_no, list_sort(list_distinct([x, y, z])) AS pins, count(*) AS weight FROM placed GROUP BY ALL)"
MODEL = """model AS (SELECT seed, ball_no, least(u, v) AS u, greatest(u, v) AS v, CAST(count(*) AS BIGINT) AS weight FROM (SELECT seed, ball_no, x AS u, y AS v FROM placed UNION ALL SELECT seed, ball_no, x, z FROM placed UNION ALL SELECT seed, ball_no, y, z FROM placed) WHERE u <> v GROUP BY ALL)"""
W = "w AS (SELECT u, v, CAST(count(*) AS BIGINT) AS weight FROM (SELECT a AS u, b AS v FROM tri UNION ALL SELECT a, c FROM tri UNION ALL SELECT b, c FROM tri) GROUP BY ALL)"
SIDES = """deep AS (SELECT seed, ball_no, max(depth) AS deep FROM balls GROUP BY ALL), sides AS (SELECT b.seed, b.ball_no, d.i AS trial, b.node FROM balls b JOIN deep USING (seed, ball_no) JOIN (SELECT unnest(range(0, 20)) AS i) d ON d.i <= deep AND b.depth <= d.i
 UNION ALL SELECT b.seed, b.ball_no, d.i + 100, b.node FROM balls b JOIN deep USING (seed, ball_no) JOIN (SELECT unnest(range(0, 20)) AS i) d ON d.i <= deep AND b.depth <= d.i AND (b.node % 2 = 0 OR b.depth = 0))"""
MODEL_PHI = """me AS (SELECT seed, ball_no, u AS node, v AS other, weight FROM model UNION ALL SELECT seed, ball_no, v, u, weight FROM model),
 model_phi AS (SELECT s.seed, s.ball_no, s.trial, CAST(sum(CASE WHEN o.node IS NULL THEN weight ELSE 0 END) AS BIGINT) AS cut, CAST(sum(weight) AS BIGINT) AS vol FROM me JOIN sides s ON s.seed = me.seed AND s.ball_no = me.ball_no AND s.node = me.node
 LEFT JOIN sides o ON o.seed = me.seed AND o.ball_no = me.ball_no AND o.trial = s.trial AND o.node = me.other GROUP BY ALL)"""
NET_PHI = """pn AS (SELECT seed, ball_no, array_to_string(pins, ',') AS net, len(pins) AS k, weight, unnest(pins) AS node FROM nets),
 hit AS (SELECT s.seed, s.ball_no, s.trial, net, k, weight, count(*) AS inside FROM pn JOIN sides s ON s.seed = pn.seed AND s.ball_no = pn.ball_no AND s.node = pn.node GROUP BY ALL),
 net_phi AS (SELECT seed, ball_no, trial, CAST(sum(CASE WHEN inside < k THEN weight ELSE 0 END) AS BIGINT) AS cut, CAST(sum(inside * weight) AS BIGINT) AS vol FROM hit GROUP BY ALL)"""


def cluster_phi(clusters: str) -> str:
    """phi of clusters (cluster, node) by triangles."""
    return f"""cl AS ({clusters}), th AS (SELECT cl.cluster, t.a, t.b, t.c, count(*) AS inside FROM tri t JOIN cl ON cl.node IN (t.a, t.b, t.c) GROUP BY ALL),
 cphi AS (SELECT n.cluster, CAST(coalesce(sum(CASE WHEN inside < 3 THEN 1 ELSE 0 END) FILTER (inside IS NOT NULL), 0) AS BIGINT) AS cut, CAST(coalesce(sum(inside), 0) AS BIGINT) AS vol FROM (SELECT DISTINCT cluster FROM cl) n LEFT JOIN th ON th.cluster = n.cluster GROUP BY n.cluster),
 scored AS (SELECT cluster, cut, vol, total, CASE WHEN least(vol, total - vol) > 0 THEN cut / CAST(least(vol, total - vol) AS DOUBLE) END AS phi FROM cphi, total)"""


def nodes(graph: str) -> str:
    if graph in NODES:
        t, c = NODES[graph]
        return f"nodes AS (SELECT DISTINCT CAST({c} AS BIGINT) AS node FROM {t})"
    return "nodes AS (SELECT DISTINCT node FROM adj)"


def exhaustive(most: int = 16) -> str:
    """best(seed, ball_no, cut, vol, phi, size): the least phi over all subsets of small balls. Needs balls, nets, total."""
    return f"""fr AS (SELECT seed, ball_no, node, row_number() OVER (PARTITION BY seed, ball_no ORDER BY node) - 1 AS bit FROM balls WHERE depth > 0), fc AS (SELECT seed, ball_no, count(*) - 1 AS f FROM balls GROUP BY ALL HAVING count(*) - 1 <= {most}),
 pm AS (SELECT seed, ball_no, pins, weight, unnest(pins) AS node FROM nets), mk AS (SELECT m.seed, m.ball_no, m.pins, m.weight, coalesce(bit_or(1::BIGINT << CAST(bit AS INTEGER)) FILTER (bit IS NOT NULL), 0) AS mask, max(CASE WHEN m.node = m.seed THEN 1 ELSE 0 END) AS s, max(CASE WHEN m.node = -1 THEN 1 ELSE 0 END) AS t
 FROM pm m JOIN fc USING (seed, ball_no) LEFT JOIN fr ON fr.seed = m.seed AND fr.ball_no = m.ball_no AND fr.node = m.node GROUP BY m.seed, m.ball_no, m.pins, m.weight),
 sub AS (SELECT seed, ball_no, unnest(range(0, 1::BIGINT << CAST(f AS INTEGER))) AS x FROM fc),
 sm AS (SELECT sub.seed, sub.ball_no, x, CAST(sum(CASE WHEN bit_count(mask & x) + s > 0 AND bit_count(mask & ~x) + t > 0 THEN weight ELSE 0 END) AS BIGINT) AS cut, CAST(sum((bit_count(mask & x) + s) * weight) AS BIGINT) AS vol FROM sub JOIN mk USING (seed, ball_no) GROUP BY ALL),
 sp AS (SELECT *, CASE WHEN least(vol, total - vol) > 0 THEN cut / CAST(least(vol, total - vol) AS DOUBLE) END AS phi FROM sm, total),
 best AS (SELECT seed, ball_no, cut, vol, phi, CAST(bit_count(x) + 1 AS BIGINT) AS size, x FROM sp WHERE phi IS NOT NULL QUALIFY row_number() OVER (PARTITION BY seed, ball_no ORDER BY phi, bit_count(x), x) = 1)"""


def appr_rounds(rounds: int, walk_continue: float, tol: float) -> str:
    """state(seed, node, p, r) after a number of push rounds over w. Needs w and seeds."""
    out = ["dw AS (SELECT node, CAST(sum(weight) AS BIGINT) AS dw FROM (SELECT u AS node, weight FROM w UNION ALL SELECT v, weight FROM w) GROUP BY node)",
           "links AS (SELECT x.node, x.nbr, x.weight / CAST(dw AS DOUBLE) AS share FROM (SELECT u AS node, v AS nbr, weight FROM w UNION ALL SELECT v, u, weight FROM w) x JOIN dw USING (node))",
           "s0 AS (SELECT seed, node, CAST(0 AS DOUBLE) AS p, CAST(1 AS DOUBLE) AS r, dw FROM seeds JOIN dw ON node = seed)"]
    for i in range(1, rounds + 1):
        a = f"r >= {tol!r}::DOUBLE * dw"
        out.append(f"s{i} AS (SELECT seed, node, p, r, dw FROM (SELECT seed, node, sum(p) AS p, sum(r) AS r FROM (SELECT seed, node, CASE WHEN {a} THEN p + (1 - {walk_continue!r}::DOUBLE) * r ELSE p END AS p, CASE WHEN {a} THEN 0 ELSE r END AS r FROM s{i - 1} UNION ALL SELECT s.seed, l.nbr, 0, s.r * l.share * {walk_continue!r}::DOUBLE FROM s{i - 1} s JOIN links l ON s.node = l.node WHERE {a}) GROUP BY seed, node) JOIN dw USING (node))")
    out.append(f"state AS (SELECT seed, node, p, r FROM s{rounds})")
    return ", ".join(out)


SWEEP = """rk AS (SELECT seed, node, dw.dw, row_number() OVER (PARTITION BY seed ORDER BY round(p / dw.dw, 12) DESC, node) AS rank FROM state JOIN dw USING (node) WHERE p > 0),
 inner_w AS (SELECT a.seed, greatest(a.rank, b.rank) AS rank, sum(weight) AS back FROM rk a JOIN w ON w.u = a.node JOIN rk b ON b.seed = a.seed AND b.node = w.v GROUP BY ALL),
 pre AS (SELECT seed, rank, node, CAST(sum(dw) OVER o AS BIGINT) AS vol, CAST(sum(dw) OVER o - 2 * sum(coalesce(back, 0)) OVER o AS BIGINT) AS cut FROM rk LEFT JOIN inner_w USING (seed, rank) WINDOW o AS (PARTITION BY seed ORDER BY rank ROWS UNBOUNDED PRECEDING)),
 prefix AS (SELECT seed, rank, node, cut, vol, CASE WHEN least(vol, t - vol) > 0 THEN cut / CAST(least(vol, t - vol) AS DOUBLE) END AS phi FROM pre, (SELECT sum(dw) AS t FROM dw))"""

#: A formula that makes runs of two algorithms on six graphs and fifty seeds, with zeros and ties.
RUNS = f"""SELECT algo, graph, seed, CASE WHEN m % 17 = 0 THEN 0.0 ELSE round((m % 900) / 1000.0 + CASE WHEN algo = 'sweep' THEN 0.1 ELSE 0.0 END, 3) END AS phi, 1 + m % 3000 AS size, (1 + m2 % 5000) / 100.0 * CASE WHEN algo = 'sweep' THEN 4 ELSE 1 END AS seconds
 FROM (SELECT algo, graph, seed, {mix_sql("seed * 7 + g", 5)} AS m, {mix_sql("seed * 13 + g * 5 + length(algo)", 6)} AS m2 FROM runs_base)"""

#: Runs of two algorithms on the orders: an order is an instance, its priority the graph, and its price in cents gives the measures, with zeros and ties.
ORDER_RUNS = """SELECT algo, o_orderpriority AS graph, o_orderkey AS seed, o_custkey, CASE WHEN m % 17 = 0 THEN 0 ELSE m % 900 + CASE WHEN algo = 'sweep' THEN 100 ELSE 0 END END / CAST(1000 AS DOUBLE) AS phi, CAST(1 + m % 3000 AS DOUBLE) AS size, (1 + (13 * m + 977) % 5000) * CASE WHEN algo = 'sweep' THEN 4 ELSE 1 END / CAST(100 AS DOUBLE) AS seconds
 FROM (SELECT algo, o_orderpriority, o_orderkey, o_custkey, CAST(round(abs(o_totalprice) * 100) AS BIGINT) + 7919 * length(algo) AS m FROM orders, (VALUES ('ball'), ('sweep')) AS a(algo) WHERE abs(o_totalprice) < 1e12)"""


def sampled(p: float, salt: int) -> str:
    return f"{mix_sql('src * 1000003 + dst', salt)} < {int(p * PRIME)}"
