"""Further queries on the parts of the method: repair, denominators, presets, sizes, large models, estimators."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F

from ..operators import ball as B
from ..operators import cluster as A
from ..operators import measures as S
from ..operators import models as M
from ..operators import motifs as E
from ..operators import objective as O
from ..operators.partition import partition_models
from ..sources import graphs as G
from ..sources.shared import written
from ..sources.tables import table
from . import oracles as Q
from .oracles import base
from .queries import _BEST1, _PHI12, _RATIO, _RUNS, _SMALL, _ball, _models, _placed, _small, add, formula_runs, golden

# Splits turned, repaired and read as clusters.
_SPLIT = "split AS (SELECT seed, ball_no, node, (node * 7 + seed + ball_no) % 3 = 0 AS side FROM (SELECT seed, ball_no, node FROM balls UNION ALL SELECT DISTINCT seed, ball_no, -1 FROM balls))"


def _split(spark, sf_dir):
    """Rule-made sides of all model nodes, OUT among them, on either side."""
    nodes = M.model_nodes(B.ball_schedule(_ball(spark, sf_dir, 2), (1, 2)))
    return nodes.select("seed", "ball_no", "node", ((F.col("node") * 7 + F.col("seed") + F.col("ball_no")) % 3 == 0).alias("side"))


_PLAN = "plan AS (SELECT * FROM (VALUES (0, 1), (1, 2)) t(ball_no, layers)), balls AS (SELECT seed, ball_no, node, depth FROM ball JOIN plan ON depth <= layers)"
add("repair_seed", base("affinity", Q.ball(2), _PLAN, _SPLIT) + " SELECT s.seed, s.ball_no, s.node, (s.side <> o.side) OR s.node = s.seed AS side FROM split s JOIN split o ON o.seed = s.seed AND o.ball_no = s.ball_no AND o.node = -1")(lambda s, d: A.repair_sides(_split(s, d)))
add("to_cluster", base("affinity", Q.ball(2), _PLAN, _SPLIT) + " SELECT s.seed, s.node FROM split s JOIN split o ON o.seed = s.seed AND o.ball_no = s.ball_no AND o.node = -1 WHERE s.ball_no = 1 AND s.node >= 0 AND ((s.side <> o.side) OR s.node = s.seed)")(
    lambda s, d: A.to_cluster(A.repair_sides(_split(s, d)).where("side AND ball_no = 1").groupBy("seed").agg(F.collect_list("node").alias("members")))
)

# Both denominators on rule-made splits.
def denominator_modes(spark, sf_dir):
    sides, placed = _models(spark, sf_dir)
    total = spark.createDataFrame([(2 * G.graph(spark, sf_dir).motif_volume(),)], "total bigint")
    edges = M.graph_model(placed)
    a = O.model_conductance(edges, sides).select("seed", "ball_no", "trial", F.col("phi").alias("assumed"))
    return a.join(O.model_conductance(edges, sides, total).select("seed", "ball_no", "trial", F.col("phi").alias("exact")), ["seed", "ball_no", "trial"])


add("denominator_modes", _PHI12 + f" SELECT seed, ball_no, trial, {_RATIO.replace('phi', 'assumed')}, CASE WHEN least(vol, 2 * total - vol) > 0 THEN cut / CAST(least(vol, 2 * total - vol) AS DOUBLE) END AS exact FROM model_phi, total")(denominator_modes)
add("local_clusters_assumed")(lambda s, d: A.local_motif_clusters(G.graph(s, d), golden(s), denominator="assumed").scores)

# The main configuration over as many seeds as the experiments take, beside the baseline over the same.
add("local_clusters_50_seeds")(lambda s, d: A.local_motif_clusters(G.graph(s, d), _seeds(s, d, "affinity", 50), denominator="assumed").scores)
add("pagerank_sweep_50_seeds")(lambda s, d: A.pagerank_sweep(G.graph(s, d), _seeds(s, d, "affinity", 50)).scores)

# The four equivalences, each with its own columns; volumes of the rest too, as phi with a complement needs them.
_DEF = """, tc AS (SELECT s.seed, s.ball_no, s.trial, t.a, t.b, t.c, count(*) AS inside FROM tri t JOIN sides s ON s.node IN (t.a, t.b, t.c) GROUP BY ALL),
 gd AS (SELECT seed, ball_no, trial, count(*) FILTER (inside < 3) AS motif_cut, CAST(sum(inside) AS BIGINT) AS motif_vol FROM tc GROUP BY ALL)"""
_RATIO_OF = lambda cut, vol, total: f"CASE WHEN least({vol}, {total} - {vol}) > 0 THEN {cut} / CAST(least({vol}, {total} - {vol}) AS DOUBLE) END"


def _theorem(spark, sf_dir, which: str):
    """cut, volume and phi by the definition beside those of a model, on the same rule-made splits."""
    sides, placed = _models(spark, sf_dir)
    keys, total = ["seed", "ball_no", "trial"], G.graph(spark, sf_dir).motif_volume()
    named = sides.withColumn("cluster", F.struct(*keys))
    d = O.motif_conductance(G.graph(spark, sf_dir).occurrences(), named).select("cluster.*", F.col("cut").alias("motif_cut"), F.col("vol").alias("motif_vol"), F.col("phi").alias("motif_phi"))
    m = O.hyper_conductance(M.hyper_model(placed), sides) if which == "hyper" else O.model_conductance(M.graph_model(placed), sides)
    factor = 1 if which == "hyper" else 2
    value = O.phi(F.col("model_cut"), F.col("model_vol"), F.lit(factor * total))
    return d.join(m.select(*keys, F.col("cut").alias("model_cut"), F.col("vol").alias("model_vol")), keys).withColumn("model_phi", value)


_BOTH = _PHI12 + _DEF + " SELECT {cols} FROM gd JOIN {model} m USING (seed, ball_no, trial), total"
for _i, _which, _cols in ((1, "hyper", ("motif_cut", "model_cut")), (2, "hyper", ("motif_vol", "model_vol", "motif_phi", "model_phi")), (3, "graph", ("motif_cut", "model_cut")), (4, "graph", ("motif_vol", "model_vol", "motif_phi", "model_phi"))):
    _f = 1 if _which == "hyper" else 2
    _texts = {"motif_cut": "motif_cut", "motif_vol": "motif_vol", "model_cut": "m.cut AS model_cut", "model_vol": "m.vol AS model_vol", "motif_phi": _RATIO_OF("motif_cut", "motif_vol", "total") + " AS motif_phi", "model_phi": _RATIO_OF("m.cut", "m.vol", f"({_f} * total)") + " AS model_phi"}
    add(f"theorem_report_{_i}", _BOTH.format(cols=", ".join(["seed", "ball_no", "trial", *(_texts[c] for c in _cols)]), model="net_phi" if _which == "hyper" else "model_phi"))(lambda s, d, w=_which, c=_cols: _theorem(s, d, w).select("seed", "ball_no", "trial", *c))

# Small balls with the optimum known: edges as the motif, and the strong preset.
_EDGE1 = base("affinity", "total AS (SELECT 2 * count(*) AS total FROM edges)", Q.ball(1), """plan AS (SELECT 0 AS ball_no), balls AS (SELECT seed, 0 AS ball_no, node, depth FROM ball),
 oe AS (SELECT DISTINCT l.seed, e.src, e.dst FROM edges e JOIN ball l ON l.node IN (e.src, e.dst)), nets AS (SELECT o.seed, 0 AS ball_no, list_sort(list_distinct([coalesce(x.node, -1), coalesce(y.node, -1)])) AS pins, count(*) AS weight FROM oe o LEFT JOIN ball x ON x.seed = o.seed AND x.node = o.src LEFT JOIN ball y ON y.seed = o.seed AND y.node = o.dst GROUP BY ALL)""", Q.exhaustive())
add("cluster_edge_motif_small", _EDGE1 + _SMALL)(lambda s, d: _small(s, d, motif="edge", n_trials=40, effort="strong"))
add("cluster_small_ball_strong", _BEST1 + _SMALL)(lambda s, d: _small(s, d, model="graph", n_trials=20, effort="strong"))

# Motifs of four nodes through the whole method, and a model that is inexact for them.
add("local_clusters_clique4")(lambda s, d: A.local_motif_clusters(G.graph(s, d, "doc_overlap"), _seeds(s, d, "doc_overlap"), motif="clique4", layers=(1, 2)).scores)
add("local_clusters_path4")(lambda s, d: A.local_motif_clusters(G.graph(s, d, "embed_knn"), _seeds(s, d, "embed_knn"), motif="path4", layers=(1,), min_nodes=0).scores)
add("local_clusters_clique4_inexact")(lambda s, d: A.local_motif_clusters(G.graph(s, d, "doc_overlap"), _seeds(s, d, "doc_overlap"), motif="clique4", model="graph", layers=(1, 2), allow_inexact=True).scores)
add("local_clusters_budget")(lambda s, d: A.local_motif_clusters(G.graph(s, d), golden(s), n_trials=400, time_budget_s=0.0).scores)


def _seeds(spark, sf_dir, name: str, k: int = 5):
    from ..operators.prepare import pick_seeds

    return written(pick_seeds(G.graph(spark, sf_dir, name), k), "seeds")


_Q4 = "q4 AS (SELECT x.src AS a, x.dst AS b, y.dst AS c, z.dst AS d FROM edges x JOIN edges y ON y.src = x.dst JOIN edges z ON z.src = y.dst JOIN edges p ON p.src = x.src AND p.dst = y.dst JOIN edges q ON q.src = x.src AND q.dst = z.dst JOIN edges r ON r.src = x.dst AND r.dst = z.dst)"
_PL4 = "held AS (SELECT seed, list(node) AS held FROM ball GROUP BY seed), o4 AS (SELECT seed, held, a, b, c, d FROM q4, held WHERE list_contains(held, a) OR list_contains(held, b) OR list_contains(held, c) OR list_contains(held, d)), pl AS (SELECT seed, " + ", ".join(f"CASE WHEN list_contains(held, {x}) THEN {x} ELSE -1 END AS {x}" for x in "abcd") + " FROM o4)"
_PAIRS4 = " UNION ALL ".join(f"SELECT seed, {x} AS u, {y} AS v FROM pl" for x, y in ("ab", "ac", "ad", "bc", "bd", "cd"))


@add("graph_model_clique4_ball", base("affinity", Q.ball(1), _Q4, _PL4) + f" SELECT seed, least(u, v) AS u, greatest(u, v) AS v, count(*) AS weight FROM ({_PAIRS4}) WHERE u <> v GROUP BY ALL")
def graph_model_clique4_ball(spark, sf_dir):
    """The graph model of balls for a motif of four nodes, where its cuts are no longer the motif's."""
    ball = _ball(spark, sf_dir, 1)
    return M.graph_model(M.placed_occurrences(E.ball_occurrences(G.graph(spark, sf_dir), ball, E.CLIQUE4), B.ball_schedule(ball, (1,)))).select("seed", "u", "v", "weight")


# Rules and choices.
@add("model_choice", "SELECT motif, k, CASE WHEN k <= 3 THEN 'graph' ELSE 'hyper' END AS model FROM (SELECT l_orderkey AS motif, count(DISTINCT l_partkey) AS k FROM lineitem GROUP BY l_orderkey)")
def model_choice(spark, sf_dir):
    """The model that is exact for an order, taken as a motif of its parts."""

    @F.pandas_udf("string")
    def model(k: pd.Series) -> pd.Series:
        return k.map({n: M.choose_model(E.MotifSpec("order", n, ())) for n in k.unique().tolist()})

    k = table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("motif")).agg(F.count_distinct("l_partkey").alias("k"))
    return k.select("motif", "k", model("k").alias("model"))


add("suite_split", "SELECT * FROM (VALUES ('tuning', 'copurchase2'), ('tuning', 'embed_knn'), ('tuning', 'doc_overlap'), ('tuning', 'page_nav'), ('test', 'affinity'), ('test', 'copurchase'), ('test', 'user_copresence'), ('test', 'cells')) t(suite, graph)")(lambda s, d: s.createDataFrame([(k, g) for k, gs in G.SUITES.items() for g in gs], "suite string, graph string"))
_KEPT = "kept AS (SELECT src, dst FROM edges WHERE {}), kt AS (SELECT count(*) AS n FROM kept x JOIN kept y ON x.dst = y.src JOIN kept z ON z.src = x.src AND z.dst = y.dst)"
add("triangles_estimated", base("affinity", Q.TRI, _KEPT.format(Q.sampled(0.5, 3))) + " SELECT n AS kept, n / CAST(0.125 AS DOUBLE) AS estimate, (SELECT count(*) FROM tri) AS triangles FROM kt")(lambda s, d: E.estimated_triangles(G.graph(s, d).edges, 0.5).withColumn("triangles", F.lit(G.graph(s, d).motif_volume() // 3)))
add("speedup", _RUNS + " SELECT round(exp(avg(ln(seconds)) FILTER (algo = 'sweep')) / exp(avg(ln(seconds)) FILTER (algo = 'ball')), 6) AS speedup FROM runs")(lambda s, d: S.win_shares(formula_runs(s), "ball", "sweep").select("speedup"))


@add("bisect_distributed")
def bisect_distributed(spark, sf_dir):
    """(seed, ball_no, phi, kernel_phi): models of two-layer balls split by joins, coarsened to 60 nodes, beside the kernel's best of as many trials."""
    balls, placed = _placed(spark, sf_dir, (1, 2))
    model, total = written(M.graph_model(placed), "model"), 2 * G.graph(spark, sf_dir).motif_volume()
    side = A.bisect_distributed(model, balls, total, most=60, n_trials=40)
    far = O.model_conductance(model, side.withColumn("trial", F.lit(0)), spark.createDataFrame([(total,)], "total bigint"))
    nodes = balls.select("seed", "ball_no", "node", F.lit(1).alias("size"), F.lit(0).alias("extra"))
    near = partition_models(model, total, n_trials=40, nodes=nodes).withColumn("phi", O.phi(F.col("cut"), F.col("vol"), F.lit(total)))
    return far.select("seed", "ball_no", "phi").join(near.groupBy("seed", "ball_no").agg(F.min("phi").alias("kernel_phi")), ["seed", "ball_no"])

