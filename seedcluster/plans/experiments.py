"""Experiment workloads on the derived graphs; each returns rows in the form of runs or of a summary.

All algorithms of a comparison see the same seeds, and one evaluator scores their clusters by the definition over the whole graph. A cluster without
motif volume on either side has no motif conductance; it counts as 1, the worst, for whichever algorithm returned it. Runs are written once
and serve all tables and figures that read them.
"""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import cluster as A
from ..operators import measures as S
from ..operators import models as M
from ..operators import motifs as E
from ..operators import objective as O
from ..operators import prepare as P
from ..operators.ball import ball_schedule, grow_ball, pad_last_ball
from ..sources.graphs import LAYERS, SUITES, graph
from ..sources.shared import written
from .queries import add

RUNS = ["algo", "graph", "seed", "phi", "size", "seconds"]
SEEDS, TRIALS = 50, 80
_DONE: dict[tuple, DataFrame] = {}


def once(spark: SparkSession, sf_dir: str, name: str, make) -> DataFrame:
    """What make() returns, written at the first call of a session and read from then on."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _DONE:
        _DONE[key] = written(make(), name)
    return _DONE[key]


def seeds_of(spark: SparkSession, sf_dir: str, name: str, k: int) -> DataFrame:
    """The same seeds for all algorithms."""
    return once(spark, sf_dir, f"seeds-{name}-{k}", lambda: P.pick_seeds(graph(spark, sf_dir, name), k, 1))


def timed_runs(algo: str, name: str, solve, seeds: DataFrame, g=None, kernel: bool = False) -> DataFrame:
    """Rows of runs for one algorithm on one graph; phi is by the definition, from the clusters, for all algorithms alike.

    Seeds share a job. Its time is shared evenly, but for the partition kernels' (kernel), whose share is each seed's own. All algorithms use the graph's
    list of occurrences, for its volume at least; it is made once, and its time counts for each of them alike.
    """
    listing = g.listing_seconds()
    began = time.time()
    result = solve()
    found = written(result.clusters.select(F.col("seed").alias("cluster"), "node"), "clusters")
    took, n = time.time() - began + listing, max(seeds.count(), 1)
    scored = O.motif_conductance(g.occurrences(), found)
    size = found.groupBy("cluster").agg(F.count(F.lit(1)).alias("size"))
    rows = scored.join(size, "cluster").select(F.lit(algo).alias("algo"), F.lit(name).alias("graph"), F.col("cluster").alias("seed"), F.coalesce("phi", F.lit(1.0)).alias("phi"), F.col("size").cast("double").alias("size"))
    if not kernel:
        return rows.withColumn("seconds", F.lit(took / n))
    own = result.trials.groupBy("seed").agg((F.sum("seconds") / seeds.sparkSession.sparkContext.defaultParallelism).alias("own"))
    share = max(took - (own.agg(F.sum("own")).first()[0] or 0.0), 0.1 * took) / n
    return rows.join(own, "seed", "left").withColumn("seconds", F.lit(share) + F.coalesce("own", F.lit(0.0))).select(RUNS)


def _all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def compare(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = SUITES["test"], k: int = SEEDS, n_trials: int = TRIALS) -> DataFrame:
    """runs of ball-cut and of the motif-PageRank sweep."""
    out = []
    for name in names:
        g, s = graph(spark, sf_dir, name), seeds_of(spark, sf_dir, name, k)
        out.append(timed_runs("ball", name, lambda g=g, s=s, n=name: A.local_motif_clusters(g, s, layers=LAYERS[n], n_trials=n_trials), s, g, True))
        out.append(timed_runs("sweep", name, lambda g=g, s=s: A.pagerank_sweep(g, s), s, g))
    return _all(out)


def model_duel(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = (*SUITES["tuning"], "affinity"), k: int = SEEDS, n_trials: int = TRIALS) -> DataFrame:
    """runs of the graph model without search and of the hypergraph model.

    For triangles the gains of both models are proportional, so that equal random numbers would make equal moves: the models' trials are salted apart.
    """
    out = []
    for name in names:
        g, s = graph(spark, sf_dir, name), seeds_of(spark, sf_dir, name, k)
        for model in ("graph", "hyper"):
            out.append(timed_runs(model, name, lambda g=g, s=s, n=name, m=model: A.local_motif_clusters(g, s, model=m, layers=LAYERS[n], n_trials=n_trials, search_rounds=0, salt=int(m == "hyper")), s, g, True))
    return _all(out)


def model_duel_summary(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = (*SUITES["tuning"], "affinity"), k: int = SEEDS) -> DataFrame:
    """One row: shares of best phi, the hypergraph model's time over the graph model's, and the ratios of their sizes in memory, mean and largest."""
    runs = once(spark, sf_dir, "model_duel", lambda: model_duel(spark, sf_dir))
    sizes = []
    for name in names:
        g = graph(spark, sf_dir, name)
        ball = written(pad_last_ball(g, grow_ball(g, seeds_of(spark, sf_dir, name, k), max(LAYERS[name])), LAYERS[name]), "ball")
        placed = written(M.placed_occurrences(E.ball_triangles(g, ball), ball_schedule(ball, LAYERS[name])), "placed")
        sizes.append(M.model_sizes(M.hyper_model(placed), M.graph_model(placed)).select((F.col("net_bytes") / F.col("edge_bytes")).alias("ratio")))
    memory = _all(sizes).agg(F.avg("ratio").alias("memory_ratio"), F.max("ratio").alias("memory_ratio_max"))
    return S.win_shares(runs, "graph", "hyper").select(F.col("first_best").alias("graph_best"), F.col("second_best").alias("hyper_best"), F.col("speedup").alias("time_ratio")).crossJoin(memory)


def search_ablation(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("affinity", "user_copresence", "copurchase"), k: int = SEEDS, n_trials: int = TRIALS) -> DataFrame:
    """runs with and without the local search, on the same trials."""
    out = []
    for name in names:
        g, s = graph(spark, sf_dir, name), seeds_of(spark, sf_dir, name, k)
        out += [timed_runs(algo, name, lambda r=rounds, g=g, s=s, n=name: A.local_motif_clusters(g, s, layers=LAYERS[n], n_trials=n_trials, search_rounds=r), s, g, True) for algo, rounds in (("plain", 0), ("search", 10))]
    return _all(out)


def search_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row: the relative change of phi and of time that the search brings, over averages and over instances."""
    runs = once(spark, sf_dir, "search_ablation", lambda: search_ablation(spark, sf_dir))
    by = runs.groupBy("algo").agg(F.avg("phi").alias("phi"), F.sum("seconds").alias("seconds"))
    a, b = by.where("algo = 'plain'"), by.where("algo = 'search'")
    both = a.select(F.col("phi").alias("p"), F.col("seconds").alias("t")).crossJoin(b.select("phi", "seconds")).select((F.col("phi") / F.col("p") - 1).alias("phi_change"), (F.col("seconds") / F.col("t") - 1).alias("time_change"))
    return both.crossJoin(S.relative_change(runs, "plain", "search", "phi").withColumnRenamed("change", "phi_change_by_instance"))


def consistency_duel(spark: SparkSession, sf_dir: str, name: str = "affinity", k: int = SEEDS, n_trials: int = TRIALS) -> DataFrame:
    """runs with repair of the seed and with fixed nodes, on the hypergraph model."""
    g, s = graph(spark, sf_dir, name), seeds_of(spark, sf_dir, name, k)
    return _all([timed_runs(algo, name, lambda f=fixed: A.local_motif_clusters(g, s, model="hyper", layers=LAYERS[name], n_trials=n_trials, fixed=f), s, g, True) for algo, fixed in (("repair", False), ("fixed", True))])


def curves(spark: SparkSession, sf_dir: str, name: str = "affinity", k: int = SEEDS, n_trials: int = TRIALS) -> DataFrame:
    """(seed, ball_no, trial, phi, seconds) of the main configuration, from which the curves over trials and balls are read: a trial does not depend on how many there are."""
    g, s = graph(spark, sf_dir, name), seeds_of(spark, sf_dir, name, k)
    return A.local_motif_clusters(g, s, layers=LAYERS[name], n_trials=n_trials).trials.select("seed", "ball_no", "trial", "phi", "seconds")


def _curves(spark, sf_dir):
    return once(spark, sf_dir, "curves", lambda: curves(spark, sf_dir))


def sweep_trials(spark: SparkSession, sf_dir: str, values: tuple[int, ...] = (1, 5, 20, 80)) -> DataFrame:
    """(n, phi, seconds): mean phi of the best of the first n trials, and the kernels' time a seed for as many."""
    t = _curves(spark, sf_dir)
    time_ = t.groupBy("seed", "trial").agg(F.sum("seconds").alias("s")).groupBy("seed").agg(*[F.sum(F.when(F.col("trial") < n, F.col("s"))).alias(f"s{n}") for n in values])
    per = time_.agg(F.map_from_entries(F.array(*[F.struct(F.lit(n), F.avg(f"s{n}")) for n in values])).alias("m"))
    phi = S.best_so_far(t).where(F.col("n").isin(list(values))).groupBy("n").agg(F.avg("phi").alias("phi"))
    return phi.crossJoin(per).select("n", "phi", F.col("m")[F.col("n")].alias("seconds"))


def sweep_balls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(balls, phi, seconds): mean phi of the best over the first balls, and the kernels' time a seed for them."""
    t = _curves(spark, sf_dir).groupBy("seed", "ball_no").agg(F.min("phi").alias("phi"), F.sum("seconds").alias("seconds"))
    n = F.explode(F.sequence(F.col("ball_no") + 1, F.lit(len(LAYERS["affinity"])))).alias("balls")
    return t.select("seed", "phi", "seconds", n).groupBy("balls", "seed").agg(F.min("phi").alias("phi"), F.sum("seconds").alias("seconds")).groupBy("balls").agg(F.avg("phi").alias("phi"), F.avg("seconds").alias("seconds"))


def assumption_everywhere(spark: SparkSession, sf_dir: str, k: int = SEEDS) -> DataFrame:
    """(graph, ball_no, seeds, held): for how many seeds each ball's motif volume is at most the rest's, padded last balls among them."""
    out = []
    for name in (*SUITES["tuning"], *SUITES["test"]):
        g, layers = graph(spark, sf_dir, name), LAYERS[name]
        ball = grow_ball(g, seeds_of(spark, sf_dir, name, k), max(layers))
        last = pad_last_ball(g, ball, layers).select("seed", F.lit(len(layers) - 1).alias("ball_no"), "node")
        balls = written(ball_schedule(ball, layers).where(F.col("ball_no") < len(layers) - 1).select("seed", "ball_no", "node").unionByName(last), "balls")
        named = balls.select(F.struct("seed", "ball_no").alias("seed"), "node")
        ok = O.volume_assumption(written(E.triangle_degree(g.edges), "degree"), named)
        out.append(ok.groupBy(F.col("seed.ball_no").alias("ball_no")).agg(F.count(F.lit(1)).alias("seeds"), F.count_if("ok").alias("held")).select(F.lit(name).alias("graph"), "ball_no", "seeds", "held"))
    return _all(out)


def planted_duel(spark: SparkSession, sf_dir: str, k: int = SEEDS) -> DataFrame:
    """(seed, phi, size, cell_phi, cell_size, shared): the method's cluster beside the planted cell of its seed, both by the definition."""
    from ..sources.graphs import cells

    g, s = graph(spark, sf_dir, "affinity"), seeds_of(spark, sf_dir, "affinity", k)
    found = written(A.local_motif_clusters(g, s, layers=LAYERS["affinity"]).clusters, "clusters")
    c = cells(spark, sf_dir)
    planted = s.join(c.withColumnRenamed("node", "seed"), "seed").join(c, "cell").select("seed", "node")
    score = lambda x, p: O.motif_conductance(g.occurrences(), x.withColumnRenamed("seed", "cluster")).select(F.col("cluster").alias("seed"), F.col("phi").alias(f"{p}phi")).join(x.groupBy("seed").agg(F.count(F.lit(1)).alias(f"{p}size")), "seed")
    shared = found.join(planted, ["seed", "node"]).groupBy("seed").agg(F.count(F.lit(1)).alias("shared"))
    return score(found, "").join(score(planted, "cell_"), "seed").join(shared, "seed", "left")


def _runs(spark, sf_dir):
    return once(spark, sf_dir, "compare", lambda: compare(spark, sf_dir))


TAUS = [1.0, 1.1, 1.5, 2.0, 5.0, 10.0, 100.0]
for _name, _run in (("search_ablation", search_ablation), ("consistency_duel", consistency_duel), ("model_duel", model_duel), ("compare", compare)):
    add(f"x_{_name}")(lambda s, d, n=_name, f=_run: once(s, d, n, lambda: f(s, d)))
for _name, _run in (("sweep_trials", sweep_trials), ("sweep_balls", sweep_balls), ("volume_assumption", assumption_everywhere), ("model_duel_summary", model_duel_summary), ("search_gain", search_gain)):
    add(f"x_{_name}")(_run)
add("local_clusters_planned_cells")(planted_duel)
add("x_compare_averages")(lambda s, d: S.averages(_runs(s, d)))
add("x_profile_phi")(lambda s, d: S.performance_profile(_runs(s, d), "phi", TAUS))
add("x_profile_time")(lambda s, d: S.performance_profile(_runs(s, d), "seconds", TAUS))
add("x_win_shares")(lambda s, d: S.win_shares(_runs(s, d), "ball", "sweep"))
add("x_phi_vs_size")(lambda s, d: S.phi_vs_size(_runs(s, d), "user_copresence"))
