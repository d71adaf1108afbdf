"""The whole method on graphs of the smallest tables: invariants, and optimum where it is known."""

import numpy as np
import pytest

from seedcluster.operators import ball as B
from seedcluster.operators import cluster as A
from seedcluster.operators import motifs as E
from seedcluster.operators import objective as O
from seedcluster.operators import partition as K
from seedcluster.operators import prepare as P
from seedcluster.sources.graphs import graph


def small_model(pairs, n):
    return K.from_nets([np.array(p) for p in pairs], np.ones(len(pairs), np.int64), n, np.ones(n, np.int64))


def test_kernel_splits_two_cliques():
    """Two cliques joined by one edge: nodes 0, 2..5 and 1, 6..9."""
    a, b = [0, 2, 3, 4, 5], [1, 6, 7, 8, 9]
    pairs = [(x, y) for c in (a, b) for i, x in enumerate(c) for y in c[i + 1 :]] + [(5, 6)]
    for side in K.bisect(small_model(pairs, 10), np.full(8, 0.1), np.random.default_rng(1)):
        assert sorted(np.flatnonzero(side)) == sorted(a)


def test_moves_keep_gains_cuts_and_volumes():
    """After any moves, what is kept up to date equals what is computed anew, and a gain is the fall of the cut."""
    rng = np.random.default_rng(0)
    for k in (2, 3, 4):
        n = 30
        m = K.model_of(rng.integers(0, n, (80, k)), rng.integers(1, 5, 80), n, np.ones(n, np.int64))
        s = K.Sides(m, rng.random((6, n)) < 0.5)
        for _ in range(200):
            t = np.flatnonzero(rng.random(6) < 0.6)
            s.flip(t, rng.integers(0, n, len(t)))
        f = K.Sides(m, s.side[:, :n])
        assert all((getattr(f, x) == getattr(s, x)).all() for x in ("gain", "cut", "vol", "held"))
        for v in range(n):
            moved = s.side[:, :n].copy()
            moved[:, v] = ~moved[:, v]
            assert (m.cut(moved) == s.cut - s.gain[:, v]).all()


def test_balance_and_fixed_nodes():
    rng = np.random.default_rng(2)
    pairs = [tuple(rng.choice(60, 2, replace=False)) for _ in range(300)]
    m, eps = small_model(pairs, 60), np.linspace(0, 0.9, 12)
    for strong in (False, True):
        side = K.bisect(m, eps, np.random.default_rng(0), fixed=True, strong=strong)
        held = side.sum(1)
        assert side[:, 0].all() and not side[:, 1].any() and (held <= K.max_block(60, eps)).all() and (60 - held <= K.max_block(60, eps)).all()
    many = K.bisect(m, np.full(30, 0.5), np.random.default_rng(1))
    few = K.bisect(m, np.full(3, 0.5), np.random.default_rng(1))
    assert (many[:3] == few).all(), "a trial does not depend on how many others there are"


def test_repair_puts_the_seed_inside():
    side = np.array([[True, True, False, False], [False, False, True, False], [True, False, True, False]])
    assert K.repaired(side).tolist() == [[True, False, True, True], [True, False, True, False], [True, False, True, False]]


def test_coarsening_keeps_seed_and_out_apart():
    m = small_model([(0, 1)] * 5 + [(i, i + 1) for i in range(2, 60)], 61)
    for fixed in (False, True):
        step = K.coarsen(m, np.random.default_rng(0), 10, fixed)
        assert step and step[1][0] == 0 and step[1][1] == 1


def test_search_never_rises():
    rng = np.random.default_rng(3)
    pairs = [tuple(rng.choice(30, 3, replace=False)) for _ in range(120)]
    m = small_model(pairs, 30)
    total = 3 * 400
    for s in range(5):
        side = np.random.default_rng(s).random(30) < 0.4
        side[0], side[1] = True, False
        out = K.search(m, side.copy(), total, 10, np.random.default_rng(s))
        assert out[0] and not out[1]
        assert K.less(m.cut(out), m.volume(out), m.cut(side), m.volume(side), total) <= 0


def test_clusters_hold_invariants(spark, sf_dir):
    g = graph(spark, sf_dir)
    seeds = spark.createDataFrame([(0,), (7,), (99,), (10**6,)], "seed bigint")
    r = A.local_motif_clusters(g, seeds, layers=(1, 2), n_trials=10)
    scores = {x["seed"]: x for x in r.scores.collect()}
    assert scores[10**6]["status"] == "closed_no_motif"  # a ball of one node, closed
    members = {}
    for x in r.clusters.collect():
        members.setdefault(x["seed"], set()).add(x["node"])
    true = {x["cluster"]: x for x in O.motif_conductance(E.occurrences(g.edges, E.TRIANGLE), r.clusters.withColumnRenamed("seed", "cluster")).collect()}
    for s in (0, 7, 99):
        assert s in members[s] and len(members[s]) == scores[s]["size"]
        assert 0 <= scores[s]["phi"] <= 1 and abs(scores[s]["phi"] - true[s]["phi"]) < 1e-12


def own_graph(spark, pairs):
    edges = spark.createDataFrame(pairs, "src bigint, dst bigint")
    return P.MotifGraph("own", edges, edges.selectExpr("explode(array(src, dst)) AS node").distinct())


def clique(nodes):
    return [(a, b) for i, a in enumerate(nodes) for b in nodes[i + 1 :]]


def test_closed_balls_end_the_search(spark):
    """A clique apart is closed, a path apart closed without motif, and a clique that is all of the graph the whole graph."""
    g = own_graph(spark, clique(range(5)) + [(10, 11), (11, 12)])
    seeds = spark.createDataFrame([(0,), (10,)], "seed bigint")
    got = {x["seed"]: x for x in A.local_motif_clusters(g, seeds, layers=(1, 2), n_trials=2).scores.collect()}
    assert (got[0]["status"], got[0]["phi"], got[0]["size"], got[0]["vol"]) == ("closed", 0.0, 5, 30)
    assert (got[10]["status"], got[10]["phi"], got[10]["size"]) == ("closed_no_motif", None, 3)
    whole = A.local_motif_clusters(own_graph(spark, clique(range(6))), seeds.limit(1), layers=(1,), n_trials=2).scores.first()
    assert (whole["status"], whole["size"]) == ("whole_graph", 6)
    with pytest.raises(ValueError):
        A.local_motif_clusters(g, seeds, layers=(2, 1))


def test_padding_has_no_cap(spark):
    """A path of 80 nodes is taken whole though each layer adds one node."""
    g = own_graph(spark, [(i, i + 1) for i in range(80)])
    seeds = spark.createDataFrame([(0,)], "seed bigint")
    assert B.pad_last_ball(g, B.grow_ball(g, seeds, 1), (1,), 100).count() == 81


def test_method_is_local(spark, sf_dir):
    """With the assumed denominator no number of the whole graph is asked for, and listed triangles are those near the balls."""
    edges = clique(range(6)) + [(5, 6)] + clique(range(6, 12)) + [(i, i + 1) for i in range(100, 140)] + clique(range(200, 230))
    g = own_graph(spark, edges)
    seeds = spark.createDataFrame([(0,)], "seed bigint")
    near = E.near_edges(g, B.grow_ball(g, seeds, 1)).collect()
    assert {x["src"] for x in near} <= set(range(12))
    r = A.local_motif_clusters(g, seeds, layers=(1,), n_trials=10, min_nodes=0, denominator="assumed")
    assert r.scores.first()["phi"] is not None and not g.__dict__.get("_volumes") and not g.__dict__.get("_occurrences") and "node_count" not in g.__dict__


def test_isolated_model_nodes_count_for_balance(spark):
    """A star around a triangle: nodes without motifs widen the bound, which is over the ball and OUT."""
    g = own_graph(spark, [(0, 1), (1, 2), (0, 2)] + [(0, i) for i in range(3, 40)] + [(40, 39), (40, 41), (41, 42), (40, 42)])
    seeds = spark.createDataFrame([(0,)], "seed bigint")
    r = A.local_motif_clusters(g, seeds, layers=(1,), n_trials=20, min_nodes=0)
    n = 41
    for x in r.trials.collect():
        if x["members"]:
            assert len(x["members"]) <= K.max_block(n, x["eps"]) + 1 and n - len(x["members"]) <= K.max_block(n, x["eps"]) + 1


def test_trials_do_not_depend_on_batches(spark, sf_dir):
    """The same trials whether all are held at once or three at a time, and whether there are 50 or 30 of them."""
    g = graph(spark, sf_dir)
    ball = B.grow_ball(g, spark.createDataFrame([(7,), (99,)], "seed bigint"), 1)
    balls = B.ball_schedule(ball, (1,))
    from seedcluster.operators import models as M

    model = M.graph_model(M.placed_occurrences(E.ball_triangles(g, ball), balls))
    rows = lambda n, cells=None: {(x["seed"], x["trial"]): (x["eps"], x["cut"], x["vol"]) for x in K.partition_models(model, 2 * g.motif_volume(), n_trials=n, cells=cells or K.CELLS).collect()}
    many = rows(50)
    assert rows(50, 300) == many and all(many[k] == v for k, v in rows(30).items()) and len(many) == 100


def test_time_limit_over_the_whole_run(spark, sf_dir):
    seeds = spark.createDataFrame([(7,), (99,)], "seed bigint")
    r = A.local_motif_clusters(graph(spark, sf_dir), seeds, layers=(1,), n_trials=4 * K.GROUP, min_nodes=0, time_budget_s=0.0)
    assert all(x["budget_hit"] for x in r.scores.collect()) and r.trials.count() < 8 * K.GROUP


def test_large_models_are_split_by_joins(spark, sf_dir):
    """phi of models split beyond one task is at most 1.2 times the kernel's."""
    seeds = spark.createDataFrame([(0,), (99,)], "seed bigint")
    one = {x["seed"]: x["phi"] for x in A.local_motif_clusters(graph(spark, sf_dir), seeds, layers=(1,), n_trials=20, min_nodes=60).scores.collect()}
    far = {x["seed"]: x["phi"] for x in A.local_motif_clusters(graph(spark, sf_dir), seeds, layers=(1,), n_trials=20, min_nodes=60, task_nodes=50).scores.collect()}
    assert all(far[s] <= 1.2 * one[s] + 1e-12 for s in one)


def test_sampled_triangles_estimate_all(spark, sf_dir):
    """The mean estimate over samples is near the number of triangles."""
    g = graph(spark, sf_dir)
    true = g.motif_volume() / 3
    got = [E.estimated_triangles(g.edges, 0.7, salt).first()["estimate"] for salt in range(8)]
    assert abs(np.mean(got) / true - 1) < 0.15


def test_curves_fall(spark, sf_dir, monkeypatch):
    """More trials and more balls never raise the mean phi; the search never does either."""
    from seedcluster.plans import experiments as X

    t = X.curves(spark, sf_dir, k=6, n_trials=40)
    monkeypatch.setattr(X, "_curves", lambda s, d: t)
    trials = [x["phi"] for x in X.sweep_trials(spark, sf_dir, (1, 5, 20, 40)).orderBy("n").collect()]
    balls = [x["phi"] for x in X.sweep_balls(spark, sf_dir).orderBy("balls").collect()]
    assert trials == sorted(trials, reverse=True) and balls == sorted(balls, reverse=True) and len(trials) == 4 and len(balls) == 3
    runs = X.search_ablation(spark, sf_dir, ("affinity",), k=6, n_trials=5).collect()
    by = {a: {x["seed"]: x["phi"] for x in runs if x["algo"] == a} for a in ("plain", "search")}
    assert all(by["search"][s] <= by["plain"][s] + 1e-12 for s in by["plain"])


def test_both_algorithms_are_scored_alike(spark, sf_dir):
    """Every seed has a row for either algorithm, by the definition; ball-cut has the lower mean phi."""
    from seedcluster.plans import experiments as X

    rows = X.compare(spark, sf_dir, ("affinity", "embed_knn"), k=8, n_trials=10).collect()
    by = {a: {(x["graph"], x["seed"]): x["phi"] for x in rows if x["algo"] == a} for a in ("ball", "sweep")}
    assert by["ball"].keys() == by["sweep"].keys() and all(0 <= p <= 1 for x in by.values() for p in x.values())
    assert np.mean(list(by["ball"].values())) < np.mean(list(by["sweep"].values()))


def test_planted_optimum(spark, sf_dir):
    """The one-layer ball of seed 0: cut 2, volume 107, seven nodes."""
    r = A.local_motif_clusters(graph(spark, sf_dir), spark.createDataFrame([(0,)], "seed bigint"), layers=(1,), n_trials=20, min_nodes=0)
    row = r.scores.first()
    assert (row["cut"], row["vol"], row["size"]) == (2, 107, 7)


def test_experiments_are_registered_whole(monkeypatch):
    from seedcluster.plans import experiments, queries

    asked = []
    monkeypatch.setattr(experiments, "graph", lambda s, d, name: None)
    monkeypatch.setattr(experiments, "seeds_of", lambda s, d, name, k: asked.append((name, k)))
    monkeypatch.setattr(experiments, "timed_runs", lambda algo, name, solve, seeds, *rest: None)
    monkeypatch.setattr(experiments, "once", lambda s, d, name, make: make())
    monkeypatch.setattr(experiments, "_all", lambda frames: frames)
    queries.QUERIES["x_compare"](None, None)
    assert {name for name, _ in asked} == set(experiments.SUITES["test"]) and {k for _, k in asked} == {50}
    assert {"pagerank_sweep_first_local", "edge_sweep_full"} <= set(queries.QUERIES)
