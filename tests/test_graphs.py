"""Closed forms on hand-sized graphs, and the registry against SQL on the smallest tables."""

import math

import duckdb
import pytest

from seedcluster.operators import ball as B
from seedcluster.operators import motifs as E
from seedcluster.operators import objective as O
from seedcluster.operators import prepare as P
from seedcluster.operators.models import OUT, graph_model, hyper_model, placed_occurrences
from seedcluster.plans.registry import ORACLES, QUERIES
from seedcluster.sources.tables import TABLES


def edges(spark, pairs):
    return P.normalise_edges(spark.createDataFrame(pairs, "src bigint, dst bigint"))


def graph(spark, pairs):
    e = edges(spark, pairs)
    return P.MotifGraph("g", e, P.degrees(e).select("node"))


def clique(n, start=0):
    return [(start + i, start + j) for i in range(n) for j in range(i + 1, n)]


def clusters(spark, **sets):
    return spark.createDataFrame([(k, v) for k, vs in sets.items() for v in vs], "cluster string, node bigint")


def phis(spark, pairs, motif=E.TRIANGLE, **sets):
    e = edges(spark, pairs)
    return {r["cluster"]: r for r in O.motif_conductance(E.occurrences(e, motif), clusters(spark, **sets)).collect()}


def test_normalise(spark):
    rows = edges(spark, [(1, 2), (2, 1), (1, 2), (3, 3), (2, 3)]).collect()
    assert sorted(map(tuple, rows)) == [(1, 2), (2, 3)]


@pytest.mark.parametrize("n", [3, 4, 6])
def test_clique_triangles(spark, n):
    assert E.triangles(edges(spark, clique(n))).count() == math.comb(n, 3)


def test_bipartite_has_no_odd_cycle(spark):
    assert E.triangles(edges(spark, [(a, b) for a in range(3) for b in range(3, 6)])).count() == 0


def test_bowtie_and_cliques(spark):
    r = phis(spark, [(0, 1), (0, 2), (1, 2), (2, 3), (2, 4), (3, 4)], three=[0, 1, 2], two=[0, 1])
    assert (r["three"]["cut"], r["three"]["vol"], r["three"]["phi"]) == (1, 4, 0.5)
    assert (r["two"]["cut"], r["two"]["vol"], r["two"]["phi"]) == (1, 2, 0.5)
    r = phis(spark, clique(4), one=[0], two=[0, 1])
    assert r["one"]["phi"] == 1.0 and r["two"]["phi"] == 4 / 6
    r = phis(spark, clique(5) + clique(5, 5) + [(4, 5)], half=range(5), two=[0, 1])
    assert r["half"]["phi"] == 0.0 and (r["two"]["cut"], r["two"]["vol"], r["two"]["phi"]) == (9, 12, 0.75)


def test_no_motif_is_null(spark):
    assert phis(spark, [(0, i) for i in range(1, 6)], c=[0, 1])["c"]["phi"] is None


def test_four_cliques_need_the_hypergraph(spark):
    pairs = clique(4) + clique(6, 4)
    r = phis(spark, pairs, motif=E.CLIQUE4, two=[0, 1])["two"]
    assert (r["cut"], r["vol"], r["phi"]) == (1, 2, 0.5)


def test_contraction(spark):
    ball = spark.createDataFrame([(1, 0, n, d) for n, d in ((1, 0), (2, 1), (3, 1))], "seed bigint, ball_no int, node bigint, depth int")
    listed = spark.createDataFrame([(t, 1) for t in ([1, 2, 3], [1, 2, 8], [1, 2, 9], [1, 8, 9], [7, 8, 9])], "nodes array<bigint>, ways bigint")
    occ = E.touching(listed, ball, 3)
    assert {tuple(r["nodes"]): (r["depths"], r["min_depth"]) for r in occ.collect()} == {(1, 2, 3): ([0, 1, 1], 0), (1, 2, 8): ([0, 1, None], 0), (1, 2, 9): ([0, 1, None], 0), (1, 8, 9): ([0, None, None], 0)}
    placed = placed_occurrences(occ, ball)
    assert {tuple(r["pins"]): r["weight"] for r in hyper_model(placed).collect()} == {(1, 2, 3): 1, (OUT, 1, 2): 2, (OUT, 1): 1}
    assert {(r["u"], r["v"]): r["weight"] for r in graph_model(placed).collect()} == {(1, 2): 3, (1, 3): 1, (2, 3): 1, (OUT, 1): 4, (OUT, 2): 2}


def test_closed_ball(spark):
    g = graph(spark, clique(5) + clique(5, 10))
    seeds = spark.createDataFrame([(0,)], "seed bigint")
    assert B.closed_balls(g, B.grow_ball(g, seeds, 1)).first()["closed"]


def test_halo():
    assert (E.TRIANGLE.halo, E.WEDGE.halo, E.PATH4.halo) == (1, 2, 3)


QUICK = ["g_affinity_edges", "ball_2", "triangles_ball", "graph_model_edges", "hyper_nets", "motif_conductance_cells", "theorem_report", "exhaustive_small_balls", "sweep_best_global", "refine_best_move_3", "profile_phi", "win_shares", "rel_join_asof_events", "rel_set_except_all", "volume_assumption"]


@pytest.mark.parametrize("name", QUICK)
def test_against_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    want = con.sql(ORACLES[name])
    cols = sorted(want.columns)
    df = QUERIES[name](spark, sf_dir)
    assert sorted(df.columns) == cols
    tidy = lambda x: round(float(x), 9) if isinstance(x, float) or type(x).__name__ == "Decimal" else x
    rows = lambda found, names: sorted((tuple(tidy(r[names.index(c)]) for c in cols) for r in found), key=str)
    assert rows([tuple(r) for r in df.collect()], df.columns) == rows(want.fetchall(), want.columns)
