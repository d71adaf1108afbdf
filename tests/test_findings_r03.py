"""Findings of round 3."""

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry


@pytest.fixture(scope="session")
def run(spark):
    """Runs a query on a folder of tables: the frame."""
    return lambda name, sf_dir: entry.queries()[name](spark, str(sf_dir))


def same(name, df, sf_dir, *tables):
    """The rows of a query are those of its SQL."""
    c = duckdb.connect()
    for t in tables:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    order = lambda rows: sorted((tuple(r) for r in rows), key=repr)
    got, want = order(df.collect()), order(c.execute(entry.oracle_sql()[name]).fetchall())
    assert got and got == want


@pytest.fixture(scope="session")
def crowd(tmp_path_factory):
    """A folder whose events meet in many ways: equal times, ends of ten minutes, a crowded moment, ids far apart, nulls."""
    at = tmp_path_factory.mktemp("crowd")
    duckdb.sql(f"""COPY (SELECT range AS event_id, TIMESTAMP '2024-01-01' + to_microseconds(CASE WHEN range % 5 = 0 THEN 300000000 * (range % 40) WHEN range % 97 = 0 THEN NULL ELSE range * 7919 % 20000 * 1000003 END) AS ts,
        CASE WHEN range % 83 = 0 THEN NULL WHEN range % 6 = 0 THEN -9000000000000000000 + range % 7 ELSE 1000000007 * (range * 31 % 29) END AS user_id, CASE WHEN range % 61 = 0 THEN NULL ELSE 'kind' || range % 3 END AS event_type, 1.0 AS value, '' AS props FROM range(3000)) TO '{at}/events.parquet'""")
    return at


def test_packed_lists_come_back_whole():
    from seedcluster.functions.packed import pack, pack_counts, unpack, unpack_counts

    rng = np.random.default_rng(1)
    for ids in ([], [5], [-(2**63), 2**63 - 1], [-3, 0, 1, 70000, 2**40], np.unique(rng.integers(0, 90_000, 30_000))):
        assert unpack(pack(np.array(ids, np.int64))).tolist() == list(ids)
    for n in ([], [1, 1, 300], [2**33, 0]):
        assert unpack_counts(pack_counts(np.array(n, np.int64))).tolist() == n
    assert len(pack(np.arange(0, 90_000, 3))) < 1000


@pytest.mark.parametrize("both", [False, True])
def test_f1_lists_hold_the_pairs_of_the_join(spark, crowd, both):
    from seedcluster.functions.packed import unpack, unpack_counts
    from seedcluster.sources.graphs import copresence_packed, copresence_pairs

    events = spark.read.parquet(f"{crowd}/events.parquet")
    pairs = copresence_pairs(events)
    want = {(r["u"], r["v"]): r["count"] for r in pairs.groupBy("u", "v").count().collect()}
    got, lists = {}, copresence_packed(events, both=both, slice_rows=400).collect()
    for r in lists:
        for v, n in zip(unpack(r["vs"]).tolist(), unpack_counts(r["ns"]).tolist(), strict=True):
            got[r["u"], v] = got.get((r["u"], v), 0) + n
    assert len({r["slice"] for r in lists}) > 4 and len(lists) < sum(want.values()) / 10
    if both:
        assert got.keys() == want.keys() | {(v, u) for u, v in want}
    else:
        assert got == want
    assert copresence_packed(events.limit(0), both=both).count() == 0


def test_f1_lists_are_made_in_parts_of_bounded_size():
    from seedcluster.functions.packed import unpack
    from seedcluster.sources.graphs import copresence_lists

    rng = np.random.default_rng(2)
    kind, user, at, own = rng.integers(0, 3, 900), rng.integers(0, 30, 900), rng.integers(0, 400, 900), rng.random(900) < 0.7
    pairs = lambda t: sorted({(u, v) for u, vs in zip(t.column("u").to_pylist(), t.column("vs").to_pylist(), strict=True) for v in unpack(vs).tolist()})
    whole, parts = (copresence_lists((kind[own], user[own], at[own]), (kind, user, at), 60, True, most) for most in (1 << 40, 500))
    assert pairs(whole) == pairs(parts) and len(parts) > len(whole)


def test_f1_user_degree_streams_a_row_for_a_list_of_partners(run, spark, crowd, monkeypatch):
    """A row for each pair took a disk of many times the input."""
    from seedcluster.sources.graphs import copresence_pairs
    from seedcluster.streaming import events as S

    asked, read = [], type(spark.readStream).parquet
    monkeypatch.setattr(type(spark.readStream), "parquet", lambda self, path: asked.append(path) or read(self, path))
    same("stream_user_degree", run("stream_user_degree", crowd), crowd, "events")
    assert spark.read.parquet(asked[0]).count() < copresence_pairs(spark.read.parquet(f"{crowd}/events.parquet")).count() / 10


@pytest.mark.parametrize("name", ["stream_incremental_edges", "stream_copresence_join"])
def test_f14_streams_join_lists_of_events(run, spark, crowd, name):
    """The streams met event by event in the state, and each pair was a row of each batch."""
    from seedcluster.streaming.events import pair_stream

    assert pair_stream(spark, str(crowd)).dtypes == [("u", "bigint"), ("vs", "binary"), ("ns", "binary")]
    moments = spark.read.parquet(getattr(spark, f"_seedcluster_moments_{crowd}"))
    assert moments.count() == moments.select("event_type", "b").distinct().count() < spark.read.parquet(f"{crowd}/events.parquet").count() / 10
    same(name, run(name, crowd), crowd, "events")


def test_f14_lists_of_a_pair_add_up(spark):
    from seedcluster.functions.packed import pack, pack_counts, unpack
    from seedcluster.sources.graphs import pair_counts, pair_lists

    row = lambda u, vn: (u, bytearray(pack(np.array([v for v, _ in vn]))), bytearray(pack_counts(np.array([n for _, n in vn]))))
    lists = spark.createDataFrame([row(1, [(2, 1), (9, 3)]), row(1, [(2, 1), (5, 1)]), row(-4, [(1, 1)])], "u long, vs binary, ns binary")
    assert sorted(map(tuple, pair_counts(lists).collect())) == [(-4, 1, 1), (1, 2, 2), (1, 5, 1), (1, 9, 3)]
    assert sorted(map(tuple, pair_counts(pair_lists(lists), 2).collect())) == [(1, 2, 2), (1, 9, 3)]
    assert {r["u"]: unpack(r["vs"]).tolist() for r in pair_lists(lists).collect()} == {1: [2, 5, 9], -4: [1]}
    assert pair_counts(lists.limit(0)).count() == 0


def test_f13_triangles_of_long_lists_are_found_by_colours(spark, monkeypatch):
    """Third nodes went along with each arc, whatever their number."""
    from seedcluster.operators import motifs

    rng = np.random.default_rng(5)
    far = 9_000_000_000_000_000_000
    pairs = sorted({(min(a, b), max(a, b)) for a, b in rng.integers(0, 60, (500, 2)).tolist() if a != b} | {(-far, i) for i in range(60)} | {(90, far)})
    edges = spark.createDataFrame(pairs, "src long, dst long")
    want = motifs.motif_degree(motifs.occurrences(edges, motifs.TRIANGLE))
    monkeypatch.setattr(motifs, "_closed", None)
    for per in (10**6, 40):
        real = motifs._by_cells
        with monkeypatch.context() as m:
            m.setattr(motifs, "_by_cells", lambda *a: real(*a, per))  # noqa: B023
            got = motifs.triangle_degree(edges, 0)
            assert got.dtypes == want.dtypes
            assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) != []
            count = motifs.triangle_count(edges, 0)
            assert count.dtypes == [("triangles", "bigint")] and 3 * count.first()["triangles"] == want.agg({"dmu": "sum"}).first()[0]
    assert motifs.triangle_count(spark.createDataFrame([(0, 1), (0, 2)], "src long, dst long"), -1).first()["triangles"] == 0


def test_f13_wedges_at_hand_are_bounded():
    from seedcluster.operators import motifs

    rng = np.random.default_rng(6)
    arcs = lambda n: (np.arange(n), [np.unique(rng.integers(0, 40, rng.integers(0, 30))) for _ in range(n)])
    ab, ac, bc = arcs(30), arcs(35), arcs(40)
    whole, parts = (dict(zip(*map(list, motifs.closing(ab, ac, bc, most)), strict=False)) for most in (1 << 40, 17))
    n = sum(len(np.intersect1d(ac[1][a], bc[1][b])) for a in range(30) for b in ab[1][a])
    assert whole == parts and motifs.closing(ab, ac, bc, 17)[1].sum() == 3 * n > 0


def test_f11_degrees_of_a_dense_graph_come_without_lists_along_arcs(spark):
    from seedcluster.operators import motifs

    a = spark.range(650).withColumnRenamed("id", "src")
    edges = a.crossJoin(a.withColumnRenamed("src", "dst")).where("src < dst")
    degree = motifs.triangle_degree(edges)
    assert "array_intersect" not in degree._jdf.queryExecution().optimizedPlan().toString()
    assert degree.select("dmu").distinct().collect() == [(649 * 648 // 2,)] and degree.count() == 650
