"""Graphs derived from the given tables, and SQL of the same meaning for another engine."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.packed import pack, pack_counts, unpack, unpack_counts
from ..operators.partition import runs
from ..operators.prepare import MotifGraph, normalise_edges
from .shared import written
from .tables import table

#: Suppliers' ids are shifted by this much in the part-supplier graph.
SUPPLIER_SHIFT = 1 << 30


def cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(node, cell): nation; nation and segment from 500 customers on; those and a band of balance from 5000 on, ten times narrower for each ten times 50,000 customers, so that cells stay small."""
    c = table(spark, sf_dir, "customer").where("c_custkey IS NOT NULL")
    n = c.agg(F.count(F.lit(1)).alias("n"))
    width = F.when(F.col("n") < 50_000, 1000).otherwise(F.lit(1000) / F.pow(F.lit(10), F.floor(F.log10(F.col("n") / 5000))))
    nation, segment, band = F.col("c_nationkey").cast("string"), F.col("c_mktsegment"), F.floor(F.col("c_acctbal") / width).cast("bigint").cast("string")
    cell = F.when(F.col("n") < 500, nation).when(F.col("n") < 5000, F.concat_ws("|", nation, segment)).otherwise(F.concat_ws("|", nation, segment, band))
    return c.crossJoin(n).select(F.col("c_custkey").alias("node"), cell.alias("cell"))


def _pairs_within(df: DataFrame, key: str, node: str) -> DataFrame:
    """Pairs of nodes that share a key; for keys with few nodes each."""
    other = df.select(F.col(key), F.col(node).alias("b"))
    return normalise_edges(df.select(F.col(key), F.col(node).alias("a")).join(other, key).where("a < b"), "a", "b")


def cell_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _pairs_within(cells(spark, sf_dir), "cell", "node")


def _sales(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, line = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    return o.select("o_orderkey", "o_custkey", F.to_date("o_orderdate").alias("day")).join(line.select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey"), "o_orderkey").select("o_custkey", "l_partkey", "day").distinct()


def close_orders(spark: SparkSession, sf_dir: str, days: int = 3) -> DataFrame:
    """Customers who ordered one part at most `days` days apart: an equi-join on part and a bucket of days, with neighbour buckets exploded."""
    s = _sales(spark, sf_dir).withColumn("b", F.floor(F.unix_date("day") / (days + 1)).cast("int"))
    left = s.select("l_partkey", "b", F.col("o_custkey").alias("x"), F.col("day").alias("dx"))
    right = s.select("l_partkey", F.explode(F.array(F.col("b") - 1, F.col("b"), F.col("b") + 1)).alias("b"), F.col("o_custkey").alias("y"), F.col("day").alias("dy"))
    return normalise_edges(left.join(right, ["l_partkey", "b"]).where(f"x < y AND abs(datediff(dx, dy)) <= {days}"), "x", "y")


def affinity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cell_edges(spark, sf_dir).unionByName(close_orders(spark, sf_dir)).distinct()


def pair_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst, support): parts and the number of orders that hold both."""
    op = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    pairs = op.select("l_orderkey", F.col("l_partkey").alias("src")).join(op.select("l_orderkey", F.col("l_partkey").alias("dst")), "l_orderkey").where("src < dst")
    return pairs.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("support"))


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pair_support(spark, sf_dir).select("src", "dst")


def copurchase2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pair_support(spark, sf_dir).where("support >= 2").select("src", "dst")


def nearest(vectors: DataFrame, k: int = 8, block: int = 2048) -> DataFrame:
    """(a, b, rank): the k nearest of each vector by cosine in double precision, ties by id. Vectors that are null or zero or hold a null have none.

    The exact way, whose work grows with the square of the vectors: blocks meet pairwise as matrices; a block pair keeps k for each row.
    """
    vectors = vectors.where("vec_id IS NOT NULL AND embedding IS NOT NULL AND NOT exists(embedding, x -> x IS NULL OR isnan(x)) AND exists(embedding, x -> x <> 0)")
    n = vectors.count()
    blocks = max(1, -(-n // block))
    v = vectors.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"), F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("own"))
    left = v.select("id", "v", F.lit(0).alias("side"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other"), "own").select("id", "v", "side", F.col("own").alias("i"), F.col("other").alias("j"))
    right = v.select("id", "v", F.lit(1).alias("side"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other"), "own").select("id", "v", "side", F.col("other").alias("i"), F.col("own").alias("j"))

    def top(group: pa.Table) -> pa.Table:
        side = group.column("side").to_numpy()
        ids = group.column("id").to_numpy()
        m = np.array(group.column("v").to_pylist(), float)
        m /= np.sqrt((m * m).sum(1))[:, None]
        a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        b = b[np.argsort(ids[b])]
        if not len(a) or not len(b):
            return pa.table([pa.array([], pa.int64())] * 2 + [pa.array([], pa.float64())], ["a", "b", "s"])
        s = m[a] @ m[b].T
        s[ids[a][:, None] == ids[b][None, :]] = -2
        pick = np.argsort(-s, axis=1, kind="stable")[:, :k]
        return pa.table([pa.array(np.repeat(ids[a], pick.shape[1])), pa.array(ids[b][pick].ravel()), pa.array(np.take_along_axis(s, pick, 1).ravel())], ["a", "b", "s"])

    near = left.unionByName(right).groupBy("i", "j").applyInArrow(top, "a long, b long, s double").where("s >= -1.5")
    from pyspark.sql import Window

    return near.withColumn("rank", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("s"), "b"))).where(F.col("rank") <= k).select("a", "b", "rank")


def embed_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    near = nearest(table(spark, sf_dir, "embeddings")).select("a", "b")
    return normalise_edges(near.join(near.select(F.col("b").alias("a"), F.col("a").alias("b")), ["a", "b"], "left_semi"), "a", "b")


def copresence_pairs(events: DataFrame, minutes: int = 10) -> DataFrame:
    """(u, v): for each two events of one type by different users, the later less than `minutes` after the earlier, (earlier user, later user)."""
    width = minutes * 60
    e = events.select("event_type", "user_id", F.col("ts").cast("timestamp").alias("ts"), F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / width).alias("b"))
    early = e.select("event_type", F.explode(F.array(F.col("b"), F.col("b") + 1)).alias("b"), F.col("user_id").alias("u"), F.col("ts").alias("t0"))
    late = e.select("event_type", "b", F.col("user_id").alias("v"), F.col("ts").alias("t1"))
    return early.join(late, ["event_type", "b"]).where(f"u <> v AND t1 >= t0 AND t1 < t0 + INTERVAL {minutes} MINUTES").select("u", "v")


def _met(left: tuple[np.ndarray, np.ndarray], right: tuple[np.ndarray, np.ndarray], width: int, both: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order, first, count): the right events (kind, time) in order of kind and time, and for each left one the run of those of its kind that are less than `width` later, or earlier too (both)."""
    (kind, at), order = left, np.lexsort(right[::-1])
    other, then = right[0][order], right[1][order]
    first, count = np.zeros(len(kind), np.int64), np.zeros(len(kind), np.int64)
    by = np.argsort(kind, kind="stable")
    kinds, starts = np.unique(kind[by], return_index=True)
    for k, i, j, a, b in zip(kinds, starts, [*starts[1:], len(by)], np.searchsorted(other, kinds), np.searchsorted(other, kinds, "right"), strict=True):
        mine, t = by[i:j], at[by[i:j]]
        first[mine] = a + np.searchsorted(then[a:b], t - width + 1 if both else t)
        count[mine] = a + np.searchsorted(then[a:b], t + width) - first[mine]
    return order, first, count


def copresence_lists(left: tuple[np.ndarray, np.ndarray, np.ndarray], right: tuple[np.ndarray, np.ndarray, np.ndarray], width: int, both: bool = False, most: int = 16_000_000) -> pa.Table:
    """(u, vs, ns) of the pairs between left and right events (kind, user, time): for each left user the right users, ascending and packed, and how often each. At most about `most` pairs are at hand at once, so that a user can come in several rows."""
    names = np.unique(np.concatenate([left[1], right[1]]))
    order, first, count = _met(left[::2], right[::2], width, both)
    user, other = np.searchsorted(names, left[1]), np.searchsorted(names, right[1])[order]
    by = np.argsort(user, kind="stable")
    user, first, count = user[by], first[by], count[by]
    part = (np.cumsum(count) - count) // most
    us, vs, ns = [np.zeros(0, np.int64)], [], []
    for i, j in zip(*(np.searchsorted(part, np.unique(part), side) for side in ("left", "right")), strict=True):
        u, v = np.repeat(user[i:j], count[i:j]), other[runs(first[i:j], count[i:j])]
        code, n = np.unique((u * len(names) + v)[u != v], return_counts=True)
        if not len(code):
            continue
        u, v = code // len(names), names[code % len(names)]
        start = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]]))
        us.append(names[u[start]])
        for a, b in zip(start, [*start[1:], len(u)], strict=True):
            vs.append(pack(v[a:b]))
            ns.append(pack_counts(n[a:b]))
    return pa.table([np.concatenate(us), pa.array(vs, pa.binary()), pa.array(ns, pa.binary())], ["u", "vs", "ns"])


def copresence_packed(events: DataFrame, minutes: int = 10, both: bool = False, slice_rows: int = 1_500_000) -> DataFrame:
    """(slice, u, vs, ns): the pairs of copresence_pairs() as lists, counted within slices of time; with `both`, of each event with those before and after it.

    A slice holds about slice_rows events, and sees those of its neighbours that its own can meet. Its users are dealt to as many tasks as keep the cores busy. No pair ever is a row.
    """
    width, spark = minutes * 60_000_000, events.sparkSession
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    e = events.select(F.col("event_type").cast("string").alias("kind"), F.col("user_id").cast("bigint").alias("user"), t.alias("at")).where("kind IS NOT NULL AND user IS NOT NULL AND at IS NOT NULL")
    slices = max(4, -(-e.count() // slice_rows))
    bounds = sorted(set(e.approxQuantile("at", [i / slices for i in range(1, slices)], 0.1 / slices)))
    blocks = max(1, -(-2 * spark.sparkContext.defaultParallelism // slices))
    place = lambda c: F.size(F.filter(F.array(*[F.lit(int(b)) for b in bounds]).cast("array<bigint>"), lambda b: b <= c))
    seen = e.select("*", place(F.col("at")).alias("home"), F.explode(F.sequence(place(F.col("at") - width), place(F.col("at") + width))).alias("slice"))
    seen = seen.select("*", F.pmod(F.xxhash64("user"), F.lit(blocks)).cast("int").alias("mine"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"))
    seen = seen.select("slice", "block", "kind", "user", "at", (F.expr("slice = home AND block = mine")).alias("own"))

    def cell(group: pa.Table) -> pa.Table:
        own = group.column("own").to_numpy()
        seen = group.column("kind").combine_chunks().dictionary_encode().indices.to_numpy(), group.column("user").to_numpy(), group.column("at").to_numpy()
        found = copresence_lists(tuple(x[own] for x in seen), seen, width, both)
        return found.add_column(0, "slice", pa.array(np.full(len(found), group.column("slice")[0].as_py(), np.int32)))

    return seen.groupBy("slice", "block").applyInArrow(cell, "slice int, u long, vs binary, ns binary")


def _added(lists: DataFrame, schema: str, rows, at_once: int) -> DataFrame:
    """What rows(u, v, n) gives of each user of a table of lists (u, vs, ns), with the counts of a pair added up. A task holds about at_once bytes of lists, or those of one user."""
    held = lists.agg(F.sum(F.octet_length("vs") + F.octet_length("ns"))).first()[0] or 0
    blocks = max(lists.sparkSession.sparkContext.defaultParallelism, held // at_once)

    def add(group: pa.Table) -> pa.Table:
        user = group.column("u").to_numpy()
        vs, ns = (group.column(c).to_pylist() for c in ("vs", "ns"))
        order = np.argsort(user, kind="stable")
        starts = np.flatnonzero(np.concatenate([[True], np.diff(user[order]) != 0]))
        out = []
        for a, b in zip(starts, [*starts[1:], len(user)], strict=True):
            v, back = np.unique(np.concatenate([unpack(vs[i]) for i in order[a:b]]), return_inverse=True)
            n = np.bincount(back, np.concatenate([unpack_counts(ns[i]) for i in order[a:b]]), len(v)).astype(np.int64)
            out.append(rows(user[order[a]], v, n))
        return pa.concat_tables(out)

    return lists.select("u", "vs", "ns", F.pmod(F.xxhash64("u"), F.lit(blocks)).alias("block")).groupBy("block").applyInArrow(add, schema)


def pair_lists(lists: DataFrame, at_once: int = 16_000_000) -> DataFrame:
    """(u, vs, ns): a row for each user of a table of lists."""
    return _added(lists, "u long, vs binary, ns binary", lambda u, v, n: pa.table([[u], [pack(v)], [pack_counts(n)]], ["u", "vs", "ns"]), at_once)


def pair_counts(lists: DataFrame, least: int = 1, at_once: int = 4_000_000) -> DataFrame:
    """(u, v, n) of a table of lists (u, vs, ns); pairs that come less than `least` times are left out."""
    return _added(lists, "u long, v long, n long", lambda u, v, n: pa.table([np.full(len(v), u), v, n], ["u", "v", "n"]).filter(pa.array(n >= least)), at_once)


def user_copresence(spark: SparkSession, sf_dir: str) -> DataFrame:
    return normalise_edges(pair_counts(written(copresence_packed(table(spark, sf_dir, "events")), "pairs"), 2), "u", "v")


def _shared(rows: DataFrame, key: str, node: str, most: int, least: int) -> DataFrame:
    """Nodes that share at least `least` keys, of those keys that 2 to `most` nodes have."""
    rare = rows.groupBy(key).agg(F.count(F.lit(1)).alias("n")).where(f"n BETWEEN 2 AND {most}").select(key)
    kept = rows.join(rare, key)
    pairs = kept.select(key, F.col(node).alias("src")).join(kept.select(key, F.col(node).alias("dst")), key).where("src < dst")
    return pairs.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n")).where(f"n >= {least}").select("src", "dst")


def shingles(docs: DataFrame, width: int = 5) -> DataFrame:
    """(doc_id, s): distinct shingles of words between single blanks, as 64-bit hashes, made by array functions alone."""
    w = docs.select("doc_id", F.split("text", " ", -1).alias("w")).where(F.size("w") >= width)
    return w.select("doc_id", F.explode(F.array_distinct(F.expr(f"transform(sequence(1, size(w) - {width - 1}), i -> xxhash64(array_join(slice(w, i, {width}), ' ')))"))).alias("s"))


def doc_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shared(shingles(table(spark, sf_dir, "documents")), "s", "doc_id", 10, 3)


def hrefs(pages: DataFrame) -> DataFrame:
    return pages.select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))).alias("href"))


def page_nav(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shared(hrefs(table(spark, sf_dir, "pages")), "href", "page_id", 50, 1)


def supply(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = table(spark, sf_dir, "lineitem")
    return normalise_edges(line.select(F.col("l_partkey").alias("a"), (F.col("l_suppkey") + SUPPLIER_SHIFT).alias("b")), "a", "b")


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {"affinity": affinity, "copurchase": copurchase, "copurchase2": copurchase2, "embed_knn": embed_knn, "user_copresence": user_copresence, "doc_overlap": doc_overlap, "page_nav": page_nav, "cells": cell_edges, "supply": supply}
NODES = {"affinity": ("customer", "c_custkey"), "cells": ("customer", "c_custkey"), "copurchase": ("part", "p_partkey"), "copurchase2": ("part", "p_partkey"), "embed_knn": ("embeddings", "vec_id"), "doc_overlap": ("documents", "doc_id"), "page_nav": ("pages", "page_id")}
#: Layers of the balls by graph; tuning and test graphs.
LAYERS = {"affinity": (1, 2, 3), "copurchase": (1,), "copurchase2": (2, 3, 4), "embed_knn": (1, 2, 3), "user_copresence": (1, 2), "doc_overlap": (1, 2, 3), "page_nav": (1, 2), "cells": (1,), "supply": (1,)}
SUITES = {"tuning": ("copurchase2", "embed_knn", "doc_overlap", "page_nav"), "test": ("affinity", "copurchase", "user_copresence", "cells")}
_KEPT: dict[tuple, MotifGraph] = {}


def graph(spark: SparkSession, sf_dir: str, name: str = "affinity") -> MotifGraph:
    """The named graph; held for reuse within one session."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _KEPT:
        edges = GRAPHS[name](spark, sf_dir)
        if name in NODES:
            t, c = NODES[name]
            nodes = table(spark, sf_dir, t).select(F.col(c).cast("bigint").alias("node")).where("node IS NOT NULL").distinct()
        else:
            nodes = edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct()
        _KEPT[key] = MotifGraph(name, edges, nodes).kept()
    return _KEPT[key]


def release(spark: SparkSession) -> None:
    """Lets go of the graphs held for this session."""
    for key in [k for k in _KEPT if k[0] == spark.sparkContext.applicationId]:
        g = _KEPT.pop(key)
        g.edges.unpersist()
        g.adj.unpersist()


_CELLS = """cells AS (SELECT c_custkey AS node, CASE WHEN (SELECT count(*) FROM customer) < 500 THEN CAST(c_nationkey AS VARCHAR)
 WHEN (SELECT count(*) FROM customer) < 5000 THEN CAST(c_nationkey AS VARCHAR) || '|' || c_mktsegment
 ELSE CAST(c_nationkey AS VARCHAR) || '|' || c_mktsegment || '|' || CAST(CAST(floor(c_acctbal / CASE WHEN (SELECT count(*) FROM customer) < 50000 THEN 1000 ELSE 1000 / pow(10, floor(log10((SELECT count(*) FROM customer) / 5000))) END) AS BIGINT) AS VARCHAR) END AS cell FROM customer)"""
_CELL_EDGES = "cell_edges AS (SELECT a.node AS src, b.node AS dst FROM cells a JOIN cells b ON a.cell = b.cell AND a.node < b.node)"
_SALES = "sales AS (SELECT DISTINCT o_custkey AS c, l_partkey AS p, CAST(o_orderdate AS DATE) AS d FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"
_OP = "op AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem)"
_SUPPORT = "support AS (SELECT a.p AS src, b.p AS dst, count(*) AS support FROM op a JOIN op b ON a.o = b.o AND a.p < b.p GROUP BY ALL)"
#: Common table expressions that end in edges(src, dst), by graph.
SQL: dict[str, str] = {
    "affinity": f"{_CELLS}, {_CELL_EDGES}, {_SALES}, edges AS (SELECT src, dst FROM cell_edges UNION SELECT a.c, b.c FROM sales a JOIN sales b ON a.p = b.p AND a.c < b.c AND abs(datediff('day', a.d, b.d)) <= 3)",
    "cells": f"{_CELLS}, {_CELL_EDGES}, edges AS (SELECT src, dst FROM cell_edges)",
    "copurchase": f"{_OP}, {_SUPPORT}, edges AS (SELECT src, dst FROM support)",
    "copurchase2": f"{_OP}, {_SUPPORT}, edges AS (SELECT src, dst FROM support WHERE support >= 2)",
    "embed_knn": """v AS (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings), sim AS (SELECT a.id AS a, b.id AS b, list_cosine_similarity(a.e, b.e) AS s FROM v a JOIN v b ON a.id <> b.id),
 near AS (SELECT a, b FROM sim QUALIFY row_number() OVER (PARTITION BY a ORDER BY s DESC, b) <= 8), edges AS (SELECT x.a AS src, x.b AS dst FROM near x JOIN near y ON x.a = y.b AND x.b = y.a WHERE x.a < x.b)""",
    "user_copresence": "pairs AS (SELECT a.user_id AS u, b.user_id AS v FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id <> b.user_id AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 10 MINUTE), edges AS (SELECT DISTINCT least(u, v) AS src, greatest(u, v) AS dst FROM (SELECT u, v FROM pairs GROUP BY u, v HAVING count(*) >= 2))",
    "doc_overlap": """w AS (SELECT doc_id, string_split(text, ' ') AS w FROM documents), sh AS (SELECT DISTINCT doc_id, unnest(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) AS s FROM w WHERE len(w) >= 5),
 rare AS (SELECT s FROM sh GROUP BY s HAVING count(*) BETWEEN 2 AND 10), kept AS (SELECT doc_id, s FROM sh WHERE s IN (SELECT s FROM rare)), edges AS (SELECT a.doc_id AS src, b.doc_id AS dst FROM kept a JOIN kept b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY ALL HAVING count(*) >= 3)""",
    "page_nav": """h AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages), rare AS (SELECT href FROM h GROUP BY href HAVING count(*) BETWEEN 2 AND 50),
 kept AS (SELECT page_id, href FROM h WHERE href IN (SELECT href FROM rare)), edges AS (SELECT DISTINCT a.page_id AS src, b.page_id AS dst FROM kept a JOIN kept b ON a.href = b.href AND a.page_id < b.page_id)""",
    "supply": f"edges AS (SELECT DISTINCT l_partkey AS src, l_suppkey + {SUPPLIER_SHIFT} AS dst FROM lineitem)",
}
