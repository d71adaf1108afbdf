"""Relational queries around the method: making graphs, attaching attributes, reporting. Where one text serves both engines it is written once."""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import motif as fn
from ..operators import ball as B
from ..operators import motifs as E
from ..sources import edges as R
from ..sources import graphs as G
from ..sources.shared import shared_dir
from ..sources.tables import table, views
from . import oracles as Q
from .oracles import base
from .queries import ORACLES, QUERIES, _ball, _ORDER_RUNS, _RUNS, add, formula_runs, golden, order_runs


def both(name: str, sql: str, *tables: str) -> None:
    def run(spark, sf_dir):
        views(spark, sf_dir, *tables)
        return spark.sql(sql)

    QUERIES[name], ORACLES[name] = run, sql


# Sources and sinks.
_G2 = "WITH " + G.SQL["copurchase2"] + " SELECT src, dst FROM edges"


@add("rel_scan_edge_csv", _G2)
def scan_edge_csv(spark, sf_dir):
    path = f"{shared_dir(spark)}/edges-{uuid.uuid4().hex}"
    R.write_edge_list(G.graph(spark, sf_dir, "copurchase2").edges, path)
    return R.read_edge_list(spark, path)


@add("rel_scan_orc", "SELECT r_name, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def scan_orc(spark, sf_dir):
    path = f"{shared_dir(spark)}/nation-{uuid.uuid4().hex}"
    table(spark, sf_dir, "nation").write.orc(path)
    return spark.read.orc(path).join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@add("rel_scan_json_edges", _G2)
def scan_json(spark, sf_dir):
    path = f"{shared_dir(spark)}/edges-{uuid.uuid4().hex}"
    G.graph(spark, sf_dir, "copurchase2").edges.write.json(path)
    return R.read_edges(spark, path, "json")


@add("rel_adjacency_text", base("copurchase2") + " SELECT src, dst FROM edges")
def adjacency_text(spark, sf_dir):
    """Written as one line for each node from 0 on, in one file, and read by line number in ranges of bytes."""
    g = G.graph(spark, sf_dir, "copurchase2")
    top = g.degree.agg(F.max("node")).first()[0]
    lines = spark.range(top + 1).withColumnRenamed("id", "node").join(g.adj.groupBy("node").agg(F.array_join(F.array_sort(F.collect_list("nbr")), " ").alias("l")), "node", "left")
    path = f"{shared_dir(spark)}/adjacency-{uuid.uuid4().hex}"
    lines.repartition(1).sortWithinPartitions("node").select(F.coalesce("l", F.lit("")).alias("value")).write.text(path)
    files = spark.read.format("binaryFile").load(f"{path}/*.txt").select("path").collect()
    return R.read_adjacency_text(spark, files[0][0].replace("file:", ""), first=0, part_bytes=8192)


@add("rel_adjacency_bucketed", base() + " SELECT node, count(*) AS two_steps FROM (SELECT a.node, b.nbr FROM adj a JOIN adj b ON a.nbr = b.node) GROUP BY node")
def adjacency_bucketed(spark, sf_dir):
    """Nodes two steps away, counted with repetition, from an adjacency bucketed by node."""
    name = f"adjacency_{uuid.uuid4().hex}"
    R.save_adjacency(G.graph(spark, sf_dir).adj.select("node", "nbr"), name, 8)
    adj, degree = spark.table(name), spark.table(name).groupBy("node").agg(F.count(F.lit(1)).alias("d"))
    return adj.join(degree.withColumnRenamed("node", "nbr"), "nbr").groupBy("node").agg(F.sum("d").alias("two_steps"))


@add("rel_adjacency_lookup", base() + " SELECT node, nbr FROM adj WHERE node IN (0, 7, 42)")
def adjacency_lookup(spark, sf_dir):
    path = f"{shared_dir(spark)}/adj-{uuid.uuid4().hex}"
    R.write_adjacency(G.graph(spark, sf_dir).adj.select("node", "nbr"), path, 8)
    return R.open_adjacency(spark, path, [0, 7, 42], 8)


@add("rel_partitioned_sink", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus = 'F'")
def partitioned_sink(spark, sf_dir):
    path = f"{shared_dir(spark)}/orders-{uuid.uuid4().hex}"
    R.write_result(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus"), path, partition="o_orderstatus")
    return spark.read.parquet(path).where("o_orderstatus = 'F'").select("o_orderkey", "o_custkey")


# Filters, projections, joins.
both("rel_filter_dates", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderdate >= DATE '1995-01-01' AND o_orderdate < DATE '1995-07-01'", "orders")
both("rel_filter_in_like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%a%' AND p_size BETWEEN 5 AND 20 AND p_brand IN (SELECT min(p_brand) FROM part)", "part")
both("rel_project_case", "SELECT c_custkey, CAST(floor(c_acctbal / 1000) AS BIGINT) AS band, CASE WHEN c_acctbal < 0 THEN 'owes' WHEN c_acctbal < 5000 THEN 'low' ELSE 'high' END AS kind, coalesce(c_mktsegment, '-') AS segment FROM customer", "customer")
both("rel_join_inner_star", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey", "customer", "nation", "region")
_TRIPLES = "SELECT DISTINCT o_custkey, l_partkey, CAST(o_orderdate AS DATE) AS day FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
for _hint in ("merge", "shuffle_hash"):
    add(f"rel_join_{'smj' if _hint == 'merge' else 'shj'}", _TRIPLES)(lambda s, d, h=_hint: table(s, d, "orders").select(F.col("o_orderkey").alias("k"), "o_custkey", F.to_date("o_orderdate").alias("day")).hint(h).join(table(s, d, "lineitem").select(F.col("l_orderkey").alias("k"), "l_partkey"), "k").select("o_custkey", "l_partkey", "day").distinct())
both("rel_join_left_outer", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey", "customer", "orders")
both("rel_join_full_outer", "SELECT coalesce(a.node, b.node) AS node, a.c AS first_cluster, b.c AS second_cluster FROM (SELECT c_custkey AS node, c_nationkey AS c FROM customer WHERE c_acctbal > 2000) a FULL OUTER JOIN (SELECT c_custkey AS node, c_mktsegment AS c FROM customer WHERE c_acctbal < 6000) b ON a.node = b.node", "customer")
both("rel_join_semi", "SELECT p_partkey FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 45)", "part", "lineitem")
both("rel_join_anti", "SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 45)", "part", "lineitem")


@add("rel_join_theta_balance", "SELECT a.c_custkey AS x, b.c_custkey AS y FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_custkey < b.c_custkey AND abs(a.c_acctbal - b.c_acctbal) < 100")
def theta_balance(spark, sf_dir):
    """Customers of one nation whose balances differ by less than 100: an equi-join on nation and bucket of balance, with neighbour buckets exploded. Buckets are 128 wide, a power of two, so that division is exact.

    Both sides are shuffled: the table is small and its pairs are many, and beside a broadcast the file's few splits would make them all."""
    c = table(spark, sf_dir, "customer").select("c_nationkey", "c_custkey", "c_acctbal", F.rint(F.col("c_acctbal") / 128).alias("b"))
    left = c.select("c_nationkey", "b", F.col("c_custkey").alias("x"), F.col("c_acctbal").alias("bx"))
    right = c.select("c_nationkey", F.explode(F.array_distinct(F.array(F.col("b") - 1, F.col("b"), F.col("b") + 1))).alias("b"), F.col("c_custkey").alias("y"), F.col("c_acctbal").alias("by"))
    return left.hint("merge").join(right, ["c_nationkey", "b"]).where("x < y AND abs(bx - by) < 100").select("x", "y")

add("rel_join_cross_tau", _RUNS + " SELECT algo, tau, count(*) FILTER (phi <= tau) AS n FROM runs, (SELECT unnest([0.1::DOUBLE, 0.2::DOUBLE, 0.5::DOUBLE]) AS tau) GROUP BY ALL")(lambda s, d: formula_runs(s).crossJoin(F.broadcast(s.createDataFrame([(0.1,), (0.2,), (0.5,)], "tau double"))).groupBy("algo", "tau").agg(F.count_if(F.col("phi") <= F.col("tau")).alias("n")))
add("rel_join_interval_orders", f"WITH {G._SALES} SELECT DISTINCT a.c AS src, b.c AS dst FROM sales a JOIN sales b ON a.p = b.p AND a.c < b.c AND abs(datediff('day', a.d, b.d)) <= 3")(lambda s, d: G.close_orders(s, d))
add("rel_join_interval_events", "SELECT a.user_id AS u, b.user_id AS v, count(*) AS n FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id <> b.user_id AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 10 MINUTE GROUP BY ALL")(lambda s, d: G.copresence_pairs(table(s, d, "events")).groupBy("u", "v").agg(F.count(F.lit(1)).alias("n")))


@add("rel_join_asof_events", "SELECT e.event_id, p.event_id AS purchase_id FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY ALL) p ON e.user_id = p.user_id AND e.ts >= p.ts")
def asof_events(spark, sf_dir):
    """The last purchase at or before each error of the same user: one window over both, no join."""
    e = table(spark, sf_dir, "events").where("event_type IN ('error', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("purchase_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)).where("event_type = 'error'").select("event_id", "purchase_id")


@add("rel_join_asof_orders", "SELECT o.o_orderkey, p.o_orderkey AS before FROM orders o ASOF LEFT JOIN (SELECT o_custkey, o_orderdate, max(o_orderkey) AS o_orderkey FROM orders WHERE o_orderstatus = 'F' GROUP BY ALL) p ON o.o_custkey = p.o_custkey AND o.o_orderdate > p.o_orderdate WHERE o.o_orderstatus = 'O'")
def asof_orders(spark, sf_dir):
    """The last finished order strictly before each open one of the same customer: one window over both, which ends before the row's own date."""
    o = table(spark, sf_dir, "orders").where("o_orderstatus IN ('F', 'O')").withColumn("at", F.unix_micros(F.col("o_orderdate").cast("timestamp")))
    done = F.when(F.col("o_orderstatus") == "F", F.struct("at", "o_orderkey"))
    w = Window.partitionBy("o_custkey").orderBy("at").rangeBetween(Window.unboundedPreceding, -1)
    return o.withColumn("b", F.max(done).over(w)).where("o_orderstatus = 'O'").select("o_orderkey", F.col("b.o_orderkey").alias("before"))


# The price is selected too: a sort by a column that is not is parted from its limit, and rows are then numbered as they arrive.
add("rel_lateral_topk", "SELECT c_custkey, o_orderkey FROM customer JOIN (SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3) ON o_custkey = c_custkey")(lambda s, d: (views(s, d, "customer", "orders"), s.sql("SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey NULLS LAST LIMIT 3)"))[1])

# Aggregates.
add("rel_agg_partial_final", f"WITH {G._OP}, {G._SUPPORT} SELECT src, dst, support FROM support")(G.pair_support)
add("rel_agg_having", f"WITH {G._OP}, {G._SUPPORT} SELECT src, dst FROM support WHERE support >= 2")(G.copurchase2)
both("rel_agg_distinct", "SELECT l_orderkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_orderkey", "lineitem")
both("rel_agg_filter", "SELECT l_linestatus, count(*) FILTER (WHERE l_returnflag = 'R') AS returned, count(*) FILTER (WHERE l_quantity > 25) AS large FROM lineitem GROUP BY l_linestatus", "lineitem")
_CNR = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
both("rel_agg_grouping_sets", f"SELECT r_name, n_name, c_mktsegment, count(*) AS n {_CNR} GROUP BY GROUPING SETS ((r_name), (n_name, c_mktsegment), ())", "customer", "nation", "region")
both("rel_agg_rollup_nation", f"SELECT r_name, n_name, count(*) AS n, grouping(n_name) AS g {_CNR} GROUP BY ROLLUP (r_name, n_name)", "customer", "nation", "region")
both("rel_agg_cube", f"SELECT r_name, c_mktsegment, count(*) AS n {_CNR} GROUP BY CUBE (r_name, c_mktsegment)", "customer", "nation", "region")
add("rel_agg_pivot_algorithms", _ORDER_RUNS + " SELECT graph, round(avg(phi) FILTER (algo = 'ball'), 9) AS ball, round(avg(phi) FILTER (algo = 'sweep'), 9) AS sweep FROM runs GROUP BY graph")(lambda s, d: order_runs(s, d).groupBy("graph").pivot("algo", ["ball", "sweep"]).agg(F.round(F.avg("phi"), 9)))
add("rel_agg_min_by", _ORDER_RUNS + " SELECT graph, seed FROM runs WHERE algo = 'ball' QUALIFY row_number() OVER (PARTITION BY graph ORDER BY phi, seed) = 1")(lambda s, d: order_runs(s, d).where("algo = 'ball'").groupBy("graph").agg(F.min_by("seed", F.struct("phi", "seed")).alias("seed")))
add("rel_agg_collect_sorted", base() + " SELECT cell, array_to_string(list_sort(list(node)), ',') AS members FROM cells GROUP BY cell")(lambda s, d: G.cells(s, d).groupBy("cell").agg(F.array_join(F.array_sort(F.collect_list("node")), ",").alias("members")))
add("rel_agg_percentile", base() + " SELECT quantile_cont(d, 0.5) AS median, quantile_cont(d, 0.9) AS p90, max(d) AS top FROM deg")(lambda s, d: G.graph(s, d).degree.agg(F.percentile("d", 0.5).alias("median"), F.percentile("d", 0.9).alias("p90"), F.max("d").alias("top")))
add("rel_agg_approx_distinct")(lambda s, d: _ball(s, d, 2).groupBy("seed").agg(F.approx_count_distinct("node").alias("about")))
add("rel_agg_percentile_approx")(lambda s, d: G.graph(s, d).degree.agg(F.percentile_approx("d", [0.5, 0.9, 0.99]).alias("quantiles")))
add("rel_sketch_overlap")(lambda s, d: (lambda h: h.alias("a").join(h.alias("b"), F.expr("a.seed < b.seed")).select(F.col("a.seed").alias("x"), F.col("b.seed").alias("y"), F.expr("hll_sketch_estimate(hll_union(a.h, b.h))").alias("union_size")))(_ball(s, d, 2).groupBy("seed").agg(F.hll_sketch_agg("node").alias("h"))))

# Windows, sorts, sets.
both("rel_win_rank_family", "SELECT n_nationkey, n_regionkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr, ntile(4) OVER (PARTITION BY n_regionkey ORDER BY n_nationkey) AS nt, round(cume_dist() OVER w, 9) AS cd FROM nation WINDOW w AS (PARTITION BY n_regionkey ORDER BY n_nationkey)", "nation")
both("rel_win_lag_lead", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "events")
add("rel_win_running_min", _RUNS + " SELECT graph, seed, min(phi) OVER (PARTITION BY graph ORDER BY seed ROWS UNBOUNDED PRECEDING) AS best FROM runs WHERE algo = 'ball'")(lambda s, d: formula_runs(s).where("algo = 'ball'").select("graph", "seed", F.min("phi").over(Window.partitionBy("graph").orderBy("seed").rowsBetween(Window.unboundedPreceding, 0)).alias("best")))
add("rel_win_frame_range", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 600000000 PRECEDING AND CURRENT ROW), 6) AS s FROM events")(lambda s, d: table(s, d, "events").select("event_id", F.round(F.sum("value").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-600_000_000, 0)), 6).alias("s")))
both("rel_win_first_last_nth", "SELECT DISTINCT o_custkey, first_value(o_orderkey) OVER w AS first_order, last_value(o_orderkey) OVER w AS last_order, nth_value(o_orderkey, 2) OVER w AS second_order FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", "orders")
both("rel_sort_global", "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey", "customer")
both("rel_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25", "orders")
both("rel_offset", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25 OFFSET 50", "orders")
_TWO = base("affinity", Q.ball(2, (7, 42)))
for _op in ("UNION", "UNION ALL", "INTERSECT", "INTERSECT ALL", "EXCEPT", "EXCEPT ALL"):

    def _set(spark, sf_dir, op=_op):
        B.grow_ball(G.graph(spark, sf_dir), spark.createDataFrame([(7,), (42,)], "seed bigint"), 2).createOrReplaceTempView("two_balls")
        return spark.sql(f"SELECT node FROM two_balls WHERE seed = 7 {op} SELECT node FROM two_balls WHERE seed = 42")

    add(f"rel_set_{_op.lower().replace(' ', '_')}", _TWO + f" SELECT node FROM ball WHERE seed = 7 {_op} SELECT node FROM ball WHERE seed = 42")(_set)

# Functions.
add("rel_fn_hrefs", "SELECT page_id, unnest(list_distinct(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))) AS href FROM pages")(lambda s, d: G.hrefs(table(s, d, "pages")))
both("rel_fn_string", "SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, lower(substr(url, 1, 12)) AS head, length(html) AS n FROM pages", "pages")
add("rel_fn_date", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, quarter(o_orderdate) AS q, datediff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")(lambda s, d: table(s, d, "orders").select("o_orderkey", F.to_date(F.date_trunc("month", F.col("o_orderdate").cast("timestamp"))).alias("month"), F.quarter("o_orderdate").alias("q"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days")))
both("rel_fn_math", f"SELECT c_custkey, {Q.mix_sql('c_custkey', 9)} AS m, round(ln(1 + abs(c_acctbal)), 9) AS l, round(sqrt(abs(c_acctbal)), 9) AS r, round(pow(c_nationkey, 2), 6) AS p, c_custkey & 7 AS b FROM customer", "customer")
add("rel_fn_array", "SELECT a.vec_id AS x, b.vec_id AS y, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 9) AS c FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")(lambda s, d: cosine_next(s, d))
add("rel_fn_map", _RUNS + " SELECT graph, count(*) FILTER (phi < 0.3) AS low FROM runs WHERE algo = 'ball' GROUP BY graph")(lambda s, d: formula_runs(s).where("algo = 'ball'").groupBy("graph").agg(F.map_from_entries(F.collect_list(F.struct("seed", "phi"))).alias("m")).select("graph", F.size(F.map_filter("m", lambda k, v: v < 0.3)).cast("bigint").alias("low")))
add("rel_fn_json_props", "SELECT event_type, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY ALL")(lambda s, d: table(s, d, "events").groupBy("event_type", F.get_json_object("props", "$.k").cast("bigint").alias("k")).agg(F.count(F.lit(1)).alias("n")))
add("rel_fn_from_json", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, round(avg(value), 6) AS value FROM events GROUP BY ALL")(lambda s, d: table(s, d, "events").select(F.from_json("props", "k BIGINT").alias("p"), "value").groupBy("p.k").agg(F.round(F.avg("value"), 6).alias("value")))
both("rel_subquery_exists_scalar", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o.o_orderkey AND l_discount > 0.09)", "orders", "lineitem")
add("rel_cluster_attributes", base("doc_overlap", "reach(node, r) AS (SELECT node, node FROM deg UNION SELECT a.nbr, r FROM reach JOIN adj a USING (node) WHERE a.nbr > r), comp AS (SELECT node, min(r) AS c FROM reach GROUP BY node)") + " SELECT c, count(*) AS n, round(avg(quality), 9) AS quality, round(avg(toxic), 9) AS toxic FROM comp JOIN labels ON doc_id = node GROUP BY c")(lambda s, d: cluster_attributes(s, d))


def cosine_next(spark, sf_dir):
    """Cosine of each vector and the one of the next id, by array functions in double precision."""
    v = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    p = v.select(F.col("vec_id").alias("x"), F.col("e").alias("a")).join(v.select((F.col("vec_id") - 1).alias("x"), F.col("vec_id").alias("y"), F.col("e").alias("b")), "x")
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    return p.select("x", "y", F.round(dot("a", "b") / F.sqrt(dot("a", "a") * dot("b", "b")), 9).alias("c"))


def cluster_attributes(spark, sf_dir):
    from ..operators.prepare import label_components

    comp = label_components(G.graph(spark, sf_dir, "doc_overlap").edges)
    return comp.join(table(spark, sf_dir, "labels").withColumnRenamed("doc_id", "node"), "node").groupBy(F.col("component").alias("c")).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("quality"), 9).alias("quality"), F.round(F.avg("toxic"), 9).alias("toxic"))


@add("rel_cte_recursive", base("cells", "walk AS (SELECT node, node AS start, 0 AS step FROM deg WHERE node % 100 = 7 UNION SELECT a.nbr, w.start, w.step + 1 FROM walk w JOIN adj a USING (node) WHERE w.step < 2)") + " SELECT start, node, min(step) AS step FROM walk GROUP BY ALL")
def cte_recursive(spark, sf_dir):
    """Steps from some nodes by a recursive query; the graph's cells keep it small."""
    G.graph(spark, sf_dir, "cells").adj.createOrReplaceTempView("cells_adj")
    return spark.sql("WITH RECURSIVE walk(node, start, step) AS (SELECT DISTINCT node, node, 0 FROM cells_adj WHERE node % 100 = 7 UNION ALL SELECT a.nbr, w.start, w.step + 1 FROM walk w JOIN cells_adj a ON a.node = w.node WHERE w.step < 2) SELECT start, node, min(step) AS step FROM walk GROUP BY start, node")


# User-defined functions.
@add("sql_udf_motif_phi", "SELECT c_custkey % 50 AS cut, 1 + c_custkey % 90 AS vol, CASE WHEN least(1 + c_custkey % 90, 119 - c_custkey % 90) > 0 THEN (c_custkey % 50) / CAST(least(1 + c_custkey % 90, 119 - c_custkey % 90) AS DOUBLE) END AS phi FROM customer")
def sql_udf(spark, sf_dir):
    fn.register(spark)
    views(spark, sf_dir, "customer")
    return spark.sql("SELECT c_custkey % 50 AS cut, 1 + c_custkey % 90 AS vol, motif_phi(c_custkey % 50, 1 + c_custkey % 90, 120L) AS phi FROM customer")


@add("sql_table_fn_neighbours", base() + " SELECT node AS seed, nbr FROM adj WHERE node IN (0, 7, 42, 99, 149)")
def table_fn(spark, sf_dir):
    G.graph(spark, sf_dir).adj.createOrReplaceTempView("adj_view")
    fn.register_neighbours(spark, "adj_view")
    golden(spark).createOrReplaceTempView("golden_seeds")
    return spark.sql("SELECT seed, nbr FROM golden_seeds, LATERAL neighbours(seed)")


@add("udtf_pattern_edges", "SELECT * FROM (VALUES ('diamond', 0, 1), ('diamond', 0, 2), ('diamond', 0, 3), ('diamond', 1, 2), ('diamond', 1, 3), ('path4', 0, 1), ('path4', 1, 2), ('path4', 2, 3)) t(name, i, j)")
def pattern_edges(spark, sf_dir):
    """A pattern text such as 0-1,1-2 as rows of edges."""
    from pyspark.sql.functions import lit, udtf

    @udtf(returnType="i int, j int")
    class DecodePattern:
        def eval(self, text: str):
            for e in text.split(","):
                i, j = e.split("-")
                yield int(i), int(j)

    text = lambda m: ",".join(f"{i}-{j}" for i, j in m.edges)
    one = lambda m: DecodePattern(lit(text(m))).select(lit(m.name).alias("name"), "i", "j")
    return one(E.DIAMOND).unionByName(one(E.PATH4))


@add("sql_table_fn_ball_of", base("affinity", Q.ball(2)) + " SELECT seed, node, depth FROM ball")
def ball_of(spark, sf_dir):
    """Balls of two layers by the SQL table function ball_of(seed)."""
    G.graph(spark, sf_dir).adj.createOrReplaceTempView("adj_view")
    fn.register_ball_of(spark, "adj_view", 2)
    golden(spark).createOrReplaceTempView("golden_seeds")
    return spark.sql("SELECT seed, b.node, b.depth FROM golden_seeds, LATERAL ball_of(seed) b")


@add("udtf_shingles", "SELECT doc_id, count(DISTINCT s) AS n FROM (SELECT doc_id, unnest(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) AS s FROM (SELECT doc_id, string_split(text, ' ') AS w FROM documents) WHERE len(w) >= 5) GROUP BY doc_id")
def udtf_shingles(spark, sf_dir):
    """Shingles by a table function in Python, twin of the column expression."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="s string")
    class Shingles:
        def eval(self, text: str, width: int):
            w = (text or "").split(" ")
            for s in dict.fromkeys(" ".join(w[i : i + width]) for i in range(len(w) - width + 1)):
                yield (s,)

    spark.udtf.register("shingles_of", Shingles)
    views(spark, sf_dir, "documents")
    return spark.sql("SELECT doc_id, count(*) AS n FROM documents, LATERAL shingles_of(text, 5) GROUP BY doc_id")


@add("pattern_from_text", base("doc_overlap") + """ SELECT count(*) AS n FROM edges m JOIN adj x ON x.node = m.src JOIN adj x2 ON x2.node = m.dst AND x2.nbr = x.nbr JOIN adj y ON y.node = m.src AND y.nbr > x.nbr JOIN adj y2 ON y2.node = m.dst AND y2.nbr = y.nbr""")
def pattern_from_text(spark, sf_dir):
    """A pattern written as text, decoded and enumerated: symmetries are broken by the rule that automorphic images count once."""
    return E.enumerate_pattern(G.graph(spark, sf_dir, "doc_overlap").edges, E.pattern_of("0-1,0-2,0-3,1-2,1-3")).agg(F.count(F.lit(1)).alias("n"))


@add("udaf_geo_mean", _RUNS + " SELECT graph, round(exp(avg(ln(size))), 6) AS size FROM runs GROUP BY graph")
def udaf(spark, sf_dir):
    """The geometric mean as a grouped pandas function, twin of the column expression."""
    @F.pandas_udf("double")
    def geo(x: pd.Series) -> float:
        return float(np.exp(np.log(x).mean()))

    return formula_runs(spark).groupBy("graph").agg(F.round(geo("size"), 6).alias("size"))
