"""Balls around seeds: breadth-first layers of all seeds at once."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import mix
from ..sources.shared import written
from .prepare import MotifGraph


def _step(adj: DataFrame, ball: DataFrame, depth: int) -> DataFrame:
    """The next layer: neighbours of the last one that no layer has yet. AQE broadcasts the frontier if it proves small."""
    front = ball.where(F.col("depth") == depth - 1).select("seed", "node")
    near = front.join(adj.select("node", "nbr"), "node").select("seed", F.col("nbr").alias("node")).distinct()
    return near.join(ball.select("seed", "node"), ["seed", "node"], "left_anti").select("seed", "node", F.lit(depth).alias("depth"))


def grow_ball(graph: MotifGraph, seeds: DataFrame, layers: int, cut: bool = True) -> DataFrame:
    """(seed, node, depth) of the nodes at most `layers` steps away. Each layer is written, for its plan names the one before twice; without cut, plans stay whole, for at most two layers."""
    ball = seeds.select(F.col("seed").cast("bigint").alias("seed"), F.col("seed").cast("bigint").alias("node"), F.lit(0).alias("depth")).distinct()
    for depth in range(1, layers + 1):
        ball = ball.unionByName(_step(graph.adj, ball, depth))
        if cut:
            ball = written(ball, "ball")
    return ball


def ball_schedule(ball: DataFrame, layers: tuple[int, ...]) -> DataFrame:
    """(seed, ball_no, node, depth): ball number i is the prefix of layers[i] layers of the one search."""
    plan = ball.sparkSession.createDataFrame([(i, n) for i, n in enumerate(layers)], "ball_no int, layers int")
    return ball.join(F.broadcast(plan), ball.depth <= plan.layers).select("seed", "ball_no", "node", "depth")


def pad_last_ball(graph: MotifGraph, ball: DataFrame, layers: tuple[int, ...], min_nodes: int = 100) -> DataFrame:
    """(seed, node, depth, layers): the last ball of each seed, with further layers while it has fewer than min_nodes nodes and still grows. Each layer adds a node, so there are fewer than min_nodes of them."""
    last = layers[-1]
    whole = ball.where(F.col("depth") <= last)
    size = ball.groupBy("seed").agg(F.max("depth").alias("top"), F.count(F.lit(1)).alias("n"))
    short = size.where(F.col("n") < min_nodes).select("seed")
    grown, depth = ball.join(short, "seed", "left_semi"), max(layers)
    while True:
        depth += 1
        layer = written(_step(graph.adj, grown, depth), "layer")
        if not layer.limit(1).count():
            break
        counted = grown.groupBy("seed").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") < min_nodes).select("seed")
        layer = layer.join(counted, "seed", "left_semi")
        if not layer.limit(1).count():
            break
        grown = written(grown.unionByName(layer), "grown")
    full = whole.join(short, "seed", "left_anti").unionByName(grown)
    return full.withColumn("layers", F.max("depth").over(Window.partitionBy("seed")))


def ball_boundary(graph: MotifGraph, ball: DataFrame) -> DataFrame:
    """(seed, node): neighbours of the ball outside it."""
    near = ball.select("seed", "node").join(graph.adj.select("node", "nbr"), "node").select("seed", F.col("nbr").alias("node")).distinct()
    return near.join(ball.select("seed", "node"), ["seed", "node"], "left_anti")


def closed_balls(graph: MotifGraph, ball: DataFrame) -> DataFrame:
    """(seed, size, closed): whether the ball has no neighbour outside."""
    out = ball_boundary(graph, ball).groupBy("seed").agg(F.count(F.lit(1)).alias("out"))
    size = ball.groupBy("seed").agg(F.count(F.lit(1)).alias("size"))
    return size.join(out, "seed", "left").select("seed", "size", F.coalesce(F.col("out") == 0, F.lit(True)).alias("closed"))


def ball_stats(ball: DataFrame) -> DataFrame:
    return ball.groupBy("seed", "depth").agg(F.count(F.lit(1)).alias("n"))


def capped_ball(ball: DataFrame, most: int, salt: int = 0) -> DataFrame:
    """At most `most` nodes a seed, near ones first, then in pseudo-random order: protects from hubs; not part of the method."""
    order = Window.partitionBy("seed").orderBy("depth", mix("node", salt), "node")
    return ball.withColumn("rn", F.row_number().over(order)).where(F.col("rn") <= most).drop("rn")
