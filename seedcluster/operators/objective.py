"""Objectives, computed by one evaluator for all algorithms. A cluster table is (cluster, node)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.motif import phi, ratio
from .models import OUT


def conductance(edges: DataFrame, clusters: DataFrame) -> DataFrame:
    """(cluster, cut, vol, total, phi): crossing edges over the smaller volume."""
    occ = edges.select(F.array("src", "dst").alias("nodes"), F.lit(1).cast("bigint").alias("ways"))
    return motif_conductance(occ, clusters)


def motif_conductance(occ: DataFrame, clusters: DataFrame) -> DataFrame:
    """(cluster, cut, vol, total, phi) from the definition: occurrences cut, and motif volume of the smaller side.

    Members meet occurrences by an equi-join; an occurrence without members never leaves the join, so the complement is not read.
    """
    named = occ.withColumn("occ", F.col("nodes")).withColumn("k", F.size("nodes"))
    total = occ.agg(F.coalesce(F.sum(F.size("nodes") * F.col("ways")), F.lit(0)).alias("total"))
    hit = named.select("occ", "k", "ways", F.explode("nodes").alias("node")).join(clusters.select("cluster", "node"), "node").groupBy("cluster", "occ", "k", "ways").agg(F.count(F.lit(1)).alias("inside"))
    sums = hit.groupBy("cluster").agg(F.sum(F.when(F.col("inside") < F.col("k"), F.col("ways")).otherwise(0)).alias("cut"), F.sum(F.col("inside") * F.col("ways")).alias("vol"))
    every = clusters.select("cluster").distinct().join(sums, "cluster", "left").select("cluster", F.coalesce("cut", F.lit(0)).alias("cut"), F.coalesce("vol", F.lit(0)).alias("vol"))
    return every.crossJoin(total).select("cluster", "cut", "vol", "total", phi(F.col("cut"), F.col("vol"), F.col("total")).alias("phi"))


def model_conductance(edges: DataFrame, sides: DataFrame, total: DataFrame | None = None) -> DataFrame:
    """(seed, ball_no, trial, cut, vol, phi) in the graph model: edge cut over the seed block's weighted degree.

    sides: (seed, ball_no, trial, node) of the seed's block. With total (one row, one number: the graph's motif volume) the denominator is the smaller side's.
    """
    e = edges.select("seed", "ball_no", "weight", F.explode(F.array(F.struct(F.col("u").alias("node"), F.col("v").alias("other")), F.struct(F.col("v").alias("node"), F.col("u").alias("other")))).alias("x")).select("seed", "ball_no", "weight", "x.node", "x.other")
    mine = e.join(sides.select("seed", "ball_no", "trial", "node"), ["seed", "ball_no", "node"])
    inner = mine.join(sides.select("seed", "ball_no", "trial", F.col("node").alias("other"), F.lit(1).alias("in")), ["seed", "ball_no", "trial", "other"], "left")
    sums = inner.groupBy("seed", "ball_no", "trial").agg(F.sum(F.when(F.col("in").isNull(), F.col("weight")).otherwise(0)).alias("cut"), F.sum("weight").alias("vol"))
    if total is None:
        return sums.select("*", ratio(F.col("cut"), F.col("vol")).alias("phi"))
    return sums.crossJoin(total.toDF("total")).select("seed", "ball_no", "trial", "cut", "vol", phi(F.col("cut"), F.col("vol"), F.col("total")).alias("phi"))


def hyper_conductance(nets: DataFrame, sides: DataFrame) -> DataFrame:
    """(seed, ball_no, trial, cut, vol, phi) in the hypergraph model: cut-net over the seed block's net-weighted degree."""
    named = nets.withColumn("net", F.col("pins")).withColumn("k", F.size("pins"))
    hit = named.select("seed", "ball_no", "net", "k", "weight", F.explode("pins").alias("node")).join(sides.select("seed", "ball_no", "trial", "node"), ["seed", "ball_no", "node"])
    per_net = hit.groupBy("seed", "ball_no", "trial", "net", "k", "weight").agg(F.count(F.lit(1)).alias("inside"))
    sums = per_net.groupBy("seed", "ball_no", "trial").agg(F.sum(F.when(F.col("inside") < F.col("k"), F.col("weight")).otherwise(0)).alias("cut"), F.sum(F.col("inside") * F.col("weight")).alias("vol"))
    return sums.select("*", ratio(F.col("cut"), F.col("vol")).alias("phi"))


def volume_assumption(degree: DataFrame, ball: DataFrame) -> DataFrame:
    """(seed, vol, rest, ok): whether the ball's motif volume is at most the rest's. degree: (node, dmu) of the whole graph."""
    total = degree.agg(F.sum("dmu").alias("total"))
    vol = ball.select("seed", "node").join(degree, "node", "left").groupBy("seed").agg(F.coalesce(F.sum("dmu"), F.lit(0)).alias("vol"))
    return vol.crossJoin(total).select("seed", "vol", (F.col("total") - F.col("vol")).alias("rest"), (F.col("vol") <= F.col("total") - F.col("vol")).alias("ok"))


def edge_cut(edges: DataFrame, blocks: DataFrame) -> DataFrame:
    """One row: edges between different blocks of a k-way partition (node, block)."""
    a = blocks.select(F.col("node").alias("src"), F.col("block").alias("x"))
    b = blocks.select(F.col("node").alias("dst"), F.col("block").alias("y"))
    return edges.join(a, "src").join(b, "dst").where("x <> y").agg(F.count(F.lit(1)).alias("edge_cut"))


def modularity(edges: DataFrame, blocks: DataFrame) -> DataFrame:
    """One row: modularity of a partition."""
    a = blocks.select(F.col("node").alias("src"), F.col("block").alias("x"))
    b = blocks.select(F.col("node").alias("dst"), F.col("block").alias("y"))
    e = edges.join(a, "src").join(b, "dst")
    inside = e.where("x = y").groupBy(F.col("x").alias("block")).agg(F.count(F.lit(1)).alias("inner"))
    degree = e.select(F.explode(F.array("x", "y")).alias("block")).groupBy("block").agg(F.count(F.lit(1)).alias("d"))
    m = edges.agg(F.count(F.lit(1)).alias("m"))
    part = degree.join(inside, "block", "left").crossJoin(m)
    return part.agg(F.round(F.sum(F.coalesce("inner", F.lit(0)) / F.col("m") - F.pow(F.col("d") / (2 * F.col("m")), 2)), 9).alias("modularity"))


def imbalance(blocks: DataFrame, k: int) -> DataFrame:
    """One row: the largest block over the ceiling of an even share, less 1."""
    size = blocks.groupBy("block").agg(F.count(F.lit(1)).alias("n"))
    return size.agg(F.max("n").alias("largest"), F.sum("n").alias("n")).select("largest", (F.col("largest") / F.ceil(F.col("n") / k) - 1).alias("imbalance"))


def prefix_sides(balls: DataFrame) -> DataFrame:
    """(seed, ball_no, trial, node): rule-made splits of balls for checks; trial d keeps nodes of depth at most d, trial 100 + d those of even id besides the seed."""
    some = balls.where(F.col("node") != OUT)
    deep = some.groupBy("seed", "ball_no").agg(F.max("depth").alias("deep"))
    cut = some.join(deep, ["seed", "ball_no"]).select("seed", "ball_no", "node", "depth", F.explode(F.expr("sequence(0, deep)")).alias("d"))
    first = cut.where("depth <= d").select("seed", "ball_no", F.col("d").alias("trial"), "node")
    second = cut.where("depth <= d AND (node % 2 = 0 OR depth = 0)").select("seed", "ball_no", (F.col("d") + 100).alias("trial"), "node")
    return first.unionByName(second)
