"""Connected components by alternating large-star and small-star rounds on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import with_least, written


def _large(edges: DataFrame) -> DataFrame:
    """Every neighbour above u goes to the smallest of u and its neighbours."""
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    m = F.least("u", "least")
    return with_least(both, ["u"], "v").where((F.col("v") > F.col("u")) & (F.col("v") != m)).select(F.col("v").alias("u"), m.alias("v")).distinct()


def _small(edges: DataFrame) -> DataFrame:
    """u and its smaller neighbours go to the smallest of them. Edges come as u > v."""
    near = with_least(edges, ["u"], "v")
    down = near.where("v <> least").select(F.col("v").alias("u"), F.col("least").alias("v"))
    return down.unionByName(near.select("u", F.col("least").alias("v"))).distinct()


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """edges (u, v BIGINT, any order, repeats and loops allowed) -> (node, component), component the smallest node reachable.

    Nodes without an edge to another node do not appear. Each round ends in a written table, so a lost
    executor costs one round; the driver sees only a count and a sum. The rows of a hub are dealt to parts, so that no task gathers them.
    """
    now = written(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "cc")
    seen = None
    for _ in range(max_rounds):
        now = written(_small(_large(now)), "cc")
        mark = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v") % 1_000_003)).first()
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
