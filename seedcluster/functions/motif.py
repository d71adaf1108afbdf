"""Functions of motif conductance: a column expression, SQL functions and table functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def ratio(cut: Column, volume: Column) -> Column:
    """cut / volume as a double; null if the volume is 0."""
    return F.when(volume > 0, cut.cast("double") / volume.cast("double"))


def phi(cut: Column, volume: Column, total: Column) -> Column:
    """Crossing motifs over the smaller side's volume."""
    return ratio(cut, F.least(volume, total - volume))


def geo_mean(x: Column) -> Column:
    """Geometric mean of positive numbers."""
    return F.exp(F.avg(F.ln(x)))


def register(spark: SparkSession) -> None:
    """motif_phi(cut, vol, total) for SQL text. Catalyst inlines it."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION motif_phi(cut BIGINT, vol BIGINT, total BIGINT) RETURNS DOUBLE RETURN CASE WHEN least(vol, total - vol) > 0 THEN CAST(cut AS DOUBLE) / CAST(least(vol, total - vol) AS DOUBLE) END")


def register_neighbours(spark: SparkSession, view: str) -> None:
    """neighbours(n): a table function over an adjacency view (node, nbr)."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION neighbours(n BIGINT) RETURNS TABLE(nbr BIGINT) RETURN SELECT nbr FROM {view} WHERE node = n")


def register_ball_of(spark: SparkSession, view: str, layers: int) -> None:
    """ball_of(seed): a table function (node, depth) over an adjacency view (node, nbr), as many joins as layers."""
    walks = ["SELECT s AS node, 0 AS depth"]
    for n in range(1, layers + 1):
        joins = " ".join(f"JOIN {view} a{i} ON a{i}.node = a{i - 1}.nbr" for i in range(2, n + 1))
        walks.append(f"SELECT a{n}.nbr AS node, {n} AS depth FROM {view} a1 {joins} WHERE a1.node = s")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION ball_of(s BIGINT) RETURNS TABLE(node BIGINT, depth INT) RETURN SELECT node, min(depth) AS depth FROM ({' UNION ALL '.join(walks)}) GROUP BY node")
