"""Summary measures over runs (algo, graph, seed, phi, size, seconds)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.motif import geo_mean


def averages(runs: DataFrame) -> DataFrame:
    """(graph, algo, phi, size, seconds): arithmetic mean of phi, geometric means of size and seconds; graph is null in the overall rows."""
    return runs.rollup("algo", "graph").agg(F.round(F.avg("phi"), 9).alias("phi"), F.round(geo_mean(F.col("size")), 6).alias("size"), F.round(geo_mean(F.col("seconds")), 6).alias("seconds")).where("algo IS NOT NULL")


def performance_profile(runs: DataFrame, measure: str, taus: list[float]) -> DataFrame:
    """(algo, tau, share): the share of instances whose value is at most tau times the best of the instance; a best of 0 counts zeros only."""
    best = runs.withColumn("best", F.min(measure).over(Window.partitionBy("graph", "seed")))
    grid = runs.sparkSession.createDataFrame([(float(t),) for t in taus], "tau double")
    hit = F.when(F.col("best") == 0, F.col(measure) == 0).otherwise(F.col(measure) <= F.col("tau") * F.col("best"))
    return best.crossJoin(F.broadcast(grid)).groupBy("algo", "tau").agg(F.round(F.avg(F.coalesce(hit, F.lit(False)).cast("double")), 9).alias("share"))


def win_shares(runs: DataFrame, first: str, second: str) -> DataFrame:
    """One row: shares of instances where each algorithm has the best or equal phi, where the first is faster, and the mean speed-up."""
    a = runs.where(F.col("algo") == first).select("graph", "seed", F.col("phi").alias("pa"), F.col("seconds").alias("sa"))
    b = runs.where(F.col("algo") == second).select("graph", "seed", F.col("phi").alias("pb"), F.col("seconds").alias("sb"))
    share = lambda c: F.round(F.avg(c.cast("double")), 9)
    return a.join(b, ["graph", "seed"]).agg(share(F.col("pa") <= F.col("pb")).alias("first_best"), share(F.col("pb") <= F.col("pa")).alias("second_best"), share(F.col("sa") < F.col("sb")).alias("first_faster"), F.round(geo_mean(F.col("sb")) / geo_mean(F.col("sa")), 6).alias("speedup"))


def relative_change(runs: DataFrame, base: str, other: str, measure: str) -> DataFrame:
    """One row: the mean relative change of a measure from one algorithm to another, over instances where the base is not 0."""
    a = runs.where(F.col("algo") == base).select("graph", "seed", F.col(measure).alias("x"))
    b = runs.where(F.col("algo") == other).select("graph", "seed", F.col(measure).alias("y"))
    return a.join(b, ["graph", "seed"]).where("x > 0").agg(F.round(F.avg((F.col("y") - F.col("x")) / F.col("x")), 9).alias("change"))


def best_so_far(trials: DataFrame) -> DataFrame:
    """(seed, n, phi): the lowest phi among the first n trials, all balls."""
    per = trials.groupBy("seed", "trial").agg(F.min("phi").alias("p"))
    return per.select("seed", (F.col("trial") + 1).alias("n"), F.min("p").over(Window.partitionBy("seed").orderBy("trial").rowsBetween(Window.unboundedPreceding, 0)).alias("phi"))


def phi_vs_size(runs: DataFrame, graph: str) -> DataFrame:
    """(algo, phi_bin, size_bin, n): tenths of phi by powers of two of size."""
    return runs.where(F.col("graph") == graph).groupBy("algo", F.floor(F.col("phi") * 10).alias("phi_bin"), F.floor(F.log2("size")).alias("size_bin")).agg(F.count(F.lit(1)).alias("n"))
