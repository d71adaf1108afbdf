"""The whole method: balls, occurrences, models, partition trials, local search, best cluster per seed."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, mix
from ..functions.motif import phi, ratio
from ..sources.shared import written
from .ball import ball_schedule, closed_balls, grow_ball, pad_last_ball
from .models import choose_model, graph_model, hyper_model, placed_occurrences
from .motifs import SPECS, ball_occurrences
from .objective import model_conductance
from .partition import FAR, OUT, partition_models
from .prepare import MotifGraph


@dataclass
class Result:
    """scores: a row per seed; clusters: (seed, node); trials: a row per seed, ball and trial."""

    scores: DataFrame
    clusters: DataFrame
    trials: DataFrame


def motif_total(graph: MotifGraph, motif: str = "triangle") -> DataFrame:
    """One row: the sum of motif degrees over the graph."""
    return graph.edges.sparkSession.createDataFrame([(graph.motif_volume(motif),)], "total bigint")


def best_trial(trials: DataFrame) -> DataFrame:
    """The row of lowest phi for each seed; earlier balls and trials win ties, rows without phi rank last."""
    order = Window.partitionBy("seed").orderBy(F.col("phi").asc_nulls_last(), "ball_no", "trial")
    return trials.withColumn("rn", F.row_number().over(order)).where("rn = 1").drop("rn")


def to_cluster(best: DataFrame) -> DataFrame:
    """(seed, node): the seed's block of a model split, read as nodes of the graph."""
    return best.select("seed", F.explode("members").alias("node")).where("node >= 0")


def local_motif_clusters(graph: MotifGraph, seeds: DataFrame, motif: str = "triangle", model: str | None = None, layers: tuple[int, ...] = (1, 2, 3), n_trials: int = 80, search_rounds: int = 10, min_nodes: int = 100, denominator: str = "exact", fixed: bool = False, effort: str = "fast", salt: int = 0, time_budget_s: float = 3600.0, allow_inexact: bool = False, task_nodes: int = 2_000_000) -> Result:
    """Ball-cut for many seeds in one job.

    All balls of a seed are prefixes of one search and share one enumeration. A closed ball ends the search for its seed:
    it is returned whole, with phi 0 if it holds a motif. Only edges near the balls are read. denominator: "assumed" takes the seed's block
    for the side of smaller volume; "exact" compares with the graph's motif volume, a number kept with the graph that is computed on first use.
    scores: seed, ball_no, trial, cut, vol, phi, size, status, exact, budget_hit, where status is cut, closed, whole_graph or no_motif,
    `exact` tells whether cut and vol are those of the motif (a graph model of a motif of four or more nodes has none such), and budget_hit
    whether the time limit, which holds from the call on, ended the seed's trials early. Graph models of more than task_nodes nodes are split by joins instead of in one task.
    """
    spec, began = SPECS[motif], time.time()
    model = model or choose_model(spec)
    if model == "graph" and spec.k > 3 and not allow_inexact:
        raise ValueError("the graph model is exact for motifs of at most three nodes")
    if list(layers) != sorted(set(layers)):
        raise ValueError("layers must ascend")
    deep, last = max(layers), len(layers) - 1
    ball = grow_ball(graph, seeds, deep)
    padded = written(pad_last_ball(graph, ball, layers, min_nodes), "padded")
    shut = written(closed_balls(graph, padded.select("seed", "node")).where("closed").select("seed", "size"), "shut")
    n_all = graph.node_count if shut.limit(1).count() else 0
    whole = ball.unionByName(padded.select("seed", "node", "depth")).groupBy("seed", "node").agg(F.min("depth").alias("depth"))
    occ = written(ball_occurrences(graph, whole, spec), "occ")
    inner = ball_schedule(ball, layers).where(F.col("ball_no") < last)
    balls = inner.unionByName(padded.select("seed", F.lit(last).cast("int").alias("ball_no"), "node", "depth")).join(shut.select("seed"), "seed", "left_anti")
    balls = written(balls, "balls")
    placed = placed_occurrences(occ, balls)
    built = written(graph_model(placed) if model == "graph" else hyper_model(placed), "model")
    factor = spec.k - 1 if model == "graph" else 1
    total = graph.motif_volume(motif) * factor if denominator == "exact" else FAR
    nodes = balls.select("seed", "ball_no", "node", F.lit(1).alias("size"), F.lit(0).alias("extra"))
    keys = ["seed", "ball_no"]
    size = written(balls.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")), "model-sizes")
    large = size.where(F.col("n") > task_nodes).select(*keys)
    groups, n_large = size.agg(F.count(F.lit(1)), F.count_if(F.col("n") > task_nodes)).first()
    left = time_budget_s - (time.time() - began)
    value = phi(F.col("cut"), F.col("vol"), F.lit(total)) if denominator == "exact" else ratio(F.col("cut"), F.col("vol"))
    if n_large and model != "graph":
        raise ValueError(f"{n_large} hypergraph models have more than task_nodes={task_nodes} nodes; the graph model can be split by joins")
    if n_large:
        big, rest = built.join(large, keys, "left_semi"), built.join(large, keys, "left_anti")
        trials = partition_models(rest, total, model, n_trials, search_rounds, fixed, effort, salt, left, nodes.join(large, keys, "left_anti"), groups - n_large)
        side = written(bisect_distributed(big, balls.join(large, keys, "left_semi"), total, task_nodes, n_trials=n_trials, salt=salt, search_rounds=search_rounds), "side")
        sums = model_conductance(big, side.withColumn("trial", F.lit(0)))
        members = side.groupBy(*keys).agg(F.array_sort(F.collect_list("node")).alias("members"))
        one = sums.join(members, keys).select(*keys, F.lit(0).alias("trial"), F.lit(None).cast("double").alias("eps"), "cut", "vol", "members", F.lit(None).cast("double").alias("seconds"))
        trials = trials.unionByName(one)
    else:
        trials = partition_models(built, total, model, n_trials, search_rounds, fixed, effort, salt, left, nodes, groups)
    trials = written(trials.withColumn("phi", value), "trials")
    few = trials.where("eps IS NOT NULL").groupBy(*keys).agg(F.count(F.lit(1)).alias("k")).where(F.col("k") < n_trials).select("seed", F.lit(True).alias("hit")).distinct()
    best = best_trial(trials).join(few, "seed", "left").withColumn("budget_hit", F.coalesce("hit", F.lit(False)))
    has = occ.groupBy("seed").agg(F.sum("ways").alias("m"), F.sum(F.size("nodes") * F.col("ways")).alias("v"))
    none, zero, no = F.lit(None), F.lit(0).cast("bigint"), F.lit(False)
    exact = F.lit(model == "hyper" or spec.k <= 3)
    div = lambda c: F.floor(F.col(c) / factor)
    cut = best.select("seed", "ball_no", "trial", div("cut").alias("cut"), div("vol").alias("vol"), "phi", F.size("members").cast("bigint").alias("size"), F.when(F.col("phi").isNull(), "no_motif").otherwise("cut").alias("status"), exact.alias("exact"), "budget_hit")
    state = F.when(F.col("m").isNull(), "closed_no_motif").when(F.col("size") >= n_all, "whole_graph").otherwise("closed")
    closed = shut.join(has, "seed", "left").select("seed", F.lit(last).cast("int").alias("ball_no"), none.cast("int").alias("trial"), zero.alias("cut"), F.coalesce("v", zero).alias("vol"), F.when(F.col("m") > 0, 0.0).alias("phi"), F.col("size").cast("bigint").alias("size"), state.alias("status"), F.lit(True).alias("exact"), no.alias("budget_hit"))
    found = cut.unionByName(closed)
    lone = seeds.select("seed").join(found.select("seed"), "seed", "left_anti")
    rest = lone.select("seed", none.cast("int").alias("ball_no"), none.cast("int").alias("trial"), zero.alias("cut"), zero.alias("vol"), none.cast("double").alias("phi"), F.lit(1).cast("bigint").alias("size"), F.lit("no_motif").alias("status"), F.lit(True).alias("exact"), no.alias("budget_hit"))
    clusters = to_cluster(best).unionByName(padded.join(shut.select("seed"), "seed", "left_semi").select("seed", "node")).unionByName(lone.select("seed", F.col("seed").alias("node")))
    return Result(found.unionByName(rest), clusters, trials)


def pagerank_sweep(graph: MotifGraph, seeds: DataFrame, motif: str = "triangle", walk_continue: float = 0.98, tol: float = 1e-4, pick: str = "global", max_rounds: int = 2000) -> Result:
    """The baseline: motif weights of the whole graph, approximate personalised PageRank, and a sweep. The graph's weights are made once for all seeds.

    A seed in no motif, or of so large a motif degree that its walk never leaves it, gets a row without phi and itself as cluster. Raises if some walk has not converged after max_rounds.
    """
    from .baselines import appr, best_prefix, sweep, sweep_clusters
    from .models import cooccurrence_graph

    w = written(cooccurrence_graph(graph.occurrences(motif)), "weights")
    prefixes = written(sweep(w, written(appr(w, seeds, walk_continue, tol, max_rounds, converge=True), "appr")), "prefixes")
    best = written(best_prefix(prefixes, pick), "best")
    factor = SPECS[motif].k - 1
    scores = best.select("seed", F.floor(F.col("cut") / factor).alias("cut"), F.floor(F.col("vol") / factor).alias("vol"), "phi", "size", F.lit("cut").alias("status"))
    lone, zero = seeds.select("seed").join(best.select("seed"), "seed", "left_anti"), F.lit(0).cast("bigint")
    scores = scores.unionByName(lone.select("seed", zero.alias("cut"), zero.alias("vol"), F.lit(None).cast("double").alias("phi"), F.lit(1).cast("bigint").alias("size"), F.lit("no_prefix").alias("status")))
    return Result(scores, sweep_clusters(prefixes, best).unionByName(lone.select("seed", F.col("seed").alias("node"))), prefixes)


def refine_best_move(edges: DataFrame, sides: DataFrame, total: DataFrame, rounds: int) -> DataFrame:
    """(seed, ball_no, node) after rounds of the single best move in each model, all models at once: the set-at-a-time form of the search.

    edges: (seed, ball_no, u, v, weight) with OUT as u. sides: (seed, ball_no, node) of the seed's block. Ties go to the smaller node.
    """
    both = edges.select("seed", "ball_no", F.col("u").alias("node"), F.col("v").alias("other"), "weight").unionByName(edges.select("seed", "ball_no", F.col("v").alias("node"), F.col("u").alias("other"), "weight"))
    keys = ["seed", "ball_no"]
    side = sides
    for _ in range(rounds):
        mark = side.select(*keys, "node", F.lit(1).alias("in"))
        e = both.join(mark, [*keys, "node"], "left").join(mark.select(*keys, F.col("node").alias("other"), F.col("in").alias("oin")), [*keys, "other"], "left").select(*keys, "node", "weight", F.coalesce("in", F.lit(0)).alias("in"), F.coalesce("oin", F.lit(0)).alias("oin"))
        per = e.groupBy(*keys, "node", "in").agg(F.sum("weight").alias("d"), F.sum(F.col("weight") * F.col("oin")).alias("x"))
        now = per.groupBy(*keys).agg(F.sum(F.when(F.col("in") == 1, F.col("d") - F.col("x")).otherwise(0)).alias("cut"), F.sum(F.when(F.col("in") == 1, F.col("d")).otherwise(0)).alias("vol"))
        move = per.where("node >= 0 AND node <> seed").join(now, keys).crossJoin(total.toDF("total"))
        out = F.col("in") == 1
        cut = F.when(out, F.col("cut") + 2 * F.col("x") - F.col("d")).otherwise(F.col("cut") + F.col("d") - 2 * F.col("x"))
        vol = F.when(out, F.col("vol") - F.col("d")).otherwise(F.col("vol") + F.col("d"))
        scored = move.select(*keys, "node", "in", phi(F.col("cut"), F.col("vol"), F.col("total")).alias("old"), phi(cut, vol, F.col("total")).alias("new")).where("new < old OR (old IS NULL AND new IS NOT NULL)")
        best = scored.groupBy(*keys).agg(F.min(F.struct("new", "node", "in")).alias("m")).select(*keys, "m.node", "m.in")
        side = written(side.join(best.where("in = 1"), [*keys, "node"], "left_anti").unionByName(best.where("in = 0").select(*keys, "node")), "side")
    return side


def repair_sides(sides: DataFrame) -> DataFrame:
    """(seed, ball_no, node, side): splits of whole models, turned so that OUT lies outside, with the seed put inside. sides: the same, OUT among the nodes, side in either sense."""
    out = F.max(F.when(F.col("node") == OUT, F.col("side"))).over(Window.partitionBy("seed", "ball_no"))
    return sides.withColumn("side", (F.col("side") != out) | (F.col("node") == F.col("seed")))


def _joined(edges: DataFrame, size: DataFrame, round_: int, bound: DataFrame, salt: int) -> DataFrame:
    """(seed, ball_no, node, head): pairs of nodes that are each other's best neighbour, under the lesser id, or that of the seed or OUT; other nodes under their own.

    edges: (seed, ball_no, u, v, weight). size: (seed, ball_no, node, size, extra). bound: (seed, ball_no, most), the largest merged node.
    """
    keys = ["seed", "ball_no"]
    s = lambda c: size.select(*keys, F.col("node").alias(c), F.col("size").alias(f"s{c}"))
    fit = edges.join(s("u"), [*keys, "u"]).join(s("v"), [*keys, "v"]).join(bound, keys).where("su + sv <= most AND NOT (least(u, v) = -1 AND greatest(u, v) = seed)")
    noise = 0.75 + mix((F.col("u") + 1) * 1_000_003 + F.col("v"), salt + round_) / (2 * PRIME)
    rated = fit.select(*keys, "u", "v", (F.col("weight") / (F.col("su") * F.col("sv")) * noise).alias("rate"))
    both = rated.select(*keys, F.col("u").alias("node"), F.col("v").alias("mate"), "rate").unionByName(rated.select(*keys, F.col("v").alias("node"), F.col("u").alias("mate"), "rate"))
    pick = both.groupBy(*keys, "node").agg(F.max(F.struct("rate", "mate")).alias("b")).select(*keys, "node", F.col("b.mate").alias("mate"))
    pairs = pick.join(pick.select(*keys, F.col("node").alias("mate"), F.col("mate").alias("node")), [*keys, "node", "mate"], "left_semi")
    low = F.least("node", "mate")
    head = F.when((F.col("node") == F.col("seed")) | (F.col("mate") == F.col("seed")), F.col("seed")).otherwise(low)
    return size.select(*keys, "node").join(pairs, [*keys, "node"], "left").select(*keys, "node", F.when(F.col("mate").isNull(), F.col("node")).otherwise(head).alias("head"))


def refine_many_moves(edges: DataFrame, nodes: DataFrame, side: DataFrame, total: int, rounds: int, salt: int = 0) -> DataFrame:
    """(seed, ball_no, node) of the best state of each model over rounds in which many nodes move at once.

    In a round, of the nodes whose own move lowers the cut, those that a coin chooses move, so that neighbours rarely swap sides together. Seed and OUT
    stay. States are compared by the objective. nodes: (seed, ball_no, node, extra), volume of a node that no edge shows.
    """
    keys = ["seed", "ball_no"]
    both = edges.select(*keys, F.col("u").alias("node"), F.col("v").alias("other"), "weight").unionByName(edges.select(*keys, F.col("v").alias("node"), F.col("u").alias("other"), "weight"))
    states, values = [], []
    for i in range(rounds + 1):
        mark = side.select(*keys, "node", F.lit(1).alias("in"))
        e = both.join(mark, [*keys, "node"], "left").join(mark.select(*keys, F.col("node").alias("other"), F.col("in").alias("oin")), [*keys, "other"], "left")
        per = e.groupBy(*keys, "node", F.coalesce("in", F.lit(0)).alias("in")).agg(F.sum("weight").alias("d"), F.sum(F.when(F.col("oin") == 1, F.col("weight")).otherwise(0)).alias("x"))
        per = written(per.join(nodes.select(*keys, "node", "extra"), [*keys, "node"]), "moves")
        sums = per.where("in = 1").groupBy(*keys).agg(F.sum(F.col("d") - F.col("x")).alias("cut"), F.sum(F.col("d") + F.col("extra")).alias("vol"))
        states.append(side)
        values.append(sums.select(*keys, phi(F.col("cut"), F.col("vol"), F.lit(total)).alias("phi"), F.lit(i).alias("round")))
        if i == rounds:
            break
        gain = F.when(F.col("in") == 1, F.col("d") - 2 * F.col("x")).otherwise(2 * F.col("x") - F.col("d"))
        move = per.where("node >= 0 AND node <> seed").where(gain > 0).where(mix(F.col("node"), salt + i) < PRIME // 2)
        side = written(side.join(move.where("in = 1").select(*keys, "node"), [*keys, "node"], "left_anti").unionByName(move.where("in = 0").select(*keys, "node")), "side")
    score, state = values[0], states[0].withColumn("round", F.lit(0))
    for i in range(1, rounds + 1):
        score, state = score.unionByName(values[i]), state.unionByName(states[i].withColumn("round", F.lit(i)))
    best = score.groupBy(*keys).agg(F.min(F.struct(F.coalesce("phi", F.lit(2.0)).alias("p"), "round")).alias("b")).select(*keys, F.col("b.round").alias("round"))
    return written(state.join(best, [*keys, "round"], "left_semi").select(*keys, "node"), "side")


def bisect_distributed(edges: DataFrame, nodes: DataFrame, total: int, most: int = 20_000, rounds: int = 5, n_trials: int = 80, salt: int = 0, levels: int = 40, search_rounds: int = 10) -> DataFrame:
    """(seed, ball_no, node): the seed's block of each graph model, for models beyond one task's memory.

    Models of more than `most` nodes are coarsened by joins, level by level, until they are small enough or shrink no more; the partition kernel splits the
    coarse models, whose cuts and volumes are those of the fine ones; the split goes back through the levels, each with rounds of many moves by joins.
    edges: (seed, ball_no, u, v, weight). nodes: (seed, ball_no, node) of the balls. total: the motif volume in units of the model. No model meets in one task before it has at most `most` nodes.
    """
    keys = ["seed", "ball_no"]
    size = nodes.select(*keys, "node").unionByName(nodes.select(*keys).distinct().withColumn("node", F.lit(OUT).cast("bigint")))
    size = written(size.select(*keys, "node", F.lit(1).cast("bigint").alias("size"), F.lit(0).cast("bigint").alias("extra")), "sizes")
    bound = written(size.groupBy(*keys).agg(F.greatest(F.lit(2), F.floor(F.count(F.lit(1)) * 3 / (2 * min(most, 40)))).alias("most")), "bound")
    edges, chain = written(edges.select(*keys, "u", "v", "weight"), "edges"), []
    for level in range(levels):
        large = size.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > most)
        left = large.agg(F.sum("n")).first()[0]
        if not left:
            break
        todo = edges.join(large.select(*keys), keys, "left_semi")
        label = written(_joined(todo, size, level, bound, salt), "label")
        name = lambda c: label.select(*keys, F.col("node").alias(c), F.col("head").alias(f"h{c}"))  # noqa: B023, E731
        named = edges.join(name("u"), [*keys, "u"]).join(name("v"), [*keys, "v"]).select(*keys, F.least("hu", "hv").alias("u"), F.greatest("hu", "hv").alias("v"), "weight")
        inner = named.where("u = v").groupBy(*keys, F.col("u").alias("node")).agg((2 * F.sum("weight")).alias("extra"))
        grown = size.join(label, [*keys, "node"]).groupBy(*keys, F.col("head").alias("node")).agg(F.sum("size").alias("size"), F.sum("extra").alias("e"))
        grown = written(grown.join(inner, [*keys, "node"], "left").select(*keys, "node", "size", (F.col("e") + F.coalesce("extra", F.lit(0))).alias("extra")), "sizes")
        coarse = written(named.where("u <> v").groupBy(*keys, "u", "v").agg(F.sum("weight").alias("weight")), "edges")
        chain.append((edges, size, label))
        edges, size = coarse, grown
        if size.join(large.select(*keys), keys, "left_semi").count() > 0.95 * left:
            break
    best = written(best_trial(partition_models(edges, total, "graph", n_trials, search_rounds, salt=salt, nodes=size).withColumn("phi", phi(F.col("cut"), F.col("vol"), F.lit(total)))), "best")
    side = best.select(*keys, F.explode("members").alias("node"))
    for fine, sizes, label in reversed(chain):
        side = written(label.join(side.withColumnRenamed("node", "head"), [*keys, "head"]).select(*keys, "node"), "side")
        side = refine_many_moves(fine, sizes, side, total, rounds, salt)
    return side.where("node >= 0")
