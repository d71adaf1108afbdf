"""What the method is compared with: motif-PageRank sweep, exhaustive search, whole balls, planted cells."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.motif import phi
from ..sources.shared import written
from .models import OUT
from .partition import runs


def weighted_degree(w: DataFrame) -> DataFrame:
    return w.select(F.explode(F.array("u", "v")).alias("node"), "weight").groupBy("node").agg(F.sum("weight").alias("dw"))


def _links(w: DataFrame, dw: DataFrame) -> DataFrame:
    """(node, nbr, share, nbr_dw): both directions of each edge, with its share of the weight at node."""
    near = w.select(F.col("u").alias("node"), F.col("v").alias("nbr"), "weight").unionByName(w.select(F.col("v").alias("node"), F.col("u").alias("nbr"), "weight"))
    return near.join(dw, "node").join(dw.select(F.col("node").alias("nbr"), F.col("dw").alias("nbr_dw")), "nbr").select("node", "nbr", (F.col("weight") / F.col("dw")).alias("share"), "nbr_dw")


def appr(w: DataFrame, seeds: DataFrame, walk_continue: float = 0.98, tol: float = 1e-4, max_rounds: int = 500, cut_every: int = 8, converge: bool = False) -> DataFrame:
    """(seed, node, p, r): approximate personalised PageRank over weights (u, v, weight), all seeds at once.

    In a round, every node whose residual is at least tol times its weighted degree keeps 1 - walk_continue of it as score and
    spreads the rest over its edges by weight. Rounds end when no node is active, or after max_rounds, which raises with `converge`; walks that
    are to converge go by `walks`. State is written every few rounds.
    """
    if converge:
        return walks(w, seeds, walk_continue, tol, max_rounds)
    dw = weighted_degree(w)
    # A link from each node to itself carries what stays, so that a round reads the state once and plans do not double.
    links = written(_links(w, dw).unionByName(dw.select("node", F.col("node").alias("nbr"), F.lit(None).cast("double").alias("share"), F.col("dw").alias("nbr_dw"))), "links")
    state = seeds.select("seed", F.col("seed").alias("node"), F.lit(0.0).alias("p"), F.lit(1.0).alias("r")).join(dw, "node").select("seed", "node", "dw", "p", "r")
    active, stays = F.col("r") >= tol * F.col("dw"), F.col("share").isNull()
    for i in range(1, max_rounds + 1):
        step = state.join(links, "node").where(stays | active)
        p = F.when(stays, F.when(active, F.col("p") + (1 - walk_continue) * F.col("r")).otherwise(F.col("p"))).otherwise(0.0)
        r = F.when(stays, F.when(active, 0.0).otherwise(F.col("r"))).otherwise(F.col("r") * F.col("share") * walk_continue)
        state = step.select("seed", F.col("nbr").alias("node"), F.col("nbr_dw").alias("dw"), p.alias("p"), r.alias("r")).groupBy("seed", "node", "dw").agg(F.sum("p").alias("p"), F.sum("r").alias("r"))
        if i % cut_every == 0 and i < max_rounds:
            state = written(state, "appr")
            if not state.where(active).limit(1).count():
                break
    return state.select("seed", "node", "p", "r")


#: Nodes of at least this part of the residual that makes one active get their links before they are.
AHEAD = 1 / 64
WALK = "seed long, node long, dw long, p double, r double, round int, want boolean, nbr array<long>, share array<double>, nbr_dw array<long>"


def walks(w: DataFrame, seeds: DataFrame, walk_continue: float = 0.98, tol: float = 1e-4, max_rounds: int = 2000) -> DataFrame:
    """(seed, node, p, r) of appr() once no node is active, by the same rounds. Raises if some walk is still active after max_rounds.

    A seed's walk goes on in one task for as many rounds as it has the links of all active nodes; then those that are active or may soon be get theirs by a join, and it goes on.
    What a task holds is bounded whatever the graph: residuals sum to at most 1, so that the weighted degrees of the nodes of one join sum to at most 1 / (AHEAD * tol), and
    a join is asked for only when the walk has become active beyond the nodes before.
    """
    dw = weighted_degree(w)
    lists = _links(w, dw).groupBy("node").agg(F.sort_array(F.collect_list(F.struct("nbr", "share", "nbr_dw"))).alias("x")).select("node", F.col("x.nbr").alias("nbr"), F.col("x.share").alias("share"), F.col("x.nbr_dw").alias("nbr_dw"))
    lists = written(lists, "links")
    state = seeds.select("seed", F.col("seed").alias("node"), F.lit(0.0).alias("p"), F.lit(1.0).alias("r"), F.lit(0).alias("round"), F.lit(True).alias("want")).join(dw, "node")
    state = state.join(lists, "node").select("seed", "node", "dw", "p", "r", "round", "want", "nbr", "share", "nbr_dw")

    def go(group: pa.Table) -> pa.Table:
        own, known = group.column("node").to_numpy(), group.column("nbr").is_valid().to_numpy()
        listed = group.filter(group.column("nbr").is_valid())
        flat = {c: listed.column(c).combine_chunks() for c in ("nbr", "share", "nbr_dw")}
        count = np.diff(flat["nbr"].offsets.to_numpy())
        nbr, share, nbr_dw = (flat[c].flatten().to_numpy() for c in ("nbr", "share", "nbr_dw"))
        node, back = np.unique(np.concatenate([own, nbr]), return_inverse=True)
        at, target, n = back[: len(own)], back[len(own) :], len(node)
        deg, p, r = np.zeros(n, np.int64), np.zeros(n), np.zeros(n)
        deg[target], deg[at] = nbr_dw, group.column("dw").to_numpy()
        p[at], r[at] = group.column("p").to_numpy(), group.column("r").to_numpy()
        row = np.full(n, -1)
        row[at[known]] = np.arange(len(count))
        first, least, i = np.cumsum(count) - count, tol * deg, int(group.column("round")[0].as_py())
        want = np.zeros(n, bool)
        while len(v := np.flatnonzero(r >= least)):
            if (row[v] < 0).any():
                want = (row < 0) & (r >= AHEAD * least)
                break
            if i >= max_rounds:
                raise RuntimeError(f"walks are still active after {i} rounds")
            many, held = count[row[v]], r[v]
            e = runs(first[row[v]], many)
            p[v] += (1 - walk_continue) * held
            r[v] = 0.0
            r += np.bincount(target[e], np.repeat(held, many) * share[e] * walk_continue, n)
            i += 1
        keep = np.flatnonzero((p > 0) | (r > 0) | (row >= 0))
        lists_of = pa.array(row[keep], mask=row[keep] < 0)
        cols = [np.full(len(keep), group.column("seed")[0].as_py()), node[keep], deg[keep], p[keep], r[keep], np.full(len(keep), i, np.int32), want[keep]]
        return pa.table([*cols, *[flat[c].take(lists_of) for c in ("nbr", "share", "nbr_dw")]], [x.split()[0] for x in WALK.split(", ")])

    while True:
        state = written(state.groupBy("seed").applyInArrow(go, WALK), "appr")
        if not state.where("want").limit(1).count():
            return state.where("p > 0 OR r > 0").select("seed", "node", "p", "r")
        asked = state.where("want").drop("nbr", "share", "nbr_dw").join(lists, "node")
        state = state.where("NOT want").unionByName(asked)


def sweep(w: DataFrame, scores: DataFrame, total: DataFrame | None = None) -> DataFrame:
    """(seed, rank, node, cut, vol, phi) of each prefix by score over weighted degree. An edge adds its weight to the cut at its earlier end and takes it back at the later.

    A window holds the nodes that one seed's walk has scored. Each push of residual r keeps (1 - walk_continue) * r >= (1 - walk_continue) * tol * dw of a mass of 1, so
    the scored nodes' weighted degrees sum to at most 1 / ((1 - walk_continue) * tol), whatever the graph: 500,000 at the published parameters.
    """
    dw = weighted_degree(w)
    total = total if total is not None else dw.agg(F.sum("dw").alias("total"))
    order = Window.partitionBy("seed").orderBy(F.desc("score"), "node")
    ranked = scores.where("p > 0").join(dw, "node").select("seed", "node", "dw", F.round(F.col("p") / F.col("dw"), 12).alias("score")).withColumn("rank", F.row_number().over(order))
    a, b = ranked.select("seed", F.col("node").alias("u"), F.col("rank").alias("ru")), ranked.select("seed", F.col("node").alias("v"), F.col("rank").alias("rv"))
    inner = a.join(w, "u").join(b, ["seed", "v"]).select("seed", F.greatest("ru", "rv").alias("rank"), "weight").groupBy("seed", "rank").agg(F.sum("weight").alias("back"))
    run = Window.partitionBy("seed").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    step = ranked.join(inner, ["seed", "rank"], "left").select("seed", "rank", "node", F.sum("dw").over(run).alias("vol"), (F.sum("dw").over(run) - 2 * F.sum(F.coalesce("back", F.lit(0))).over(run)).alias("cut"))
    return step.crossJoin(total.toDF("total")).select("seed", "rank", "node", "cut", "vol", phi(F.col("cut"), F.col("vol"), F.col("total")).alias("phi"))


def best_prefix(prefixes: DataFrame, pick: str = "global") -> DataFrame:
    """(seed, size, cut, vol, phi): the best prefix, or the first one better than the one before and no worse than the next."""
    w = Window.partitionBy("seed").orderBy("rank")
    rows = prefixes.where("phi IS NOT NULL")
    if pick == "first":
        rows = rows.withColumn("before", F.lag("phi").over(w)).withColumn("after", F.lead("phi").over(w)).where("(before IS NULL OR phi < before) AND (after IS NULL OR phi <= after)")
        key = F.struct("rank", "cut", "vol", "phi")
    else:
        key = F.struct("phi", "rank", "cut", "vol")
    return rows.groupBy("seed").agg(F.min(key).alias("b")).select("seed", F.col("b.rank").cast("bigint").alias("size"), "b.cut", "b.vol", "b.phi")


def sweep_clusters(prefixes: DataFrame, best: DataFrame) -> DataFrame:
    """(seed, node) of the chosen prefix."""
    return prefixes.join(best.select("seed", "size"), "seed").where("rank <= size").select("seed", "node")


def exhaustive_best(nets: DataFrame, balls: DataFrame, total: DataFrame, most: int = 16) -> DataFrame:
    """(seed, ball_no, cut, vol, phi, size, members): the best split over all subsets of small balls with the seed inside and OUT outside.

    The free nodes of a ball are numbered; a subset is a number whose bits choose. Nets become pairs of bit masks; balls of more than `most` free nodes are left out.
    """
    free = balls.where("depth > 0").withColumn("bit", F.row_number().over(Window.partitionBy("seed", "ball_no").orderBy("node")) - 1)
    count = balls.groupBy("seed", "ball_no").agg((F.count(F.lit(1)) - 1).alias("f")).where(F.col("f") <= most)
    pins = nets.withColumn("net", F.col("pins")).select("seed", "ball_no", "net", "weight", F.explode("pins").alias("node"))
    masks = pins.join(free.select("seed", "ball_no", "node", "bit"), ["seed", "ball_no", "node"], "left").join(count, ["seed", "ball_no"]).groupBy("seed", "ball_no", "net", "weight").agg(
        F.coalesce(F.sum(F.when(F.col("bit").isNotNull(), F.expr("shiftleft(1L, bit)"))), F.lit(0)).alias("mask"), F.max((F.col("node") == F.col("seed")).cast("int")).alias("s"), F.max((F.col("node") == OUT).cast("int")).alias("t"))
    masks = masks.groupBy("seed", "ball_no", "mask", "s", "t").agg(F.sum("weight").alias("weight"))
    subsets = count.select("seed", "ball_no", F.explode(F.expr("sequence(0L, shiftleft(1L, CAST(f AS INT)) - 1)")).alias("x"))
    meet = subsets.join(masks, ["seed", "ball_no"]).select("seed", "ball_no", "x", "weight", (F.expr("bit_count(mask & x)") + F.col("s")).alias("inside"), (F.expr("bit_count(mask & ~x)") + F.col("t")).alias("outside"))
    sums = meet.groupBy("seed", "ball_no", "x").agg(F.sum(F.when((F.col("inside") > 0) & (F.col("outside") > 0), F.col("weight")).otherwise(0)).alias("cut"), F.sum(F.col("inside") * F.col("weight")).alias("vol"))
    scored = sums.crossJoin(total.toDF("total")).select("seed", "ball_no", "x", "cut", "vol", phi(F.col("cut"), F.col("vol"), F.col("total")).alias("phi")).where("phi IS NOT NULL")
    best = scored.groupBy("seed", "ball_no").agg(F.min(F.struct("phi", F.expr("bit_count(x)").alias("n"), "x", "cut", "vol")).alias("b"))
    members = best.join(free, ["seed", "ball_no"], "left").where("bit IS NULL OR (shiftright(b.x, bit) & 1) = 1").groupBy("seed", "ball_no").agg(F.array_sort(F.collect_list("node")).alias("members"))
    return best.join(members, ["seed", "ball_no"], "left").select("seed", "ball_no", "b.cut", "b.vol", "b.phi", (F.col("b.n") + 1).cast("bigint").alias("size"), F.array_sort(F.concat(F.array("seed"), F.coalesce("members", F.array().cast("array<bigint>")))).alias("members"))


def ball_as_cluster(balls: DataFrame) -> DataFrame:
    """(cluster, node): each ball as it is."""
    return balls.select(F.concat_ws("/", "seed", "ball_no").alias("cluster"), "node")
