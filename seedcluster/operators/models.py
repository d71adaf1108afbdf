"""The condensed models of a ball: a hypergraph of motif nets, or a graph of co-occurrence weights. Everything outside is node OUT."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .motifs import MotifSpec

#: The node that stands for all nodes outside the ball; ids are never negative.
OUT = -1


def placed_occurrences(occ: DataFrame, balls: DataFrame) -> DataFrame:
    """(seed, ball_no, nodes, ways): occurrences that touch each ball, with outside nodes as OUT. balls: (seed, ball_no, node, depth).

    Inner balls are prefixes of the deepest one, and occurrences carry the depth of each node, so a ball's rim alone tells what lies inside: no node is joined again.
    """
    rims = balls.groupBy("seed", "ball_no").agg(F.max("depth").alias("rim"))
    place = F.array_sort(F.zip_with("nodes", "depths", lambda node, d: F.when(d <= F.col("rim"), node).otherwise(F.lit(OUT).cast("bigint"))))
    return occ.join(rims, "seed").where("min_depth <= rim").select("seed", "ball_no", place.alias("nodes"), "ways")


def hyper_model(placed: DataFrame) -> DataFrame:
    """(seed, ball_no, pins, weight): a net for each set of nodes, equal nets as one with their weights' sum; nets of one pin have no cut and go."""
    nets = placed.select("seed", "ball_no", F.array_distinct("nodes").alias("pins"), "ways")
    return nets.groupBy("seed", "ball_no", "pins").agg(F.sum("ways").alias("weight"))


def model_census(placed: DataFrame, every: int) -> DataFrame:
    """Occurrences by where they lie: all inside, across the ball's border, or all outside. every: how many the graph has."""
    out = F.array_contains("nodes", OUT)
    two = placed.groupBy("seed", "ball_no").agg(F.sum(F.when(~out, F.col("ways")).otherwise(0)).alias("inside"), F.sum(F.when(out, F.col("ways")).otherwise(0)).alias("across"))
    return two.withColumn("outside", F.lit(every) - F.col("inside") - F.col("across"))


def contract(nets: DataFrame, part: DataFrame) -> DataFrame:
    """Nets (pins, weight) with all nodes of `part` as OUT; nets inside it vanish, equal nets merge."""
    named = nets.withColumn("net", F.col("pins")).select("net", "weight", F.explode("pins").alias("node"))
    pins = named.join(part.select("node", F.lit(True).alias("in")), "node", "left").groupBy("net", "weight").agg(F.array_sort(F.collect_set(F.when(F.col("in"), F.lit(OUT)).otherwise(F.col("node")))).alias("pins"))
    return pins.where("size(pins) > 1 OR pins[0] <> -1").groupBy("pins").agg(F.sum("weight").alias("weight"))


def _pairs(nodes: str = "nodes") -> F.Column:
    return F.expr(f"filter(flatten(transform({nodes}, (x, i) -> transform(slice({nodes}, i + 2, size({nodes})), y -> struct(least(x, y) AS u, greatest(x, y) AS v)))), p -> p.u <> p.v)")


def cooccurrence_graph(occ: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """([keys,] u, v, weight), u < v: occurrences that hold both nodes. Pairs are summed before they are shuffled."""
    pairs = occ.select(*keys, F.explode(_pairs()).alias("p"), "ways")
    return pairs.groupBy(*keys, F.col("p.u").alias("u"), F.col("p.v").alias("v")).agg(F.sum("ways").alias("weight"))


def graph_model(placed: DataFrame) -> DataFrame:
    """(seed, ball_no, u, v, weight): co-occurrence weights after contraction; OUT is always u, and pairs outside vanish."""
    return cooccurrence_graph(placed, ("seed", "ball_no"))


def model_nodes(balls: DataFrame, n: int | None = None) -> DataFrame:
    """(seed, ball_no, node, weight): the ball's nodes, motif or not, and OUT. With n, the graph's number of nodes, OUT weighs as many as it stands for; without, 1, as the partitions take it."""
    one = F.lit(1).cast("bigint")
    out = balls.groupBy("seed", "ball_no").agg(F.count(F.lit(1)).alias("inner")).select("seed", "ball_no", F.lit(OUT).cast("bigint").alias("node"), one.alias("weight") if n is None else (F.lit(n) - F.col("inner")).alias("weight"))
    return balls.select("seed", "ball_no", "node", one.alias("weight")).unionByName(out)


def choose_model(spec: MotifSpec) -> str:
    """The graph model is exact for motifs of at most three nodes; beyond, the hypergraph is."""
    return "graph" if spec.k <= 3 else "hyper"


def model_sizes(nets: DataFrame, edges: DataFrame) -> DataFrame:
    """(seed, ball_no, nets, pins, model_edges, net_bytes, edge_bytes).

    Bytes are those of arrays of 64-bit numbers: a net has a weight, an offset and its pins, which nodes list once more; an edge has its weight and end at both ends.
    """
    h = nets.groupBy("seed", "ball_no").agg(F.count(F.lit(1)).alias("nets"), F.sum(F.size("pins")).alias("pins"))
    g = edges.groupBy("seed", "ball_no").agg(F.count(F.lit(1)).alias("model_edges"))
    return h.join(g, ["seed", "ball_no"]).select("*", (16 * F.col("nets") + 16 * F.col("pins")).alias("net_bytes"), (32 * F.col("model_edges")).alias("edge_bytes"))


def net_degree(nets: DataFrame) -> DataFrame:
    """(seed, ball_no, node, dw): weight of nets at each pin. A net of one pin counts for it."""
    return nets.select("seed", "ball_no", F.explode("pins").alias("node"), "weight").groupBy("seed", "ball_no", "node").agg(F.sum("weight").alias("dw"))


def edge_degree(edges: DataFrame) -> DataFrame:
    """(seed, ball_no, node, dw) of a graph model."""
    return edges.select("seed", "ball_no", F.explode(F.array("u", "v")).alias("node"), "weight").groupBy("seed", "ball_no", "node").agg(F.sum("weight").alias("dw"))
