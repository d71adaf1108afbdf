"""Motif occurrences as joins."""

from __future__ import annotations

import math
from dataclasses import dataclass
from itertools import permutations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, mix
from ..functions.packed import pack, unpack
from ..sources.shared import written
from .partition import runs
from .prepare import MotifGraph, degrees, orient

#: Third nodes that may go along with all arcs, 8 bytes each.
ALONG = 40_000_000


@dataclass(frozen=True)
class MotifSpec:
    """A connected pattern on nodes 0..k-1; `less` are pairs whose images must ascend, one for each symmetry to break."""

    name: str
    k: int
    edges: tuple[tuple[int, int], ...]
    less: tuple[tuple[int, int], ...] = ()

    @property
    def halo(self) -> int:
        """Steps from any node of the pattern to any other at most."""
        far = [[0 if i == j else 99 for j in range(self.k)] for i in range(self.k)]
        for i, j in self.edges:
            far[i][j] = far[j][i] = 1
        for m in range(self.k):
            for i in range(self.k):
                for j in range(self.k):
                    far[i][j] = min(far[i][j], far[i][m] + far[m][j])
        return max(max(r) for r in far)


EDGE = MotifSpec("edge", 2, ((0, 1),), ((0, 1),))
TRIANGLE = MotifSpec("triangle", 3, ((0, 1), (0, 2), (1, 2)), ((0, 1), (1, 2)))
WEDGE = MotifSpec("wedge", 3, ((0, 1), (0, 2)), ((1, 2),))
PATH4 = MotifSpec("path4", 4, ((0, 1), (1, 2), (2, 3)), ((0, 3),))
CYCLE4 = MotifSpec("cycle4", 4, ((0, 1), (1, 2), (2, 3), (3, 0)), ((0, 1), (0, 2), (0, 3), (1, 3)))
CLIQUE4 = MotifSpec("clique4", 4, ((0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3)), ((0, 1), (1, 2), (2, 3)))
DIAMOND = MotifSpec("diamond", 4, ((0, 1), (0, 2), (0, 3), (1, 2), (1, 3)), ((0, 1), (2, 3)))
SPECS = {m.name: m for m in (EDGE, TRIANGLE, WEDGE, PATH4, CYCLE4, CLIQUE4, DIAMOND)}


def pattern_of(text: str, name: str = "pattern") -> MotifSpec:
    """A pattern from text such as 0-1,1-2. Of the numberings that the pattern's symmetries make alike, one is kept: each node in turn that some remaining symmetry moves must have the least image of its orbit."""
    edges = tuple(tuple(sorted(map(int, e.split("-")))) for e in text.split(","))
    k = 1 + max(max(e) for e in edges)
    group = [p for p in permutations(range(k)) if {tuple(sorted((p[i], p[j]))) for i, j in edges} == set(edges)]
    less = []
    for i in range(k):
        less += [(i, j) for j in sorted({p[i] for p in group} - {i})]
        group = [p for p in group if p[i] == i]
    return MotifSpec(name, k, edges, tuple(less))


def triangles(edges: DataFrame, key: str | None = None) -> DataFrame:
    """(a, b, c), a < b < c, of each triangle, once; with a key column, triangles within each key.

    Arcs go from lower (degree, id) to higher; a triangle is the one pair of arcs out of its lowest node that a third arc closes. Without a key,
    neighbour lists tell the third nodes, and no row is made for a pair that nothing closes.
    """
    if not key:
        s = F.array_sort(F.array("a", "b", "c"))
        return _closed(edges).select("a", "b", F.explode("third").alias("c")).select(s.alias("s")).select(F.col("s")[0].alias("a"), F.col("s")[1].alias("b"), F.col("s")[2].alias("c"))
    d = edges.select(key, F.explode(F.array("src", "dst")).alias("node")).groupBy(key, "node").agg(F.count(F.lit(1)).alias("d"))
    with_d = edges.join(d.select(key, F.col("node").alias("src"), F.col("d").alias("ds")), [key, "src"]).join(d.select(key, F.col("node").alias("dst"), F.col("d").alias("dd")), [key, "dst"])
    up = F.struct("ds", "src") < F.struct("dd", "dst")
    pick = lambda a, b: F.when(up, F.col(a)).otherwise(F.col(b))
    arcs = with_d.select(key, pick("src", "dst").alias("lo"), pick("dst", "src").alias("hi"), pick("dd", "ds").alias("hi_d"))
    one = arcs.select(key, "lo", F.col("hi").alias("x"), F.col("hi_d").alias("xd"))
    two = arcs.select(key, "lo", F.col("hi").alias("y"), F.col("hi_d").alias("yd"))
    wedges = one.join(two, [key, "lo"]).where("struct(xd, x) < struct(yd, y)")
    close = arcs.select(key, F.col("lo").alias("x"), F.col("hi").alias("y"))
    s = F.array_sort(F.array("lo", "x", "y"))
    return wedges.join(close, [key, "x", "y"]).select(key, s[0].alias("a"), s[1].alias("b"), s[2].alias("c"))


def _closed(edges: DataFrame) -> DataFrame:
    """(a, b, third): of each arc from a to b, the nodes that close triangles whose least nodes by (degree, id) are a and b, without a row for each wedge.

    Each arc takes what follows it in a's list to b's list. Lists ascend by (degree, id) and are at most the root of twice the edges long.
    """
    arcs = orient(edges).groupBy("lo").agg(F.sort_array(F.collect_list(F.struct("hi_d", "hi"))).alias("s")).select("lo", F.col("s.hi").alias("out"))
    one = arcs.where("size(out) > 1").select("lo", "out", F.explode(F.expr("sequence(1, size(out) - 1)")).alias("i"))
    asked = one.select(F.col("lo").alias("a"), F.expr("out[i - 1]").alias("b"), F.expr("slice(out, i + 1, size(out))").alias("rest"))
    return asked.join(arcs.withColumnRenamed("lo", "b").hint("shuffle_hash"), "b").select("a", "b", F.array_intersect("rest", "out").alias("third"))


def _by_cells(edges: DataFrame, d: DataFrame, arcs: int, per: int = 6_000_000) -> DataFrame:
    """(node, ways): parts of triangle degrees, for graphs whose neighbour lists are too long to go along with each arc.

    Nodes have one of `colours` colours, and a task looks for the triangles of three of them, in order: the arcs between its three pairs of colours are all it reads, about
    `per` of them for each pair. Arcs travel as packed lists, a node's of one colour in a row, three times the number of colours in all; neither wedges nor triangles are rows.
    """
    colours = max(2, math.ceil(math.sqrt(arcs / per)))
    colour = lambda c: F.pmod(F.xxhash64(c), F.lit(colours)).cast("int")
    lists = orient(edges, d).groupBy("lo", colour("hi").alias("y")).agg(F.array_sort(F.collect_list("hi")).alias("out")).select("lo", colour("lo").alias("x"), "y", "out")

    def packed(batches):
        for batch in batches:
            out = [pack(v) for v in _split(batch.column("out"))]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("lo", "x", "y")), pa.array(out, pa.binary())], ["lo", "x", "y", "out"])

    lists = written(lists.mapInArrow(packed, "lo long, x int, y int, out binary"), "lists")
    other = F.explode(F.sequence(F.lit(0), F.lit(colours - 1))).alias("z")
    role = lambda i, p, q, r: lists.select("lo", "x", "y", "out", other).select(F.lit(i).alias("role"), F.col(p).alias("p"), F.col(q).alias("q"), F.col(r).alias("r"), "lo", "out")
    roles = role(0, "x", "y", "z").unionByName(role(1, "x", "z", "y")).unionByName(role(2, "z", "x", "y"))

    def cell(group: pa.Table) -> pa.Table:
        kind, node, out = group.column("role").to_numpy(), group.column("lo").to_numpy(), group.column("out")
        ab, ac, bc = ((node[rows], [unpack(out[int(i)].as_py()) for i in rows]) for rows in (np.flatnonzero(kind == i) for i in range(3)))
        names, ways = closing(ab, ac, bc)
        return pa.table([names, ways], ["node", "ways"])

    return roles.groupBy("p", "q", "r").applyInArrow(cell, "node long, ways long")


def _split(lists: pa.Array) -> list[np.ndarray]:
    ends = lists.offsets.to_numpy()
    return np.split(lists.flatten().to_numpy(), (ends - ends[0])[1:-1])


Lists = tuple[np.ndarray, list[np.ndarray]]


def closing(ab: Lists, ac: Lists, bc: Lists, most: int = 4_000_000) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, ways): the triangles a -> b, a -> c, b -> c of three sets of arcs, counted for each of their nodes. Arcs are given as nodes and the list of each; about `most` wedges are at hand at once."""
    if not (len(ab[0]) and len(ac[0]) and len(bc[0])):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    a_of, c_of = {n: x for n, x in zip(ac[0].tolist(), ac[1], strict=True)}, np.unique(np.concatenate(ac[1]))
    order = np.argsort(bc[0])
    b_names, flat, size = bc[0][order], np.concatenate([bc[1][i] for i in order]), np.array([len(bc[1][i]) for i in order])
    place = np.searchsorted(c_of, flat)
    use = c_of[np.minimum(place, len(c_of) - 1)] == flat
    ends = np.concatenate([[0], np.cumsum(use)])[np.concatenate([[0], np.cumsum(size)])]
    third, start, size = place[use].astype(np.int32), ends[:-1], np.diff(ends)
    of_a, of_b, of_c, mark = [], np.zeros(len(b_names), np.int64), np.zeros(len(c_of), np.int64), np.zeros(len(c_of), bool)
    for node, bs in zip(ab[0].tolist(), ab[1], strict=True):
        cs, found = a_of.get(node), 0
        if cs is not None:
            at = np.minimum(np.searchsorted(b_names, bs), len(b_names) - 1)
            at = at[(b_names[at] == bs) & (size[at] > 0)]
            cs = np.searchsorted(c_of, cs)
            mark[cs] = True
            part = (np.cumsum(size[at]) - size[at]) // most
            for some in np.split(at, np.flatnonzero(np.diff(part)) + 1) if len(at) else ():
                c = third[runs(start[some], size[some])]
                hit = mark[c]
                of_b[some] += np.add.reduceat(hit, np.cumsum(size[some]) - size[some], dtype=np.int64)
                c = c[hit]
                of_c += np.bincount(c, minlength=len(c_of)) if len(c) else 0
                found += len(c)
            mark[cs] = False
        of_a.append(found)
    names, ways = np.concatenate([ab[0], b_names, c_of]), np.concatenate([of_a, of_b, of_c]).astype(np.int64)
    return names[ways > 0], ways[ways > 0]


def triangle_count(edges: DataFrame, along: int = ALONG) -> DataFrame:
    """One row: (triangles)."""
    cells = _cells_if_long(edges, along)
    if cells:
        return cells.agg(F.coalesce(F.floor(F.sum("ways") / 3), F.lit(0)).alias("triangles"))
    return _closed(edges).agg(F.coalesce(F.sum(F.size("third")), F.lit(0)).alias("triangles"))


def triangle_degree(edges: DataFrame, along: int = ALONG) -> DataFrame:
    """(node, dmu) as motif_degree() gives it for triangles, which are not listed; nodes are added up before they are shuffled."""
    cells = _cells_if_long(edges, along)
    if cells:
        return cells.groupBy("node").agg(F.sum("ways").alias("dmu"))
    n = F.size("third").cast("bigint")
    ends = F.array(F.struct(F.col("a").alias("node"), n.alias("ways")), F.struct(F.col("b").alias("node"), n.alias("ways")))
    third = F.transform("third", lambda x: F.struct(x.alias("node"), F.lit(1).cast("bigint").alias("ways")))
    each = _closed(edges).where("size(third) > 0").select(F.explode(F.concat(ends, third)).alias("x"))
    return each.groupBy("x.node").agg(F.sum("x.ways").alias("dmu"))


def _cells_if_long(edges: DataFrame, along: int) -> DataFrame | None:
    """Parts of triangle degrees by cells, if more than `along` numbers would go along with the arcs."""
    d = written(degrees(edges), "degrees")
    out = orient(edges, d).groupBy("lo").agg(F.count(F.lit(1)).alias("n"))
    arcs, asked = out.agg(F.sum("n"), F.sum(F.col("n") * (F.col("n") - 1) / 2)).first()
    return _by_cells(edges, d, arcs) if (asked or 0) > along else None


def near_edges(graph: MotifGraph, ball: DataFrame, halo: int = 1) -> DataFrame:
    """(src, dst): edges among the nodes at most `halo` steps from any of the balls, each once, however many balls it is near."""
    nodes = ball.select("node").distinct()
    for _ in range(halo):
        nodes = nodes.join(graph.adj.select("node", "nbr"), "node").select(F.col("nbr").alias("node")).union(nodes).distinct()
    out = nodes.join(graph.adj.select("node", "nbr"), "node").where("node < nbr").select(F.col("node").alias("src"), F.col("nbr").alias("dst"))
    return out.join(nodes.select(F.col("node").alias("dst")), "dst", "left_semi").select("src", "dst")


def touching(occ: DataFrame, ball: DataFrame, k: int) -> DataFrame:
    """(seed, nodes, ways, depths, min_depth): occurrences of k nodes for each ball that holds one of them, with the depth of each node, null outside.

    Nodes meet balls by one equi-join; what belongs together is put together by an aggregate of fixed columns, which combines before the shuffle.
    """
    at = occ.select("nodes", "ways", F.posexplode("nodes").alias("i", "node")).join(ball.select("seed", "node", "depth"), "node")
    per = at.groupBy("seed", "nodes", "ways").agg(*[F.min(F.when(F.col("i") == i, F.col("depth"))).alias(f"d{i}") for i in range(k)])
    depths = F.array(*[f"d{i}" for i in range(k)])
    return per.select("seed", "nodes", "ways", depths.alias("depths"), F.array_min(depths).alias("min_depth"))


def ball_triangles(graph: MotifGraph, ball: DataFrame) -> DataFrame:
    """Triangles that touch each ball, as touching() gives them; only edges near the balls are read, and balls that overlap share one listing."""
    return ball_occurrences(graph, ball, TRIANGLE)


def wedges(edges: DataFrame) -> DataFrame:
    """(centre, a, c), a < c."""
    both = edges.select(F.col("src").alias("centre"), F.col("dst").alias("a")).unionByName(edges.select(F.col("dst").alias("centre"), F.col("src").alias("a")))
    return both.join(both.withColumnRenamed("a", "c"), "centre").where("a < c").select("centre", "a", "c")


def paths4(edges: DataFrame) -> DataFrame:
    """(p, q, r, s): q-r the middle edge, q < r."""
    both = edges.select(F.col("src").alias("x"), F.col("dst").alias("y")).unionByName(edges.select(F.col("dst").alias("x"), F.col("src").alias("y")))
    mid = edges.select(F.col("src").alias("q"), F.col("dst").alias("r"))
    left = mid.join(both.select(F.col("x").alias("q"), F.col("y").alias("p")), "q").where("p <> r")
    return left.join(both.select(F.col("x").alias("r"), F.col("y").alias("s")), "r").where("s <> q AND s <> p").select("p", "q", "r", "s")


def cycles4(edges: DataFrame) -> DataFrame:
    """(a, b, c, d) in circle order, a the least and b < d."""
    w = wedges(edges)
    two = w.select("a", "c", F.col("centre").alias("x")).join(w.select("a", "c", F.col("centre").alias("y")), ["a", "c"]).where("x < y AND a < x")
    return two.select("a", F.col("x").alias("b"), "c", F.col("y").alias("d"))


def cliques4(edges: DataFrame) -> DataFrame:
    """(a, b, c, d), ascending: a triangle and a fourth node above it that all three meet."""
    t = triangles(edges)
    e = edges.select("src", "dst")
    out = t.join(e.select(F.col("src").alias("a"), F.col("dst").alias("d")), "a").where("d > c")
    for x in "bc":
        out = out.join(e.select(F.col("src").alias(x), F.col("dst").alias("d")), [x, "d"], "left_semi")
    return out.select("a", "b", "c", "d")


def directed_cycles3(arcs: DataFrame) -> DataFrame:
    """(a, b, c) of a -> b -> c -> a, a the least."""
    r = lambda x, y: arcs.select(F.col("src").alias(x), F.col("dst").alias(y))
    return r("a", "b").join(r("b", "c"), "b").join(r("c", "a"), ["c", "a"]).where("a < b AND a < c AND b <> c").select("a", "b", "c")


def directed_paths3(arcs: DataFrame) -> DataFrame:
    """(a, b, c) of a -> b -> c with three nodes."""
    r = lambda x, y: arcs.select(F.col("src").alias(x), F.col("dst").alias(y))
    return r("a", "b").join(r("b", "c"), "b").where("a <> b AND b <> c AND a <> c").select("a", "b", "c")


def enumerate_pattern(edges: DataFrame, spec: MotifSpec, key: str | None = None) -> DataFrame:
    """Columns n0..n(k-1) of each occurrence of a pattern: a join for each of its edges, ordered so that each meets what is there."""
    keys = [key] if key else []
    both = edges.select(*keys, F.col("src").alias("x"), F.col("dst").alias("y")).unionByName(edges.select(*keys, F.col("dst").alias("x"), F.col("src").alias("y")))
    left, (i, j) = list(spec.edges[1:]), spec.edges[0]
    out, have = both.select(*keys, F.col("x").alias(f"n{i}"), F.col("y").alias(f"n{j}")), {i, j}

    def limits(df: DataFrame, new: int | None) -> DataFrame:
        for a, b in spec.less:
            if {a, b} <= have and (new is None or new in (a, b)):
                df = df.where(f"n{a} < n{b}")
        return df if new is None else df.where(" AND ".join(f"n{new} <> n{h}" for h in have if h != new))

    out = limits(out, None)
    while left:
        i, j = next(e for e in left if e[0] in have or e[1] in have)
        left.remove((i, j))
        if i not in have:
            i, j = j, i
        on = [*keys, f"n{i}", f"n{j}"] if j in have else [*keys, f"n{i}"]
        step = both.select(*keys, F.col("x").alias(f"n{i}"), F.col("y").alias(f"n{j}"))
        if j in have:
            out = out.join(step, on, "left_semi")
        else:
            have.add(j)
            out = limits(out.join(step, on), j)
    return out.select(*keys, *[f"n{i}" for i in range(spec.k)])


def occurrences(edges: DataFrame, spec: MotifSpec, key: str | None = None) -> DataFrame:
    """([key,] nodes, ways): node sets, ascending, with the number of occurrences on each."""
    keys = [key] if key else []
    if spec.name == "triangle":
        return triangles(edges, key).select(*keys, F.array("a", "b", "c").alias("nodes"), F.lit(1).cast("bigint").alias("ways"))
    if spec.name == "edge":
        return edges.select(*keys, F.array("src", "dst").alias("nodes"), F.lit(1).cast("bigint").alias("ways"))
    found = enumerate_pattern(edges, spec, key).select(*keys, F.array_sort(F.array(*[f"n{i}" for i in range(spec.k)])).alias("nodes"))
    return found.groupBy(*keys, "nodes").agg(F.count(F.lit(1)).alias("ways"))


def ball_occurrences(graph: MotifGraph, ball: DataFrame, spec: MotifSpec = TRIANGLE) -> DataFrame:
    """Occurrences of any motif that touch each ball, as touching() gives them; the halo is as wide as the pattern."""
    return touching(written(occurrences(written(near_edges(graph, ball, spec.halo), "near"), spec), "listed"), ball, spec.k)


def sampled_triangles(edges: DataFrame, p: float, salt: int = 3) -> DataFrame:
    """Triangles whose three edges a hash keeps, each with probability p."""
    kept = edges.where(mix(F.col("src") * 1_000_003 + F.col("dst"), salt) < int(p * PRIME))
    return triangles(kept)


def estimated_triangles(edges: DataFrame, p: float, salt: int = 3) -> DataFrame:
    """One row: (kept, estimate), the number of sampled triangles over p^3, whose expectation is the number of all."""
    return sampled_triangles(edges, p, salt).agg(F.count(F.lit(1)).alias("kept")).select("kept", (F.col("kept") / F.lit(p**3)).alias("estimate"))


def motif_degree(occ: DataFrame) -> DataFrame:
    """(node, dmu) from occurrences (nodes, ways)."""
    return occ.select(F.explode("nodes").alias("node"), "ways").groupBy("node").agg(F.sum("ways").alias("dmu"))
