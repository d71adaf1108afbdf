"""Two-way multilevel partitions of models, one group of tasks for each seed and ball, all trials of a group at once.

Coarsening merges nodes along heavy ratings, the coarsest model is split by greedy growths, and the split is improved by
passes of single moves on the way back. Trials are rows of matrices: GROUP trials share one chain of coarser models, and each step moves one node in
every trial. Trials differ in the allowed imbalance, the growth's start and the random order, drawn so that a trial's result does not depend on
how many others there are.
"""

from __future__ import annotations

import time
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from ..functions.hashing import PRIME, mix_int

OUT = -1
#: Trials that share a chain of coarser models. Numbers that the matrices of trials at once may hold. Larger than any volume.
GROUP, CELLS, FAR = 40, 64_000_000, 1 << 62


def runs(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """first[i], first[i] + 1, ... count[i] numbers, for each i."""
    ends = np.cumsum(count)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(first - ends + count, count)


@dataclass
class Model:
    """Weighted nets over nodes 0..n-1; a model edge is a net of two pins. Node 0 is the seed, node 1 is OUT.

    pins has a row for each net, filled up with n. dw is the volume of each node, which may count more than the nets at hand.
    """

    n: int
    pins: np.ndarray
    weight: np.ndarray
    size: np.ndarray
    dw: np.ndarray

    def __post_init__(self):
        self.k = (self.pins < self.n).sum(1)
        net, slot = np.nonzero(self.pins < self.n)
        node = self.pins[net, slot]
        order = np.argsort(node, kind="stable")
        self.node, self.of = node[order], net[order]
        self.at = np.searchsorted(self.node, np.arange(self.n + 1))

    @cached_property
    def near(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(from, to, rating, first of each node): neighbours over all nets, a net's weight shared by its other pins; wide nets say little and are left out."""
        a, b, r = [], [], []
        narrow = self.k <= 50
        for i in range(self.pins.shape[1]):
            for j in range(i + 1, self.pins.shape[1]):
                use = np.flatnonzero((self.pins[:, j] < self.n) & narrow)
                a.append(self.pins[use, i])
                b.append(self.pins[use, j])
                r.append(self.weight[use] / (self.k[use] - 1))
        key, back = np.unique(np.concatenate(a) * self.n + np.concatenate(b), return_inverse=True) if a else (np.zeros(0, np.int64), np.zeros(0, np.int64))
        rating = np.bincount(back, np.concatenate(r), len(key)) if len(key) else np.zeros(0)
        a, b = key // max(self.n, 1), key % max(self.n, 1)
        source, target, rating = np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([rating, rating])
        order = np.argsort(source, kind="stable")
        return source[order], target[order], rating[order], np.searchsorted(source[order], np.arange(self.n + 1))

    def cut(self, side: np.ndarray) -> np.ndarray:
        """Of one side (n) or several (trials, n): the weight of nets with pins on both sides."""
        return Sides(self, np.atleast_2d(side)).cut if side.ndim > 1 else int(Sides(self, side[None]).cut[0])

    def volume(self, side: np.ndarray) -> np.ndarray:
        return side @ self.dw if side.ndim > 1 else int(side @ self.dw)


def merged(pins: np.ndarray, weight: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Nets as sets, equal ones as one with their weights' sum, those of one pin dropped."""
    p = np.sort(pins, axis=1)
    again = np.zeros(p.shape, bool)
    again[:, 1:] = p[:, 1:] == p[:, :-1]
    p = np.sort(np.where(again, n, p), axis=1)
    keep = (p < n).sum(1) > 1
    p, weight = p[keep], weight[keep]
    if not len(p):
        return p, weight
    if float(n + 1) ** p.shape[1] < 2.0**62:
        _, first, back = np.unique(p @ (n + 1) ** np.arange(p.shape[1] - 1, -1, -1), return_index=True, return_inverse=True)
    else:
        _, first, back = np.unique(p, axis=0, return_index=True, return_inverse=True)
    return p[first], np.bincount(back.ravel(), weight, len(first)).astype(np.int64)


def from_nets(pins: list[np.ndarray], weight: np.ndarray, n: int, size: np.ndarray) -> Model:
    """The model of nets given as lists of nodes; each net adds its weight to the volume of its nodes, nets of one pin too."""
    wide = max(2, *map(len, pins)) if len(pins) else 2
    full = np.full((len(pins), wide), n, np.int64)
    for i, p in enumerate(pins):
        full[i, : len(p)] = p
    return model_of(full, np.asarray(weight, np.int64), n, size)


def model_of(pins: np.ndarray, weight: np.ndarray, n: int, size: np.ndarray) -> Model:
    dw = np.bincount(pins.ravel(), np.repeat(weight, pins.shape[1]), n + 1)[:n].astype(np.int64)
    return Model(n, *merged(pins, weight, n), size, dw)


class Sides:
    """The sides of several trials of a model, with cuts, volumes and the gain of every single move kept up to date."""

    def __init__(self, m: Model, side: np.ndarray):
        self.m, self.side = m, np.concatenate([side, np.zeros((len(side), 1), bool)], 1)
        edges = m.pins.shape[1] == 2
        if edges:
            cut = self.side[:, m.pins[:, 0]] != self.side[:, m.pins[:, 1]]
        else:
            self.inside = np.zeros((len(side), len(m.weight)), np.int32)
            for j in range(m.pins.shape[1]):
                self.inside += self.side[:, m.pins[:, j]]
            cut = self._crossing(self.inside, m.k)
        self.cut = (m.weight * cut).sum(1)
        self.vol, self.held = side @ m.dw, side @ m.size
        self.gain = np.zeros((len(side), m.n + 1), np.int64)
        if len(m.of):
            # An edge across is no longer cut once an end moves, any other then is.
            part = np.where(cut, m.weight, -m.weight)[:, m.of] if edges else m.weight[m.of] * self._relief(self.inside[:, m.of], m.k[m.of], self.side[:, m.node])
            has = np.flatnonzero(np.diff(m.at))
            self.gain[:, has] = np.add.reduceat(part, m.at[has], axis=1)

    @staticmethod
    def _crossing(inside: np.ndarray, k: np.ndarray) -> np.ndarray:
        return (inside > 0) & (inside < k)

    @classmethod
    def _relief(cls, inside: np.ndarray, k: np.ndarray, s: np.ndarray) -> np.ndarray:
        """1 where a net of k pins is no longer cut once a pin on side s moves, -1 where it then is, 0 otherwise."""
        return cls._crossing(inside, k).astype(np.int64) - cls._crossing(inside + 1 - 2 * s.astype(np.int32), k)

    def flip(self, trial: np.ndarray, v: np.ndarray) -> None:
        """Moves node v[i] in trial[i]; each trial at most once."""
        m, s, g = self.m, self.side[trial, v], self.gain[trial, v]
        step = 1 - 2 * s.astype(np.int32)
        self.cut[trial] -= g
        self.vol[trial] += step * m.dw[v]
        self.held[trial] += step * m.size[v]
        count = m.at[v + 1] - m.at[v]
        row = np.repeat(np.arange(len(v)), count)
        net, t = m.of[runs(m.at[v], count)], trial[row]
        if m.pins.shape[1] == 2:  # edges: the other end gains by a move if it now lies across, and loses otherwise
            u = m.pins[net, 0] + m.pins[net, 1] - v[row]
            self.gain[t, u] += np.where(self.side[t, u] == s[row], 2, -2) * m.weight[net]
            self.side[trial, v], self.gain[trial, v] = ~s, -g
            return
        before = self.inside[t, net]
        after, k, w, moved = before + step[row], m.k[net], m.weight[net], v[row]
        for j in range(m.pins.shape[1]):
            u = m.pins[net, j]
            su = self.side[t, u]
            change = w * (self._relief(after, k, su) - self._relief(before, k, su))
            use = np.flatnonzero((change != 0) & (u != moved) & (u < m.n))
            np.add.at(self.gain, (t[use], u[use]), change[use])
        self.inside[t, net] = after
        self.side[trial, v] = ~s
        self.gain[trial, v] = -g


def coarsen(m: Model, rng: np.random.Generator, most: int, fixed: bool) -> tuple[Model, np.ndarray] | None:
    """One level: nodes that are each other's best neighbour merge, in rounds; then free nodes with the same best neighbour do. Seed and OUT never merge with each other; in fixed mode they take no partner."""
    source, target, rating, at = m.near
    if not len(source):
        return None
    noise = rng.random(m.n)
    bound = max(2, 3 * int(m.size.sum()) // (2 * most))
    rate = rating / (m.size[source] * m.size[target]) * (0.75 + (noise[source] + noise[target]) % 1 / 2)
    rate[(m.size[source] + m.size[target] > bound) | ((source < 2) & (target < 2))] = 0
    if fixed:
        rate[(source < 2) | (target < 2)] = 0
    some = np.flatnonzero(np.diff(at))
    mate, free = np.arange(m.n), np.ones(m.n, bool)

    def best(r: np.ndarray) -> np.ndarray:
        top = np.zeros(m.n)
        top[some] = np.maximum.reduceat(r, at[some])
        hit = np.flatnonzero((r > 0) & (r == top[source]))[::-1]
        pick = np.full(m.n, -1)
        pick[source[hit]] = target[hit]
        return pick

    for _ in range(8):
        pick = best(np.where(free[source] & free[target], rate, 0))
        v = np.flatnonzero(pick >= 0)
        v = v[(pick[pick[v]] == v) & (v < pick[v])]
        if not len(v):
            break
        mate[pick[v]] = v
        free[v] = free[pick[v]] = False
    lone = np.flatnonzero(free & (np.arange(m.n) > 1))
    pick = best(rate)[lone]
    lone = lone[pick >= 0][np.argsort(pick[pick >= 0], kind="stable")]
    pick = best(rate)[lone]
    pair = np.flatnonzero((pick[1:] == pick[:-1]) & (m.size[lone[1:]] + m.size[lone[:-1]] <= bound)) if len(lone) > 1 else np.zeros(0, np.int64)
    start = np.concatenate([[True], np.diff(pair) > 1]) if len(pair) else np.zeros(0, bool)
    pair = pair[(np.arange(len(pair)) - np.maximum.accumulate(np.where(start, np.arange(len(pair)), 0))) % 2 == 0]
    a, b = lone[pair], lone[pair + 1]
    mate[np.maximum(a, b)] = np.minimum(a, b)
    heads = np.unique(mate)
    if len(heads) > 0.95 * m.n:
        return None
    label = np.searchsorted(heads, mate)
    # A head has the smaller number of its pair, so that seed and OUT stay 0 and 1.
    n = len(heads)
    pins, weight = merged(np.append(label, n)[m.pins], m.weight, n)
    return Model(n, pins, weight, np.bincount(label, m.size, n).astype(np.int64), np.bincount(label, m.dw, n).astype(np.int64)), label


def grown(m: Model, bound: np.ndarray, start: np.ndarray, noise: np.ndarray) -> np.ndarray:
    """A block for each trial, grown from its start by highest attachment and noise, up to half the weight, never over OUT."""
    source, target, rating, at = m.near
    every = np.arange(len(start))
    side, pull, held = np.zeros((len(start), m.n), bool), np.zeros((len(start), m.n)), np.zeros(len(start), np.int64)
    goal, per = np.minimum(bound, int(m.size.sum()) // 2), np.maximum(m.dw, 1)
    trial, v = every, start
    while len(trial):
        side[trial, v] = True
        held[trial] += m.size[v]
        count = at[v + 1] - at[v]
        e = runs(at[v], count)
        pull[np.repeat(trial, count), target[e]] += rating[e]
        score = np.where(~side & (m.size <= (bound - held)[:, None]), pull / per + noise, -1.0)
        score[:, 1] = -1
        best = score.argmax(1)
        trial = np.flatnonzero((held < goal) & (score[every, best] >= 0))
        v = best[trial]
    return side


def improve(s: Sides, bound: np.ndarray, fixed: bool, passes: int = 3, patience: int = 40) -> None:
    """Passes of single moves by best gain under the balance bound, each node once, rolled back to the best prefix."""
    m, trials = s.m, len(s.cut)
    total, largest, low = int(m.size.sum()), int(m.size.max()), np.iinfo(np.int64).min
    going = np.ones(trials, bool)
    for _ in range(passes):
        locked = np.zeros((trials, m.n), bool)
        locked[:, :2] = fixed
        best, keep, live, moves = s.cut.copy(), np.zeros(trials, np.int64), going.copy(), []
        while True:
            live &= len(moves) - keep < patience
            t = np.flatnonzero(live)
            if not len(t):
                break
            rows = slice(None) if len(t) == trials else t
            gain = np.where(locked[rows], low, s.gain[rows, : m.n])
            room_in, room_out = bound[t] - s.held[t], bound[t] - (total - s.held[t])
            tight = np.flatnonzero(np.minimum(room_in, room_out) < largest)
            if len(tight):  # elsewhere there is room for any node
                fits = np.where(s.side[t[tight], : m.n], m.size <= room_out[tight, None], m.size <= room_in[tight, None])
                gain[tight] = np.where(fits, gain[tight], low)
            v = gain.argmax(1)
            some = gain[np.arange(len(t)), v] > low
            live[t[~some]] = False
            t, v = t[some], v[some]
            if not len(t):
                break
            s.flip(t, v)
            locked[t, v] = True
            moves.append((t, v))
            better = t[s.cut[t] < best[t]]
            best[better], keep[better] = s.cut[better], len(moves)
        for i in range(len(moves) - 1, -1, -1):
            t, v = moves[i]
            back = keep[t] <= i
            if back.any():
                s.flip(t[back], v[back])
        going &= keep > 0
        if not going.any():
            break


def max_block(n: int, eps: float | np.ndarray):
    """The most nodes that a block may hold: (1 + eps) times the ceiling of half."""
    return np.floor((1 + np.asarray(eps)) * ((n + 1) // 2)).astype(np.int64) if np.ndim(eps) else int((1 + eps) * ((n + 1) // 2))


def repaired(side: np.ndarray) -> np.ndarray:
    """Sides turned so that OUT lies outside; a seed that came to lie with OUT is then put inside."""
    side = np.where(side[:, 1:2], ~side, side)
    side[:, 0] = True
    return side


def bisect(m: Model, eps: np.ndarray, rng: np.random.Generator, fixed: bool = False, strong: bool = False, coarsest: int = 40, offset: int = 0) -> np.ndarray:
    """(trials, n): whether each node is in the seed's block, one trial for each imbalance. Seed and OUT part by repair at the end, or are kept apart as fixed nodes."""
    eps, n_tries = np.atleast_1d(eps), 12 if strong else 4
    trials, total = len(eps), int(m.size.sum())
    bound = np.minimum(max_block(total, eps), total - 1)
    levels, labels = [m], []
    while levels[-1].n > coarsest and (step := coarsen(levels[-1], rng, coarsest, fixed)):
        levels.append(step[0])
        labels.append(step[1])
    c = levels[-1]
    # All of GROUP is drawn, so that a trial, the offset-th and on, does not depend on which others there are.
    start, noise = rng.integers(0, c.n, (n_tries, GROUP)), rng.random((n_tries, GROUP, c.n))
    start[: n_tries // 2], noise[0] = 0, 0
    start[(start == 1) | fixed] = 0
    own = slice(offset, offset + trials)
    side = grown(c, np.tile(bound, n_tries), start[:, own].ravel(), noise[:, own].reshape(-1, c.n) * 0.5)
    s = Sides(c, side)
    improve(s, np.tile(bound, n_tries), fixed, 8 if strong else 4)
    poor = ~np.isin(s.held, (0, total)).reshape(n_tries, trials)
    pick = np.where(poor, s.cut.reshape(n_tries, trials), FAR).argmin(0)
    side = s.side[pick * trials + np.arange(trials), : c.n]
    for fine, label in zip(levels[-2::-1], labels[::-1], strict=True):
        s = Sides(fine, side[:, label])
        improve(s, bound, fixed, 8 if strong else 3)
        side = s.side[:, : fine.n]
    return repaired(side)


def less(cut, vol, cut2, vol2, total: int) -> np.ndarray:
    """-1, 0 or 1 as the first ratio is below, at or above the second; an empty side ranks last. Whole numbers are compared as such while products fit."""
    cut, vol, cut2, vol2 = (np.asarray(x, np.int64) for x in (cut, vol, cut2, vol2))
    a, b = np.minimum(vol, total - vol), np.minimum(vol2, total - vol2)
    big = max(int(np.max(vol, initial=0)), int(np.max(vol2, initial=0))) >= 1 << 31
    x, y = (cut / np.maximum(a, 1), cut2 / np.maximum(b, 1)) if big else (cut * b, cut2 * a)
    none_a, none_b = a <= 0, b <= 0
    return np.where(none_a | none_b, none_a.astype(np.int64) - none_b, np.sign(x - y).astype(np.int64))


def search(m: Model, side: np.ndarray, total: int, rounds: int, order: np.random.Generator, coins: list[tuple[np.random.Generator, int, int]] | None = None) -> np.ndarray:
    """Label moves on the objective itself, in a random order that the trials share: a move that lowers it is made, one that leaves it equal by a coin; seed and OUT stay.

    A trial ends after a round without a lower value, or at the cap; the best state seen is returned. coins: for each GROUP of trials a generator, and which of its trials are here.
    """
    one = side.ndim == 1
    s = Sides(m, np.atleast_2d(side))
    cut, vol, kept, going = s.cut.copy(), s.vol.copy(), s.side.copy(), np.ones(len(s.cut), bool)
    coins = coins or [(order, 0, min(GROUP, len(going) - a)) for a in range(0, len(going), GROUP)]
    movable = np.flatnonzero(np.diff(m.at) > 0)
    movable = movable[movable > 1]
    for _ in range(rounds):
        lower = np.zeros(len(going), bool)
        visit = order.permutation(movable).tolist()
        heads = np.concatenate([c.random((len(movable), GROUP), np.float32)[:, a : a + n] < 0.5 for c, a, n in coins], 1)
        for i, v in enumerate(visit):
            c = less(s.cut - s.gain[:, v], s.vol + np.where(s.side[:, v], -m.dw[v], m.dw[v]), s.cut, s.vol, total)
            move = going & ((c < 0) | ((c == 0) & heads[i]))
            if move.any():
                t = np.flatnonzero(move)
                s.flip(t, np.full(len(t), v))
                lower |= move & (c < 0)
        better = less(s.cut, s.vol, cut, vol, total) < 0
        cut[better], vol[better], kept[better] = s.cut[better], s.vol[better], s.side[better]
        going &= lower
        if not going.any():
            break
    return kept[0, : m.n] if one else kept[:, : m.n]


def eps_of(seed: int, ball_no: int, trial: int, salt: int, low: float = 0.0, high: float = 0.95) -> float:
    """The trial's imbalance, uniform in a range."""
    return low + (high - low) * mix_int(seed * 1009 + ball_no * 131 + trial, 31 + salt) / PRIME


SIDES = "seed long, ball_no int, trial int, eps double, cut long, vol long, members array<long>, seconds double"


def as_nets(model: DataFrame, kind: str) -> DataFrame:
    """(seed, ball_no, pins, weight) of a graph model (u, v, weight) or a hypergraph model."""
    return model.select("seed", "ball_no", F.array("u", "v").alias("pins"), "weight") if kind == "graph" else model.select("seed", "ball_no", "pins", "weight")


def partition_models(model: DataFrame, total: int, kind: str = "graph", n_trials: int = 80, search_rounds: int = 10, fixed: bool = False, effort: str = "fast", salt: int = 0, time_budget_s: float = 3600.0, nodes: DataFrame | None = None, groups: int = 0, cells: int = CELLS) -> DataFrame:
    """(seed, ball_no, trial, eps, cut, vol, members, seconds) for every trial; members hold the seed's block, for the best trial of a task only.

    model: graph (u, v, weight) or hypergraph (pins, weight) keyed by seed and ball_no. total: the graph's motif volume in units of the model; FAR
    takes the seed's block for the smaller side. nodes: (seed, ball_no, node, size, extra) of model nodes, for those without nets and for merged ones, whose `extra` volume no net shows.
    The search is for the graph model. Trials of a model are dealt to more tasks, each with a copy of the model, only if there are fewer models
    (`groups`) than cores. The time limit holds from the call on and is tested between groups of trials; the first group of a model always runs, and trials that did not run have no row.
    """
    search_rounds = search_rounds if kind == "graph" else 0
    cores = model.sparkSession.sparkContext.defaultParallelism
    waves = max(1, min(-(-n_trials // GROUP), -(-2 * cores // max(groups, 1)) if groups else 1))
    per = -(-n_trials // waves // GROUP) * GROUP
    rows = as_nets(model, kind).withColumns({"size": F.lit(0).cast("long")})
    if nodes is not None:
        rows = rows.unionByName(nodes.select("seed", "ball_no", F.array("node").alias("pins"), F.col("extra").cast("long").alias("weight"), F.col("size").cast("long").alias("size")))
    rows = rows.withColumn("wave", F.explode(F.sequence(F.lit(0), F.lit(waves - 1))))
    deadline, none = time.time() + time_budget_s, to_arrow_schema(StructType.fromDDL(SIDES)).empty_table()

    def run(group: pa.Table) -> pa.Table:
        seed, ball, wave = (int(group.column(c)[0].as_py()) for c in ("seed", "ball_no", "wave"))
        pins = group.column("pins").combine_chunks()
        count, flat = np.diff(pins.offsets.to_numpy()), pins.flatten().to_numpy()
        weight, size = group.column("weight").to_numpy(), group.column("size").to_numpy()
        ids = np.unique(np.concatenate([flat, [seed, OUT]]))
        ids = np.concatenate([[seed, OUT], ids[(ids != seed) & (ids != OUT)]])
        order = np.argsort(ids)
        place, n = order[np.searchsorted(ids[order], flat)], len(ids)
        full = np.full((len(count), max(2, count.max())), n, np.int64)
        full[np.repeat(np.arange(len(count)), count), runs(np.zeros(len(count), np.int64), count)] = place
        own, sizes = size > 0, np.ones(n, np.int64)
        sizes[full[own, 0]] = size[own]
        sort = np.lexsort(full.T[::-1])
        m = model_of(full[sort], weight[sort], n, sizes)
        began, last = time.time(), min((wave + 1) * per, n_trials)
        # Trials at once as memory allows; what a trial gives does not depend on it.
        at_once = max(1, cells // (n + len(m.weight)))
        whole = at_once >= last - wave * per
        batches = [(f, a, min(a + at_once, f + GROUP, last)) for f in range(wave * per, last, GROUP) for a in range(f, min(f + GROUP, last), at_once)]
        eps_all, sides = [], []
        coin = lambda f, a, b: (np.random.default_rng([seed, ball, f, salt, 1]), a - f, b - a)
        for f, a, b in batches:
            if a and time.time() > deadline:
                break
            eps_all.append(np.array([eps_of(seed, ball, t, salt) for t in range(a, b)]))
            sides.append(bisect(m, eps_all[-1], np.random.default_rng([seed, ball, f, salt]), fixed, effort == "strong", offset=a - f))
            if search_rounds and not whole:
                sides[-1] = search(m, sides[-1], total, search_rounds, np.random.default_rng([seed, ball, salt]), [coin(f, a, b)])
        if not sides:
            return none
        eps, side = np.concatenate(eps_all), np.concatenate(sides)
        if search_rounds and whole:
            side = search(m, side, total, search_rounds, np.random.default_rng([seed, ball, salt]), [coin(*x) for x in batches[: len(sides)]])
        cut, vol = m.cut(side), m.volume(side)
        small = np.minimum(vol, total - vol)
        best = int(np.where(small > 0, cut / np.maximum(small, 1), np.inf).argmin())
        done = len(eps)
        members = [np.sort(ids[side[best]]) if i == best else None for i in range(done)]
        cols = [np.full(done, seed), np.full(done, ball, np.int32), np.arange(wave * per, wave * per + done, dtype=np.int32), eps, cut, vol, pa.array(members, pa.list_(pa.int64())), np.full(done, (time.time() - began) / done)]
        return pa.table(cols, ["seed", "ball_no", "trial", "eps", "cut", "vol", "members", "seconds"])

    return rows.groupBy("seed", "ball_no", "wave").applyInArrow(run, SIDES)
