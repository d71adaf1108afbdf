"""Token ids on disk as Re-Pair grammars: rounds replace frequent id pairs by nonterminals, per shard.

A shard holds a run of documents in ascending doc_id order. Its record stores the rules as pairs, the length each rule expands to
and the shortened sequence, so that any stretch of ids is decoded without the rest. A round counts pairs through a hashed
histogram, takes the most frequent exactly, and replaces all their occurrences that do not overlap, from the left.
Null text counts as empty (its end id alone); repeated rows give a row each; an empty table makes no shard.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import parts_for, ready, shard_bounds, written
from .tokens import code_points, encoder

TERMINALS = 1 << 16
CELL_BITS = 18
#: Shards whose sizes are summed up in one task.
RUN = 4096
FIELDS = "shard long, n_ids long, doc_ids binary, doc_tokens binary, rules binary, lengths binary, sequence binary"


@dataclass
class Grammar:
    """rules[i] is the pair that symbol TERMINALS + i stands for, lengths[i] the number of ids it expands to."""

    rules: np.ndarray
    lengths: np.ndarray
    sequence: np.ndarray

    def _expansions(self) -> tuple[np.ndarray, np.ndarray]:
        """All rules' ids end to end, and where each begins. Rules refer to earlier symbols only."""
        first = np.cumsum(self.lengths) - self.lengths
        flat = np.zeros(int(self.lengths.sum()), np.uint32)
        for a, b in self._rounds():
            to = first[a:b].copy()
            for side in (0, 1):
                s = self.rules[a:b, side].astype(np.int64)
                plain = s < TERMINALS
                flat[to[plain]] = s[plain]
                r = s[~plain] - TERMINALS
                n = self.lengths[r]
                step = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
                flat[np.repeat(to[~plain], n) + step] = flat[np.repeat(first[r], n) + step]
                size = np.ones(b - a, np.int64)
                size[~plain] = n
                to += size
        return flat, first

    def _stretch(self, symbols: np.ndarray, skip: int, length: int) -> np.ndarray:
        """ids of a few symbols, each round one level down, with only the rules that they reach; symbols that lie wholly before or behind the stretch go at once."""
        while True:
            rule = symbols - TERMINALS
            n = np.where(rule < 0, 1, self.lengths[np.maximum(rule, 0)] if len(self.lengths) else 1)
            ends = np.cumsum(n)
            a, b = np.searchsorted(ends, skip, "right"), np.searchsorted(ends, skip + length - 1, "right") + 1
            skip -= int(ends[a] - n[a])
            symbols, rule = symbols[a:b], rule[a:b]
            down = rule >= 0
            if not down.any():
                return symbols[skip : skip + length].astype(np.uint32)
            pair = np.zeros((len(symbols), 2), np.int64)
            pair[:, 0] = symbols
            pair[down] = self.rules[rule[down]]
            keep = np.ones((len(symbols), 2), bool)
            keep[~down, 1] = False
            symbols = pair[keep]

    def _rounds(self) -> Iterator[tuple[int, int]]:
        """Runs of rules that refer to symbols before the run only."""
        a = 0
        top = self.rules.max(1).astype(np.int64) - TERMINALS if len(self.rules) else np.zeros(0, np.int64)
        while a < len(top):
            beyond = np.flatnonzero(top[a:] >= a)
            b = a + int(beyond[0]) if len(beyond) else len(top)
            yield a, b
            a = b

    def sizes(self) -> np.ndarray:
        s = self.sequence.astype(np.int64) - TERMINALS
        return np.where(s < 0, 1, self.lengths[np.maximum(s, 0)] if len(self.lengths) else 1)

    def decode(self, start: int = 0, length: int | None = None) -> np.ndarray:
        """ids [start, start + length): only the symbols that hold them are expanded."""
        size = self.sizes()
        ends = np.cumsum(size)
        total = int(ends[-1]) if len(ends) else 0
        stop = total if length is None else min(start + length, total)
        if start >= stop:
            return np.zeros(0, np.uint32)
        a, b = np.searchsorted(ends, start, "right"), np.searchsorted(ends, stop - 1, "right") + 1
        s, n = self.sequence[a:b].astype(np.int64), size[a:b]
        if b - a < len(self.sequence):
            return self._stretch(s, start - int(ends[a] - size[a]), stop - start)
        flat, first = self._expansions()
        flat = np.concatenate([flat, s[s < TERMINALS].astype(np.uint32)])
        source = np.empty(len(s), np.int64)
        source[s >= TERMINALS] = first[s[s >= TERMINALS] - TERMINALS]
        source[s < TERMINALS] = np.arange(len(flat) - int((s < TERMINALS).sum()), len(flat))
        e = np.cumsum(n)
        out = flat[np.repeat(source - e + n, n) + np.arange(e[-1])]
        skip = start - int(ends[a] - size[a])
        return out[skip : skip + stop - start]


def _cells(pairs: np.ndarray) -> np.ndarray:
    """A cell of the histogram for each pair; so few that its tables stay in a core's cache."""
    return (pairs * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - CELL_BITS)).astype(np.int64)


def compress(ids: np.ndarray, least: int = 6, per_round: int = 4096) -> Grammar:
    """Ends when no pair occurs `least` times.

    A round replaces up to per_round pairs at once, the most frequent of those in its cells, where one at a time would be the textbook way. Once a round over
    the whole sequence has reached pairs of `least`, the next ones look only where it has put new symbols, until nothing is frequent there; a round over the whole comes last.
    """
    seq = ids.astype(np.uint32)
    rules, lengths = np.zeros((0, 2), np.uint32), np.zeros(0, np.int64)
    fresh = None
    while len(seq) > 1:
        if fresh is None:
            pos, left, right = None, seq[:-1], seq[1:]
        else:
            new = seq >= fresh
            pos = np.flatnonzero(new[:-1] | new[1:])
            left, right = seq[pos], seq[pos + 1]
        key = left.astype(np.uint64) << np.uint64(32) | right
        cell = _cells(key)
        heat = np.bincount(cell, minlength=1 << CELL_BITS)
        bound = max(least, int(np.partition(heat, -per_round)[-per_round])) if per_round < len(heat) else least
        use = np.flatnonzero((heat >= bound)[cell])
        key, cell = key[use], cell[use]
        at = use if pos is None else pos[use]
        pairs, count = np.unique(key, return_counts=True)
        good = count >= least
        pairs, count = pairs[good], count[good]
        if not len(pairs):
            if fresh is not None:
                fresh = None
                continue
            if bound == least:
                break
            # The hottest cells hold no frequent pair; a cell of pairs below the bound may.
            per_round = 1 << CELL_BITS
            continue
        fresh = TERMINALS + len(rules) if fresh is not None or bound == least else None
        if len(pairs) > per_round:
            best = np.argsort(-count, kind="stable")[:per_round]
            pairs, count = pairs[best], count[best]
        # From cells to pairs; of pairs that share a cell the most frequent is replaced in this round.
        slot = np.full(1 << CELL_BITS, -1, np.int32)
        by_count = np.argsort(count, kind="stable")
        slot[_cells(pairs[by_count])] = by_count
        which = slot[cell].astype(np.int64)
        hit = (which >= 0) & (pairs[which] == key)
        at, which = at[hit], which[hit]
        head = np.r_[True, np.diff(at) > 1]
        odd = (at - at[np.maximum.accumulate(np.where(head, np.arange(len(at)), 0))]) % 2 == 0
        at, which = at[odd], which[odd]
        used, which = np.unique(which, return_inverse=True)
        new = np.stack([pairs[used] >> np.uint64(32), pairs[used] & np.uint64(0xFFFFFFFF)], 1).astype(np.uint32)
        old = new.astype(np.int64) - TERMINALS
        size = np.where(old < 0, 1, lengths[np.maximum(old, 0)] if len(lengths) else 1).sum(1)
        seq[at] = TERMINALS + len(rules) + which
        keep = np.ones(len(seq), bool)
        keep[at + 1] = False
        seq = seq[keep]
        rules, lengths = np.concatenate([rules, new]), np.concatenate([lengths, size])
    return Grammar(rules, lengths, seq)


def write_shards(docs: DataFrame, path: str, end_id: int = 2, doc_id: str = "doc_id", text: str = "text", shard_bytes: int = 4 << 20) -> DataFrame:
    """Encodes each text, appends end_id, and writes one record per shard of documents; returns the table as read back.

    Shards are runs of doc_id between quantiles of that column alone, so the texts move once; the bounds, a number a shard, pass through the driver.
    Rows of one id are ordered by text.
    """
    ready(docs.sparkSession)
    docs = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    bounds = np.array(shard_bounds(docs, "doc_id", parts_for(docs, shard_bytes)), np.int64)

    def placed(batches):
        for batch in batches:
            shard = np.searchsorted(bounds, batch.column(0).fill_null(-(1 << 63)).to_numpy(zero_copy_only=False), "right")
            yield pa.RecordBatch.from_arrays([pa.array(shard), batch.column(0), batch.column(1)], ["shard", "doc_id", "text"])

    def shard(group: pa.Table) -> pa.Table:
        e = encoder("tokenizers", path)
        group = group.sort_by([("doc_id", "ascending"), ("text", "ascending")])
        ids = []
        counts = []
        for i in range(0, group.num_rows, 500):
            got, n = e.encode(*code_points(group.column("text").slice(i, 500)))
            at = np.cumsum(n)
            ids.append(np.insert(got.astype(np.uint32), at, end_id))
            counts.append(n + 1)
        ids, counts = np.concatenate(ids), np.concatenate(counts)
        g = compress(ids)
        null = [group.column("shard")[0].as_py(), len(ids), group.column("doc_id").fill_null(-(1 << 63)).to_numpy().astype("<i8").tobytes(), counts.astype("<u4").tobytes(), g.rules.astype("<u4").tobytes(), g.lengths.astype("<u4").tobytes(), _packed(g.sequence)]
        return pa.table([pa.array([x], t) for x, t in zip(null, [pa.int64()] * 2 + [pa.binary()] * 5, strict=True)], ["shard", "n_ids", "doc_ids", "doc_tokens", "rules", "lengths", "sequence"])

    return written(docs.mapInArrow(placed, "shard long, doc_id long, text string").groupBy("shard").applyInArrow(shard, FIELDS), "repair")


def _packed(sequence: np.ndarray) -> bytes:
    """Three bytes a symbol, laid out by significance, which the file's codec shortens further."""
    return np.ascontiguousarray(sequence.astype("<u4").view(np.uint8).reshape(-1, 4)[:, :3].T).tobytes()


def grammar(rules: bytes, lengths: bytes, sequence: bytes) -> Grammar:
    planes = np.frombuffer(sequence, np.uint8).reshape(3, -1).astype(np.uint32)
    return Grammar(np.frombuffer(rules, "<u4").reshape(-1, 2), np.frombuffer(lengths, "<u4").astype(np.int64), planes[0] | planes[1] << 8 | planes[2] << 16)


def read_documents(shards: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of each document, from the written records alone."""
    # Sums of runs of shards first, so that no task sees all shards' sizes.
    sizes = shards.select("shard", "n_ids", F.floor(F.col("shard") / RUN).alias("run"))
    runs = sizes.groupBy("run").agg(F.sum("n_ids").alias("all"))
    ahead = runs.select("run", (F.sum("all").over(Window.orderBy("run")) - F.col("all")).alias("ahead"))
    inside = F.sum("n_ids").over(Window.partitionBy("run").orderBy("shard")) - F.col("n_ids")
    before = sizes.withColumn("inside", inside).join(ahead, "run").select("shard", (F.col("ahead") + F.col("inside")).alias("before"))

    def read(batches):
        for batch in batches:
            for row in batch.to_pylist():
                ids = grammar(row["rules"], row["lengths"], row["sequence"]).decode().astype("<u4")
                n = np.frombuffer(row["doc_tokens"], "<u4").astype(np.int64)
                at = np.cumsum(n) - n
                raw = memoryview(ids.tobytes())
                crc = [zlib.crc32(raw[4 * a : 4 * (a + k)]) for a, k in zip(at.tolist(), n.tolist(), strict=True)]
                doc = np.frombuffer(row["doc_ids"], "<i8")
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), row["shard"])), pa.array(doc, mask=doc == -(1 << 63)), pa.array(at), pa.array(n), pa.array(crc, pa.int64())], ["shard", "doc_id", "at", "n_tokens", "ids_crc32"])

    rows = shards.select("shard", "doc_ids", "doc_tokens", "rules", "lengths", "sequence").mapInArrow(read, "shard long, doc_id long, at long, n_tokens long, ids_crc32 long")
    return rows.join(before, "shard").select("doc_id", (F.col("before") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")
