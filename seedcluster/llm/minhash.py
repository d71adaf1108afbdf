"""MinHash near-duplicates: universal hash minima, banding, signature check, full-set check, components.

Edge cases: null or wordless text has an empty set, is linked with nothing and stays its own component; fewer words than
a shingle make one shingle of the whole sequence; repeated rows of one id count as one document whose rows are joined by
their id; equal sets are one class before any pair is made, so copies never meet pairwise; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BASE, CODES, LOWER, chunks, lean, lean_group, mix64, parts_for, ready, spans_hash, utf8, with_least, word_spans, written
from .components import components

BANDS, ROWS = 32, 4
#: A pair whose signatures agree on less than this share is dropped unverified: 0.8 less seven standard errors of 128 minima.
AGREE = 0.56


def shingle_sets(column: pa.Array, width: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, row of each distinct shingle, its hash) by chunks of the batch; sorted by row and hash."""
    raw, offsets = utf8(column)
    for a, b in chunks(np.diff(offsets)):
        part, off = LOWER[raw[offsets[a] : offsets[b]]], offsets[a : b + 1] - offsets[a]
        starts, ends, row = word_spans(part, off)
        if not len(starts):
            yield a, np.zeros(0, np.int64), np.zeros(0, np.uint64)
            continue
        words = spans_hash(CODES[part], starts, ends)
        count = np.bincount(row, minlength=b - a)
        first = np.concatenate([[0], np.cumsum(count)])
        at = np.arange(len(words)) - first[row]
        whole = np.flatnonzero((count > 0) & (count < width))
        go = np.flatnonzero(at + width <= count[row])
        salt = [mix64(np.array([i + 11], np.uint64) * BASE)[0] | np.uint64(1) for i in range(width)]
        got = np.zeros(len(go), np.uint64)
        for i in range(width):
            got += words[go + i] * salt[i]
        got, got_row = mix64(got), row[go]
        short, short_row = [], []
        for r in whole:
            h = np.uint64(count[r])
            for i in range(count[r]):
                h = mix64(np.array([h], np.uint64) + words[first[r] + i : first[r] + i + 1] * salt[i])[0]
            short.append(h)
            short_row.append(r)
        got, got_row = np.concatenate([got, np.array(short, np.uint64)]), np.concatenate([got_row, np.array(short_row, np.int64)])
        order = np.lexsort((got, got_row))
        got, got_row = got[order], got_row[order]
        new = np.ones(len(got), bool)
        new[1:] = (got[1:] != got[:-1]) | (got_row[1:] != got_row[:-1])
        yield a, got_row[new], got[new]


def _hashes(n: int) -> tuple[np.ndarray, np.ndarray]:
    x = mix64(np.arange(1, 2 * n + 1, dtype=np.uint64) * BASE)
    return x[:n] | np.uint64(1), x[n:]


def signatures(docs: DataFrame, width: int, n_hashes: int, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_shingles, same: hash of the whole set as two longs, sig: minima as 32-bit integers)."""
    mul, add = _hashes(n_hashes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            size, same_a, same_b = np.zeros(n, np.int64), np.zeros(n, np.uint64), np.zeros(n, np.uint64)
            sig: list[bytes | None] = [None] * n
            for a, row, got in shingle_sets(batch.column(1), width):
                if not len(got):
                    continue
                heads = np.flatnonzero(np.r_[True, row[1:] != row[:-1]])
                rows = row[heads] + a
                size[rows] = np.diff(np.r_[heads, len(got)])
                same_a[rows], same_b[rows] = np.add.reduceat(mix64(got), heads), np.add.reduceat(mix64(got ^ BASE), heads)
                minima = np.empty((len(heads), n_hashes), np.uint32)
                for i in range(n_hashes):
                    minima[:, i] = np.minimum.reduceat(((got * mul[i] + add[i]) >> np.uint64(32)).astype(np.uint32), heads)
                for r, m in zip(rows, minima, strict=True):
                    sig[r] = m.tobytes()
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size), pa.array(same_a.view(np.int64)), pa.array(same_b.view(np.int64)), pa.array(sig, pa.binary())], ["doc_id", "n_shingles", "same_a", "same_b", "sig"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(lean(run), "doc_id long, n_shingles long, same_a long, same_b long, sig binary")


def _bands(sigs: DataFrame, bands: int, rows: int) -> DataFrame:
    """(key, doc_id): a row for each document and band; the key holds the band."""
    keys = F.expr(f"transform(sequence(0, {bands - 1}), i -> xxhash64(i, substring(sig, i * {4 * rows} + 1, {4 * rows})))")
    return sigs.select("doc_id", F.explode(keys).alias("key"))


def _forest(weight: np.ndarray, label: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of rows that span what weights of at least `least` connect, heaviest first; rows of one label count as connected."""
    i, j = np.nonzero(np.triu(weight >= least, 1))
    other = label[i] != label[j]
    i, j = i[other], j[other]
    order = np.argsort(-weight[i, j].astype(np.int32), kind="stable")
    up = list(range(len(label)))
    heads: dict[int, int] = {}
    for r, x in enumerate(label.tolist()):
        up[r] = heads.setdefault(x, r)
    out, left = [], len(heads) - 1

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for x, y in zip(i[order].tolist(), j[order].tolist(), strict=True):
        a, b = root(x), root(y)
        if a != b:
            up[b] = a
            out.append((x, y))
            left -= 1
            if not left:
                break
    got = np.array(out, np.int64).reshape(-1, 2)
    return got[:, 0], got[:, 1]


def _shared_sizes(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections of a block's sets, by matrix products over the items that two of them hold, some thousands of items at a time."""
    n = np.array([len(x) for x in sets])
    row = np.repeat(np.arange(len(sets)), n)
    _, item, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    keep = count[item] > 1
    row, item = row[keep], (np.cumsum(count > 1) - 1)[item[keep]]
    order = np.argsort(item)
    row, item = row[order], item[order]
    out = np.zeros((len(sets), len(sets)), np.float64)
    step = 4096
    for at in range(0, int(item[-1]) + 1 if len(item) else 0, step):
        a, b = np.searchsorted(item, [at, at + step])
        m = np.zeros((len(sets), step), np.float32)
        m[row[a:b], item[a:b] - at] = 1
        out += m @ m.T
    return out


def _blocks(rows: DataFrame, n_hashes: int, agree: float, find: str, percent: int = 80, block: int = 512) -> DataFrame:
    """What is alike in buckets, (u, v). rows: (key, doc_id, label, brief, n), and items for find "links"; n is the bucket's size.

    A bucket of more than `block` members becomes pairs of blocks, each a task's work. Only members of different labels are compared. Each block gives at most as many rows as it has
    members: for "forest" pairs that span what agrees by signature, the most alike first; for "members" (key, member) of those that agree with some
    other; for "links" pairs that span what full sets link.
    """
    spark = rows.sparkSession
    extra = ["items"] if find == "links" else []
    placed = rows.withColumn("m", F.ceil(F.col("n") / block).cast("int")).withColumn("own", F.pmod(F.xxhash64("doc_id"), F.col("m")).cast("int"))
    spread = placed.select("key", "doc_id", "label", "brief", *extra, "own", F.explode(F.sequence(F.lit(0), F.col("m") - 1)).alias("o"))
    spread = spread.select("key", "doc_id", "label", "brief", *extra, "own", F.least("own", "o").alias("lo"), F.greatest("own", "o").alias("hi"))
    cells = max(4 * int(spark.conf.get("spark.sql.shuffle.partitions")), parts_for(rows, 1 << 20))
    least = int(np.ceil(agree * n_hashes))

    def run(group: pa.Table) -> pa.Table:
        keys = np.stack([group.column(c).to_numpy() for c in ("key", "lo", "hi")])
        order = np.lexsort(keys)
        cut = np.flatnonzero(np.any(np.diff(keys[:, order]) != 0, axis=0)) + 1
        doc, label, own = (group.column(c).to_numpy() for c in ("doc_id", "label", "own"))
        sig = np.frombuffer(b"".join(group.column("brief").to_pylist()), np.uint8).reshape(-1, n_hashes)
        items = group.column("items").combine_chunks() if extra else None
        u, v = [], []
        for at in np.split(order, cut):
            if len(at) < 2:
                continue
            s = sig[at]
            if len(at) <= 24:
                same = (s[:, None, :] == s[None, :, :]).sum(2)
            else:
                same = np.zeros((len(at), len(at)), np.int16)
                for k in range(n_hashes):
                    c = s[:, k]
                    same += c[:, None] == c[None, :]
            if keys[1, at[0]] != keys[2, at[0]]:
                same[own[at][:, None] == own[at][None, :]] = 0
            if find == "forest":
                i, j = _forest(same, label[at], least)
            else:
                close = (same >= least) & (label[at][:, None] != label[at][None, :])
                if not close.any():
                    continue
                if find == "members":
                    hit = np.flatnonzero(close.any(0))
                    u.append(np.full(len(hit), keys[0, at[0]]))
                    v.append(doc[at[hit]])
                    continue
                sets = [np.frombuffer(items[int(r)].as_buffer(), np.uint64) for r in at]
                both, size = _shared_sizes(sets), np.array([len(x) for x in sets])
                i, j = _forest((close & (100 * both >= percent * (size[:, None] + size[None, :] - both))).astype(np.int8), label[at], 1)
            if len(i):
                a, b = doc[at[i]], doc[at[j]]
                u.append(np.minimum(a, b))
                v.append(np.maximum(a, b))
        u, v = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (u, v))
        return pa.table([pa.array(u), pa.array(v)], ["u", "v"])

    tasks = spread.withColumn("cell", F.pmod(F.xxhash64("key", "lo", "hi"), F.lit(cells)))
    return tasks.groupBy("cell").applyInArrow(lean_group(run), "u long, v long").distinct()


def _sets(docs: DataFrame, width: int) -> DataFrame:
    def run(batches):
        for batch in batches:
            for a, row, got in shingle_sets(batch.column(1), width):
                heads = np.flatnonzero(np.r_[True, row[1:] != row[:-1]]) if len(got) else np.zeros(0, np.int64)
                ends = np.r_[heads[1:], len(got)] if len(got) else heads
                ids = batch.column(0).take(pa.array(row[heads] + a)) if len(heads) else batch.column(0).slice(0, 0)
                yield pa.RecordBatch.from_arrays([ids, pa.array([got[i:j].tobytes() for i, j in zip(heads, ends, strict=True)], pa.binary())], ["doc_id", "items"])

    return docs.mapInArrow(lean(run), "doc_id long, items binary")


def _linked(pairs: DataFrame, items: DataFrame, percent: int) -> DataFrame:
    """The pairs whose full sets have 100 * |both| >= percent * |either|. items: (doc_id, items)."""

    def run(batches):
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                a, b = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                small, large = (a, b) if len(a) <= len(b) else (b, a)
                both = 0
                if 100 * len(small) >= percent * len(large):
                    both = int((large[np.minimum(np.searchsorted(large, small), len(large) - 1)] == small).sum())
                keep.append(100 * both >= percent * (len(a) + len(b) - both))
            yield pa.RecordBatch.from_arrays([batch.column(i).filter(pa.array(keep, pa.bool_())) for i in (0, 1)], ["u", "v"])

    left, right = items.select(F.col("doc_id").alias("u"), F.col("items").alias("a")), items.select(F.col("doc_id").alias("v"), F.col("items").alias("b"))
    return pairs.join(left, "u").join(right, "v").select("u", "v", "a", "b").mapInArrow(lean(run), "u long, v long")


def near_duplicates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = 5, percent: int = 80, bands: int = BANDS, rows: int = ROWS, agree: float = AGREE) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for each document.

    Equal sets are one class. In round 1 every bucket gives pairs that span what agrees by signature in it, the most alike first, and full sets
    verify them. The links make components. Round 2 takes the buckets that still hold several components, joined by their smallest id so that the bands of one
    group meet once, and compares full sets of all members of different components that agree by signature, inside blocks, which answer with spanning links. So no
    group gives more pairs than members for each block, and a link is lost only if no band shows its pair or its
    signatures disagree: with probability (1 - s^rows)^bands, or by `agree`, seven standard errors off at 0.8 (3e-10), at similarity s.
    """
    ready(docs.sparkSession)
    n_hashes = bands * rows
    docs = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    sigs = written(signatures(docs, width, n_hashes), "sigs")
    full = sigs.where("n_shingles > 0 AND doc_id IS NOT NULL")
    member = written(with_least(full.select("doc_id", "same_a", "same_b", "n_shingles"), ["same_a", "same_b", "n_shingles"], "doc_id").select("doc_id", F.col("least").alias("rep")), "member")
    heads = full.join(member.where("doc_id = rep").select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", "sig").dropDuplicates(["doc_id"])

    def brief(batches):
        for batch in batches:
            sig = [np.frombuffer(x.as_buffer(), np.uint32).astype(np.uint8).tobytes() for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sig, pa.binary())], ["doc_id", "brief"])

    keys = _bands(heads, bands, rows)
    counts = keys.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    shared = written(keys.join(counts, "key").select("key", "doc_id", "n"), "shared")
    briefs = written(heads.join(shared.select("doc_id").distinct(), "doc_id", "left_semi").mapInArrow(lean(brief), "doc_id long, brief binary"), "briefs")
    tried = written(_blocks(shared.withColumn("label", F.col("doc_id")).join(briefs, "doc_id"), n_hashes, agree, "forest"), "tried")
    wanted = tried.select(F.col("u").alias("doc_id")).union(tried.select("v")).distinct()
    items = written(_sets(docs.join(wanted, "doc_id", "left_semi").select("doc_id", "text"), width).dropDuplicates(["doc_id"]), "sets")
    links = written(_linked(tried, items, percent), "links")
    comp = written(components(links), "comp")
    labelled = shared.join(items.select("doc_id"), "doc_id", "left_semi").join(comp.withColumnRenamed("node", "doc_id"), "doc_id", "left").select("key", "doc_id", F.coalesce("component", "doc_id").alias("label"))
    mixed = labelled.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.min("doc_id").alias("first")).where("lo < hi").select("key", "first")
    members = written(labelled.join(mixed, "key").select(F.col("first").alias("key"), "doc_id", "label").distinct(), "members")
    sized = members.join(members.groupBy("key").agg(F.count(F.lit(1)).alias("n")), "key").join(briefs, "doc_id")
    alike = written(_blocks(sized, n_hashes, agree, "members").select(F.col("u").alias("key"), F.col("v").alias("doc_id")), "alike")
    chosen = members.join(alike, ["key", "doc_id"], "left_semi").join(alike.groupBy("key").agg(F.count(F.lit(1)).alias("n")), "key").join(briefs, "doc_id").join(items, "doc_id")
    late = written(_blocks(chosen, n_hashes, agree, "links", percent), "late")
    if late.limit(1).count():
        comp = components(links.unionByName(late))
    joined = member.join(comp.withColumnRenamed("node", "rep"), "rep", "left").select("doc_id", F.coalesce("component", "rep").alias("c"))
    joined = joined.groupBy("doc_id").agg(F.min("c").alias("c"))
    return sigs.groupBy("doc_id").agg(F.max("n_shingles").alias("n_shingles")).join(joined, "doc_id", "left").select("doc_id", "n_shingles", F.coalesce("c", "doc_id").alias("component_id"), (F.coalesce("c", "doc_id") == F.col("doc_id")).alias("kept"))
