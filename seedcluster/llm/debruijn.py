"""Exact removal of long spans of words that also stand in an earlier document, through a compacted de Bruijn graph.

A window is `width` words of one document; it goes if its content also starts in a document with a smaller id. In the graph a window is an edge
between the nodes of its first and its last width - 1 words.

1.  Windows are named by their least k-mer, and only those whose name more than one document has are edges; see exchange(). The edges of one name meet in
    one block, as stretches of node hashes with the coordinates of their source. A group settles by itself what it holds twice, so that a name
    that very many documents share is sent once by each group.
2.  A block keeps the edges that more than one document has, and compacts them: edges in a row through nodes of one way in and one way out make a unitig.
    Every later occurrence becomes a claim: so many words of this document, from here on, are those of that document, from there on.
3.  Unitigs of different blocks that meet in a node of one way in and one way out are joined to paths by Spark: degrees by aggregates, chains by pointers that
    double. Claims that go on along a path, in document and source alike, become one span.
4.  Each span is verified by its source coordinates: the source's group digests the words that stand there, and the document's group compares
    them with its own. Covered words go.

Null text counts as empty, a null id as the smallest; rows of one id never remove from each other; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import mix64, written
from .repeats import SHIFT, Texts, _covered, _ids, _table, contents, exchange, joined, runs, texts

SENT = "key long, g long, kind int, a binary, b binary, c binary, d binary"
#: A unitig (kind 0): uid, n edges, first and last node; a claim (kind 1): n windows of a document's row are those of a source's, at `off` in unitig uid.
MET = "kind int, uid long, off long, n long, g long, row int, start long, og long, orow int, ostart long, first long, last long"
UNITIG, CLAIM, OWN = 0, 1, 2


def edges_of(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """A window is told by its two nodes."""
    return mix64(left * np.uint64(SHIFT) + right)


def first_of_same(edge: np.ndarray) -> np.ndarray:
    """For each edge the position of the first equal one."""
    order = np.argsort(edge, kind="stable")
    s = edge[order]
    head = np.r_[True, s[1:] != s[:-1]]
    out = np.empty(len(edge), np.int64)
    out[order] = order[np.flatnonzero(head)][np.cumsum(head) - 1]
    return out


def unitigs(left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first edge, place, last edge) of the chain of each edge, by pointers that double; edges in rings stand alone."""
    _, node = np.unique(np.concatenate([left, right]), return_inverse=True)
    n = len(left)
    tail, tip = node[:n], node[n:]
    size = int(node.max()) + 1 if n else 0
    unary = (np.bincount(tail, minlength=size) == 1) & (np.bincount(tip, minlength=size) == 1)
    into = np.full(size, -1)
    into[tip] = np.arange(n)
    before = np.where(unary[tail] & (into[tail] != np.arange(n)), into[tail], np.arange(n))
    root = before == np.arange(n)
    head, place = before.copy(), (~root).astype(np.int64)
    for _ in range(max(1, int(n).bit_length())):
        if root[head].all():
            break
        place, head = place + place[head], head[head]
    ring = ~root[head]
    head[ring], place[ring] = np.flatnonzero(ring), 0
    last = np.full(n, -1)
    order = np.argsort(place, kind="stable")
    last[head[order]] = order
    return head, place, last[head]


def _rows(count: int, **columns) -> pa.Table:
    """Rows of MET; what is not given is 0."""
    kinds = {"long": np.int64, "int": np.int32}
    fields = [x.split() for x in MET.split(", ")]
    return pa.table([pa.array(np.broadcast_to(np.asarray(columns.get(c, 0)), count).astype(kinds[k])) for c, k in fields], [c for c, _ in fields])


def _digest(t: Texts, row: int, start: int, words: int) -> bytes:
    a = int(t.at[row]) + start
    return hashlib.blake2b(b" ".join(t.raw[t.starts[a] : t.ends[a + words - 1]].tobytes().split()), digest_size=16).digest()


def compacted(found: DataFrame) -> DataFrame:
    """(uid, path, shift): unitigs joined through nodes that one unitig ends in and one begins with; shift is a unitig's place in its path, in edges. Rings stay apart."""
    ends = found.groupBy("last").agg(F.count(F.lit(1)).alias("k"), F.min("uid").alias("a"), F.min("n").alias("m")).where("k = 1")
    begins = found.groupBy("first").agg(F.count(F.lit(1)).alias("k"), F.min("uid").alias("uid")).where("k = 1")
    links = begins.select(F.col("first").alias("node"), "uid").join(ends.select(F.col("last").alias("node"), "a", "m"), "node").where("a <> uid").select("uid", "a", "m")
    p = written(found.select("uid").join(links, "uid", "left").select("uid", F.coalesce("a", "uid").alias("path"), F.coalesce("m", F.lit(0)).alias("shift"), F.col("a").isNull().alias("root")), "pointers")
    rounds = p.count().bit_length() + 1
    for _ in range(rounds):
        up = p.select(F.col("uid").alias("path"), F.col("path").alias("above"), F.col("shift").alias("more"), F.col("root").alias("top"))
        step = p.join(up, "path").select("uid", F.col("above").alias("path"), (F.col("shift") + F.col("more")).alias("shift"), "root", "top")
        p = written(step, "pointers")
        if not p.where("NOT top").limit(1).count():
            return p.select("uid", "path", "shift")
        p = p.drop("top")
    roots = p.where("root").select(F.col("uid").alias("path"), F.lit(True).alias("ok"))
    return p.join(roots, "path", "left").select("uid", F.when(F.col("ok"), F.col("path")).otherwise(F.col("uid")).alias("path"), F.when(F.col("ok"), F.col("shift")).otherwise(0).alias("shift"))


def repeated_word_spans(docs: DataFrame, width: int, k: int, finish, fields: str, **names) -> DataFrame:
    """finish(texts, row, start, length) makes a group's rows from the runs of windows to go."""
    x = exchange(docs, True, width, k, **names)
    plan = x.names

    def sent_paths(group: pa.Table, answers: pa.Table) -> pa.Table:
        if not group.num_rows:
            return _table([], SENT)
        g, t = group.column("g")[0].as_py(), texts(group, True)
        pos, key, left, right = [], [], [], []
        for a, at, least, prefix in plan.candidates(t, answers):
            pos.append(at + a)
            key.append(least)
            left.append(contents(prefix, at, width - 1))
            right.append(contents(prefix, at + 1, width - 1))
        if not pos:
            return _table([], SENT)
        pos, key, left, right = np.concatenate(pos), np.concatenate(key), np.concatenate(left), np.concatenate(right)
        row = np.searchsorted(t.at, pos, "right") - 1
        # Texts stand in order of id, so the first of equal edges has the least.
        own = first_of_same(edges_of(left, right))
        gone = np.flatnonzero(t.ids[row[own]] < t.ids[row])
        out = []
        if len(gone):
            o = own[gone]
            first, n = runs(gone, np.r_[0, np.cumsum((np.diff(pos[gone]) != 1) | (np.diff(pos[o]) != 1) | (np.diff(row[gone]) != 0) | (np.diff(row[o]) != 0))])
            i, o = gone[first], o[first]
            local = lambda at: (pos[at] - t.at[row[at]]).astype("<i8").tobytes()
            out.append((-1 - g, g, 1, np.stack([row[i], n, row[o]], 1).astype("<i4").tobytes(), local(i), local(o), b""))
        rest = np.ones(len(pos), bool)
        rest[gone] = False
        rest = np.flatnonzero(rest)
        if len(rest):
            pos, key, left, right, row = (v[rest] for v in (pos, key, left, right, row))
            first, n = runs(pos, key)
            block = plan.block_of(key[first])
            order = np.argsort(block, kind="stable")
            cut = np.searchsorted(block[order], np.arange(plan.blocks + 1))
            for b in np.unique(block).tolist():
                use = order[cut[b] : cut[b + 1]]
                f, m = first[use], n[use]
                # The nodes of a stretch: the left ones of its windows, and the right one of its last.
                at = np.repeat(f - np.cumsum(m + 1) + m + 1, m + 1) + np.arange((m + 1).sum())
                body = left[np.minimum(at, len(left) - 1)]
                body[np.cumsum(m + 1) - 1] = right[f + m - 1]
                out.append((b, g, 0, np.stack([row[f], m], 1).astype("<i4").tobytes(), (pos[f] - t.at[row[f]]).astype("<i8").tobytes(), t.ids[row[f]].astype("<i8").tobytes(), body.astype("<u8").tobytes()))
        return _table(out, SENT)

    def met(group: pa.Table) -> pa.Table:
        rows = group.to_pylist()
        if rows[0]["kind"] == 1:
            head = np.concatenate([np.frombuffer(r["a"], "<i4").reshape(-1, 3) for r in rows])
            start, ostart = (np.concatenate([np.frombuffer(r[c], "<i8") for r in rows]) for c in "bc")
            g = rows[0]["g"]
            return _rows(len(head), kind=OWN, n=head[:, 1], g=g, row=head[:, 0], start=start, og=g, orow=head[:, 2], ostart=ostart)
        head = [np.frombuffer(r["a"], "<i4").reshape(-1, 2) for r in rows]
        row, n = np.concatenate([h[:, 0] for h in head]), np.concatenate([h[:, 1] for h in head]).astype(np.int64)
        start, doc = (np.concatenate([np.frombuffer(r[c], "<i8") for r in rows]) for c in "bc")
        g = np.repeat([r["g"] for r in rows], [len(h) for h in head])
        nodes = np.frombuffer(b"".join(r["d"] for r in rows), "<u8").astype(np.uint64)
        base = np.cumsum(n + 1) - n - 1
        # Stretches in order of document and place, so that the first of equal edges is the source.
        order = np.lexsort((start, row, g, doc))
        row, n, start, doc, g, base = (v[order] for v in (row, n, start, doc, g, base))
        each = np.repeat(np.arange(len(n)), n)
        step = np.arange(len(each)) - np.repeat(np.cumsum(n) - n, n)
        left, right = nodes[base[each] + step], nodes[base[each] + step + 1]
        edge = edges_of(left, right)
        own = first_of_same(edge)
        gone = np.flatnonzero(doc[each[own]] < doc[each])
        if not len(gone):
            return _rows(0)
        sources, which = np.unique(own[gone], return_inverse=True)
        top, place, last = unitigs(left[sources], right[sources])
        uid = edge[sources[top]].view(np.int64)
        heads = np.flatnonzero(place == 0)
        made = _rows(len(heads), kind=UNITIG, uid=uid[heads], n=place[last[heads]] + 1, first=left[sources[heads]].view(np.int64), last=right[sources[last[heads]]].view(np.int64))
        o, off, u = own[gone], place[which], top[which]
        split = (np.diff(each[gone]) != 0) | (np.diff(o) != 1) | (np.diff(each[o]) != 0) | (np.diff(u) != 0) | (np.diff(off) != 1)
        f, m = runs(gone, np.r_[0, np.cumsum(split)])
        i, o = gone[f], o[f]
        claims = _rows(len(f), kind=CLAIM, uid=uid[which[f]], off=off[f], n=m, g=g[each[i]], row=row[each[i]], start=start[each[i]] + step[i], og=g[each[o]], orow=row[each[o]], ostart=start[each[o]] + step[o])
        return pa.concat_tables([made, claims])

    def digested(group: pa.Table, asked: pa.Table) -> pa.Table:
        got: list[bytes] = []
        if asked.num_rows:
            t = texts(group, True)
            got = [_digest(t, *a) for a in zip(asked.column("orow").to_pylist(), asked.column("ostart").to_pylist(), [n + width - 1 for n in asked.column("n").to_pylist()], strict=True)]
        return pa.table([*(asked.column(c) for c in ("og", "orow", "ostart", "n")), pa.array(got, pa.binary())], ["og", "orow", "ostart", "n", "digest"])

    def spans(t: Texts, answers: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        row, start, n, orow, ostart = (answers.column(c).to_numpy() for c in ("row", "start", "n", "orow", "ostart"))
        same = np.zeros(len(row), bool)
        for i, (r, a, m, digest) in enumerate(zip(row.tolist(), start.tolist(), n.tolist(), answers.column("digest").to_pylist(), strict=True)):
            want = digest if digest is not None else _digest(t, int(orow[i]), int(ostart[i]), m + width - 1)
            same[i] = _digest(t, r, a, m + width - 1) == want
        return row[same], start[same], n[same]

    paths = x.held.groupBy("g").cogroup(x.answers.groupBy("g")).applyInArrow(sent_paths, SENT)
    found = written(paths.groupBy("key").applyInArrow(met, MET), "graph")
    place = compacted(found.where(F.col("kind") == UNITIG))
    claim = found.where(F.col("kind") == CLAIM).join(place, "uid").withColumn("at", F.col("shift") + F.col("off"))
    way = Window.partitionBy("path", "g", "row", "og", "orow", F.col("start") - F.col("at"), F.col("ostart") - F.col("at")).orderBy("at")
    fresh = (F.col("at") != F.coalesce(F.lag(F.col("at") + F.col("n")).over(way), F.lit(-1))).cast("int")
    claim = claim.withColumn("fresh", fresh).withColumn("island", F.sum("fresh").over(way))
    long = claim.groupBy("path", "g", "row", "og", "orow", (F.col("start") - F.col("at")).alias("x"), (F.col("ostart") - F.col("at")).alias("y"), "island")
    long = written(long.agg(F.min("start").alias("start"), F.min("ostart").alias("ostart"), F.sum("n").alias("n")).select("g", "row", "start", "n", "og", "orow", "ostart"), "spans")
    asked = long.select("og", "orow", "ostart", "n").distinct()
    digests = x.held.groupBy("g").cogroup(asked.groupBy("og")).applyInArrow(digested, "og long, orow int, ostart long, n long, digest binary")
    keys = ["og", "orow", "ostart", "n"]
    own = found.where(F.col("kind") == OWN).select("g", "row", "start", "n", "orow", "ostart", F.lit(None).cast("binary").alias("digest"))
    answers = long.join(digests, keys).select("g", "row", "start", "n", "orow", "ostart", "digest").unionByName(own)
    return x.finished(finish, fields, answers, spans)


def without_repeated_words(docs: DataFrame, width: int = 50, k: int = 16, keep_text: bool = False, **names) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256), and the kept words joined by a blank if asked."""
    fields = "doc_id long, n_words long, n_removed long, kept_sha256 string" + ", kept string" * keep_text

    def finish(t, row, start, length):
        cols = [], [], []
        kept_texts = []
        gone = _covered(t, row, start, length, width)
        for i in range(len(t.ids)):
            words = t.raw[t.offsets[i] : t.offsets[i + 1]].tobytes().split()
            mask = gone[t.at[i] : t.at[i + 1]]
            if mask.any():
                words = [words[j] for j in np.flatnonzero(~mask).tolist()]
            kept = b" ".join(words)
            for c, x in zip(cols, (len(mask), int(mask.sum()), hashlib.sha256(kept).hexdigest()), strict=True):
                c.append(x)
            if keep_text:
                kept_texts.append(kept.decode())
        out = [_ids(t), *(pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.string()), strict=True))]
        return pa.table(out + [pa.array(kept_texts, pa.string())] * keep_text, ["doc_id", "n_words", "n_removed", "kept_sha256"] + ["kept"] * keep_text)

    return repeated_word_spans(docs, width, k, finish, fields, **names)
