"""Exact removal of long spans of bytes that also stand in an earlier document, through suffix blocks; and the exchange of names that the words' way shares.

A window is `width` symbols of one document. A window goes if its content also starts in a document with a smaller id.

1.  Every window is named by its least k-mer. Groups of documents send the distinct names, as sorted runs, to ranges of names;
    each range answers which of them more than one document has.
2.  Windows with such a name are candidates. A group settles those that it holds twice itself, and packs the others into paths: stretches of
    consecutive candidates with one name, which carry one coordinate. A path goes to the block of its name, so that equal windows meet.
3.  A block finds equal windows and their smallest document, and answers with coordinates of the windows to go.
    A block's suffixes are sorted by the difference-cover method, see suffix_owners(); suffixes whose window no other document can have, by a
    64-bit hash, are not sorted.
4.  The answers meet the texts again, and covered symbols go.

A name or window that very many documents share is sent once by each group, with its group's smallest document, so no
task gathers all its copies. The texts are shuffled once; all steps read that exchange. Null text counts as empty, a null id as the smallest;
rows of one id never remove from each other; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from .common import CODES, _POWERS, lean_group, lean_groups, mix64, parts_for, powers, ready, size_bytes, spans_hash, utf8, word_spans

LOWEST = -(1 << 63)
STEP = 300_000
SHIFT, BACK = 0xD1342543DE82EF95, pow(0xD1342543DE82EF95, -1, 1 << 64)


@dataclass
class Texts:
    """A group's documents in order of id and text: symbols end to end."""

    ids: np.ndarray
    raw: np.ndarray
    offsets: np.ndarray
    words: bool

    def __post_init__(self):
        if self.words:
            self.starts, self.ends, row = word_spans(self.raw, self.offsets)
            self.codes, self.at = np.empty(len(self.starts), np.uint64), np.searchsorted(row, np.arange(len(self.ids) + 1))
            step = 60_000
            for a in range(0, len(self.starts), step):
                s, e = self.starts[a : a + step], self.ends[a : a + step]
                lo = int(s[0])
                self.codes[a : a + step] = spans_hash(CODES[self.raw[lo : int(e[-1])]], s - lo, e - lo)
        else:
            self.at = self.offsets

    def symbols(self, a: int, b: int) -> np.ndarray:
        return self.codes[a:b] if self.words else CODES[self.raw[a:b]]

    @property
    def n(self) -> int:
        return int(self.at[-1])


def ordered(group: pa.Table) -> pa.Table:
    return group.sort_by([("doc_id", "ascending"), ("text", "ascending")])


def texts(group: pa.Table, words: bool) -> Texts:
    group = ordered(group)
    raw, offsets = utf8(group.column("text"))
    return Texts(group.column("doc_id").to_numpy(), raw, offsets, words)


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """The least of each w in a row."""
    have = 1
    while have < w:
        step = min(have, w - have)
        x = np.minimum(x[: len(x) - step], x[step:])
        have += step
    return x


def named(t: Texts, width: int, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(first window, window starts that lie in one document, their names, prefix sums) by chunks."""
    for p in (SHIFT, BACK):
        if len(_POWERS.get(p, ())) <= STEP + width:
            _POWERS[p] = powers(STEP + width, p)
    up, down = _POWERS[SHIFT], _POWERS[BACK]
    long = np.flatnonzero(np.diff(t.at) >= width)
    if not len(long):
        return
    for a in range(0, t.n - width + 1, STEP):
        b = min(a + STEP + width - 1, t.n)
        n = b - a
        prefix = np.zeros(n + 1, np.uint64)
        np.cumsum(t.symbols(a, b) * up[:n], out=prefix[1:])
        h = mix64((prefix[k:] - prefix[:-k]) * down[: n - k + 1])
        least = sliding_min(h, width - k + 1)
        valid = np.ones(len(least), bool)
        # A window that starts within width - 1 of its document's end would cross it.
        ends = t.at[1:][(t.at[1:] > a) & (t.at[1:] < b)] - a
        if len(ends):
            cross = np.zeros(len(least) + 1, np.int32)
            np.add.at(cross, np.minimum(np.maximum(ends - width + 1, 0), len(least)), 1)
            np.add.at(cross, np.minimum(ends, len(least)), -1)
            valid = np.cumsum(cross[:-1]) == 0
        yield a, np.flatnonzero(valid), least, prefix


def contents(prefix: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
    """A 64-bit hash of each window."""
    return mix64((prefix[at + width] - prefix[at]) * _POWERS[BACK][at])


def short(least: np.ndarray, bits: int) -> np.ndarray:
    """The upper bits of mixed names: a least hash is small, so names as they are would crowd in the lowest ranges."""
    return mix64(least ^ np.uint64(SHIFT)) >> np.uint64(64 - bits)


def names_of(t: Texts, width: int, k: int, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """The distinct names, shortened, ascending, and whether two of the group's ids have it."""
    name, doc = [], []
    for a, at, least, _ in named(t, width, k):
        if len(at):
            got = short(least[at], bits)
            # Windows of two documents are never next to each other, for those across the border between do not count.
            new = np.flatnonzero(np.r_[True, (got[1:] != got[:-1]) | (at[1:] != at[:-1] + 1)])
            name.append(got[new])
            doc.append(t.ids[np.searchsorted(t.at, at[new] + a, "right") - 1])
    if not name:
        return np.zeros(0, np.uint64), np.zeros(0, bool)
    name, doc = np.concatenate(name), np.concatenate(doc)
    order = np.argsort(name)
    name, doc = name[order], doc[order]
    head = np.flatnonzero(np.r_[True, name[1:] != name[:-1]])
    return name[head], np.minimum.reduceat(doc, head) != np.maximum.reduceat(doc, head)


def packed(sorted_values: np.ndarray) -> bytes:
    """Ascending numbers as differences, laid out by significance."""
    d = np.diff(sorted_values, prepend=np.uint64(0)).astype("<u8")
    return np.ascontiguousarray(d.view(np.uint8).reshape(-1, 8).T).tobytes()


def unpacked(data: bytes) -> np.ndarray:
    return np.cumsum(np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(8, -1).T).view("<u8").ravel())


def suffix_owners(text: np.ndarray, at: np.ndarray, owner: np.ndarray, width: int = 50) -> np.ndarray:
    """For each suffix at[i] of a block, the least owner among suffixes with the same first `width` bytes.

    The sample holds the positions that leave 0 or 1 modulo 3, a difference cover: any two positions have a shift below 3 that takes both into the
    sample. Sample positions are ranked by their first 6, 12, 24 and 48 bytes, each ranking sorted from the one before; a long tie between two
    suffixes is then settled by the ranks at their shift and the two bytes besides. Memory is a few numbers a position of this one block.
    """
    if width != 50:
        raise ValueError("ranks of 48 bytes and two bytes more make 50")
    n = len(text)
    wide = np.concatenate([text, np.zeros(64, np.uint8)])
    asked = np.zeros(n + 64, bool)
    for shift in range(3):
        asked[at + shift] = True
    asked[2::3] = False
    # Which sample positions need a rank by 24, 12 and 6 bytes, so that those asked for get one by 48.
    need = [asked]
    for depth in (24, 12, 6):
        more = need[-1].copy()
        more[depth:] |= need[-1][:-depth]
        need.append(more)
    rank = np.zeros(n + 64, np.uint64)
    for depth, mask in zip((0, 6, 12, 24), need[::-1], strict=True):
        p = np.flatnonzero(mask)
        if depth:
            key = rank[p] << np.uint64(32) | rank[p + depth]
        else:
            key = np.zeros(len(p), np.uint64)
            for i in range(6):
                key = key << np.uint64(8) | wide[np.minimum(p + i, n)]
        order = np.argsort(key)
        s = key[order]
        rank[p[order]] = np.cumsum(np.r_[False, s[1:] != s[:-1]]).astype(np.uint64)
    out = owner.copy()
    for shift in range(3):
        use = np.flatnonzero((at + shift) % 3 < 2)
        if not len(use):
            continue
        p = at[use]
        two = [j for j in (*range(shift), *range(48 + shift, 50))]
        key = rank[p + shift] << np.uint64(16) | wide[p + two[0]].astype(np.uint64) << np.uint64(8) | wide[p + two[1]]
        order = np.argsort(key)
        s = key[order]
        head = np.r_[True, s[1:] != s[:-1]]
        least = np.minimum.reduceat(owner[use][order], np.flatnonzero(head))
        out[use[order]] = np.minimum(out[use[order]], least[np.cumsum(head) - 1])
    return out


def least_owner(content: np.ndarray, owner: np.ndarray) -> np.ndarray:
    """For each window the least owner of one of the same content."""
    order = np.argsort(content)
    s = content[order]
    head = np.r_[True, s[1:] != s[:-1]]
    out = np.empty_like(owner)
    out[order] = np.minimum.reduceat(owner[order], np.flatnonzero(head))[np.cumsum(head) - 1]
    return out


def twins(text: np.ndarray, at: np.ndarray, owner: np.ndarray, width: int) -> np.ndarray:
    """Which of the ascending windows at[i] some window of another owner may equal: no other has a twin, for equal bytes have equal hashes."""
    for p in (SHIFT, BACK):
        if len(_POWERS.get(p, ())) <= STEP + width:
            _POWERS[p] = powers(STEP + width, p)
    content = np.empty(len(at), np.uint64)
    for a in range(0, len(text), STEP):
        i, j = np.searchsorted(at, (a, a + STEP))
        if i < j:
            part = CODES[text[a : a + STEP + width]]
            prefix = np.zeros(len(part) + 1, np.uint64)
            np.cumsum(part * _POWERS[SHIFT][: len(part)], out=prefix[1:])
            content[i:j] = contents(prefix, at[i:j] - a, width)
    order = np.argsort(content)
    s, own = content[order], owner[order]
    head = np.flatnonzero(np.r_[True, s[1:] != s[:-1]])
    many = np.minimum.reduceat(own, head) != np.maximum.reduceat(own, head)
    out = np.empty(len(at), bool)
    out[order] = np.repeat(many, np.diff(np.r_[head, len(at)]))
    return out


def runs(start: np.ndarray, split: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Where runs of consecutive numbers begin, and their lengths; a run also ends where `split` changes."""
    head = np.r_[True, np.diff(start) != 1]
    if split is not None:
        head[1:] |= split[1:] != split[:-1]
    first = np.flatnonzero(head)
    return first, np.diff(np.r_[first, len(start)])


SENT = "key long, g long, kind int, a binary, b binary, c binary, d binary"
ANSWER = "g long, row binary, start binary, length binary"


def _table(rows: list[tuple], names: str) -> pa.Table:
    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    fields = [x.split() for x in names.split(", ")]
    cols = list(zip(*rows, strict=True)) if rows else [()] * len(fields)
    return pa.table([pa.array(c, kinds[k]) for c, (_, k) in zip(cols, fields, strict=True)], [x for x, _ in fields])


@dataclass
class Names:
    """How windows are named, and how names and blocks are dealt."""

    words: bool
    width: int
    k: int
    bits: int
    low: np.uint64
    ranges: int
    blocks: int

    def candidates(self, t: Texts, answers: pa.Table) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
        """(first window, windows whose name more than one document has, their least k-mers, prefix sums) by chunks."""
        name, _ = names_of(t, self.width, self.k, self.bits)
        cut = np.searchsorted(name >> self.low, np.arange(self.ranges + 1, dtype=np.uint64))
        many = np.zeros(len(name), bool)
        for r, x in zip(answers.column("r").to_pylist(), answers.column("many").to_pylist(), strict=True):
            a, b = cut[r], cut[r + 1]
            many[a:b] = np.unpackbits(np.frombuffer(x, np.uint8), count=b - a).astype(bool)
        shared = name[many]
        if not len(shared):
            return
        for a, at, least, prefix in named(t, self.width, self.k):
            own = short(least[at], self.bits)
            head = np.flatnonzero(np.r_[True, own[1:] != own[:-1]]) if len(own) else np.zeros(0, np.int64)
            hit = shared[np.minimum(np.searchsorted(shared, own[head]), len(shared) - 1)] == own[head]
            at = at[np.repeat(hit, np.diff(np.r_[head, len(own)]))]
            if len(at):
                yield a, at, least[at], prefix

    def block_of(self, key: np.ndarray) -> np.ndarray:
        return (mix64(key) >> np.uint64(64 - int(math.log2(self.blocks)))).astype(np.int64)


@dataclass
class Exchange:
    """What all steps share: the texts by group g, and which names more than one document has."""

    held: DataFrame
    answers: DataFrame
    names: Names
    rest: list[tuple[str, str, str]]

    def finished(self, finish, fields: str, answers: DataFrame, spans) -> DataFrame:
        """The groups' rows: finish(texts, row, start, length) of what spans(texts, answers) takes from a group's answers; carried columns go along."""
        words, rest = self.names.words, self.rest
        fields += "".join(f", {a} {kind}" for a, _, kind in rest)
        schema = to_arrow_schema(StructType.fromDDL(fields))

        def run(group: pa.Table, got: pa.Table) -> pa.Table:
            if not group.num_rows:
                return schema.empty_table()
            t = texts(group, words)
            out = finish(t, *spans(t, got))
            group = ordered(group)
            for a, _, _ in rest:
                out = out.append_column(a, group.column(a))
            return out

        return self.held.groupBy("g").cogroup(answers.groupBy("g")).applyInArrow(lean_groups(run), fields).withColumnsRenamed({a: c for a, c, _ in rest})


def joined(column: pa.ChunkedArray, kind: str) -> np.ndarray:
    """The numbers of a column of packed arrays, end to end."""
    return np.concatenate([np.zeros(0, kind), *(np.frombuffer(x, kind) for x in column.to_pylist())])


def exchange(docs: DataFrame, words: bool, width: int, k: int, doc_id: str = "doc_id", text: str = "text", carry: tuple[str, ...] = (), group_bytes: int = 2 << 20) -> Exchange:
    """Deals texts to groups and finds the names that more than one document has."""
    ready(docs.sparkSession)
    total = size_bytes(docs)
    groups = parts_for(docs, group_bytes)
    bits = min(60, max(40, math.ceil(math.log2(max(total, 1))) + 8))
    ranges, blocks = (1 << min(14, max(3, math.ceil(math.log2(groups)) - i)) for i in (1, 0))
    rest = [(f"carried_{i}", c, docs.schema[c].dataType.simpleString()) for i, c in enumerate(carry)]
    docs = docs.select(F.coalesce(F.col(doc_id).cast("long"), F.lit(LOWEST)).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"), *(F.col(f"`{c}`").alias(a) for a, c, _ in rest))
    held = docs.select(F.pmod(F.xxhash64("doc_id"), F.lit(groups)).alias("g"), "doc_id", "text", *(a for a, _, _ in rest))
    low = np.uint64(bits - int(math.log2(ranges)))

    def sent_names(group: pa.Table) -> pa.Table:
        g = group.column("g")[0].as_py()
        name, many = names_of(texts(group, words), width, k, bits)
        cut = np.searchsorted(name >> low, np.arange(ranges + 1, dtype=np.uint64))
        return _table([(r, g, packed(name[a:b]), np.packbits(many[a:b]).tobytes()) for r, (a, b) in enumerate(zip(cut.tolist(), cut[1:].tolist(), strict=False)) if b > a], "r long, g long, names binary, many binary")

    def answered(group: pa.Table) -> pa.Table:
        name = [unpacked(x) for x in group.column("names").to_pylist()]
        size = [len(x) for x in name]
        many = np.concatenate([np.unpackbits(np.frombuffer(x, np.uint8), count=n) for x, n in zip(group.column("many").to_pylist(), size, strict=True)]).astype(bool)
        name = np.concatenate(name)
        order = np.argsort(name)
        s = name[order]
        again = np.r_[s[1:] == s[:-1], False] | np.r_[False, s[1:] == s[:-1]]
        many[order] |= again
        at = np.cumsum([0, *size])
        r = group.column("r")[0].as_py()
        # A name flagged by one group only is repeated inside it.
        return _table([(g, r, np.packbits(many[a:b]).tobytes()) for g, a, b in zip(group.column("g").to_pylist(), at, at[1:], strict=False)], "g long, r long, many binary")

    names = held.groupBy("g").applyInArrow(lean_group(sent_names), "r long, g long, names binary, many binary")
    answers = names.groupBy("r").applyInArrow(lean_group(answered), "g long, r long, many binary")
    return Exchange(held, answers, Names(words, width, k, bits, low, ranges, blocks), rest)


def repeated_byte_spans(docs: DataFrame, width: int, k: int, finish, fields: str, **names) -> DataFrame:
    """finish(texts, row, start, length) makes a group's rows from the runs of windows to go."""
    x = exchange(docs, False, width, k, **names)
    plan = x.names

    def sent_paths(group: pa.Table, answers: pa.Table) -> pa.Table:
        if not group.num_rows:
            return _table([], SENT)
        g, t = group.column("g")[0].as_py(), texts(group, False)
        pos, key, content = [], [], []
        for a, at, least, prefix in plan.candidates(t, answers):
            pos.append(at + a)
            key.append(least)
            content.append(contents(prefix, at, width))
        if not pos:
            return _table([], SENT)
        pos, key, content = np.concatenate(pos), np.concatenate(key), np.concatenate(content)
        row = np.searchsorted(t.at, pos, "right") - 1
        doc = t.ids[row]
        gone = least_owner(content, doc) < doc
        out = []
        if gone.any():
            first, length = runs(pos[gone], row[gone])
            out.append((-1 - g, g, 1, row[gone][first].astype("<i4").tobytes(), (pos - t.at[row])[gone][first].astype("<i8").tobytes(), length.astype("<i4").tobytes(), b""))
        left = np.flatnonzero(~gone)
        if len(left):
            pos, key, row = pos[left], key[left], row[left]
            first, length = runs(pos, key)
            block = plan.block_of(key[first])
            order = np.argsort(block, kind="stable")
            cut = np.searchsorted(block[order], np.arange(plan.blocks + 1))
            for b in np.unique(block).tolist():
                use = order[cut[b] : cut[b + 1]]
                f, n = first[use], length[use]
                m = n + width - 1
                body = t.raw[np.repeat(pos[f] - np.cumsum(m) + m, m) + np.arange(m.sum())].tobytes()
                out.append((b, g, 0, np.stack([row[f], n], 1).astype("<i4").tobytes(), (pos[f] - t.at[row[f]]).astype("<i8").tobytes(), t.ids[row[f]].astype("<i8").tobytes(), body))
        return _table(out, SENT)

    def met(group: pa.Table) -> pa.Table:
        rows = group.to_pylist()
        if rows[0]["kind"] == 1:
            return _table([(r["g"], r["a"], r["b"], r["c"]) for r in rows], ANSWER)
        head = [np.frombuffer(r["a"], "<i4").reshape(-1, 2) for r in rows]
        row, n = np.concatenate([h[:, 0] for h in head]), np.concatenate([h[:, 1] for h in head]).astype(np.int64)
        start, owner = (np.concatenate([np.frombuffer(r[c], "<i8") for r in rows]) for c in "bc")
        g = np.repeat([r["g"] for r in rows], [len(h) for h in head])
        each = np.repeat(np.arange(len(n)), n)
        step = np.arange(len(each)) - np.repeat(np.cumsum(n) - n, n)
        mine = owner[each]
        m = n + width - 1
        text, at, least = np.frombuffer(b"".join(r["d"] for r in rows), np.uint8), (np.cumsum(m) - m)[each] + step, mine.copy()
        # The suffixes sorted are those whose window another document may have; none that has a twin is left out.
        some = np.flatnonzero(twins(text, at, mine, width))
        if len(some):
            least[some] = suffix_owners(text, at[some], mine[some], width)
        gone = np.flatnonzero(least < mine)
        if not len(gone):
            return _table([], ANSWER)
        first, length = runs(gone, each[gone])
        path, at = each[gone[first]], start[each[gone[first]]] + step[gone[first]]
        out = []
        for i in np.unique(g[path]).tolist():
            use = g[path] == i
            out.append((i, row[path[use]].astype("<i4").tobytes(), at[use].astype("<i8").tobytes(), length[use].astype("<i4").tobytes()))
        return _table(out, ANSWER)

    def spans(t: Texts, answers: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return joined(answers.column("row"), "<i4"), joined(answers.column("start"), "<i8"), joined(answers.column("length"), "<i4")

    paths = x.held.groupBy("g").cogroup(x.answers.groupBy("g")).applyInArrow(lean_groups(sent_paths), SENT)
    return x.finished(finish, fields, paths.groupBy("key").applyInArrow(lean_group(met), ANSWER), spans)


def _covered(t: Texts, row: np.ndarray, start: np.ndarray, length: np.ndarray, width: int) -> np.ndarray:
    change = np.zeros(t.n + 1, np.int32)
    first = t.at[row] + start
    np.add.at(change, first, 1)
    np.add.at(change, first + length + width - 1, -1)
    return np.cumsum(change[:-1]) > 0


def _ids(t: Texts) -> pa.Array:
    return pa.array(t.ids, mask=t.ids == LOWEST)


def without_repeated_bytes(docs: DataFrame, k: int = 20, keep_text: bool = False, **names) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256), and the kept bytes as text if asked (a character cut in two is dropped there)."""
    width = 50
    fields = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept string" * keep_text

    def finish(t, row, start, length):
        cols = [], [], [], []
        kept_texts = []
        gone = _covered(t, row, start, length, width)
        for i in range(len(t.ids)):
            mask, raw = gone[t.at[i] : t.at[i + 1]], t.raw[t.at[i] : t.at[i + 1]]
            lost = int(mask.sum())
            spans = int(mask[0]) + int((mask[1:] & ~mask[:-1]).sum()) if lost else 0
            kept = (raw[~mask] if lost else raw).tobytes()
            for c, x in zip(cols, (len(mask), lost, spans, hashlib.sha256(kept).hexdigest()), strict=True):
                c.append(x)
            if keep_text:
                kept_texts.append(kept.decode("utf-8", "ignore"))
        out = [_ids(t), *(pa.array(c, k) for c, k in zip(cols, (*[pa.int64()] * 3, pa.string()), strict=True))]
        return pa.table(out + [pa.array(kept_texts, pa.string())] * keep_text, ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"] + ["kept"] * keep_text)

    return repeated_byte_spans(docs, width, k, finish, fields, **names)
