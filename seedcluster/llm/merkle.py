"""Merkle fingerprints of documents: leaves are runs of words, under paragraphs, under sections, under one root.

A leaf ends at a line's end or behind a word whose hash says so, and a section behind a paragraph whose hash says so, so an edit
changes the leaves it touches and leaves the others where they were. Leaves partition the text's bytes; equal roots mean equal texts, and
walking down from differing roots finds what was edited. Null text counts as empty; repeated ids are ordered by text; a lone document
is its own next one; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import CODES, parts_for, ready, shard_bounds, spans_hash, word_spans

#: A word in so many ends a leaf, a paragraph in so many a section.
LEAF, SECTION = 8, 4
LOWEST = -(1 << 63)


def _h(data: bytes, size: int = 16) -> bytes:
    return hashlib.blake2b(data, digest_size=size).digest()


#: What tree() returns.
Tree = tuple[bytes, list[tuple[bytes, list[tuple[bytes, list[tuple[bytes, int, int]]]]]]]


def tree(text: str) -> Tree:
    """(root, sections); a section is (hash, paragraphs), a paragraph (hash, leaves), a leaf (hash, first byte, end)."""
    data = text.encode()
    raw = np.frombuffer(data, np.uint8)
    starts, ends, _ = word_spans(raw, np.array([0, len(raw)], np.int64))
    lines = np.flatnonzero(raw == 10) + 1
    cuts = ends[spans_hash(CODES[raw], starts, ends) % np.uint64(LEAF) == 0] if len(starts) else starts
    cuts = np.unique(np.concatenate([cuts, lines, [len(raw)]])).astype(np.int64)
    is_line = np.isin(cuts, lines).tolist()
    sections, paragraphs, leaves, at = [], [], [], 0
    for end, line in zip(cuts.tolist(), is_line, strict=True):
        if end > at:
            leaves.append((_h(data[at:end]), at, end))
        at = end
        if leaves and (line or end == len(data)):
            h = _h(b"".join(x[0] for x in leaves))
            paragraphs.append((h, leaves))
            leaves = []
            if h[0] % SECTION == 0 or end == len(data):
                sections.append((_h(b"s" + b"".join(x[0] for x in paragraphs)), paragraphs))
                paragraphs = []
    if paragraphs:
        sections.append((_h(b"s" + b"".join(x[0] for x in paragraphs)), paragraphs))
    return _h(b"r" + b"".join(x[0] for x in sections), 32), sections


def edited(a: str, b: str) -> list[tuple[int, int]]:
    """Byte spans of b's leaves that a does not have in its differing branches; none if the roots agree."""
    (root, mine), (other, theirs) = tree(a), tree(b)
    if root == other:
        return []
    same = {h for h, _ in mine}
    left = [p for h, ps in mine if h not in {x for x, _ in theirs} for p in ps]
    same_p = {h for h, _ in left}
    same_l = {x[0] for h, leaves in left for x in leaves}
    return [(s, e) for h, ps in theirs if h not in same for p, leaves in ps if p not in same_p for x, s, e in leaves if x not in same_l]


def fingerprint(text: str) -> str:
    """The root in hex, and the tree in text order: sections apart by '|', each its shortened hash, ':' and its paragraphs; these apart by ';', each its shortened hash, '=' and its leaves."""
    return shown(tree(text))


def shown(t: Tree) -> str:
    root, sections = t
    return f"{root.hex()}:" + "|".join(f"{s[:4].hex()}:" + ";".join(f"{p[:4].hex()}=" + ".".join(x[0][:4].hex() for x in leaves) for p, leaves in ps) for s, ps in sections)


def likeness(a: Tree, b: Tree) -> float:
    """Twice the leaves in both, each as often as in either, over the leaves of each; 1 for equal roots. Leaves are looked at only under differing branches."""
    (root, mine), (other, theirs) = a, b
    if root == other:
        return 1.0
    total, both = sum(len(x) for t in (mine, theirs) for _, ps in t for _, x in ps), 0

    def apart(x: list, y: list) -> tuple[list, list]:
        """What is below the branches that the other side does not have; the leaves of the others are in both."""
        nonlocal both
        n, m = Counter(h for h, _ in x), Counter(h for h, _ in y)
        common = n & m
        left = []
        for side in (x, y):
            spare, rest = Counter(common), []
            for h, under in side:
                if spare[h] > 0:
                    spare[h] -= 1
                    both += size(under) if side is x else 0
                else:
                    rest += under
            left.append(rest)
        return left[0], left[1]

    def size(under: list) -> int:
        return sum(len(leaves) for _, leaves in under) if len(under[0]) == 2 else len(under)

    x, y = apart(*apart(mine, theirs))
    both += (Counter(h for h, _, _ in x) & Counter(h for h, _, _ in y)).total()
    return min(2 * both / total, 1 - 1e-9) if total else 0.0


FIELDS = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def edited_against_next(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shard_bytes: int = 4 << 20) -> DataFrame:
    """Fingerprints of each text and of its edit by the next document's beginning.

    Texts move once, to runs of doc_id between quantiles that are ids of the table; a run's first document goes to the
    run before it as well, and the first of all to the last run.
    """
    ready(docs.sparkSession)
    docs = docs.select(F.coalesce(F.col(doc_id).cast("long"), F.lit(LOWEST)).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    bounds = np.array(shard_bounds(docs, "doc_id", parts_for(docs, shard_bytes)), np.int64)
    first = docs.agg(F.min("doc_id")).first()[0]
    bounds = bounds[bounds > first] if first is not None else bounds
    last = len(bounds)

    def placed(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            own = np.searchsorted(bounds, ids, "right")
            yield pa.RecordBatch.from_arrays([pa.array(own), pa.array(np.zeros(len(ids), bool)), *batch.columns], names)
            again = np.flatnonzero((ids == first) | ((own > 0) & (ids == bounds[np.maximum(own, 1) - 1] if last else False)))
            if len(again):
                part = batch.take(pa.array(again))
                to = np.where(ids[again] == first, last, own[again] - 1)
                yield pa.RecordBatch.from_arrays([pa.array(to), pa.array(np.ones(len(again), bool)), *part.columns], names)

    def run(group: pa.Table) -> pa.Table:
        group = group.sort_by([("beyond", "ascending"), ("doc_id", "ascending"), ("text", "ascending")])
        ids, texts, beyond = (group.column(c).to_pylist() for c in ("doc_id", "text", "beyond"))
        n = beyond.index(True) if True in beyond else len(ids)
        trees: list[Tree | None] = [None] * len(ids)
        out = []
        for i in range(n):
            a, b = texts[i], texts[i + 1]
            for k in (i, i + 1):
                trees[k] = trees[k] or tree(texts[k])
            half = len(a) // 2
            edit = a[: len(a) - half] + b[:half]
            changed = tree(edit)
            out.append((None if ids[i] == LOWEST else ids[i], len(a), hashlib.sha256(edit.encode()).hexdigest(), shown(trees[i]), shown(changed), likeness(trees[i], changed), likeness(trees[i], trees[i + 1])))
            trees[i] = None
        cols = list(zip(*out, strict=True)) or [()] * 7
        kinds = [pa.int64(), pa.int64(), *[pa.string()] * 3, *[pa.float64()] * 2]
        return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

    names = ["shard", "beyond", "doc_id", "text"]
    return docs.mapInArrow(placed, "shard long, beyond boolean, doc_id long, text string").groupBy("shard").applyInArrow(run, FIELDS)
