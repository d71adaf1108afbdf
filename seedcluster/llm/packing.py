"""Lexical retrieval packing: a sharded BM25 index returns unused neighbours that fill each seed document's window.

Document frequencies and the average length are taken over all documents in the pass that encodes them; they
are one number for each id of the vocabulary, so their size is fixed. Documents are placed by their heaviest ids: sorted by them and dealt to
ranges, so that texts with the same key words come to lie in one index shard, a run of at most `shard_docs` documents and `shard_ids` ids. Within a shard every
document is indexed and a query is all ids of its seed. A window takes its seed's best unused neighbours until it is full; the document that reaches the end is
cut there, and its rest opens the next window as its seed. Windows run on from shard to shard, so only the last one of a range has padding.
Neighbours in other shards are not seen; the cost is linear in the corpus for that.
Null text counts as empty (its end id alone); repeated rows are packed each, next to each other; an empty table gives no rows.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, ready, written
from .tokens import code_points, encoder

K1, B = 1.2, 0.75
#: Ids that make a document's place; ids of a shard's vocabulary whose postings are a dense matrix; ids a range holds; ranges at most.
KEYS, DENSE, RANGE_IDS, RANGES = 4, 2048, 4_000_000, 100_000
FIELDS = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def counted(docs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, id, times) of each id in each document, by document."""
    flat = np.concatenate(docs).astype(np.uint64) if len(docs) else np.zeros(0, np.uint64)
    key, tf = np.unique(np.repeat(np.arange(len(docs), dtype=np.uint64), [len(d) for d in docs]) << np.uint64(17) | flat, return_counts=True)
    return (key >> np.uint64(17)).astype(np.int64), (key & np.uint64(0x1FFFF)).astype(np.int64), tf


def bm25(doc: np.ndarray, term: np.ndarray, tf: np.ndarray, size: np.ndarray, df: np.ndarray, n_all: int, mean_all: float) -> np.ndarray:
    idf = np.log1p((n_all - df + 0.5) / (df + 0.5))
    return idf[term] * tf * (K1 + 1) / (tf + K1 * (1 - B + B * size[doc] / max(mean_all, 1e-9)))


def places(doc: np.ndarray, term: np.ndarray, tf: np.ndarray, n: int) -> np.ndarray:
    """A number for each document that its heaviest ids make, the heaviest first: times by the logarithm of the id, since ids were learnt by falling frequency."""
    weight = tf * np.log(term + 2.0)
    order = np.lexsort((term, -weight, doc))
    rank = np.arange(len(doc)) - np.searchsorted(doc, doc)
    key = np.zeros(n, np.uint64)
    for k in range(KEYS):
        at = order[rank == k]
        key[doc[at]] |= term[at].astype(np.uint64) << np.uint64(16 * (KEYS - 1 - k))
    return (key ^ np.uint64(1 << 63)).astype(np.int64)


class Index:
    """BM25 over a shard's documents; a query is all ids of its seed, each once. Postings of the commonest ids are multiplied as one matrix, the others are lists."""

    def __init__(self, docs: list[np.ndarray], df: np.ndarray, n_all: int, mean_all: float):
        self.n = len(docs)
        doc, term, tf = counted(docs)
        weight = bm25(doc, term, tf, np.array([len(d) for d in docs]), df, n_all, mean_all)
        local = np.bincount(term, minlength=len(df))
        common = np.argsort(-local, kind="stable")[:DENSE]
        column = np.full(len(df), -1)
        column[common] = np.arange(len(common))
        dense = column[term] >= 0
        w = np.zeros((self.n, len(common)), np.float32)
        w[doc[dense], column[term[dense]]] = weight[dense]
        self.close = (w > 0).astype(np.float32) @ w.T
        rest = np.flatnonzero(~dense & (local[term] > 1))
        self.queries = np.split(term[rest], np.searchsorted(doc[rest], np.arange(1, self.n)))
        by_term = rest[np.argsort(term[rest], kind="stable")]
        self.doc, self.weight = doc[by_term], weight[by_term]
        self.at = np.searchsorted(term[by_term], np.arange(len(df) + 1))

    def scores(self, seed: int) -> np.ndarray:
        out = self.close[seed].astype(float)
        spans = [(self.at[t], self.at[t + 1]) for t in self.queries[seed].tolist()]
        if spans:
            out += np.bincount(np.concatenate([self.doc[a:b] for a, b in spans]), np.concatenate([self.weight[a:b] for a, b in spans]), self.n)
        return out

    def neighbours(self, seed: int, unused: np.ndarray, n: int) -> np.ndarray:
        """The n best unused documents with a score above 0, best first, ties by position."""
        score = np.where(unused, self.scores(seed), 0)
        if len(score) > 4 * n:
            top = np.flatnonzero(score >= max(np.partition(score, -n)[-n], 1e-6))
        else:
            top = np.flatnonzero(score > 1e-6)
        return top[np.lexsort((top, -score[top]))][:n]


def arrange(docs: list[np.ndarray], index: Index, window: int, fill: int = 0) -> list[int]:
    """The order in which a shard's documents are laid end to end and cut into windows; the first window has `fill` ids already."""
    unused, order, seed, following = np.ones(len(docs), bool), [], -1, 0

    def put(d: int) -> None:
        nonlocal fill
        unused[d] = False
        order.append(d)
        fill += len(docs[d])

    while len(order) < len(docs):
        if seed < 0:
            while not unused[following]:
                following += 1
            seed = following
            put(seed)
        while fill < window:
            got = index.neighbours(seed, unused, 8)
            for d in got.tolist():
                put(d)
                if fill >= window:
                    break
            if not len(got):
                break
        # No neighbour left: the next document seeds the rest of the window.
        seed = order[-1] if fill >= window and fill % window else -1
        fill %= window
    return order


def pack(docs: DataFrame, path: str, window: int = 2048, end_id: int = 1, doc_id: str = "doc_id", text: str = "text", shard_docs: int = 4000, shard_ids: int = 4_000_000) -> DataFrame:
    """A row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    ready(docs.sparkSession)
    docs = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    names = ["rid", "doc_id", "place", "ids", "df", "n_docs", "n_ids"]
    types = [pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.int64(), pa.int64()]

    def encoded(batches):
        e = encoder("tokenizers", path)
        df, n_docs, n_ids = np.zeros(1 << 16, np.int64), 0, 0
        own = TaskContext.get().partitionId() << 40
        for batch in batches:
            for i in range(0, batch.num_rows, 500):
                part = batch.slice(i, 500)
                ids, n = e.encode(*code_points(part.column(1)))
                ids, n = np.insert(ids, np.cumsum(n), end_id), n + 1
                at = np.concatenate([[0], np.cumsum(n)])
                doc, term, tf = counted([ids[a:b] for a, b in zip(at, at[1:], strict=False)])
                df += np.bincount(term, minlength=1 << 16)
                rid = pa.array(own + n_docs + np.arange(len(n)))
                n_docs, n_ids = n_docs + len(n), n_ids + len(ids)
                place = places(doc, term, tf, len(n))
                rows = [rid, part.column(0), pa.array(place), pa.array([ids[a:b].tobytes() for a, b in zip(at, at[1:], strict=False)], pa.binary())]
                yield pa.RecordBatch.from_arrays([*rows, *(pa.nulls(len(n), t) for t in types[4:])], names)
        if n_docs:
            yield pa.RecordBatch.from_arrays([*(pa.nulls(1, t) for t in types[:4]), pa.array([df.astype("<i8").tobytes()]), pa.array([n_docs]), pa.array([n_ids])], names)

    def summed(batches):
        df, n_docs, n_ids = np.zeros(1 << 16, np.int64), 0, 0
        for batch in batches:
            for x in batch.column(0).to_pylist():
                df += np.frombuffer(x, "<i8")
            n_docs, n_ids = n_docs + sum(batch.column(1).to_pylist()), n_ids + sum(batch.column(2).to_pylist())
        if n_docs:
            yield pa.RecordBatch.from_arrays([pa.array([df.astype("<i8").tobytes()]), pa.array([n_docs]), pa.array([n_ids])], ["df", "n_docs", "n_ids"])

    table = written(docs.mapInArrow(lean(encoded, keep=True), "rid long, doc_id long, place long, ids binary, df binary, n_docs long, n_ids long"), "packing")
    parts = table.where("df IS NOT NULL").select("df", "n_docs", "n_ids").coalesce(8).mapInArrow(lean(summed), "df binary, n_docs long, n_ids long").collect()
    df, n_all, n_ids = sum((np.frombuffer(x["df"], "<i8") for x in parts), np.zeros(1 << 16, np.int64)), sum(x["n_docs"] for x in parts), sum(x["n_ids"] for x in parts)
    mean = n_ids / max(n_all, 1)

    def packed(batches):
        own, at = TaskContext.get().partitionId() << 32, 0
        doc, ids, held = [], [], 0

        def laid() -> pa.RecordBatch:
            nonlocal at
            rows = []
            for d in arrange(ids, Index(ids, df, n_all, mean), window, at % window):
                start = 0
                while start < len(ids[d]):
                    length = min(len(ids[d]) - start, window - at % window)
                    rows.append((doc[d], start, length, zlib.crc32(ids[d][start : start + length].astype("<u4").tobytes()), len(ids[d]), own | at // window, at % window))
                    start, at = start + length, at + length
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

        for batch in batches:
            for i, x in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if ids and (len(ids) == shard_docs or held + len(x) // 2 > shard_ids):
                    yield laid()
                    doc, ids, held = [], [], 0
                doc.append(i)
                ids.append(np.frombuffer(x, np.uint16))
                held += len(ids[-1])
        if ids:
            yield laid()

    ranges = max(1, min(RANGES, -(-n_ids // min(RANGE_IDS, shard_ids))))
    texts = table.where("ids IS NOT NULL").select("rid", "doc_id", "place", "ids")
    sorted_ = texts.repartitionByRange(ranges, "place", "doc_id", "rid").sortWithinPartitions("place", "doc_id", "rid")
    return sorted_.select("doc_id", "ids").mapInArrow(lean(packed), FIELDS)
