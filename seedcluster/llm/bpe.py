"""Byte-level BPE encoding and decoding of whole texts.

Every text becomes overlapping chunks, which are cut into pre-tokens in parallel and stitched where their boundaries resynchronise; then the
pieces are encoded. The chunks of a batch's texts are cut side by side as rows of one array. A text of more than `long_chars` characters is
besides dealt to executors in parts, which are chunks themselves, and meets again to be stitched. Null text counts as empty; repeated rows give a row
each; an empty table no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, ready
from .tokens import code_points, cut, encoder, rows_in_chunks, stitch

#: Characters of a chunk and of what it shares with the next; of a text that is dealt to executors, and of its parts and their overlap.
CHUNK, SHARED = 1024, 128
LONG_CHARS, CHUNK_CHARS, OVERLAP = 1 << 16, 1 << 15, 1 << 9
FIELDS = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, n_chunks long"


class Joined:
    """Concatenates byte strings picked from a table by number."""

    def __init__(self, strings: list[bytes]):
        self.size = np.fromiter(map(len, strings), np.int64, len(strings))
        self.first = np.cumsum(self.size) - self.size
        self.flat = np.frombuffer(b"".join(strings), np.uint8)

    def __call__(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        size = self.size[ids]
        ends = np.cumsum(size)
        return self.flat[np.repeat(self.first[ids] - ends + size, size) + np.arange(ends[-1] if len(ends) else 0)], np.concatenate([[0], ends])


def _tables(path: str):
    e = encoder("tiktoken", path)
    if not hasattr(e, "decimal"):
        e.decimal = Joined([b"%d " % i for i in range(len(e.bytes))])
        e.raw = Joined(list(e.bytes))
    return e


def decode(ids: np.ndarray, path: str) -> bytes:
    """The raw bytes of the ids' tokens, one after the other."""
    return _tables(path).raw(np.asarray(ids, np.int64))[0].tobytes()


def _digests(e, ids: np.ndarray, counts: np.ndarray) -> tuple[list[int], list[str], list[str]]:
    n, a, b = [], [], []
    at = np.concatenate([[0], np.cumsum(counts)])
    step = 2000
    for i in range(0, len(counts), step):
        j = min(i + step, len(counts))
        for k in range(i, j):
            h, g = hashlib.sha256(), hashlib.sha256()
            for x in range(int(at[k]), int(at[k + 1]), 100_000):
                part = ids[x : min(x + 100_000, int(at[k + 1]))]
                text = e.decimal(part)[0]
                h.update(text[: -1 if x + len(part) == at[k + 1] else None])
                g.update(e.raw(part)[0])
            n.append(int(counts[k]))
            a.append(h.hexdigest())
            b.append(g.hexdigest())
    return n, a, b


def _out(ids: pa.Array, digests, chunk_counts) -> pa.RecordBatch:
    n, a, b = digests
    return pa.RecordBatch.from_arrays([ids, pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string()), pa.array(chunk_counts, pa.int64())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "n_chunks"])


def encode_and_decode(docs: DataFrame, path: str, doc_id: str = "doc_id", text: str = "text", long_chars: int = LONG_CHARS, chunk_chars: int = CHUNK_CHARS, overlap: int = OVERLAP, chunk: int = CHUNK, shared: int = SHARED) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256, n_chunks): digests of each text's ids and of the bytes they decode to, and the chunks it was cut in."""
    ready(docs.sparkSession)

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = _tables(path)
        for batch in batches:
            for i in range(0, batch.num_rows, 500):
                part = batch.slice(i, 500)
                points, offsets = code_points(part.column(1))
                for r, to in chunks(np.diff(offsets), 500_000):
                    own, at = points[offsets[r] : offsets[to]], offsets[r : to + 1] - offsets[r]
                    starts, n = rows_in_chunks(own, at, e.table, chunk, shared)
                    ids, counts = e.encode_cut(own, at, starts)
                    yield _out(part.column(0).slice(r, to - r), _digests(e, ids, counts), n)

    def parted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                points, _ = code_points(batch.column(2).slice(i, 1))
                for no, a in enumerate(range(0, len(points), chunk_chars)):
                    piece = points[a : a + chunk_chars + overlap].tobytes().decode("utf-32-le")
                    yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, 1), batch.column(1).slice(i, 1), pa.array([no], pa.int32()), pa.array([a + chunk_chars + overlap >= len(points)]), pa.array([piece])], ["doc_id", "same", "no", "last", "piece"])

    def boundaries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _tables(path).table
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1)
                points, _ = code_points(row.column(4))
                got = cut(points, row.column(3)[0].as_py(), table)
                yield pa.RecordBatch.from_arrays([*row.columns, pa.array([got.astype(np.int32).tobytes()])], ["doc_id", "same", "no", "last", "piece", "cuts"])

    def stitched(group: pa.Table) -> pa.Table:
        e = _tables(path)
        no = group.column("no").to_numpy()
        copies = int((no == 0).sum())
        rows = [int(np.flatnonzero(no == k)[0]) for k in range(int(no.max()) + 1)]
        pieces = [code_points(group.column("piece").slice(r, 1))[0] for r in rows]
        points = np.concatenate([p[:chunk_chars] for p in pieces[:-1]] + pieces[-1:])
        cuts = [(k * chunk_chars, np.frombuffer(group.column("cuts")[r].as_py(), np.int32).astype(np.int64)) for k, r in enumerate(rows)]
        starts = stitch(points, cuts, e.table)
        ids, counts = e.pieces(points, starts)
        n, a, b = _digests(e, ids, np.array([counts]))
        return pa.Table.from_batches([_out(group.column("doc_id").slice(0, 1).combine_chunks(), (n, a, b), [len(rows)])] * copies)

    docs = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    size = F.length("text")
    short = docs.where(size <= long_chars).mapInArrow(whole, FIELDS)
    long = docs.where(size > long_chars).select("doc_id", F.xxhash64("text").alias("same"), "text")
    long = long.mapInArrow(parted, "doc_id long, same long, no int, last boolean, piece string")
    long = long.repartition("doc_id", "same", "no").mapInArrow(boundaries, "doc_id long, same long, no int, last boolean, piece string, cuts binary")
    return short.unionByName(long.groupBy("doc_id", "same").applyInArrow(stitched, FIELDS))
