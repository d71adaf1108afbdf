"""Helpers shared by the operators: shared-folder tables, sizes, shards and byte-array hashing."""

from __future__ import annotations

import ctypes
import math
import os
import re
import sys
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Odd 64-bit multipliers and shifts of the splitmix64 finaliser (fixed values of that function).
MIX_1, MIX_2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
BASE = np.uint64(0x9E3779B97F4A7C15)
#: Characters of text that numpy code holds at once within a batch.
CHUNK = 400_000
#: Sizes from here on are Catalyst's stand-in for not known.
UNKNOWN = 1 << 60


def ready(spark: SparkSession) -> SparkSession:
    """Lets Python workers import this package, wherever the driver was started."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    env = spark.sparkContext.environment
    paths = env.get("PYTHONPATH", "").split(os.pathsep)
    if root not in paths:
        env["PYTHONPATH"] = os.pathsep.join([root, *filter(None, paths)])
    if root not in sys.path:
        sys.path.insert(0, root)
    return spark


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return ready(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir, which all executors see; one of our own only where that is unset and all runs in one process, as in tests."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not re.fullmatch(r"local(\[[^]]*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors see")
        found = getattr(spark, "_seedcluster_shared", None) or tempfile.mkdtemp(prefix="seedcluster-")
        spark._seedcluster_shared = found
    return found.rstrip("/")


def written(df: DataFrame, name: str) -> DataFrame:
    """df, written as Parquet in the shared folder and read again, so that lineage ends there. The table stays for clean() of the sources to delete."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    spark.__dict__.setdefault("_seedcluster_tables", []).append(path)
    return spark.read.schema(df.schema).parquet(path)


def with_least(rows: DataFrame, keys: list[str], value: str) -> DataFrame:
    """rows with a column `least`: the smallest value among rows of the same keys, where one key may hold a great share of all rows.

    Each key's rows are dealt to as many parts as there are shuffle partitions. Parts have their own least, a row a part; those meet by key, of which no more than
    the parts come together; and rows meet the answer by key and part. No task gets a key's rows.
    """
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.withColumn("_part", F.pmod(F.xxhash64(F.lit(17), value), F.lit(parts)))
    own = dealt.groupBy(*keys, "_part").agg(F.min(value).alias("_own"))
    return dealt.join(own.join(own.groupBy(*keys).agg(F.min("_own").alias("least")), keys).select(*keys, "_part", "least"), [*keys, "_part"]).drop("_part")


def size_bytes(df: DataFrame) -> int:
    """Catalyst's estimate for what df reads: for scans, the bytes of their files, and nothing runs. Where Catalyst knows no size, a kilobyte a row."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    found = [int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size())]
    return sum(found) if max(found, default=0) < UNKNOWN else 1000 * df.count()


def parts_for(df: DataFrame, each: int = 4 << 20) -> int:
    """Into how many groups of about `each` bytes of files df goes."""
    spark = df.sparkSession
    n = math.ceil(size_bytes(df) / each)
    return max(8, min(int(spark.conf.get("spark.sql.shuffle.partitions")), 64), min(n, 1 << 20))


#: Called before a task of an operator that does not use what others have left in its worker.
CLEARED: list = []


def _given_back() -> None:
    """Freed memory goes back to the system, where the C library can do so."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def lean(f, keep: bool = False):
    """f(batches) for mapInArrow. Workers serve all operators of a session one after another: what others keep in one goes first, unless `keep`, and freed memory is given back at the end."""

    def run(batches):
        if not keep:
            for clear in CLEARED:
                clear()
        try:
            yield from f(batches)
        finally:
            _given_back()

    return run


def lean_group(f):
    """The same for f(group) of applyInArrow."""

    def run(group):
        try:
            return f(group)
        finally:
            _given_back()

    return run


def lean_groups(f):
    """The same for f(left, right) of cogrouped ones."""

    def run(left, right):
        try:
            return f(left, right)
        finally:
            _given_back()

    return run


def chunks(lengths: np.ndarray, most: int = CHUNK) -> Iterator[tuple[int, int]]:
    """Ranges of rows of at most `most` units together; a longer row stands alone."""
    at = 0
    while at < len(lengths):
        end, total = at, 0
        while end < len(lengths) and (end == at or total + int(lengths[end]) <= most):
            total += int(lengths[end])
            end += 1
        yield at, end
        at = end


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string column (null: empty) and where each row starts (one more entry for the end)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string()).fill_null("")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    data = column.buffers()[2] if len(column) else None
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], (offsets - offsets[0]).astype(np.int64)


def mix64(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= MIX_1
    x ^= x >> np.uint64(27)
    x *= MIX_2
    x ^= x >> np.uint64(31)
    return x


def coded(seed: int) -> np.ndarray:
    """A 64-bit code for each byte."""
    return mix64(np.arange(1, 257, dtype=np.uint64) * BASE + np.uint64(seed))


CODES = coded(7)


def powers(n: int, base: int) -> np.ndarray:
    """base**0 .. base**n modulo 2**64."""
    out = np.full(n + 1, base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


_POWERS: dict[int, np.ndarray] = {}


def spans_hash(codes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of codes[s:e] for each pair: differences of one polynomial's prefix sums, shifted to a common degree."""
    n = len(codes)
    base, back = 0xD1342543DE82EF95, pow(0xD1342543DE82EF95, -1, 1 << 64)
    for b in (base, back):
        if len(_POWERS.get(b, ())) <= n:
            _POWERS[b] = powers(max(n, 1 << 16), b)
    prefix = np.zeros(n + 1, np.uint64)
    np.cumsum(codes * _POWERS[base][:n], out=prefix[1:])
    got = (prefix[ends] - prefix[starts]) * _POWERS[back][starts]
    return mix64(got ^ (ends - starts).astype(np.uint64) * MIX_1)


SPACES = np.zeros(256, bool)
SPACES[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def word_spans(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each word [^\\x20\\x09-\\x0D]+: first byte, end, row. Words end where their row ends."""
    if not len(raw):
        return (np.zeros(0, np.int64),) * 3
    word = ~SPACES[raw]
    first = word.copy()
    first[1:] &= ~word[:-1]
    cut = offsets[1:-1]
    cut = cut[cut < len(raw)]
    first[cut] = word[cut]
    starts = np.flatnonzero(first)
    last = word.copy()
    last[:-1] &= ~word[1:]
    cut = offsets[1:] - 1
    cut = cut[(cut >= 0) & (cut < len(raw))]
    last[cut] |= word[cut]
    return starts, np.flatnonzero(last) + 1, np.searchsorted(offsets, starts, "right") - 1


def shard_bounds(df: DataFrame, key: str, shards: int) -> list[int]:
    """Ascending keys at which about equal shards begin (all but the first): one aggregate of the key alone, as many values as shards."""
    if shards <= 1:
        return []
    asked = [i / shards for i in range(1, shards)]
    got = df.agg(F.percentile_approx(F.col(key), asked, max(10_000, 20 * shards)).alias("b")).first()
    return sorted(set(got["b"] or []))
