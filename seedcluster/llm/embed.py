"""Embedding near-duplicates: sign hashing by random hyperplanes in several tables, exact cosines, components.

Equal vectors are one class with a count. Tables and bits follow the number of classes, so that a bucket holds about a fixed number of
unlike vectors and a pair at the threshold is missed by all tables with probability `miss`. A bucket with more members than
a block becomes pairs of blocks, each a task's work; no pair leaves a task, only each member's number of partners and its block component. A pair is
counted in the first table that shows it. Vectors that are null, of zero norm or hold null or non-finite components link with nothing; vectors of
different lengths do not link; repeated rows count as vectors of their own; an empty table gives no rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ready, written
from .components import components

BLOCK = 1024


def plan(n: int, cosine: float, miss: float, load: int = 64) -> tuple[int, int]:
    """Bits to a table and tables."""
    bits = min(max(4, round(math.log2(max(n, 1) / load)) if n > load else 4), 30)
    agree = (1 - math.acos(cosine) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(miss) / math.log1p(-agree)))


def planes(dim: int, n: int, seed: int = 3) -> np.ndarray:
    return np.random.default_rng([seed, dim]).standard_normal((dim, n))


def _matrix(column: pa.Array) -> list[np.ndarray | None]:
    """Vectors in double precision; None for those that link with nothing."""
    out = []
    for x in column.to_pylist():
        v = None
        if x and None not in x:
            v = np.array(x, float)
            v = v if np.isfinite(v).all() and v.any() else None
        out.append(v)
    return out


def _labels(link: np.ndarray) -> np.ndarray:
    """Components of a block by its links: the least position reached."""
    label = np.arange(len(link))
    seen = np.zeros(len(link), bool)
    for i in range(len(link)):
        if seen[i]:
            continue
        front = np.zeros(len(link), bool)
        front[i] = True
        group = front.copy()
        while front.any():
            front = link[front].any(0) & ~group
            group |= front
        label[group] = i
        seen |= group
    return label


def near_vectors(vectors: DataFrame, cosine: float = 0.95, miss: float = 1e-6, vec_id: str = "vec_id", embedding: str = "embedding", block: int = BLOCK) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for each vector."""
    spark = ready(vectors.sparkSession)

    def packed(batches):
        for batch in batches:
            got = _matrix(batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([None if v is None else v.tobytes() for v in got], pa.binary())], ["vec_id", "v"])

    rows = written(vectors.select(F.col(vec_id).cast("long").alias("vec_id"), F.col(embedding).cast("array<double>").alias("e")).mapInArrow(packed, "vec_id long, v binary"), "vectors")
    classes = written(rows.where("v IS NOT NULL").groupBy("v").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("n")), "classes")
    n = classes.count()
    bits, tables = plan(n, cosine, miss)
    weights = (1 << np.arange(bits)).astype(np.int64)

    def hashed(batches):
        for batch in batches:
            got = [np.frombuffer(x.as_buffer(), float) for x in batch.column(0)]
            codes = [None] * len(got)
            for dim in {len(v) for v in got}:
                at = [i for i, v in enumerate(got) if len(v) == dim]
                sign = (np.stack([got[i] for i in at]) @ planes(dim, bits * tables) > 0).reshape(len(at), tables, bits)
                for i, c in zip(at, (sign @ weights).astype(np.int32), strict=True):
                    codes[i] = c.tolist()
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(codes, pa.list_(pa.int32())), pa.array([len(v) for v in got], pa.int32())], ["v", "rep", "n", "codes", "dim"])

    heads = written(classes.select("v", "rep", "n").mapInArrow(hashed, "v binary, rep long, n long, codes array<int>, dim int"), "hashed")
    keyed = heads.select("rep", F.posexplode("codes").alias("t", "code"), "dim").select("rep", "t", "code", "dim")
    crowd = keyed.groupBy("t", "code", "dim").agg(F.count(F.lit(1)).alias("crowd")).where("crowd > 1")
    placed = keyed.join(crowd, ["t", "code", "dim"]).select("rep", "t", "code", "dim", F.ceil(F.col("crowd") / block).cast("int").alias("m"))
    placed = placed.withColumn("own", F.pmod(F.xxhash64("rep"), F.col("m")).cast("int"))
    pairs = placed.select("*", F.explode(F.sequence(F.lit(0), F.col("m") - 1)).alias("o"))
    pairs = pairs.select("rep", "t", "code", "dim", "own", F.least("own", "o").alias("lo"), F.greatest("own", "o").alias("hi"))
    cells = max(int(spark.conf.get("spark.sql.shuffle.partitions")), n * tables // 8192)
    tasks = pairs.withColumn("cell", F.pmod(F.xxhash64("t", "code", "dim", "lo", "hi"), F.lit(cells))).join(heads.select("rep", "v", "n", "codes"), "rep")

    def linked(group: pa.Table) -> pa.Table:
        keys = np.stack([group.column(c).to_numpy() for c in ("t", "code", "dim", "lo", "hi")])
        order = np.lexsort(keys)
        cut = np.flatnonzero(np.any(np.diff(keys[:, order]) != 0, axis=0)) + 1
        rep, own, size = (group.column(c).to_numpy() for c in ("rep", "own", "n"))
        v, codes = group.column("v").combine_chunks(), group.column("codes").combine_chunks()
        out = [], [], []
        for at in np.split(order, cut):
            t, _, _, lo, hi = keys[:, at[0]]
            if len(at) < 2:
                continue
            m = np.stack([np.frombuffer(v[int(i)].as_buffer(), float) for i in at])
            norm = np.sqrt((m * m).sum(1))
            link = (m @ m.T) / np.outer(norm, norm) >= cosine
            np.fill_diagonal(link, False)
            if lo != hi:
                link &= own[at][:, None] != own[at][None, :]
            if not link.any():
                continue
            label = _labels(link)
            c = np.stack([codes[int(i)].values.to_numpy()[:t] for i in at]) if t else np.zeros((len(at), 0), np.int32)
            new = link.copy()
            for k in range(int(t)):
                new &= c[:, k][:, None] != c[:, k][None, :]
            out[0].append(rep[at])
            out[1].append(new @ size[at])
            out[2].append(rep[at][label])
        got = [np.concatenate(x).astype(np.int64) if x else np.zeros(0, np.int64) for x in out]
        return pa.table([pa.array(x) for x in got], ["rep", "partners", "label"])

    found = written(tasks.groupBy("cell").applyInArrow(linked, "rep long, partners long, label long"), "linked")
    comp = components(found.select(F.col("rep").alias("u"), F.col("label").alias("v"))).withColumnRenamed("node", "rep")
    partners = found.groupBy("rep").agg(F.sum("partners").alias("partners"))
    per_class = classes.join(partners, "rep", "left").join(comp, "rep", "left").select("v", (F.coalesce("partners", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "rep").alias("c"))
    return rows.join(per_class, "v", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("c", "vec_id").alias("component_id"), (F.coalesce("c", "vec_id") == F.col("vec_id")).alias("kept"))
