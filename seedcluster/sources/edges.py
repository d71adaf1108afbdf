"""Reading and writing graphs: edge lists, adjacency lines, a directory-partitioned adjacency."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.prepare import normalise_edges


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", comment: str = "#") -> DataFrame:
    """Two ids to a line; lines that start with `comment` are skipped."""
    raw = spark.read.schema("a BIGINT, b BIGINT").csv(path, sep=sep, comment=comment)
    return normalise_edges(raw, "a", "b")


def write_edge_list(edges: DataFrame, path: str, sep: str = "\t") -> None:
    edges.select("src", "dst").write.mode("overwrite").csv(path, sep=sep)


def read_edges(spark: SparkSession, path: str, fmt: str) -> DataFrame:
    """Edges (src, dst) in a format that Spark reads itself: parquet, orc, json."""
    reader = spark.read.schema("src BIGINT, dst BIGINT") if fmt == "json" else spark.read
    return normalise_edges(reader.format(fmt).load(path), "src", "dst")


def read_adjacency_text(spark: SparkSession, path: str, first: int = 1, part_bytes: int = 64 << 20) -> DataFrame:
    """Line i of a file holds the neighbours of node i, counted from `first`. Tasks read ranges of lines; the numbers of their first lines come from one count of line ends."""
    from .reader import register

    register(spark)
    pairs = spark.read.format("adjacency_lines").options(path=path, first=str(first), partBytes=str(part_bytes)).load()
    return normalise_edges(pairs, "line", "nbr")


def write_adjacency(adj: DataFrame, path: str, buckets: int = 64) -> None:
    """Adjacency by directories of node_bucket, sorted by node inside, so that a lookup prunes directories and row groups."""
    adj.withColumn("node_bucket", F.pmod("node", F.lit(buckets)).cast("int")).repartition(buckets, "node_bucket").sortWithinPartitions("node_bucket", "node", "nbr").write.mode("overwrite").partitionBy("node_bucket").parquet(path)


def open_adjacency(spark: SparkSession, path: str, nodes: list[int] | None = None, buckets: int = 64) -> DataFrame:
    """The adjacency, or only what holds the given few nodes."""
    adj = spark.read.parquet(path)
    if nodes is not None:
        adj = adj.where(F.col("node_bucket").isin(sorted({n % buckets for n in nodes})) & F.col("node").isin(nodes))
    return adj.drop("node_bucket")


def save_adjacency(adj: DataFrame, name: str, buckets: int = 64) -> None:
    """Adjacency as a bucketed table, sorted by node: joins on node with another table of as many buckets need no exchange."""
    adj.write.mode("overwrite").bucketBy(buckets, "node").sortBy("node", "nbr").saveAsTable(name)


def write_result(df: DataFrame, path: str, fmt: str = "parquet", partition: str | None = None) -> None:
    writer = df.write.mode("overwrite").format(fmt)
    (writer.partitionBy(partition) if partition else writer).save(path)
