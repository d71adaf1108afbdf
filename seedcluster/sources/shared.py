"""Tables that cut lineage, in the folder that every executor sees."""

from __future__ import annotations

import os
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; one of our own only where that is unset and all runs in one process, as in tests."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not re.fullmatch(r"local(\[[^]]*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors see")
        found = getattr(spark, "_seedcluster_shared", None) or tempfile.mkdtemp(prefix="seedcluster-")
        spark._seedcluster_shared = found
    return found.rstrip("/")


def written(df: DataFrame, name: str) -> DataFrame:
    """df, written as Parquet in the shared folder and read again. The table stays until clean()."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    spark.__dict__.setdefault("_seedcluster_tables", []).append(path)
    return spark.read.schema(df.schema).parquet(path)


def clean(spark: SparkSession) -> int:
    """Deletes the tables that written() has made in this session; frames that read them are of no use afterwards. How many went."""
    paths = spark.__dict__.pop("_seedcluster_tables", [])
    for path in paths:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    return len(paths)


def importable(spark: SparkSession, root: str) -> SparkSession:
    """Lets Python workers import modules from root, wherever the driver was started."""
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if root not in paths:
        env["PYTHONPATH"] = os.pathsep.join([root, *paths])
    return spark
