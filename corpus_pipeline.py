"""A training-corpus pipeline of four stages; each takes what the one before it kept.

A stage takes (spark, docs, sf_dir). All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seedcluster.llm import minhash, packing, repeats, toxicity
from seedcluster.llm.common import ready, table, written
from seedcluster.llm.tokens import tokenizer_path


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored 0.7 or more go. Trained on the labelled ones that are not held out."""
    ready(spark)
    return toxicity.without_toxic(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of documents of similarity 0.8 on five-word shingles, the smallest id stays; rows without id stay."""
    ready(spark)
    gone = minhash.near_duplicates(docs, width=5, percent=80).where(~F.col("kept")).select("doc_id")
    return docs.join(gone, "doc_id", "left_anti").select(docs.columns)


def cut_repeated_spans(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Bytes of 50-byte strings that an earlier document has go from the text; n_chars follows. Null texts stay null."""
    ready(spark)
    rest = tuple(c for c in docs.columns if c not in ("doc_id", "text"))
    kept = repeats.without_repeated_bytes(docs.withColumn("had_text", F.col("text").isNotNull()), keep_text=True, carry=(*rest, "had_text"))
    text = F.when(F.col("had_text"), F.col("kept"))
    now = {"text": text, "n_chars": F.length(text).cast("long")}
    return kept.select([now.get(c, F.col(f"`{c}`")).alias(c) for c in docs.columns])


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Windows of 2048 ids, filled with lexical neighbours."""
    return packing.pack(docs, tokenizer_path("byte_bpe_50k.json"), window=2048, end_id=1)


STAGES = [("toxicity", drop_toxic), ("minhash", drop_near_copies), ("suffix_array", cut_repeated_spans), ("packing", pack)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = written(docs, name)
    return docs
