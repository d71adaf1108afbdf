"""The operators' queries over whole tables, and SQL for those that SQL expresses."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import bpe, debruijn, embed, html_blocks, merkle, minhash, oracles, packing, repair, repeats, toxicity
from .common import table
from .tokens import tokenizer_path


def op1_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents"), width=4, percent=80)


def op2_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_and_decode(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.tiktoken"))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    return toxicity.scored(docs, model).withColumn("held_out", toxicity.held_out()).select("doc_id", "held_out", "score", "predicted")


def op4_merkle(spark: SparkSession, sf_dir: str) -> DataFrame:
    return merkle.edited_against_next(table(spark, sf_dir, "documents"))


def op5_debruijn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return debruijn.without_repeated_words(table(spark, sf_dir, "documents"), width=50)


def op6_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed.near_vectors(table(spark, sf_dir, "embeddings"), cosine=0.95)


def op7_repair(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repair.read_documents(repair.write_shards(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"), end_id=2))


def op8_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.without_repeated_bytes(table(spark, sf_dir, "documents"))


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"), window=2048, end_id=1)


def op10_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_blocks.main_text(table(spark, sf_dir, "pages"))


QUERIES = {f.__name__: f for f in (op1_minhash, op2_bpe, op3_toxicity, op4_merkle, op5_debruijn, op6_embeddings, op7_repair, op8_suffixes, op9_packing, op10_html)}
SQL: dict[str, str] = {
    "op1_minhash": oracles.near_duplicates(width=4, percent=80),
    "op5_debruijn": oracles.without_repeated_words(width=50),
    "op6_embeddings": oracles.near_vectors(cosine=0.95),
    "op8_suffixes": oracles.without_repeated_bytes(),
}
