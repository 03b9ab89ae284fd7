"""A pretraining-corpus pipeline: each stage reads what the one before it wrote.

Toxic documents go, near duplicates leave one document a group, documents that hold benchmark items
go, the rest is sampled to target weights and written as token blocks.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from mts_search.llm import decontaminate, mixing, ngram_join, token_output, toxicity
from mts_search.llm.common import drop_at_end, scratch, table
from mts_search.llm.queries import TOKENIZER
from mts_search.session import ship


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is under 0.5; the detector learns from labelled rows of its input."""
    ship(spark)
    detector = toxicity.learn(docs, table(spark, sf_dir, "labels"))
    return toxicity.score(docs, detector, docs.columns, column="__score").where("__score < 0.5").drop("__score")


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: the one with the smallest doc_id."""
    ship(spark)
    return ngram_join.one_of_each(docs)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a benchmark item."""
    ship(spark)
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A sample whose sources, languages and topics have the target shares of tokens."""
    ship(spark)
    return mixing.mixed(docs)


def token_blocks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document, read back from the token blocks."""
    ship(spark)
    return token_output.read(token_output.write(docs, public_tokenizers.path(TOKENIZER)))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark),
    ("mixing", mix_sources),
    ("token_blocks", token_blocks),
]

#: SQL can't express the first stage; tests compare the stages with brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written as Parquet to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    base = f"{scratch(spark)}/pipeline_{uuid.uuid4().hex}"
    for name, stage in STAGES:
        out = stage(spark, docs, sf_dir)
        out.write.parquet(f"{base}/{name}")
        drop_at_end(spark, f"{base}/{name}")
        docs = spark.read.schema(out.schema).parquet(f"{base}/{name}")
    return docs
