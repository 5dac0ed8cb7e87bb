"""A corpus-cleaning pipeline from the operators of rareblock.llm: toxic texts, near copies and benchmark
leaks go, private values are replaced, and what is left is packed into training sequences."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rareblock.llm import decontamination, neardup, packing, pseudonyms, toxicity
from rareblock.llm.common import settle, table

#: Of this pipeline; a user puts a secret of their own here.
PSEUDONYM_KEY = "rareblock pipeline key"


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model, trained on the labelled ones among them, scores below one half."""
    labels = table(spark, sf_dir, "labels").select("doc_id", F.col("toxic").alias("label"))
    return toxicity.keep_clean(docs, toxicity.train(docs.select("doc_id", "text"), labels), limit=0.5)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked at 0.8 on five-word shingles, the one of least id."""
    return neardup.keep_one(docs, k=5, per_cent=80)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no ten-word window of a benchmark item occurs."""
    return decontamination.drop_contaminated(docs, table(spark, sf_dir, "benchmark"), window=10)


def replace_private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, their private values replaced by pseudonyms of the same format."""
    found = pseudonyms.pseudonymise(docs, PSEUDONYM_KEY, private_col=None)
    return found.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document's tokens in sequences of at most 2048."""
    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.json"), seq_len=2048)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_copies),
    ("decontamination", drop_leaks),
    ("private_data", replace_private),
    ("packing", pack_sequences),
]

#: Stages one and five have no SQL form; the pipeline is tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
