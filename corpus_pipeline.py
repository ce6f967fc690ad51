"""A corpus pipeline of the llm operators: toxicity, exact and near duplicates, benchmark passages, packing.

Each stage takes (spark, docs, sf_dir) and returns the documents that it keeps, with their columns; the last returns
packed pieces. Stages are written and read again in between, so a lost executor costs at most one stage.

In every stage null and empty texts are texts without words: the first, of equal ones, that exact dedup keeps is kept to the
end, as one end id. Rows without an id are judged like others; where copies are told by id, they count as the last. Rows
that repeat an id are rows of their own, but equal rows are one after exact dedup. Empty tables stay empty, and columns
beside the documents' own are carried along under any name.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from clipflow.llm import decontam, exact, packing, simhash, toxicity
from clipflow.llm.common import materialise, table
from clipflow.llm.queries import index_for, tokenizer_path


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose score is below the threshold; the model learns from the labels that aren't held out."""
    return toxicity.reject(docs, toxicity.learn(docs, table(spark, sf_dir, "labels")))


def drop_exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, the row with the smallest id."""
    return exact.keep_first(docs, index_for(spark))


def drop_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies, the row with the smallest id."""
    return simhash.keep_one(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark passage."""
    return decontam.clean(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 2048 tokens in sequences of at most 2048."""
    return packing.pack(docs, tokenizer_path())


STAGES = [
    ("toxicity", drop_toxic),
    ("exact dedup", drop_exact),
    ("simhash near-dedup", drop_near),
    ("benchmark decontamination", drop_contaminated),
    ("best-fit packing", pack),
]

#: The model of the first stage and the tokenizer of the last are beyond SQL; tests hold the rest against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
