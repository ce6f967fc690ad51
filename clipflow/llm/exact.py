"""Exact duplicates against a persistent digest index.

The index is a bucketed table, sorted by digest in each bucket. New rows are reduced to one row a
digest, compared with the index by a sort-merge anti-join, and what is new is appended. The index side
is never shuffled: its buckets are the join's partitions.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from clipflow.llm.common import fresh, materialise

WHITE = "[\\x20\\x09-\\x0D]+"


def digest(column: str) -> Column:
    """SHA-256 of the text with every run of white space as one space; null counts as empty."""
    return F.sha2(F.regexp_replace(F.coalesce(F.col(column), F.lit("")), WHITE, " ").cast("binary"), 256)


class DigestIndex:
    """A persistent table (text_sha256, keep_id, batch) in the warehouse, bucketed and sorted by digest.

    ``keep_id`` is the smallest id of the first batch that had the digest: earlier batches win over later ones.
    """

    def __init__(self, spark: SparkSession, name: str | None = None, buckets: int = 16):
        self.spark, self.buckets = spark, buckets
        self.name = name or f"digest_index_{uuid.uuid4().hex}"

    def exists(self) -> bool:
        return self.spark.catalog.tableExists(self.name)

    def batches(self) -> int:
        return (self.spark.table(self.name).agg(F.max("batch")).first()[0] or 0) if self.exists() else 0

    def drop(self) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")

    def add(self, groups: DataFrame) -> None:
        """Append the digests of ``groups`` (text_sha256, keep_id: one row a digest) that the index lacks.

        Null ids are kept as they are, as the id of a digest that no row with an id has; an empty table appends nothing.
        """
        batch = self.batches() + 1
        if self.exists():
            known = self.spark.table(self.name).select("text_sha256").hint("merge")
            groups = groups.join(known, "text_sha256", "left_anti")
        (
            groups.select("text_sha256", "keep_id", F.lit(batch).alias("batch"))
            .repartition(self.buckets, "text_sha256")
            .write.bucketBy(self.buckets, "text_sha256").sortBy("text_sha256")
            .mode("append").format("parquet").saveAsTable(self.name)
        )

    def lookup(self) -> DataFrame:
        return self.spark.table(self.name).select("text_sha256", "keep_id")


def exact_dedup(docs: DataFrame, index: DigestIndex, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, keep_id, group_size (in this batch), kept, text_sha256.

    Null and empty texts are equal and form one group. Rows that repeat an id as well keep that id; all of them
    are returned. An empty table gives no rows. Other columns are not read, so their names cannot clash.
    A digest that a third of all rows share is summed before the shuffle, and the join back to the rows is one
    that adaptive execution splits.
    """
    rows = docs.select(F.col(id_col).alias("doc_id"), digest(text_col).alias("text_sha256"))
    rows = materialise(rows, "digests")
    groups = rows.groupBy("text_sha256").agg(F.min("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    index.add(groups)
    known = index.lookup().join(groups.select("text_sha256", "group_size"), "text_sha256")
    return rows.join(known.hint("merge"), "text_sha256").select(
        "doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256"
    )


def in_arrivals(batches: list[DataFrame], index: DigestIndex, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``exact_dedup`` of a table that arrives in batches, ids growing from one to the next; group_size is of all batches."""
    rows = None
    for batch in batches:
        new = materialise(batch.select(F.col(id_col).alias("doc_id"), digest(text_col).alias("text_sha256")), "digests")
        index.add(new.groupBy("text_sha256").agg(F.min("doc_id").alias("keep_id")))
        rows = new if rows is None else rows.unionByName(new)
    groups = rows.groupBy("text_sha256").agg(F.count(F.lit(1)).alias("group_size"))
    known = index.lookup().join(groups, "text_sha256")
    return rows.join(known.hint("merge"), "text_sha256").select(
        "doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256"
    )


def keep_first(docs: DataFrame, index: DigestIndex, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, all columns kept. Of rows that repeat an id and a text, one stays.

    Null and empty texts are equal; a null id counts as larger than all. An empty table stays empty; columns may have any names.
    """
    tag = fresh("digest", docs.columns)
    marked = docs.withColumn(tag, digest(text_col))  # the join's keys are those of the last step: one shuffle
    found = exact_dedup(docs, index, id_col, text_col).where("kept").select(
        F.col("doc_id").alias("_exact_id"), F.col("text_sha256").alias("_exact_sha")
    ).distinct()
    joined = marked.join(found, (marked[id_col].eqNullSafe(found["_exact_id"])) & (marked[tag] == found["_exact_sha"]), "left_semi")
    return joined.dropDuplicates([id_col, tag]).drop(tag)
