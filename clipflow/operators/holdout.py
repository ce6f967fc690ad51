"""Keeping test text out of training text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def word_windows(col: Column, n: int) -> Column:
    """Hashes of each ``n`` consecutive words (split at single spaces and line feeds)."""
    text = F.transform(F.array(F.split(col, "[ \n]")), lambda ws: F.when(  # one element: the words are cut once
        F.size(ws) >= n, F.transform(F.sequence(F.lit(0), F.size(ws) - n), lambda i: F.xxhash64(F.array_join(F.slice(ws, i + 1, n), " ")))
    ).otherwise(F.array().cast("array<bigint>")))
    return text[0]


def without_passages(docs: DataFrame, bench: DataFrame, n: int = 5) -> DataFrame:
    """Documents that hold no test item verbatim.

    An item's inner words occur whole in any text that holds it, so one inner window of ``n`` words finds the candidates
    by an equi-join; each is then verified. Items of fewer words than that are compared with every document: their number
    is the test set's, which is broadcast by size only.
    """
    items = bench.select(F.col("text").alias("item")).where("item IS NOT NULL").distinct().withColumn("ws", F.split("item", "[ \n]"))
    long_ones = items.where(F.size("ws") >= n + 2).select("item", F.xxhash64(F.array_join(F.slice("ws", 2, n), " ")).alias("h"))
    short = items.where(F.size("ws") < n + 2).select("item")
    # only hashes move; the texts of the documents that are hit are fetched once
    seen = docs.select("doc_id", F.explode(F.array_distinct(word_windows(F.col("text"), n))).alias("h"))
    pairs = seen.join(long_ones, "h").select("doc_id", "item").distinct()
    hit = docs.select("doc_id", "text").join(pairs, "doc_id").where(F.contains("text", "item")).select("doc_id")
    hit = hit.union(docs.join(short, F.contains("text", "item"), "left_semi").select("doc_id")).distinct()
    return docs.join(hit, "doc_id", "left_anti")
