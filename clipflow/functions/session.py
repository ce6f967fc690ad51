"""The engine's functions in a session's SQL: expressions as SQL functions, Arrow twins of some of them, a table function.

Expressions are what queries should use; the Arrow twins say the same in Python and are there to compare with, and for
callers whose logic no expression can say.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from clipflow.functions import phonemes as G
from clipflow.operators.evaluate import align


def _edit(a: str, b: str) -> int:
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


@F.pandas_udf(T.LongType())
def edit_arrow(a: pd.Series, b: pd.Series) -> pd.Series:
    """Edit distance of two texts, null if one is null: the twin of levenshtein."""
    return pd.Series([None if x is None or y is None else _edit(x, y) for x, y in zip(a, b)], dtype="Int64")


@F.pandas_udf(T.StringType())
def viseme_arrow(phones: pd.Series) -> pd.Series:
    """The twin of ``phonemes.viseme``."""
    table = str.maketrans({p: k for k, members in G.VISEMES.items() for p in members})
    return phones.map(lambda p: None if p is None else p.translate(table))


@F.pandas_udf(T.DoubleType())
def pooled_rate(edits: pd.Series, lengths: pd.Series) -> float:
    """An aggregate: sum of edits over sum of lengths. A group's rows reach one worker, so it is for bounded groups."""
    total = float(lengths.sum())
    return float(edits.sum()) / total if total else None


@F.udtf(returnType=T.StructType().add("pos", T.IntegerType()).add("phone", T.StringType()).add("frames", T.IntegerType()))
class PhoneFrames:
    """phones, fps -> one row a phoneme with the frames it lasts at 80 ms a vowel and 60 ms a consonant."""

    def eval(self, phones: str, fps: float) -> Iterator[tuple[int, str, int]]:
        for i, p in enumerate(phones or ""):
            yield i, p, max(1, round(fps * (0.08 if p in G.VOWELS else 0.06)))


@F.udtf(returnType=T.StructType().add("pos", T.IntegerType()).add("gram", T.ArrayType(T.StringType())))
class Ngrams:
    """words, n -> each n consecutive words with the place of the first, from 0."""

    def eval(self, words: list[str], n: int) -> Iterator[tuple[int, list[str]]]:
        for i in range(len(words or []) - n + 1):
            yield i, words[i : i + n]


@F.udtf(returnType=T.StructType().add("op", T.StringType()).add("ref_tok", T.StringType()).add("hyp_tok", T.StringType()))
class EditOps:
    """ref, hyp (arrays) -> the operations of a least-cost alignment."""

    def eval(self, ref: list[str], hyp: list[str]) -> Iterator[tuple[str, str | None, str | None]]:
        yield from align(list(ref or []), list(hyp or []))


@F.udtf(returnType=T.StructType().add("start", T.IntegerType()))
class Windows:
    """n, count, width -> where ``count`` equally spaced windows of ``width`` frames start in n; none if n is less."""

    def eval(self, n: int, count: int, width: int) -> Iterator[tuple[int]]:
        if n >= width:
            for i in range(count):
                yield (int(i * (n - width) // max(count - 1, 1)),)


def register(spark: SparkSession) -> list[str]:
    """Make the functions known to the session's SQL; returns their names."""
    at, to = "".join(G.VISEMES.values()), "".join(k * len(v) for k, v in G.VISEMES.items())
    bodies = {
        "clip_viseme(phones STRING) RETURNS STRING": f"translate(phones, '{at}', '{to}')",
        "clip_collapse(path ARRAY<STRING>) RETURNS STRING": "array_join(transform(filter(transform(path, (s, i) -> struct(s AS s, i AS i)), x -> x.s <> '_' AND (x.i = 0 OR x.s <> path[x.i - 1])), x -> x.s), '')",
        "clip_edits(a STRING, b STRING) RETURNS BIGINT": "cast(levenshtein(a, b) AS BIGINT)",
        "clip_duration_ok(seconds DOUBLE) RETURNS BOOLEAN": "seconds BETWEEN 1 AND 12",
    }
    for head, body in bodies.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udf.register("clip_edits_arrow", edit_arrow)
    spark.udf.register("clip_viseme_arrow", viseme_arrow)
    spark.udf.register("clip_pooled_rate", pooled_rate)
    tables = {"clip_phone_frames": PhoneFrames, "clip_ngrams": Ngrams, "clip_edit_ops": EditOps, "clip_windows": Windows}
    for name, table in tables.items():
        spark.udtf.register(name, table)
    return [*(h.partition("(")[0] for h in bodies), "clip_edits_arrow", "clip_viseme_arrow", "clip_pooled_rate", *tables]
