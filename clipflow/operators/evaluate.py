"""Accuracy measures: pooled error rates, bootstrap spread, alignment operations, confusion, entropy, comparison."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def error_rate(df: DataFrame, by: list[str], edits: str = "edits", length: str = "ref_len") -> DataFrame:
    """Sum of edits over sum of reference lengths, by group: pooled, so it may exceed 1; null for empty references."""
    return df.groupBy(*by).agg(F.try_divide(F.sum(edits).cast("double"), F.sum(length)).alias("rate"), F.sum(length).alias("ref_len"))


def poisson_weight(u: Column, most: int = 8) -> Column:
    """Poisson(1) by inversion of a uniform number."""
    import math

    total, w = 0.0, F.lit(most)
    cuts = []
    for k in range(most):
        total += math.exp(-1) / math.factorial(k)
        cuts.append((k, total))
    for k, c in reversed(cuts):
        w = F.when(u < c, k).otherwise(w)
    return w


def bootstrap_se(df: DataFrame, by: list[str], keys: list[str], replicates: int = 100, seed: str = "boot", edits: str = "edits", length: str = "ref_len") -> DataFrame:
    """by, rate, se: utterances weighed by Poisson(1) from a hash of the utterance and a block of eight replicates.

    Each hash gives eight weights of 16 bits. Rows are copied once a block, not once a replicate, and weights are summed
    where the row is: what moves is one row a group, block and task.
    """
    blocks = -(-replicates // 8)
    h = F.md5(F.concat_ws("|", F.lit(seed), F.col("block").cast("string"), *[F.col(k).cast("string") for k in keys]))
    reps = df.select(*by, *keys, edits, length, F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block")).withColumn("h", h)
    sums = []
    for j in range(8):
        w = poisson_weight(F.conv(F.substring("h", 4 * j + 1, 4), 16, 10).cast("int") / 65536.0)
        reps = reps.withColumn(f"w{j}", w)
        sums += [F.sum(F.col(edits) * F.col(f"w{j}")).alias(f"e{j}"), F.sum(F.col(length) * F.col(f"w{j}")).alias(f"n{j}")]
    wide = reps.groupBy(*by, "block").agg(*sums)
    each = wide.select(*by, F.inline(F.array(*[F.struct((F.col("block") * 8 + j).alias("rep"), F.col(f"e{j}").alias("e"), F.col(f"n{j}").alias("n")) for j in range(8)])))
    rate = F.try_divide(F.col("e").cast("double"), F.col("n"))
    se = each.where(F.col("rep") < replicates).groupBy(*by).agg(F.stddev_samp(rate).alias("se"))
    return error_rate(df, by, edits, length).join(se, by) if by else error_rate(df, by, edits, length).crossJoin(F.broadcast(se))


def bootstrap_exact(edits: np.ndarray, lengths: np.ndarray, replicates: int = 200, seed: int = 0) -> float:
    """Multinomial resampling of one group's utterances, for tests and small sets."""
    rng, n = np.random.default_rng(seed), len(edits)
    picks = rng.integers(0, n, (replicates, n))
    return float((edits[picks].sum(axis=1) / lengths[picks].sum(axis=1)).std(ddof=1))


def align(ref: list[str], hyp: list[str]) -> list[tuple[str, str | None, str | None]]:
    """(op, ref, hyp) of a least-cost alignment; ties: match, substitution, deletion, insertion."""
    n, m = len(ref), len(hyp)
    d = np.zeros((n + 1, m + 1), int)
    d[:, 0], d[0] = np.arange(n + 1), np.arange(m + 1)
    for i in range(1, n + 1):
        for j in range(1, m + 1):
            d[i, j] = min(d[i - 1, j - 1] + (ref[i - 1] != hyp[j - 1]), d[i - 1, j] + 1, d[i, j - 1] + 1)
    out, i, j = [], n, m
    while i or j:
        if i and j and ref[i - 1] == hyp[j - 1] and d[i, j] == d[i - 1, j - 1]:
            out.append(("match", ref[i - 1], hyp[j - 1]))
            i, j = i - 1, j - 1
        elif i and j and d[i, j] == d[i - 1, j - 1] + 1:
            out.append(("sub", ref[i - 1], hyp[j - 1]))
            i, j = i - 1, j - 1
        elif i and d[i, j] == d[i - 1, j] + 1:
            out.append(("del", ref[i - 1], None))
            i -= 1
        else:
            out.append(("ins", None, hyp[j - 1]))
            j -= 1
    return out[::-1]


def align_ops(pairs: DataFrame, keys: list[str], ref: str = "ref", hyp: str = "hyp") -> DataFrame:
    """keys, op, ref_tok, hyp_tok: one row an operation. Arrow batches; counts of them are small aggregations."""
    types = dict(pairs.dtypes)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = [(*r[: len(keys)], *o) for r in b.itertuples(index=False) for o in align(list(r[-2]), list(r[-1]))]
            yield pd.DataFrame(rows, columns=[*keys, "op", "ref_tok", "hyp_tok"])

    return pairs.select(*keys, ref, hyp).mapInPandas(run, ", ".join(f"{k} {types[k]}" for k in keys) + ", op string, ref_tok string, hyp_tok string")


def insdel_heatmap(ops: DataFrame) -> DataFrame:
    """phone, ins_share, del_share: each kind divided by its own total."""
    phone = F.coalesce(F.when(F.col("op") == "del", F.col("ref_tok")), F.col("hyp_tok"))
    g = ops.where("op IN ('ins', 'del')").groupBy(phone.alias("phone")).agg(F.count_if(F.col("op") == "ins").alias("i"), F.count_if(F.col("op") == "del").alias("d"))
    w = Window.partitionBy()  # at most one row a phoneme
    return g.select("phone", F.try_divide("i", F.sum("i").over(w)).alias("ins_share"), F.try_divide("d", F.sum("d").over(w)).alias("del_share"))


def confusion(ops: DataFrame) -> DataFrame:
    """ref, hyp, n, share of the reference symbol's substitutions."""
    g = ops.where("op = 'sub'").groupBy(F.col("ref_tok").alias("ref"), F.col("hyp_tok").alias("hyp")).agg(F.count(F.lit(1)).alias("n"))
    return g.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy("ref")))


def frame_entropy(lattice: DataFrame, keys: list[str]) -> DataFrame:
    """keys, t, h in nats, equal symbols of a frame added first."""
    p = lattice.groupBy(*keys, "t", "sym").agg(F.sum("p").alias("p"))
    return p.groupBy(*keys, "t").agg((-F.sum(F.when(F.col("p") > 0, F.col("p") * F.log("p")).otherwise(0.0))).alias("h"))


def frame_topk(lattice: DataFrame, keys: list[str], k: int = 3) -> DataFrame:
    """keys, t, rank, sym, p: the likeliest symbols of each frame, ties by symbol."""
    p = lattice.groupBy(*keys, "t", "sym").agg(F.sum("p").alias("p"))
    w = Window.partitionBy(*keys, "t").orderBy(F.desc(F.round("p", 9)), "sym")
    return p.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select(*keys, "t", "rank", "sym", "p")


def compare(rates: DataFrame, method: str = "method", rate: str = "wer") -> DataFrame:
    """method, rate, difference and relative reduction to the best and to the next worse method; a few rows."""
    w = Window.orderBy(F.desc(rate), method)
    best = F.min(rate).over(Window.partitionBy())
    before = F.lag(rate).over(w)
    return rates.select(method, rate, (F.col(rate) - best).alias("to_best"), (1 - best / F.col(rate)).alias("best_reduction"), (before - F.col(rate)).alias("to_previous"), (1 - F.col(rate) / before).alias("reduction"))
