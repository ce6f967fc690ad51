"""CTC as columns: collapse, forward probability, counts of alignments."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def ctc_collapse(col: str, blank: str = "_") -> Column:
    """Equal neighbours merged, then blanks dropped."""
    return F.expr(f"filter(transform({col}, (x, i) -> CASE WHEN i > 0 AND {col}[i - 1] = x THEN '{blank}' ELSE x END), x -> x <> '{blank}')")


def ctc_probability(frames: str, label: str, blank: int = 0) -> Column:
    """Probability of a label (array of symbol numbers) under frames (array of arrays of doubles).

    The forward pass over positions of the label with blanks in between: a position is reached from itself, the one before,
    and two before if it is a symbol other than that one. Linear space: short clips and oracles; long ones use kernels.
    """
    spread = f"flatten(transform({label}, x -> array({blank}, x))) || array({blank})"
    start = "transform(l, (s, i) -> CASE WHEN i < 2 THEN f0[s] ELSE 0D END)"
    step = f"""transform(l, (s, i) -> f[s] * (a[i] + CASE WHEN i > 0 THEN a[i - 1] ELSE 0D END
        + CASE WHEN i > 1 AND s <> {blank} AND s <> l[i - 2] THEN a[i - 2] ELSE 0D END))"""
    walk = f"transform(array({frames}[0]), f0 -> aggregate(slice({frames}, 2, size({frames})), {start}, (a, f) -> {step}, a -> a[size(a) - 1] + CASE WHEN size(a) > 1 THEN a[size(a) - 2] ELSE 0D END))[0]"
    return F.expr(f"transform(array({spread}), l -> {walk})[0]")


def ctc_alignments(frames: Column, length: Column, repeats: Column) -> Column:
    """How many strings of ``frames`` symbols and blanks collapse to a label: C(T - r + U, 2U)."""
    n, k = frames - repeats + length, 2 * length
    product = F.aggregate(F.sequence(F.lit(1), F.greatest(k, F.lit(1))), F.lit(1.0), lambda p, i: p * (n - k + i) / i)
    return F.when(n < k, 0).when(k == 0, 1).otherwise(F.round(product)).cast("long")


def adjacent_repeats(label: str) -> Column:
    return F.expr(f"size(filter(transform({label}, (x, i) -> i > 0 AND {label}[i - 1] = x), b -> b))")


def entropy(col: str) -> Column:
    """In nats, of an array of probabilities."""
    return F.expr(f"aggregate({col}, 0D, (s, p) -> s - CASE WHEN p > 0 THEN p * ln(p) ELSE 0D END)")


def logsumexp(col: str) -> Column:
    return F.expr(f"transform(array(array_max({col})), m -> m + ln(aggregate({col}, 0D, (s, x) -> s + exp(x - m))))[0]")


def softmax(col: str) -> Column:
    e = f"transform({col}, x -> exp(cast(x AS double) - cast(array_max({col}) AS double)))"
    return F.expr(f"transform(array({e}), e -> transform(array(aggregate(e, 0D, (s, x) -> s + x)), z -> transform(e, x -> x / z))[0])[0]")
