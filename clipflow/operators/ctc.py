"""CTC kernels in log space and their DataFrame forms: loss, gradient, best alignment, greedy and beam decoding."""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Callable, Iterator
from itertools import product

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from clipflow.functions.ctc import ctc_collapse

NEG = -np.inf


def spread(label: list[int], blank: int = 0) -> np.ndarray:
    out = np.full(2 * len(label) + 1, blank)
    out[1::2] = label
    return out


def _reach(l: np.ndarray, blank: int) -> np.ndarray:
    """May position s be entered from s - 2?"""
    ok = np.zeros(len(l), bool)
    ok[2:] = (l[2:] != blank) & (l[2:] != l[:-2])
    return ok


def _shift(a: np.ndarray, n: int) -> np.ndarray:
    return np.concatenate([np.full(n, NEG), a[:-n]]) if n <= len(a) else np.full(len(a), NEG)


def forward(logp: np.ndarray, label: list[int], blank: int = 0) -> np.ndarray:
    l = spread(label, blank)
    jump = _reach(l, blank)
    a = np.full((len(logp), len(l)), NEG)
    a[0, :2] = logp[0, l[:2]]
    for t in range(1, len(logp)):
        p = a[t - 1]
        a[t] = np.logaddexp(np.logaddexp(p, _shift(p, 1)), np.where(jump, _shift(p, 2), NEG)) + logp[t, l]
    return a


def backward(logp: np.ndarray, label: list[int], blank: int = 0) -> np.ndarray:
    """By the mirror: the reversed label over the reversed frames; emission at t is not counted twice."""
    a = forward(logp[::-1], label[::-1], blank)[::-1, ::-1]
    return a - logp[:, spread(label, blank)]


def log_prob(logp: np.ndarray, label: list[int], blank: int = 0) -> float:
    a = forward(logp, label, blank)[-1]
    return float(np.logaddexp(a[-1], a[-2]) if len(a) > 1 else a[-1])


def loss_and_gradient(logits: np.ndarray, label: list[int], blank: int = 0) -> tuple[float, np.ndarray]:
    """-log p and its gradient by the logits: the output less each symbol's occupancy."""
    logp = logits - np.logaddexp.reduce(logits, axis=1, keepdims=True)
    a, b = forward(logp, label, blank), backward(logp, label, blank)
    total = log_prob(logp, label, blank)
    if total == NEG:
        return np.inf, np.zeros_like(logits)
    occupancy = np.zeros_like(logp)
    np.add.at(occupancy.T, spread(label, blank), np.exp(a + b - total).T)
    return -total, np.exp(logp) - occupancy


def best_path(logp: np.ndarray, label: list[int], blank: int = 0) -> tuple[list[int], float]:
    """The likeliest alignment: a symbol for each frame."""
    l = spread(label, blank)
    jump = _reach(l, blank)
    a, back = np.full((len(logp), len(l)), NEG), np.zeros((len(logp), len(l)), int)
    a[0, :2] = logp[0, l[:2]]
    for t in range(1, len(logp)):
        p = a[t - 1]
        from_ = np.stack([p, _shift(p, 1), np.where(jump, _shift(p, 2), NEG)])
        back[t] = from_.argmax(axis=0)
        a[t] = from_.max(axis=0) + logp[t, l]
    s = len(l) - 1 if len(l) == 1 or a[-1, -1] >= a[-1, -2] else len(l) - 2
    score, path = float(a[-1, s]), []
    for t in range(len(logp) - 1, -1, -1):
        path.append(int(l[s]))
        s -= back[t, s]
    return path[::-1], score


def collapse(path: list[int] | tuple[int, ...], blank: int = 0) -> tuple[int, ...]:
    return tuple(x for i, x in enumerate(path) if x != blank and (i == 0 or path[i - 1] != x))


def brute(logp: np.ndarray, label: list[int], blank: int = 0) -> float:
    """Over all strings: for tests."""
    return float(sum(np.exp(sum(logp[t, k] for t, k in enumerate(u))) for u in product(range(logp.shape[1]), repeat=len(logp)) if collapse(u, blank) == tuple(label)))


def beam_search(logp: np.ndarray, width: int = 16, blank: int = 0, lm: Callable[[tuple[int, ...], int], float] | None = None, alpha: float = 1.0, beta: float = 0.0) -> list[tuple[tuple[int, ...], float]]:
    """Prefixes by probability, ends in blank and in a symbol apart; ``lm(prefix, symbol)`` weighs each extension."""
    beams: dict[tuple[int, ...], tuple[float, float]] = {(): (0.0, NEG)}
    for row in logp:
        new: dict[tuple[int, ...], list[float]] = defaultdict(lambda: [NEG, NEG])
        for prefix, (pb, pn) in beams.items():
            both = np.logaddexp(pb, pn)
            e = new[prefix]
            e[0] = np.logaddexp(e[0], both + row[blank])
            if prefix:
                e[1] = np.logaddexp(e[1], pn + row[prefix[-1]])
            for k in range(len(row)):
                if k != blank:
                    extra = (alpha * lm(prefix, k) if lm else 0.0) + beta
                    e = new[(*prefix, k)]
                    e[1] = np.logaddexp(e[1], (pb if prefix and prefix[-1] == k else both) + row[k] + extra)
        beams = dict(sorted(((p, (a, b)) for p, (a, b) in new.items()), key=lambda x: -np.logaddexp(*x[1]))[:width])
    return sorted(((p, float(np.logaddexp(a, b))) for p, (a, b) in beams.items()), key=lambda x: -x[1])


# ---- on DataFrames


def ctc_logprob(df: DataFrame, frames: str = "lattice", label: str = "label", blank: int = 0) -> DataFrame:
    """Adds logp. One clip is one row; nothing is shuffled."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield b.assign(logp=[log_prob(np.log(np.maximum(np.array([list(f) for f in x], float), 1e-300)), [int(i) for i in y], blank) for x, y in zip(b[frames], b[label])])

    return df.mapInPandas(run, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in df.schema) + ", logp double")


def ctc_beam(df: DataFrame, width: int = 16, frames: str = "lattice", key: str = "utt", blank: int = 0, lm: dict[tuple[int, ...], float] | None = None, order: int = 2, alpha: float = 1.0, beta: float = 0.0) -> DataFrame:
    """key, rank, label, logp: the n-best of each clip.

    ``lm``: log probability of each (symbols before.., symbol) of at most ``order``; unseen ones take the longest known end
    of their context, else -10. Each extension adds ``alpha`` times that and ``beta``. It is of symbols, so it is small;
    word models go with ``fst.Decoder``.
    """
    sent = df.sparkSession.sparkContext.broadcast(lm) if lm else None

    def score(prefix: tuple[int, ...], symbol: int) -> float:
        context = prefix[max(0, len(prefix) - order + 1) :] if order > 1 else ()
        while True:
            if (p := sent.value.get((*context, symbol))) is not None:
                return p
            if not context:
                return -10.0
            context = context[1:]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for u, x in zip(b[key], b[frames]):
                logp = np.log(np.maximum(np.array([list(f) for f in x], float), 1e-300))
                rows += [(u, r, [int(i) for i in p], s) for r, (p, s) in enumerate(beam_search(logp, width, blank, score if sent else None, alpha, beta))]
            yield pd.DataFrame(rows, columns=[key, "rank", "label", "logp"])

    return df.select(key, frames).mapInPandas(run, f"{key} {df.schema[key].dataType.simpleString()}, rank int, label array<int>, logp double")


def ctc_greedy(lattice: DataFrame, keys: list[str]) -> DataFrame:
    """lattice (keys, t, sym, p) -> keys, labels: the likeliest symbol of each frame (ties: the later letter), collapsed.

    Frames are reduced to one row before a clip's are gathered; a clip has at most 12 seconds of them.
    """
    top = lattice.groupBy(*keys, "t").agg(F.max(F.struct("p", "sym")).alias("m"))
    path = top.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("t", F.col("m.sym").alias("s")))).alias("x")).withColumn("u", F.expr("transform(x, r -> r.s)"))
    return path.select(*keys, F.array_join(ctc_collapse("u"), "").alias("labels"))


def greedy_labels(frames: str) -> Column:
    """The same of a clip that is one row, from its frames in order, each an array of (.., sym, p)."""
    return F.expr(f"transform(array(transform({frames}, f -> array_max(transform(f, x -> struct(x.p AS p, x.sym AS sym))).sym)), u -> array_join(filter(transform(u, (x, i) -> CASE WHEN i > 0 AND u[i - 1] = x THEN '_' ELSE x END), x -> x <> '_'), ''))[0]")
