"""Forced alignment: the best monotone segmentation of frames by the phonemes of a transcript."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def viterbi_cuts(logp: np.ndarray) -> tuple[list[int], float]:
    """logp[t, u]: frame t under phoneme u; each phoneme has at least one frame. Where phonemes 1, 2, ... start, and the score."""
    frames, units = logp.shape
    best, back = np.full((frames, units), -np.inf), np.zeros((frames, units), bool)
    best[0, 0] = logp[0, 0]
    for t in range(1, frames):
        stay, move = best[t - 1], np.concatenate([[-np.inf], best[t - 1, :-1]])
        back[t] = move > stay
        best[t] = np.maximum(stay, move) + logp[t]
    u, cuts = units - 1, []
    for t in range(frames - 1, 0, -1):
        if back[t, u]:
            cuts.append(t)
            u -= 1
    return cuts[::-1], float(best[-1, -1])


def best_cuts(lattice: DataFrame, columns: list[str]) -> DataFrame:
    """One clip's lattice (t, a probability column for each phoneme in order) -> cuts, logp."""
    rows = lattice.agg(F.array_sort(F.collect_list(F.struct("t", *columns))).alias("rows"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            found = [viterbi_cuts(np.log(np.array([[r[c] for c in columns] for r in rows]))) for rows in b["rows"]]
            yield pd.DataFrame({"cuts": [c for c, _ in found], "logp": [s for _, s in found]})

    return rows.mapInPandas(run, "cuts array<int>, logp double")


def forced_align(clips: DataFrame, symbols: list[str]) -> DataFrame:
    """clips (utt, lattice: array of frames over ``symbols``, prons: array of pronunciations, each an array of symbols).

    Every pronunciation is aligned and the likeliest kept: utt, phones, cuts, logp. A clip shorter than all its
    pronunciations has none (null). One clip is one task's row, at most 12 seconds of frames.
    """
    at = {s: i for i, s in enumerate(symbols)}

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for utt, lattice, prons in zip(b["utt"], b["lattice"], b["prons"]):
                lp = np.log(np.maximum(np.array([list(f) for f in lattice], float), 1e-300)) if lattice is not None else np.zeros((0, 0))
                best = None
                for p in prons if prons is not None else []:
                    if 0 < len(p) <= len(lp):
                        cuts, score = viterbi_cuts(lp[:, [at[s] for s in p]])
                        if best is None or score > best[2]:
                            best = (list(p), cuts, score)
                out.append((utt, *(best or (None, None, None))))
            yield pd.DataFrame(out, columns=["utt", "phones", "cuts", "logp"])

    return clips.select("utt", "lattice", "prons").mapInPandas(run, f"utt {clips.schema['utt'].dataType.simpleString()}, phones array<string>, cuts array<int>, logp double")
