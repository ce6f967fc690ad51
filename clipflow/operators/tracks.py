"""Linking detections to tracks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from clipflow.operators.pipeline import iou_1d_box


def link_next(boxes: DataFrame, keys: list[str], least: float) -> DataFrame:
    """boxes (keys, t, x, y, s: corner and side) -> with the next frame's box and whether the overlap links them."""
    w = Window.partitionBy(*keys).orderBy("t")
    out = boxes.withColumns({"x2": F.lead("x").over(w), "y2": F.lead("y").over(w), "s2": F.lead("s").over(w)})
    c = F.col
    return out.withColumn("linked", F.coalesce(iou_1d_box(c("x"), c("y"), c("s"), c("x2"), c("y2"), c("s2")) >= least, F.lit(False)))


def link_tracks(boxes: DataFrame, keys: list[str], least: float = 0.3, max_gap: float | None = None) -> DataFrame:
    """With one face a frame a track is a maximal row of linked frames: track counts the breaks so far."""
    w = Window.partitionBy(*keys).orderBy("t")
    linked = link_next(boxes, keys, least)
    before = F.coalesce(F.lag("linked").over(w), F.lit(False))
    if max_gap is not None:
        before = before & (F.col("t") - F.lag("t").over(w) <= max_gap)
    marked = linked.withColumn("starts", (~before).cast("int"))
    return marked.withColumn("track", F.sum("starts").over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("starts", "x2", "y2", "s2", "linked")


def multi_face_tracks(boxes: DataFrame, keys: list[str], least: float = 0.3, identity: str | None = None, most: float = 1.0) -> DataFrame:
    """boxes (keys, t, face, x, y, s [, identity: array of doubles]) -> with track, for any number of faces a frame.

    A face is linked to the face of the frame before that overlaps it most, if that is ``least`` or more, its identity
    vector within ``most``, and each is the other's best (ties: the smaller face number). Tracks are the components of
    these links, numbered in a clip by their first face. Clips come one after the other, and those of a batch are linked
    at once; the last, which may go on, waits for the next batch.
    """
    order = Window.partitionBy(*keys).orderBy(F.col("t").asc_nulls_last(), F.col("face").asc_nulls_last())
    rows = boxes.withColumn("_first", F.row_number().over(order) == 1)

    def link(whole: pa.Table) -> list[pa.RecordBatch]:
        ids = np.stack(whole[identity].to_pandas().to_numpy()) if identity is not None else None
        number = lambda c: whole[c].to_numpy().astype(float)
        track = _tracks(whole["_first"].to_numpy(), *map(number, ("t", "x", "y", "s")), ids, least, most)
        return whole.drop_columns("_first").append_column("track", pa.array(track, pa.int32())).combine_chunks().to_batches()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[pa.RecordBatch] = []
        for b in batches:
            starts = np.nonzero(b.column("_first").to_numpy(zero_copy_only=False))[0]
            if len(starts) and (kept or starts[-1]):
                yield from link(pa.Table.from_batches([*kept, b.slice(0, starts[-1])]))
                kept = []
            kept.append(b.slice(starts[-1]) if len(starts) else b)
        if kept:
            yield from link(pa.Table.from_batches(kept))

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in boxes.schema) + ", track int"
    return rows.mapInArrow(run, schema)


def _tracks(first: np.ndarray, t: np.ndarray, x: np.ndarray, y: np.ndarray, s: np.ndarray, ids: np.ndarray | None, least: float, most: float) -> np.ndarray:
    """Track of each box; boxes are in the order of clip, time and face, ``first`` marks the first of each clip. -1 without a time."""
    n = len(t)
    if not n:
        return np.zeros(0, np.int32)
    clip = np.cumsum(first) - 1
    opens = np.concatenate([[True], (clip[1:] != clip[:-1]) | (t[1:] != t[:-1])])  # the first box of each frame
    frame, at = np.cumsum(opens) - 1, np.nonzero(opens)[0]
    size = np.diff(np.append(at, n))
    follows = np.concatenate([[False], (clip[at[1:]] == clip[at[:-1]]) & (t[at[1:]] == t[at[:-1]] + 1)])
    # every face with every face of the frame before
    before = np.where(follows[frame], size[frame - 1], 0)
    new = np.repeat(np.arange(n), before)
    old = np.arange(len(new)) - np.repeat(np.cumsum(before) - before, before) + np.repeat(at[frame - 1], before)
    side = lambda p: np.clip(np.minimum(p[old] + s[old], p[new] + s[new]) - np.maximum(p[old], p[new]), 0, None)
    inter = side(x) * side(y)
    score = inter / np.maximum(s[old] ** 2 + s[new] ** 2 - inter, 1e-12)
    if ids is not None:
        score = np.where(np.linalg.norm(ids[old] - ids[new], axis=1) <= most, score, 0)

    def best(of: np.ndarray, other: np.ndarray) -> np.ndarray:
        """Of each box, the other of the best score, the first of equal ones; unknown scores are no one's best."""
        by = np.lexsort((other, -np.where(np.isnan(score), np.inf, score), of))
        pick = by[np.diff(of[by], prepend=-1) != 0]
        out = np.full(n, -1)
        out[of[pick]] = other[pick]
        return out

    of_new, of_old = best(new, old), best(old, new)
    hit = (score >= least) & (of_new[new] == old) & (of_old[old] == new)
    root = np.arange(n)
    root[new[hit]] = old[hit]
    while True:
        further = root[root]
        if (further == root).all():
            break
        root = further
    starts = (root == np.arange(n)) & ~np.isnan(t)
    made = np.cumsum(starts)
    number = made[root] - 1 - (made - starts)[np.nonzero(first)[0]][clip]
    return np.where(np.isnan(t), -1, number).astype(np.int32)
