"""Suffix-array deduplication by bytes, block by block, with a difference cover.

Of the suffixes that may repeat (see ``spans``: a whole suffix array would move eight bytes and more for each byte), those
that their strings' hashes don't settle are sorted one bucket at a time, a bucket being those with some smallest grams
near their start. Suffixes whose ends no other of the bucket has are left out first. The rest is sorted by the first
``PERIOD`` bytes. Longer ties are resolved by ranks that were computed before for the suffixes at cover positions only: for
any two positions there is a shift below the period that takes both to the cover, where one comparison of ranks decides
the rest. Neighbours in the order that share the length asked for are repeats.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame

from clipflow.llm.common import mix64
from clipflow.llm.spans import Kind, byte_tokens, one_batch

LENGTH, PERIOD = 50, 32  # the period is a multiple of 8


def difference_cover(period: int) -> np.ndarray:
    """A small set whose differences are all residues: the least ones, then multiples of about the period's root."""
    root = int(np.ceil(period**0.5))
    return np.unique(np.concatenate([np.arange(root), np.arange(0, period + root, root) % period]))


def shifts(period: int, cover: np.ndarray) -> np.ndarray:
    """shifts[a, b]: the least s with (a + s) and (b + s) both in the cover, modulo the period."""
    inside = np.isin(np.arange(period), cover)
    table = np.full((period, period), -1)
    a, b = np.meshgrid(np.arange(period), np.arange(period), indexing="ij")
    for s in range(period):
        hit = inside[(a + s) % period] & inside[(b + s) % period] & (table < 0)
        table[hit] = s
    return table


def _words(text: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Eight bytes from each position as one number that sorts like them."""
    out = np.zeros(len(at), np.uint64)
    for i in range(8):
        out = (out << np.uint64(8)) | text[at + i].astype(np.uint64)
    return out


def _rank(keys: list[np.ndarray]) -> np.ndarray:
    """Dense ranks of rows of keys, the first key leading."""
    order = np.lexsort(keys[::-1])
    new = np.zeros(len(order), bool)
    for k in keys:
        new[1:] |= k[order[1:]] != k[order[:-1]]
    rank = np.empty(len(order), np.int64)
    rank[order] = np.cumsum(new)
    return rank


def cover_ranks(text: np.ndarray, n: int, depth: int, period: int, cover: np.ndarray) -> np.ndarray:
    """Ranks, by their next ``depth`` bytes, of the suffixes at cover positions below ``n`` (elsewhere -1)."""
    at = np.nonzero(np.isin(np.arange(n) % period, cover))[0]
    ranks = np.full(n, -1, np.int64)
    if len(at):
        ranks[at] = _rank([_words(text, at + s) for s in range(0, depth, 8)])
    return ranks


def sort_suffixes(text: bytes, at: np.ndarray, depth: int, period: int = PERIOD) -> np.ndarray:
    """``at`` in the order of the suffixes that start there, which differ within ``depth`` bytes or count as equal.

    Memory is bounded by a rank for each cover position and the first ``period`` bytes of what is sorted.
    """
    cover = difference_cover(period)
    n = len(text) + period
    padded = np.concatenate([np.frombuffer(text, np.uint8), np.zeros(depth + 2 * period + 8, np.uint8)])
    ranks, table = cover_ranks(padded, n, depth, period, cover), shifts(period, cover)
    heads = [_words(padded, at + s) for s in range(0, period, 8)]
    order = np.lexsort(heads[::-1])
    fresh = np.zeros(len(at), bool)
    fresh[:1] = True
    for h in heads:
        fresh[1:] |= h[order[1:]] != h[order[:-1]]
    place = at[order]
    # a tie is named by where it starts; each round parts every open tie at its first suffix, by cover ranks
    tie = np.maximum.accumulate(np.where(fresh, np.arange(len(at)), 0))
    open_ = np.nonzero(np.bincount(tie, minlength=len(at))[tie] > 1)[0]
    while len(open_):
        lead = np.nonzero(np.concatenate([[True], tie[open_[1:]] != tie[open_[:-1]]]))[0]
        size = np.diff(np.append(lead, len(open_)))
        head = np.repeat(open_[lead], size)
        s = table[place[head] % period, place[open_] % period]
        a, b = ranks[place[head] + s], ranks[place[open_] + s]
        less, same = b < a, b == a
        n_less, n_same = np.add.reduceat(less.astype(np.int64), lead), np.add.reduceat(same.astype(np.int64), lead)
        tie[open_] += np.where(less, 0, np.repeat(n_less, size) + np.where(same, 0, np.repeat(n_same, size)))
        open_ = open_[~same]
        open_ = open_[np.argsort(tie[open_], kind="stable")]
    return place[np.argsort(tie, kind="stable")]


def prefix_classes(text: bytes, ordered: np.ndarray, length: int) -> np.ndarray:
    """Numbers of sorted suffixes, equal for neighbours that share ``length`` bytes."""
    padded = np.concatenate([np.frombuffer(text, np.uint8), np.zeros(length + 8, np.uint8)])
    new = np.zeros(len(ordered), bool)
    for s in [*range(0, length - 8, 8), max(length - 8, 0)]:
        w = _words(padded, ordered + s)
        w = w >> np.uint64(8 * (8 - length)) if length < 8 else w
        new[1:] |= w[1:] != w[:-1]
    return np.cumsum(new)


def _alone(text: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
    """Which suffixes differ from all others in their first or last eight bytes of ``width``: no other repeats them."""
    if width < 16:
        return np.zeros(len(at), bool)
    ends = mix64(_words(text, at) * np.uint64(0x9E3779B97F4A7C15) + _words(text, at + width - 8))
    order = np.argsort(ends)
    same = ends[order[1:]] == ends[order[:-1]]
    alone = np.ones(len(at), bool)
    alone[order[1:]] &= ~same
    alone[order[:-1]] &= ~same
    return alone


def _same_bytes(strings: list[bytes], windows: list[int], kind: Kind) -> list[np.ndarray]:
    """Classes of the windows of each string, from the sorted suffixes of these strings' text."""
    text = b"\0".join(strings)
    base = np.concatenate([[0], np.cumsum([len(s) + 1 for s in strings])[:-1]]).astype(np.int64)
    count = np.array(windows)
    at = np.repeat(base, count) + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    raw = np.concatenate([np.frombuffer(text, np.uint8), np.zeros(8, np.uint8)])
    alone = _alone(raw, at, kind.width)
    number = np.empty(len(text), np.int64)
    number[at[alone]] = np.arange(alone.sum())
    ordered = sort_suffixes(text, at[~alone], kind.width)
    number[ordered] = prefix_classes(text, ordered, kind.width) + alone.sum()
    return np.split(number[at], np.cumsum(count)[:-1])


def _finish_all(doc, data: bytes, starts: np.ndarray, ends: np.ndarray, removed: np.ndarray) -> dict:
    raw = np.frombuffer(data, np.uint8)
    kept = raw[~removed].tobytes()
    spans = int(removed[0]) + int((removed[1:] & ~removed[:-1]).sum()) if len(removed) else 0
    return {"doc_id": doc, "n_bytes": len(raw), "n_removed": int(removed.sum()), "n_spans": spans, "kept": kept, "kept_sha256": hashlib.sha256(kept).hexdigest()}


def _finish(*args) -> dict:
    found = _finish_all(*args)
    del found["kept"]
    return found


def dedup_bytes(docs: DataFrame, length: int = LENGTH, with_kept: bool = True, id_col: str = "doc_id", text_col: str = "text", **sizes: int) -> DataFrame:
    """One row per row: doc_id, n_bytes, n_removed, n_spans (maximal removed runs), kept (bytes), kept_sha256.

    A byte goes if a string of ``length`` bytes over it also starts in a document with a smaller id. Null, empty and
    short texts lose nothing. Rows that repeat an id are one document's: they take nothing from each other. A null id
    counts as larger than all. An empty table gives no rows. Columns beside id and text are not read. What is kept may
    cut a character in two, so it is bytes.
    """
    kind = Kind(length, max(1, min(20, length // 2)), byte_tokens)
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, " + "kept binary, " * with_kept + "kept_sha256 string"
    return one_batch(docs, kind, _same_bytes, _finish_all if with_kept else _finish, schema, id_col, text_col, **sizes)
