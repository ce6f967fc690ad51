"""A whole back-off model as arrays of numbers, every n-gram kept. Windows of words are dealt to ranges of first words, where
they are sorted and counted; ranges laid end to end are the model, so nothing is put together in one task or on the driver."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from clipflow.operators import fst as T
from clipflow.operators import lm as M
from clipflow.sources.tables import dropped, written

#: Windows of a range, if its words are not more frequent than that, and words that a task turns to windows at once.
RANGE, TOKENS = 1 << 18, 1 << 20


def word_counts(sentences: DataFrame) -> DataFrame:
    return sentences.select(F.explode("words").alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("c"))


def _windows(lists: list[pa.Array], known: pa.Array, order: int, start: int, end: int) -> np.ndarray:
    """order x n: each word of each sentence, and its marks, with the words after it; -1 beyond the sentence."""
    size = np.concatenate([pc.fill_null(pc.list_value_length(x), 0).to_numpy(zero_copy_only=False) for x in lists]).astype(np.int64) + 2
    ids = pc.index_in(pa.concat_arrays([x.flatten() for x in lists]), value_set=known).to_numpy(zero_copy_only=False)
    last = np.cumsum(size) - 1
    words = np.ones(size.sum(), bool)
    words[last] = words[last - size + 1] = False
    tokens = np.full(len(words) + order, -1, np.int32)
    tokens[last], tokens[last - size + 1] = end, start
    tokens[: len(words)][words] = ids
    left = np.repeat(last, size) - np.arange(len(words))
    return np.stack([np.where(left >= j, tokens[j : j + len(words)], -1) for j in range(order)])


def _dealt(sentences: DataFrame, words: Broadcast, ranges: Broadcast, order: int) -> DataFrame:
    """part, data: packets of windows for each range of first words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, part_of = pa.array(words.value, pa.string()), ranges.value
        start, end = (known.index(m).as_py() for m in ("<s>", "</s>"))
        held, n = [], 0

        def packets() -> Iterator[pa.RecordBatch]:
            rows = _windows(held, known, order, start, end)
            part = part_of[rows[0]]
            at = np.argsort(part, kind="stable")
            rows, part = rows[:, at], part[at]
            edge = [*np.nonzero(np.diff(part, prepend=-1))[0].tolist(), len(part)]
            for a, b in zip(edge, edge[1:]):
                yield pa.RecordBatch.from_arrays([pa.array([part[a]], pa.int32()), pa.array([rows[:, a:b].tobytes()], pa.binary())], names=["part", "data"])

        for batch in batches:
            held.append(batch.column(0))
            n += len(held[-1].flatten()) + 2 * len(held[-1])
            if n >= TOKENS:
                yield from packets()
                held, n = [], 0
        if n:
            yield from packets()

    return sentences.select("words").mapInArrow(run, "part int, data binary")


def _counted(rows: np.ndarray, v: int) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Windows -> for each order, in the order of their words: the place of the n-gram's context among those one shorter, the last word, the count."""
    order = len(rows)
    pair = lambda j: (rows[j].astype(np.int64) + 1) * (v + 1) + rows[j + 1] + 1 if j + 1 < order else rows[j]
    rows = rows[:, np.lexsort([pair(j) for j in range(0, order, 2)][::-1])]
    fresh, out, before = np.zeros(rows.shape[1], bool), [], np.zeros(rows.shape[1], np.int32)
    for word in rows:
        fresh[:1] = True
        fresh[1:] |= word[1:] != word[:-1]
        first = np.nonzero(fresh)[0]
        count = np.diff(first, append=len(fresh))
        known = word[first] >= 0
        first = first[known]
        out.append((before[first], word[first], count[known].astype(np.int32)))
        begins = np.zeros(len(fresh), np.int32)
        begins[first] = 1
        before = np.cumsum(begins, dtype=np.int32) - 1
    return out


def _kept(levels: list, start: int, most: int) -> tuple[list[int], list[int], list[list[int]], int]:
    """Of each order: n-grams, contexts, counts of counts; and words in all. The mark of the beginning is a context, no n-gram."""
    sizes, states, often, total = [], [], [], 0
    for n, (_, word, count) in enumerate(levels):
        real = word != start if n == 0 else np.ones(len(word), bool)
        sizes.append(int(real.sum()))
        states.append(len(np.unique(levels[n + 1][0])) if n + 1 < len(levels) else 0)
        often.append(np.bincount(np.minimum(count[real], most + 1), minlength=most + 2)[1 : most + 1].tolist())
        total += int(count[real].sum()) if n == 0 else 0
    return sizes, states, often, total


class _Range:
    """A range's n-grams with their places and states in the whole model."""

    def __init__(self, data: list[bytes], place: list[int], state: list[int], start: int, total: int, discount: np.ndarray, v: int):
        flat = [np.frombuffer(x, np.int32) for x in data]
        self.levels = [(np.cumsum(flat[i], dtype=np.int32), flat[i + 1], flat[i + 2]) for i in range(0, len(flat), 3)]
        self.place, self.base, self.order = place, state, len(self.levels)
        self.real = [w != start if n == 0 else slice(None) for n, (_, w, _) in enumerate(self.levels)]
        self.own, self.p, self.key = [], [], []
        for n, (parent, word, count) in enumerate(self.levels):
            leads = np.zeros(len(word), bool)
            if n + 1 < self.order:
                leads[self.levels[n + 1][0]] = True
            self.own.append(np.where(leads, self.base[n] + np.cumsum(leads) - 1, 0))
            if n == 0:
                self.p.append(count / total)
                self.key.append(word.astype(np.int64))
            else:
                sums = np.bincount(parent, weights=count, minlength=len(self.levels[n - 1][1]))
                self.p.append(discount[n, np.minimum(count, discount.shape[1] - 1)] * count / sums[parent])
                self.key.append(self.own[n - 1][parent] * v + word)


def _rows(name: str, at: int, x: np.ndarray) -> Iterator[tuple[str, int, bytes]]:
    data = np.ascontiguousarray(x).view(np.uint8).data
    for i in range(0, len(data), T.PIECE_BYTES):
        yield name, at * x.itemsize + i, bytes(data[i : i + T.PIECE_BYTES])


def _forward(r: _Range) -> Iterator[tuple[str, int, bytes]]:
    for n in range(r.order):
        at, real = r.place[n], r.real[n]
        yield from _rows("lm_key", at, r.key[n][real])
        yield from _rows("lm_p", at, np.log(r.p[n][real]))
        yield from _rows("own", at, r.own[n][real].astype(np.int32))
        if n + 1 < r.order and len(r.levels[n + 1][0]):
            below = np.nonzero(np.diff(r.levels[n + 1][0], prepend=-1))[0]
            yield from _rows("first", r.base[n], r.place[n + 1] + below)


def _backward(r: _Range, keys: np.ndarray, logs: np.ndarray, own: np.ndarray, v: int) -> Iterator[tuple[str, int, bytes]]:
    """Where each context backs off to and at what weight, and the state that each n-gram leads to, by the whole model's n-grams."""
    shorter = np.zeros(len(r.levels[0][1]), np.int64)  # state of each n-gram without its first word
    for n in range(1, r.order):
        parent, word, _ = r.levels[n]
        if not len(parent):
            shorter = np.zeros(0, np.int64)
            continue
        at = np.argsort(key := shorter[parent] * v + word)  # in order, the array's pages are read once
        place = np.empty(len(key), np.int64)
        place[at] = np.searchsorted(keys, key[at])
        lower = np.bincount(parent, weights=np.exp(logs[place]), minlength=len(shorter))
        used = np.bincount(parent, weights=r.p[n], minlength=len(shorter))
        leads = np.unique(parent)
        free = 1 - lower[leads]
        some = np.round(free, 12) > 0
        weight = np.where(some, np.maximum((1 - used[leads]) / np.where(some, free, 1.0), 0.0), 0.0)
        yield from _rows("back", r.base[n - 1], np.log(np.maximum(weight, 1e-12)))
        yield from _rows("back_to", r.base[n - 1], shorter[leads].astype(np.int32))
        shorter = own[place].astype(np.int64)
    for n in range(r.order):
        yield from _rows("lm_to", r.place[n], (r.own[n] if n + 1 < r.order else shorter)[r.real[n]].astype(np.int32))


def whole_model(sentences: DataFrame, words: Broadcast, tally: pa.Table, order: int, k: int = 5, floor: float = math.log(1e-7)) -> T.Pieces:
    """``fst.WordModel`` of every n-gram of the sentences, its arrays broadcast by pieces and mapped into memory by tasks.

    ``words``: all words of the sentences and the two marks, sorted; ``tally`` (w, c): their counts. order: 2 or more.
    """
    spark = sentences.sparkSession
    context, vocabulary = spark.sparkContext, words.value
    v, start, end = len(vocabulary), vocabulary.index("<s>"), vocabulary.index("</s>")
    lines = sentences.count()
    often = np.zeros(v, np.int64)
    often[pc.index_in(tally["w"], value_set=pa.array(vocabulary, pa.string())).to_numpy()] = tally["c"].to_numpy()
    often[[start, end]] += lines
    ranges = context.broadcast(((np.cumsum(often) - often) // RANGE).astype(np.int32))
    kind = "part int, sizes array<long>, states array<long>, often array<array<long>>, total long, levels array<binary>"

    def count(packets: pa.Table) -> pa.Table:
        rows = np.concatenate([np.frombuffer(x.as_buffer(), np.int32).reshape(order, -1) for x in packets.column("data")], axis=1)
        levels = _counted(rows, v)
        sizes, states, seen, total = _kept(levels, start, k + 1)
        data = [x.tobytes() for parent, word, c in levels for x in (np.diff(parent, prepend=np.int32(0)), word, c)]
        row = {"part": packets.column("part")[0].as_py(), "sizes": sizes, "states": states, "often": seen, "total": total, "levels": data}
        kinds = [pa.int32(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.list_(pa.int64())), pa.int64(), pa.list_(pa.binary())]
        return pa.Table.from_pylist([row], schema=pa.schema(list(zip(row, kinds))))

    made = written(_dealt(sentences, words, ranges, order).groupBy("part").applyInArrow(count, kind), "ngrams", maxRecordsPerFile=T.PIECES_A_FILE)
    info = sorted(made.select("part", "sizes", "states", "often", "total").collect())  # a row a range
    table = lambda c: np.array([r[c] for r in info], np.int64).reshape(len(info), order)
    sizes, states, total = table("sizes"), table("states"), sum(r["total"] for r in info)
    # n-grams and states are numbered by order, then by range
    place = np.cumsum(sizes.T).reshape(order, -1).T - sizes
    base = np.cumsum(states.T).reshape(order, -1).T - states + 1
    n_grams, n_states = int(sizes.sum()), int(states.sum()) + 1
    seen = np.array([r["often"] for r in info], np.int64).reshape(len(info), order, k + 1).sum(axis=0).tolist()
    table = spark.createDataFrame([(n + 1, *x) for n, x in enumerate(seen)], "order int, " + ", ".join(f"n{r} long" for r in range(1, k + 2)))
    discount = np.ones((order, k + 2))
    for r in M.discounts_of(table, k).collect():  # k rows an order
        discount[r["order"] - 1, r["r"]] = r["d"]
    where = context.broadcast({r["part"]: (place[i].tolist(), base[i].tolist()) for i, r in enumerate(info)})

    def ranged(work):  # noqa: ANN001, ANN202
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for part, data in zip(b.column(0).to_pylist(), b.column(1)):
                    found = _Range([x.as_buffer() for x in data.values], *where.value[part], start, total, discount, v)
                    for name, at, piece in work(found):
                        yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([at], pa.int64()), pa.array([piece], pa.binary())], names=["name", "at", "data"])

        return written(made.select("part", "levels").mapInArrow(run, "name string, at long, data binary"), "word-model", by="name", maxRecordsPerFile=16)

    ahead = ranged(_forward)
    ends = [("first", 0, np.zeros(1, np.int64)), ("first", n_states, np.array([n_grams]))]
    sent = T.Mapped.several(ahead, {"lm_key": ("<i8", n_grams), "lm_p": ("<f8", n_grams), "own": ("<i4", n_grams), "first": ("<i8", n_states + 1, ends)})
    dropped(ahead)
    keys, logs, own = sent["lm_key"], sent["lm_p"], sent.pop("own")
    behind = ranged(lambda r: _backward(r, keys.value, logs.value, own.value, v))
    none = {"back": ("<f8", n_states, [("back", 0, np.zeros(1))]), "back_to": ("<i4", n_states, [("back_to", 0, np.zeros(1, np.int32))])}
    sent |= T.Mapped.several(behind, none | {"lm_to": ("<i4", n_grams)})
    for used in (behind, made):
        dropped(used)
    own.cast.destroy()
    begin = 1 + int((often[:start] > 0).sum()) - (end < start) if lines else 0  # all words but the end are contexts, in their order
    rest = {"vocabulary": vocabulary, "order": order, "floor": floor, "v": v, "end": end, "n_states": n_states, "start": begin}
    return T.Pieces(context.broadcast((T.WordModel, rest)), sent)
