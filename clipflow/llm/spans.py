"""Repeated spans: which windows of tokens also start in a document with a smaller id, exactly.

Texts are gathered, as they are read, to chunks of a few MB, each one row of a table. Windows with the same smallest gram
(by hash) form a run, whose string of tokens depends on nothing but the text around that gram.

1. Each chunk sends, for every range of gram hashes, a sorted immutable run of its grams: hash, smallest document, and the
   hash of the gram's string (or how many strings it has). A range merges them with those of earlier batches.
   A gram of one document is done. If all strings of a gram are one, its windows are repeats after the smallest id.
2. Of grams with several strings the strings themselves meet at their gram's range, where each window's bytes are
   compared. Grams with more than ``HOT`` strings are not brought together: their windows are dealt out one by one, by
   128-bit digests, so that only equal windows meet, as one entry a chunk.
3. Chunks mark the tokens that repeated windows cover.

Only packets that hold something are sent, so rows grow with grams at most, not with chunks times ranges. What many
documents share is one entry a chunk in every exchange. Sizes are those of the texts themselves.

That a string is another's equal is held by two hashes (95 bits); windows that only some strings share are told by bytes.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import accumulate

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from clipflow.llm.common import materialise, mix64, release, ship, utf8

CHUNK_BYTES, RANGE_BYTES = 4 << 20, 8 << 20  # of text
HOT = 1 << 11  # strings of one gram that one task may compare
SEGMENT = 1 << 18  # tokens that are hashed at once
PLACE_BITS = 20  # enough for a segment and a window
LAST_ID, FIRST_ID = np.iinfo(np.int64).max, np.iinfo(np.int64).min
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)


@dataclass(frozen=True)
class Kind:
    """What a token is. ``cut``: text -> (bytes, starts, ends) with a token's bytes at [start, end)."""

    width: int
    gram: int
    cut: Callable[[bytes], tuple[bytes, np.ndarray, np.ndarray]]


def _places(x: np.ndarray) -> np.ndarray:
    return x.astype(np.int32) if not len(x) or x[-1] < 1 << 31 else x


def byte_tokens(text: bytes) -> tuple[bytes, np.ndarray, np.ndarray]:
    at = _places(np.arange(len(text) + 1))
    return text, at[:-1], at[1:]


def word_tokens(text: bytes) -> tuple[bytes, np.ndarray, np.ndarray]:
    words = text.split()
    ends = _places(np.fromiter(accumulate(len(w) + 1 for w in words), np.int64, len(words)))
    return b" ".join(words), np.concatenate([np.zeros(min(1, len(words)), ends.dtype), ends[:-1]]), ends - 1


_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """1, base, base ** 2, ... modulo 2 ** 64; at most a segment's bytes of them."""
    if len(_powers.get(base, ())) < n:
        _powers[base] = np.cumprod(np.concatenate([[np.uint64(1)], np.full(max(n, 1 << 16), np.uint64(base))]), dtype=np.uint64)
    return _powers[base][:n]


def _sums(data: bytes) -> np.ndarray:
    """Prefix sums of the bytes as a polynomial modulo 2 ** 64."""
    raw = np.frombuffer(data, np.uint8).astype(np.uint64) + np.uint64(1)
    return np.concatenate([[np.uint64(0)], np.cumsum(raw * powers(_BASE, len(raw)), dtype=np.uint64)])


def _slices(sums: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """A hash of each data[first:last]."""
    return mix64((sums[last] - sums[first]) * powers(_INVERSE, len(sums))[first])


def _runs(data: bytes, starts: np.ndarray, ends: np.ndarray, doc: np.ndarray, kind: Kind) -> tuple[np.ndarray, ...]:
    """(first, last, hash, string's hash) of the runs of some documents' tokens, which lie in ``data`` one after the other.

    A run is a maximal row of neighbouring windows with one smallest gram: windows first[i] to last[i].
    """
    sums = _sums(data)
    h = _slices(sums, starts[: len(starts) - kind.gram + 1], ends[kind.gram - 1 :])
    # the smallest of the next hashes with its place in the low bits, so that the first of equals wins: rows of 1, 2, 4, ...
    low = np.uint64((1 << PLACE_BITS) - 1)
    at, reach, span = (h & ~low) | np.arange(len(h), dtype=np.uint64), 1, kind.width - kind.gram + 1
    while reach < span:
        step = min(reach, span - reach)
        at = np.minimum(at[:-step], at[step:])
        reach += step
    at = (at & low).astype(np.int64)
    whole = doc[: len(at)] == doc[kind.width - 1 :]  # windows that end in the document where they start
    change = at[1:] != at[:-1]
    change |= whole[1:] != whole[:-1]
    change |= doc[1 : len(at)] != doc[: len(at) - 1]
    first = np.concatenate([[0], np.nonzero(change)[0] + 1])
    last = np.concatenate([first[1:], [len(at)]]) - 1
    keep = whole[first]
    first, last = first[keep], last[keep]
    a, b = starts[first], ends[last + kind.width - 1]
    string = mix64(_slices(sums, a, b) + (b - a).astype(np.uint64))
    return first, last, h[at[first]], string


def runs_of(cuts: list[tuple[bytes, np.ndarray, np.ndarray]], kind: Kind) -> tuple[np.ndarray, ...]:
    """(document, first, last, hash, string's hash) of all runs, by document and place; short documents are hashed together."""
    parts: list[tuple] = []
    batch: list[tuple[int, int, bytes, np.ndarray, np.ndarray]] = []  # document, its token where the piece starts, ...

    def flush() -> None:
        if not batch:
            return
        sizes = np.array([len(b[3]) for b in batch])
        base = np.concatenate([[0], np.cumsum([len(b[2]) for b in batch])])[:-1]
        number = np.repeat(np.arange(len(batch)), sizes)
        starts = np.concatenate([b[3] + o for b, o in zip(batch, base)])
        ends = np.concatenate([b[4] + o for b, o in zip(batch, base)])
        first, last, h, string = _runs(b"".join(b[2] for b in batch), starts, ends, number, kind)
        piece = number[first]
        shift = np.array([b[1] for b in batch]) - np.concatenate([[0], np.cumsum(sizes)[:-1]])
        parts.append((np.array([b[0] for b in batch], np.int64)[piece], first + shift[piece], last + shift[piece], h, string))
        batch.clear()

    held = 0
    for n, (data, starts, ends) in enumerate(cuts):
        for a in range(0, max(len(starts) - kind.width + 1, 0), SEGMENT):
            b = min(a + SEGMENT + kind.width - 1, len(starts))
            lo = int(starts[a])
            if held and held + b - a > SEGMENT:
                flush()
                held = 0
            batch.append((n, a, data[lo : int(ends[b - 1])], starts[a:b] - lo, ends[a:b] - lo))
            held += b - a
    flush()
    if not parts:
        return (*(np.zeros(0, np.int64) for _ in range(3)), np.zeros(0, np.uint64), np.zeros(0, np.uint64))
    return tuple(np.concatenate(c) for c in zip(*parts))


# ---- packing of columns and bits

_shrink, _grow = zstandard.ZstdCompressor(level=1), zstandard.ZstdDecompressor()


def pack(raw: bytes) -> bytes:
    return _shrink.compress(raw)


def unpack(blob: bytes) -> bytes:
    return _grow.decompress(blob)


def pack_columns(keys: np.ndarray, *more: np.ndarray) -> bytes:
    """Sorted keys and columns beside them. Bytes of one significance lie together, so those that hardly vary cost little."""
    columns = [np.diff(keys.view(np.int64), prepend=np.int64(0)), *more]
    return pack(b"".join(np.ascontiguousarray(np.ascontiguousarray(c, np.int64).view(np.uint8).reshape(-1, 8).T).tobytes() for c in columns))


def unpack_columns(blob: bytes, n: int) -> list[np.ndarray]:
    raw = np.frombuffer(unpack(blob), np.uint8).reshape(n, 8, -1)
    keys, *more = (np.ascontiguousarray(c.T).view(np.int64)[:, 0] for c in raw)
    return [np.cumsum(keys), *more]


def pack_bits(x: np.ndarray) -> bytes:
    return pack(len(x).to_bytes(8, "little") + np.packbits(x).tobytes())


def unpack_bits(blob: bytes) -> np.ndarray:
    raw = unpack(blob)
    return np.unpackbits(np.frombuffer(raw, np.uint8, offset=8), count=int.from_bytes(raw[:8], "little")).astype(bool)


# ---- chunks

KEY_BITS = 48
#: What a range says of a gram: one string, whose smallest id is in the chunk itself or elsewhere; several; very many.
HERE, ELSEWHERE, SEVERAL, MANY = 1, 2, 3, 4


def filled(keys: np.ndarray, ranges: int) -> list[tuple[int, slice]]:
    """The ranges that some of the sorted keys are in, and which."""
    number = (keys.astype(object) * ranges >> KEY_BITS).astype(np.int64) if ranges > 1 << 15 else keys * ranges >> KEY_BITS
    start = np.nonzero(np.diff(number, prepend=-1))[0]
    return [(int(number[a]), slice(a, b)) for a, b in zip(start.tolist(), [*start[1:].tolist(), len(keys)])]


def gather(docs: DataFrame, batch: int, id_col: str = "doc_id", text_col: str = "text", chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """docs -> (chunk, bytes, docs): one row for about ``chunk_bytes`` of text, its ids and texts in one packed value."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, made = (batch << 44) | (TaskContext.get().partitionId() << 20), 0
        held, size = [], 0

        def emit() -> pa.RecordBatch:
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, held[0].schema) as out:
                for b in held:
                    out.write_batch(b)
            return pa.RecordBatch.from_arrays([pa.array([base + made]), pa.array([size]), pa.array([pack(sink.getvalue().to_pybytes())], pa.binary())], names=["chunk", "bytes", "docs"])

        for b in batches:
            lengths = np.array(pa.compute.binary_length(b.column(1)), np.int64) + 16
            number = (np.cumsum(lengths) - lengths + size) // chunk_bytes
            start = [0, *(np.nonzero(np.diff(number))[0] + 1).tolist(), b.num_rows]
            for i, j in zip(start, start[1:]):
                if i:
                    yield emit()
                    held, size, made = [], 0, made + 1
                if j > i:
                    held.append(b.slice(i, j - i))
                    size += int(lengths[i:j].sum())
            if size >= chunk_bytes:
                yield emit()
                held, size, made = [], 0, made + 1
        if held:
            yield emit()

    import pyarrow.compute  # noqa: F401

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text"))
    return rows.mapInArrow(run, "chunk long, bytes long, docs binary")


class Chunk:
    """A chunk's documents and what all three passes derive from them."""

    def __init__(self, texts: pa.Table, kind: Kind):
        self.kind = kind
        self.ids = texts.column("doc_id").to_pylist()
        numbers = np.array([LAST_ID if i is None else i for i in self.ids], np.int64)
        order = np.argsort(numbers, kind="stable")
        self.numbers, self.ids = numbers[order], [self.ids[i] for i in order]
        column = texts.column("text")
        self.cuts = [kind.cut(column[int(i)].as_py()) for i in order]
        self.doc, self.first, self.last, h, string = runs_of(self.cuts, kind)
        # the smallest hashes are small: only scrambled anew do they spread over the ranges
        key, string = (mix64(h) >> np.uint64(64 - KEY_BITS)).astype(np.int64), (string >> np.uint64(64 - KEY_BITS)).astype(np.int64)
        order = np.argsort(key, kind="stable")  # runs come by document, so each key's first is of the smallest id
        sorted_key = key[order]
        fresh = np.diff(sorted_key, prepend=-1) != 0
        again = ~fresh
        again[:-1] |= again[1:]
        again = np.nonzero(again)[0]
        order[again] = order[again][np.lexsort((string[order[again]], sorted_key[again]))]
        start = np.nonzero(fresh)[0]
        self.keys = sorted_key[start]
        self.slot = np.empty(len(key), np.int64)
        self.slot[order] = np.cumsum(fresh) - 1
        # strings are numbered by key; the run that stands for one is of its smallest document
        new = fresh | (np.diff(string[order], prepend=-1) != 0)
        self.string = np.empty(len(key), np.int64)
        self.string[order] = np.cumsum(new) - 1
        self.stands = order[new]
        self.slot_of_string = self.slot[self.stands]
        self.least_of_string = self.numbers[self.doc[self.stands]] if len(key) else np.zeros(0, np.int64)
        if len(key):
            of = self.doc[order]
            self.least = self.numbers[np.minimum.reduceat(of, start)]
            self.twice = self.least < self.numbers[np.maximum.reduceat(of, start)]
        else:
            self.least, self.twice = np.zeros(0, np.int64), np.zeros(0, bool)
        several = np.bincount(self.slot_of_string, minlength=len(self.keys))
        first_string = np.searchsorted(self.slot_of_string, np.arange(len(self.keys)))
        self.about = np.where(several == 1, string[self.stands[first_string]] | 1, several << 1) if len(key) else np.zeros(0, np.int64)

    @classmethod
    def read(cls, blob: bytes, kind: Kind) -> Chunk:
        return cls(pa.ipc.open_stream(unpack(blob)).read_all(), kind)

    def codes(self, replies: pa.Table) -> np.ndarray:
        out = np.zeros(len(self.keys), np.int8)
        for body in replies.column("body"):
            keys, code = unpack_columns(body.as_py(), 2)
            out[np.searchsorted(self.keys, keys)] = code
        return out

    def windows_of(self, strings: np.ndarray) -> np.ndarray:
        run = self.stands[strings]
        return self.last[run] - self.first[run] + 1

    def texts_of(self, strings: np.ndarray) -> list[bytes]:
        out = []
        for run in self.stands[strings].tolist():
            data, starts, ends = self.cuts[self.doc[run]]
            out.append(data[starts[self.first[run]] : ends[self.last[run] + self.kind.width - 1]])
        return out

    def digests_of(self, strings: np.ndarray) -> np.ndarray:
        """128-bit digests of the strings' windows, one after the other, as byte strings."""
        out, digest = [], xxhash.xxh3_128_digest
        for run in self.stands[strings].tolist():
            data, starts, ends = self.cuts[self.doc[run]]
            a, b = int(self.first[run]), int(self.last[run]) + 1
            out += [digest(data[i:j]) for i, j in zip(starts[a:b].tolist(), ends[a + self.kind.width - 1 : b + self.kind.width - 1].tolist())]
        return np.array(out, "S16")


def _high(digests: np.ndarray) -> np.ndarray:
    """The leading bits of digests, which order them, as keys."""
    return (np.frombuffer(digests.tobytes(), ">u8")[::2] >> np.uint64(64 - KEY_BITS)).astype(np.int64)


def _many(chunk: Chunk, strings: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct window digests of the strings, the smallest id of each in the chunk, and each window's place among them."""
    digests = chunk.digests_of(strings)
    distinct, place = np.unique(digests, return_inverse=True)
    least = np.full(len(distinct), LAST_ID)
    np.minimum.at(least, place, np.repeat(chunk.least_of_string[strings], chunk.windows_of(strings)))
    return distinct, least, place


def _table(columns: dict[str, tuple[list, pa.DataType]]) -> pa.Table:
    return pa.table({n: pa.array(v, k) for n, (v, k) in columns.items()})


Classes = Callable[[list[bytes], list[int], Kind], list[np.ndarray]]
BATCH = 200_000  # windows whose strings are compared at a time


def compare_strings(keys: np.ndarray, own: np.ndarray, windows: np.ndarray, texts: list[bytes], classes: Classes, kind: Kind) -> np.ndarray:
    """For each window of each string, in turn: does a string of the same key with a smaller id have it?

    Whole keys are compared at a time; a key has at most ``HOT`` strings a chunk's worth.
    """
    order = np.argsort(keys, kind="stable")
    out: list[np.ndarray] = [np.zeros(0, bool)] * len(keys)
    batch: list[int] = []

    def flush() -> None:
        least: dict[tuple[int, bytes], int] = {}
        for i in batch:
            e, a = (int(keys[i]), texts[i]), int(own[i])
            if a < least.get(e, LAST_ID + 1):
                least[e] = a
        known = list(least)
        count = {e: n for e, n in ((((int(keys[i]), texts[i])), int(windows[i])) for i in batch)}
        numbers = classes([t for _, t in known], [count[e] for e in known], kind)
        ids = np.concatenate(numbers)
        owner = np.repeat(np.array(list(least.values()), np.int64), [len(n) for n in numbers])
        low = np.full(ids.max() + 1, LAST_ID)
        np.minimum.at(low, ids, owner)
        best = dict(zip(known, np.split(low[ids], np.cumsum([len(n) for n in numbers])[:-1])))
        for i in batch:
            out[i] = best[int(keys[i]), texts[i]] < own[i]
        batch.clear()

    held = 0
    for n, i in enumerate(order.tolist()):
        if held >= BATCH and keys[i] != keys[order[n - 1]]:
            flush()
            held = 0
        batch.append(i)
        held += int(windows[i])
    if batch:
        flush()
    return np.concatenate(out) if out else np.zeros(0, bool)


# ---- the passes

PLACE = "chunk long, range int, what string, body binary, more binary"


def _rows(rows: list[tuple]) -> pa.Table:
    names = (("chunk", pa.int64()), ("range", pa.int32()), ("what", pa.string()), ("body", pa.binary()), ("more", pa.binary()))
    return _table({n: (list(c), k) for (n, k), c in zip(names, zip(*rows) if rows else [()] * 5)})


def sorted_runs(chunks: DataFrame, kind: Kind, ranges: int) -> DataFrame:
    """Pass 1: each chunk's sorted grams, cut into the ranges that have any."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for number, blob in zip(batch.column(0).to_pylist(), batch.column(1)):
                c = Chunk.read(blob.as_py(), kind)
                rows = [(number, r, "grams", pack_columns(c.keys[s], c.about[s], c.least[s], c.twice[s]), None) for r, s in filled(c.keys, ranges)]
                del c
                yield from _rows(rows).to_batches()
                del rows
                release()

    return chunks.select("chunk", "docs").mapInArrow(run, PLACE)


def merge_runs(rows: pa.Table, old: list[tuple[np.ndarray, np.ndarray, np.ndarray]], keep: bool, hot: int = HOT) -> pa.Table:
    """Merge a range's sorted runs: answers to the chunks that sent some, to old chunks that are asked, and the new run.

    ``old``: (keys, about, chunk) of runs of earlier batches, sorted by key. Their ids count as smaller than all new ones.
    """
    chunk, number = rows.column("chunk").to_pylist(), (rows.column("range")[0].as_py() if rows.num_rows else 0)
    new = [unpack_columns(b.as_py(), 4) for b in rows.column("body")]
    sizes = [len(n[0]) for n in new]
    every = np.concatenate([n[0] for n in new] or [np.zeros(0, np.int64)])
    seen, place = np.unique(every, return_inverse=True)
    met = []
    for keys, about, where in old:  # of the old runs only what new ones meet
        at = np.minimum(np.searchsorted(seen, keys), max(len(seen) - 1, 0))
        hit = (seen[at] == keys) if len(seen) else np.zeros(len(keys), bool)
        met.append((at[hit], about[hit], where[hit]))
    about = np.concatenate([n[1] for n in new] + [m[1] for m in met] or [np.zeros(0, np.int64)])
    slot = np.concatenate([place, *(m[0] for m in met)])
    count = np.bincount(slot, minlength=len(seen))
    strings = np.bincount(slot, weights=np.where(about & 1, 1, about >> 1), minlength=len(seen))
    low, high = np.full(len(seen), LAST_ID), np.full(len(seen), FIRST_ID)
    np.minimum.at(low, slot, about)
    np.maximum.at(high, slot, about)
    one = (low == high) & (low & 1 == 1)
    least = np.full(len(seen), LAST_ID)
    np.minimum.at(least, place, np.concatenate([n[2] for n in new] or [np.zeros(0, np.int64)]))
    shared = count > 1
    shared[place[np.concatenate([n[3] for n in new] or [np.zeros(0, np.int64)]).astype(bool)]] = True
    for m in met:
        least[m[0]] = FIRST_ID
    code = np.where(~shared, 0, np.where(one, HERE, np.where(strings <= hot, SEVERAL, MANY)))
    out, end = [], 0
    for c, n, columns in zip(chunk, sizes, new):
        own = place[end : end + n]
        end += n
        mine = code[own]
        mine = np.where((mine == HERE) & (least[own] < columns[2]), ELSEWHERE, mine)
        if (told := np.nonzero(mine)[0]).size:
            out.append((c, number, "answer", pack_columns(columns[0][told], mine[told]), None))
    if met:
        at, _, where = (np.concatenate(c) for c in zip(*met))
        asked = code[at] >= SEVERAL
        at, where = at[asked], where[asked]
        order = np.lexsort((at, where))
        at, where = at[order], where[order]
        start = np.nonzero(np.diff(where, prepend=-1))[0]
        for a, b in zip(start.tolist(), [*start[1:].tolist(), len(at)]):
            out.append((int(where[a]), number, "old", pack_columns(seen[at[a:b]], code[at[a:b]]), None))
    if keep and len(every):
        where = np.repeat(np.array(chunk, np.int64), sizes)
        order = np.lexsort((where, every))
        out.append((len(every), number, "run", pack_columns(every[order], about[: len(every)][order], where[order]), None))
    return _rows(out)


def send_strings(number: int, c: Chunk, codes: np.ndarray, ranges: int, old: bool) -> list[tuple]:
    """Pass 2: the strings of grams that have several, and the windows of those with very many, to their ranges."""
    what, rows = "o" if old else "n", []
    of_string = codes[c.slot_of_string]
    picked = np.nonzero(of_string == SEVERAL)[0]
    keys, windows = c.keys[c.slot_of_string[picked]], c.windows_of(picked)
    own = np.full(len(picked), FIRST_ID) if old else c.least_of_string[picked]
    texts = c.texts_of(picked)
    lengths = np.array([len(t) for t in texts], np.int64)
    for r, s in filled(keys, ranges):
        rows.append((number, r, what + "strings", pack_columns(keys[s], lengths[s], windows[s], own[s]), pack(b"".join(texts[s]))))
    picked = np.nonzero(of_string == MANY)[0]
    if len(picked):
        digests, least, _ = _many(c, picked)
        if old:
            least[:] = FIRST_ID
        for r, s in filled(_high(digests), ranges):
            rows.append((number, r, what + "windows", pack(digests[s].tobytes()), pack_columns(least[s])))
    return rows


def merge_strings(rows: pa.Table, classes: Classes, kind: Kind) -> pa.Table:
    """Answer each new chunk: for every window that it sent, does a smaller id have it?"""
    out, number = [], rows.column("range")[0].as_py()
    columns = [rows.column(n).to_pylist() for n in ("chunk", "what", "body", "more")]
    sent = [(c, w, *unpack_columns(b, 4), unpack(m)) for c, w, b, m in zip(*columns) if w.endswith("strings")]
    if sent:
        keys, own, windows = (np.concatenate([s[i] for s in sent]) for i in (2, 5, 4))
        texts: list[bytes] = []
        for _, _, _, lengths, _, _, text in sent:
            ends = np.cumsum(lengths).tolist()
            texts += [text[a:b] for a, b in zip([0, *ends], ends)]
        repeat = compare_strings(keys, own, windows, texts, classes, kind)
        ends = np.cumsum([int(s[4].sum()) for s in sent]).tolist()
        out += [(s[0], number, "strings", pack_bits(repeat[a:b]), None) for s, a, b in zip(sent, [0, *ends], ends) if s[1] == "nstrings" and repeat[a:b].any()]
    sent = [(c, w, np.frombuffer(unpack(b), "S16"), unpack_columns(m, 1)[0]) for c, w, b, m in zip(*columns) if w.endswith("windows")]
    if sent:
        distinct, place = np.unique(np.concatenate([s[2] for s in sent]), return_inverse=True)
        own = np.concatenate([s[3] for s in sent])
        least = np.full(len(distinct), LAST_ID)
        np.minimum.at(least, place, own)
        repeat, ends = least[place] < own, np.cumsum([len(s[2]) for s in sent]).tolist()
        out += [(s[0], number, "windows", pack_bits(repeat[a:b]), None) for s, a, b in zip(sent, [0, *ends], ends) if s[1] == "nwindows" and repeat[a:b].any()]
    return _rows(out)


def removed_of(c: Chunk, codes: np.ndarray, replies: pa.Table, ranges: int) -> Iterator[np.ndarray]:
    """Pass 3: for each document, which of its tokens a repeated window covers."""
    said = {(w, r): b for w, r, b in zip(*(replies.column(n).to_pylist() for n in ("what", "range", "body"))) if w in ("strings", "windows")}
    of_string = codes[c.slot_of_string]
    picked = [np.nonzero(of_string == code)[0] for code in (SEVERAL, MANY)]
    # whether each window of such a string is an earlier document's, as seen by the string's smallest document
    flags = []
    windows = c.windows_of(picked[0])
    bits, ends = np.zeros(int(windows.sum()), bool), np.concatenate([[0], np.cumsum(windows)]).astype(np.int64)
    for r, s in filled(c.keys[c.slot_of_string[picked[0]]], ranges):
        if ("strings", r) in said:
            bits[ends[s.start] : ends[s.stop]] = unpack_bits(said["strings", r])
    flags.append(bits)
    if len(picked[1]):
        digests, least, place = _many(c, picked[1])
        earlier = np.zeros(len(digests), bool)
        for r, s in filled(_high(digests), ranges):
            if ("windows", r) in said:
                earlier[s] = unpack_bits(said["windows", r])
        own = np.repeat(c.least_of_string[picked[1]], c.windows_of(picked[1]))
        flags.append(earlier[place] | (least[place] < own))
    else:
        flags.append(np.zeros(0, bool))
    base = np.concatenate([[0], np.cumsum([len(s) + 1 for _, s, _ in c.cuts])]).astype(np.int64)
    step = np.zeros(base[-1] + 1, np.int32)
    of_run = codes[c.slot]
    mine = c.numbers[c.doc] if len(c.doc) else np.zeros(0, np.int64)
    whole = (of_run == ELSEWHERE) | ((of_run == HERE) & (mine > c.least[c.slot]))
    whole |= (of_run >= SEVERAL) & (mine > c.least_of_string[c.string])
    np.add.at(step, base[c.doc[whole]] + c.first[whole], 1)
    np.add.at(step, base[c.doc[whole]] + c.last[whole] + c.kind.width, -1)
    for strings, bits, code in zip(picked, flags, (SEVERAL, MANY)):
        rest = np.nonzero((of_run == code) & ~whole)[0]
        if not len(rest) or not bits.any():
            continue
        ends = np.concatenate([[0], np.cumsum(c.windows_of(strings))]).astype(np.int64)
        at = np.searchsorted(strings, c.string[rest])
        n = (ends[at + 1] - ends[at])
        within = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        hit = bits[np.repeat(ends[at], n) + within]
        place = (np.repeat(base[c.doc[rest]] + c.first[rest], n) + within)[hit]
        np.add.at(step, place, 1)
        np.add.at(step, place + c.kind.width, -1)
    for i, (_, starts, _) in enumerate(c.cuts):
        yield np.cumsum(step[base[i] : base[i] + len(starts)]) > 0


def ranges_for(size: int, range_bytes: int) -> int:
    return max(12, -(-size // range_bytes))


def repeats(chunks: DataFrame, told: DataFrame, kind: Kind, classes: Classes, finish: Callable, schema: str, ranges: int, old_chunks: DataFrame | None = None) -> DataFrame:
    """``finish(id, text, starts, ends, removed)`` for each document of the chunks, removed being a boolean for each token.

    ``told``: what ``merge_runs`` answered, written. ``classes(strings, windows, kind)``: for some strings, numbers of their
    windows, equal just for equal ones. ``old_chunks`` are of earlier batches: those that are asked send their strings too.
    """
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    arrow = to_arrow_schema(StructType.fromDDL(schema))

    def send(old: bool) -> Callable:
        def run(key: tuple, rows: pa.Table, replies: pa.Table) -> pa.Table:
            if not rows.num_rows or not replies.num_rows:
                return _rows([])
            c = Chunk.read(rows.column("docs")[0].as_py(), kind)
            out = _rows(send_strings(key[0].as_py(), c, c.codes(replies), ranges, old))
            del c
            release()
            return out

        return run

    def mark(key: tuple, rows: pa.Table, replies: pa.Table) -> pa.Table:
        c = Chunk.read(rows.column("docs")[0].as_py(), kind)
        mine = replies.filter(pa.compute.equal(replies.column("what"), "answer"))
        gone = removed_of(c, c.codes(mine), replies, ranges)
        out = pa.Table.from_pylist([finish(i, *cut, removed) for i, cut, removed in zip(c.ids, c.cuts, gone)], schema=arrow)
        del c, gone
        release()
        return out

    import pyarrow.compute  # noqa: F401

    texts = chunks.select("chunk", "docs").groupBy("chunk")
    answers = told.where("what = 'answer'")
    asked = texts.cogroup(answers.groupBy("chunk")).applyInArrow(send(False), PLACE)
    if old_chunks is not None:
        wanted = told.where("what = 'old'")
        # only chunks that are asked travel
        history = old_chunks.select("chunk", "docs").join(wanted.select("chunk").distinct().hint("merge"), "chunk", "left_semi")
        asked = asked.unionByName(history.groupBy("chunk").cogroup(wanted.groupBy("chunk")).applyInArrow(send(True), PLACE))
    known = asked.groupBy("range").applyInArrow(lambda rows: merge_strings(rows, classes, kind), PLACE)
    return texts.cogroup(answers.unionByName(known).groupBy("chunk")).applyInArrow(mark, schema)


def one_batch(docs: DataFrame, kind: Kind, classes: Classes, finish: Callable, schema: str, id_col: str = "doc_id", text_col: str = "text",
              chunk_bytes: int = CHUNK_BYTES, range_bytes: int = RANGE_BYTES, hot: int = HOT) -> DataFrame:
    """The repeats within one table."""
    chunks = materialise(gather(docs, 0, id_col, text_col, chunk_bytes), "chunks")
    ranges = ranges_for(int(chunks.agg(F.sum("bytes")).first()[0] or 0), range_bytes)
    told = sorted_runs(chunks, kind, ranges).groupBy("range").applyInArrow(lambda rows: merge_runs(rows, [], False, hot), PLACE)
    return repeats(chunks, materialise(told, "answers"), kind, classes, finish, schema, ranges)
