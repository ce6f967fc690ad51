"""Best-fit packing of token sequences with a bounded number of open bins.

Bins that can still take something are found through a bitset keyed by free space: the lowest set bit at or above a
piece's length is the tightest bin. When all bins are open and none fits, the fullest closes. Each task packs what
it reads and hands on its open bins; they are dealt out again as pieces of one length, to fewer and fewer tasks.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from clipflow.llm.common import materialise, ship, utf8


class WordTokenizer:
    """Ids of a word-level BPE file as little-endian 32-bit bytes, equal to those of the library.

    Words never reach over white space, so each is encoded by itself and remembered. Plain words (letters that lower
    and compose to themselves) go to the BPE model straight; every other one to the whole tokenizer.
    """

    PLAIN = re.compile("([A-Za-zÀ-ÖØ-öø-ÿ]+)([.,;:!?]*)")
    KEEP = 800_000

    def __init__(self, path: str):
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.full = Tokenizer.from_file(path)
        self.model = Tokenizer.from_file(path)
        self.model.normalizer = normalizers.Sequence([])
        self.model.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        size = self.full.get_vocab_size()
        self.ends = bytes((self.full.id_to_token(i) or "").endswith("</w>") for i in range(size))
        printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [b for b in range(256) if b not in set(printable)]
        self.byte_chars = {b: chr(b) for b in printable} | {b: chr(256 + n) for n, b in enumerate(rest)}
        self.known: dict[str, bytes] = {}
        self.cores: dict[str, bytes] = {}

    def _whole(self, chunk: str) -> bytes:
        ids = self.full.encode(chunk, add_special_tokens=False).ids
        return struct.pack(f"<{len(ids)}I", *ids)

    def _learn(self, chunks: set[str]) -> None:
        plain, cores = [], set()
        for c in chunks:
            if m := self.PLAIN.fullmatch(c):
                core = m[1].lower()
                plain.append((c, core, m[2]))
                if core not in self.cores:
                    cores.add(core)
            else:
                self.known[c] = self._whole(c)
        if cores:
            order = sorted(cores)
            line = " ".join(w.encode().decode("latin-1").translate(self.byte_chars) for w in order)
            ids = self.model.encode_batch_fast([line], add_special_tokens=False)[0].ids
            start, word = 0, iter(order)
            for n, i in enumerate(ids, 1):
                if self.ends[i]:
                    self.cores[next(word)] = struct.pack(f"<{n - start}I", *ids[start:n])
                    start = n
        for c, core, tail in plain:
            if tail and tail not in self.known:
                self.known[tail] = self._whole(tail)
            self.known[c] = self.cores[core] + self.known[tail] if tail else self.cores[core]

    def encode(self, text: str) -> bytes:
        chunks = text.replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" ")
        if len(self.known) > self.KEEP:  # what is remembered is bounded
            self.known.clear()
            self.cores.clear()
        if missing := set(chunks).difference(self.known):
            self._learn(missing)
        return b"".join(map(self.known.__getitem__, chunks))


_tokenizers: dict[str, WordTokenizer] = {}


def word_tokenizer(path: str) -> WordTokenizer:
    if path not in _tokenizers:
        _tokenizers[path] = WordTokenizer(path)
    return _tokenizers[path]


class BestFit:
    """Online best-fit over at most ``open_bins`` bins of ``capacity``. Yields bins as they close."""

    def __init__(self, capacity: int, open_bins: int):
        self.capacity, self.limit = capacity, open_bins
        self.free: dict[int, list[list]] = {}
        self.bits = self.count = 0

    def _take(self, space: int) -> list:
        stack = self.free[space]
        found = stack.pop()
        if not stack:
            self.bits &= ~(1 << space)
        self.count -= 1
        return found

    def add(self, length: int, item: object) -> list | None:
        """Place one piece of 1 to ``capacity``; the bin that closes for it, if any."""
        if length == self.capacity:
            return [(0, length, item)]
        closed, space = None, self.capacity
        if fit := self.bits >> length:
            space = length + (fit & -fit).bit_length() - 1
            chosen = self._take(space)
        else:
            chosen = []
            if self.count >= self.limit:
                closed = self._take((self.bits & -self.bits).bit_length() - 1)  # the fullest
        chosen.append((self.capacity - space, length, item))
        if left := space - length:
            self.free.setdefault(left, []).append(chosen)
            self.bits |= 1 << left
            self.count += 1
            return closed
        return chosen

    def rest(self) -> list[list]:
        """The open bins, emptiest last."""
        return [b for space in sorted(self.free) for b in self.free[space]]


PART = [("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())]
IDS = ("ids", pa.binary())


def _spark_fields(with_ids: bool) -> str:
    return ", ".join(f"{n}: {k}" for n, k in zip([*dict(PART), "ids"], ("long", "int", "long", "long", "long", "binary")[: 5 + with_ids]))


def cut(ids: bytes, doc: int | None, capacity: int, with_ids: bool) -> Iterator[tuple]:
    """A document's pieces: all but the last are full."""
    for n, at in enumerate(range(0, len(ids), 4 * capacity)):
        part = ids[at : at + 4 * capacity]
        yield (doc, n, at // 4, len(part) // 4, zlib.crc32(part), part)[: 5 + with_ids]


def _number(level: int, made: int) -> int:
    return (level << 56) | (TaskContext.get().partitionId() << 32) | made


def _bins_schema(with_ids: bool) -> tuple[str, pa.Schema]:
    part = pa.struct([*PART, *[IDS] * with_ids, ("offset", pa.int64())])
    spark = f"sequence_id long, closed boolean, total int, parts array<struct<{_spark_fields(with_ids)}, offset: long>>"
    return spark, pa.schema([("sequence_id", pa.int64()), ("closed", pa.bool_()), ("total", pa.int32()), ("parts", pa.list_(part))])


def _emit(bins: list[tuple[bool, list]], schema: pa.Schema, level: int, made: int) -> pa.RecordBatch:
    """bins: (closed, [(base, length, parts)]); each part's last value is its place within its bundle."""
    names = [f.name for f in schema.field("parts").type.value_type]
    columns: tuple[list, ...] = ([], [], [], [])
    for n, (closed, found) in enumerate(bins, made):
        columns[0].append(_number(level, n))
        columns[1].append(closed)
        columns[2].append(sum(length for _, length, _ in found))
        columns[3].append([dict(zip(names, (*p[:-1], base + p[-1]))) for base, _, parts in found for p in parts])
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema)], schema=schema)


def _packed(bundles: Iterator[list[tuple[int, list]]], capacity: int, open_bins: int, schema: pa.Schema, level: int, last: bool) -> Iterator[pa.RecordBatch]:
    """Pack batches of (length, parts); the longest of a batch come first."""
    bins, out, made = BestFit(capacity, open_bins), [], 0
    for batch in bundles:
        for length, parts in sorted(batch, key=lambda b: -b[0]):
            if found := bins.add(length, parts):
                out.append((True, found))
        if len(out) >= 1000:
            yield _emit(out, schema, level, made)
            made, out = made + len(out), []
    out += [(last, found) for found in bins.rest()]
    if out:
        yield _emit(out, schema, level, made)


def pack(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 0, open_bins: int = 512, fan_in: int = 8,
         with_ids: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset (and ids, little-endian 32-bit).

    Ids end with ``end_id``; only documents longer than ``capacity`` are cut. Null and empty texts are the end id alone.
    Rows that repeat an id are packed each. An empty table gives no rows. Columns beside id and text are not read.
    A task holds ``open_bins`` bins and one batch. What it leaves open goes, as one bundle a bin, to ``fan_in`` times
    fewer tasks, until one task has the rest; that one reads at most ``fan_in * open_bins`` bundles.
    """
    spark = docs.sparkSession
    ship(spark)
    ddl, schema = _bins_schema(with_ids)

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, end = word_tokenizer(tokenizer).encode, struct.pack("<I", end_id)

        def cut_up() -> Iterator[list[tuple[int, list]]]:
            for batch in batches:
                done = []
                for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                    done += [(p[3], [(*p, 0)]) for p in cut(encode(text.as_py()) + end, doc, capacity, with_ids)]
                yield done

        return _packed(cut_up(), capacity, open_bins, schema, 0, False)

    def again(level: int, last: bool) -> Callable:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            bundles = ([(r["total"], [tuple(p.values()) for p in r["parts"]]) for r in b.to_pylist()] for b in batches)
            return _packed(bundles, capacity, open_bins, schema, level, last)

        return run

    source = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    made = materialise(source.mapInArrow(first, ddl), "bins")
    done, tasks, level = made.where("closed"), source.rdd.getNumPartitions(), 0
    while True:
        tasks, level = -(-tasks // fan_in), level + 1
        rest = made.where("not closed").repartition(tasks).mapInArrow(again(level, tasks == 1), ddl)
        made = materialise(rest, f"bins{level}")
        done = done.unionByName(made.where("closed"))
        if tasks == 1:
            return done.select("sequence_id", F.inline("parts")).select(*[n for n, _ in PART], *["ids"] * with_ids, "sequence_id", "offset")
