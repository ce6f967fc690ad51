"""Benchmark decontamination: one Aho-Corasick automaton over the windows of all test items.

Text is reduced to its words (A-Z lowered; runs of ASCII digits, letters and all that lies beyond ASCII), joined by
single spaces. A pattern is a window of consecutive item words between spaces, so a match starts and ends at words.
Each document is scanned once, whole.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import reduce
from itertools import accumulate, chain

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from clipflow.llm.common import materialise, ship, utf8

#: Every byte that parts words becomes a space, A-Z become a-z, the rest stays.
_WORDS = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))

#: Characters of test text in one automaton. Larger test sets are scanned in blocks of that size.
BLOCK_CHARS = 8_000_000


def words_of(text: bytes) -> list[bytes]:
    return text.translate(_WORDS).split()


def windows(words: list[bytes], width: int) -> Iterator[bytes]:
    """Windows of ``width`` words; shorter items are one window, wordless ones none."""
    if words and len(words) < width:
        yield b" ".join(words)
    for i in range(len(words) - width + 1):
        yield b" ".join(words[i : i + width])


_built: dict[tuple, tuple] = {}


def automaton(items: list[tuple[object, bytes]], width: int) -> tuple:
    """(automaton, number of patterns): each pattern has its number of words and the items it comes from.

    Built once a worker, which holds one block's at a time. An item without an id is looked for, but has no name to report.
    """
    key = (width, hashlib.sha256(repr(items).encode()).digest())
    if key not in _built:
        _built.clear()
        owners: dict[bytes, list] = {}
        for item, text in items:
            for w in windows(words_of(text), width):
                own = owners.setdefault(w, [])
                if item is not None and item not in own[-1:]:
                    own.append(item)
        machine = ahocorasick.Automaton() if owners else None
        for w, own in owners.items():
            machine.add_word(f" {w.decode()} ", (w.count(b" ") + 1, own))
        if machine:
            machine.make_automaton()
        _built[key] = (machine, len(owners))
    return _built[key]


def hits(words: list[bytes], machine: ahocorasick.Automaton | None) -> list[tuple[int, int, list]]:
    """(first word, last word, items) of every occurrence."""
    if not words or machine is None:
        return []
    line = b" ".join(words).decode("utf-8", "surrogateescape")
    found = [(end, value) for end, value in machine.iter(f" {line} ")]
    if not found:
        return []
    # a word of the line ends where the next space is; positions in characters
    ends = np.fromiter(accumulate(len(w.decode("utf-8", "surrogateescape")) + 1 for w in words), np.int64, len(words))
    return [(last - n + 1, last, own) for (end, (n, own)) in found for last in [int(np.searchsorted(ends, end))]]


_WORD = re.compile(b"[0-9A-Za-z\x80-\xff]+")


def offsets_of(text: bytes, spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Characters of the original UTF-8 text that words ``first`` to ``last`` span: start and end (exclusive), span by span."""
    places = [m.span() for m in _WORD.finditer(text)]
    out, seen, at = [], 0, 0
    for first, last in spans:  # in order, so each stretch is decoded once
        a, b = places[first][0], places[last][1]
        start = seen + len(text[at:a].decode("utf-8", "replace"))
        seen, at = start + len(text[a:b].decode("utf-8", "replace")), b
        out.append((start, seen))
    return out


def _merged(found: list[tuple[int, int, list]]) -> list[tuple[int, int]]:
    spans: list[list[int]] = []
    for first, last, _ in sorted(found, key=lambda h: h[:2]):
        if spans and first <= spans[-1][1] + 1:
            spans[-1][1] = max(spans[-1][1], last)
        else:
            spans.append([first, last])
    return [(a, b) for a, b in spans]


def _blocks(bench: DataFrame, id_col: str, text_col: str) -> Iterator[list[tuple[object, bytes]]]:
    """The test set, block after block: the driver, a broadcast and a worker's automaton hold ``BLOCK_CHARS`` and an item at most."""
    block: list[tuple[object, bytes]] = []
    size = 0
    for item, text in bench.select(F.col(id_col), utf8(text_col)).distinct().orderBy(id_col).toLocalIterator():
        if block and size + len(text) > BLOCK_CHARS:
            yield block
            block, size = [], 0
        block.append((item, bytes(text)))
        size += len(text)
    yield block


SPANS = "array<struct<first:int,last:int>>"


def _scan(rows: DataFrame, block: list[tuple[object, bytes]], width: int, only_hits: bool = False) -> DataFrame:
    """rows (key, text as bytes) -> key, n_words, n_hit, items, spans, by one block's automaton."""
    sent = rows.sparkSession.sparkContext.broadcast(block)
    schema = f"key long, n_words long, n_hit long, items array<string>, spans {SPANS}"
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.string()), pa.list_(pa.struct([("first", pa.int32()), ("last", pa.int32())]))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = automaton(sent.value, width)[0]
        for batch in batches:
            out: tuple[list, ...] = ([], [], [], [], [])
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                words = words_of(text.as_py())
                found = hits(words, machine)
                if only_hits and not found:
                    continue
                spans = _merged(found)
                for column, value in zip(out, (key, len(words), sum(b - a + 1 for a, b in spans), sorted({str(i) for _, _, own in found for i in own}), [{"first": a, "last": b} for a, b in spans])):
                    column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds)], names=["key", "n_words", "n_hit", "items", "spans"])

    return rows.mapInArrow(run, schema)


_UNITE = f"""aggregate(array_sort(spans), cast(array() AS {SPANS}), (s, x) -> CASE
    WHEN size(s) > 0 AND x.first <= element_at(s, -1).last + 1
    THEN concat(slice(s, 1, size(s) - 1), array(named_struct('first', element_at(s, -1).first, 'last', greatest(element_at(s, -1).last, x.last))))
    ELSE concat(s, array(x)) END)"""


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The rows with a number of their own, written: ids may repeat or be null."""
    rows = docs.select(F.monotonically_increasing_id().alias("key"), F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text"))
    return materialise(rows, "numbered")


def _scan_all(rows: DataFrame, first: list, others: Iterator[list], width: int) -> DataFrame:
    """_scan by several blocks, one after the other; their hits are united by row."""
    parts = [materialise(_scan(rows, block, width, True), "hits") for block in (first, *others)]
    every = reduce(DataFrame.unionByName, parts).groupBy("key").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"), F.flatten(F.collect_list("spans")).alias("spans"))
    every = every.withColumn("spans", F.expr(_UNITE)).withColumn("n_hit", F.expr("aggregate(spans, 0L, (n, x) -> n + x.last - x.first + 1)"))
    counted = _scan(rows, [], width).select("key", "n_words")
    return counted.join(every.hint("merge"), "key", "left").select(
        "key", "n_words", F.coalesce("n_hit", F.lit(0)).alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"), F.coalesce("spans", F.array().cast(SPANS)).alias("spans"))


def scan(docs: DataFrame, bench: DataFrame, width: int = 10, id_col: str = "doc_id", text_col: str = "text",
         item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """One row per document: id, n_words, n_hit, items (sorted array of strings), spans (word ranges, merged).

    Null or empty texts have no words and no hits; an empty test set hits nothing; an empty table gives no rows. Rows
    that repeat an id are judged apart. Items with a null text have no window; those with a null id hit, but aren't
    named; rows that repeat an item are one. Columns beside id and text are not read.
    """
    ship(docs.sparkSession)
    blocks = _blocks(bench, item_col, item_text)
    first, second = next(blocks), next(blocks, None)
    if second is None:
        rows = docs.select(F.col(id_col).cast("long").alias("key"), utf8(text_col).alias("text"))
        return _scan(rows, first, width).withColumnRenamed("key", "doc_id")
    rows = _keyed(docs, id_col, text_col)
    found = _scan_all(rows.select("key", "text"), first, chain([second], blocks), width)
    return rows.select("key", "doc_id").join(found.hint("merge"), "key").drop("key")


def located(docs: DataFrame, bench: DataFrame, width: int = 10, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Hit passages with offsets in the original text: doc_id, start, end (exclusive, in characters), passage.

    One row a passage, overlapping ones being one; null and empty texts have none. Rows that repeat an id are told
    apart by a number of their own; items are treated as in ``scan``. An empty table gives no rows.
    """
    ship(docs.sparkSession)
    rows = _keyed(docs, id_col, text_col)
    blocks = _blocks(bench, "item_id", "text")
    found = _scan_all(rows.select("key", "text"), next(blocks), blocks, width).where("n_hit > 0").select("key", "spans")
    kinds = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("end", pa.int64()), ("passage", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                whole = r["text"].decode("utf-8", "replace")
                out += [{"doc_id": r["doc_id"], "start": a, "end": b, "passage": whole[a:b]} for a, b in offsets_of(r["text"], [(s["first"], s["last"]) for s in r["spans"]])]
            yield pa.RecordBatch.from_pylist(out, schema=kinds)

    return rows.join(found.hint("merge"), "key").select("doc_id", "text", "spans").mapInArrow(run, "doc_id long, start long, end long, passage string")


def clean(docs: DataFrame, bench: DataFrame, width: int = 10, text_col: str = "text") -> DataFrame:
    """The documents without a hit, with all their columns. Rows are judged where they stand; nothing is shuffled.

    Null, empty and wordless texts stay, as do all rows if the test set is empty. Rows that repeat an id or all of a
    row are judged each; an empty table stays empty; other columns may have any names. Items are treated as in ``scan``.
    """
    spark = docs.sparkSession
    ship(spark)

    def passed(rows: DataFrame, block: list[tuple[object, bytes]]) -> DataFrame:
        sent = spark.sparkContext.broadcast(block)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            machine = automaton(sent.value, width)[0]
            for batch in batches:
                texts = batch.column(batch.schema.get_field_index(text_col))
                yield batch.filter(pa.array([not hits(words_of((t.as_py() or "").encode()), machine) for t in texts], pa.bool_()))

        return rows.mapInArrow(run, rows.schema)

    blocks = _blocks(bench, "item_id", "text")
    docs = passed(docs, next(blocks))
    for block in blocks:  # a block's automaton is gone before the next one's is built
        docs = passed(materialise(docs, "passed"), block)
    return docs
