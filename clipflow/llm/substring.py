"""Substring deduplication by words: a log-structured index of window fingerprints, batch after batch (see ``spans``).

The index is a folder: packed texts, sorted runs of fingerprints cut into ranges, and a manifest. A new batch's runs are
merge-joined with all historical ones, range by range; what meets and isn't settled by its string's hash is verified word
by word, for which only the historical chunks that are asked are read. Then the batch's own run is added and committed,
and runs of similar size are compacted to one. Files are never changed.
"""

from __future__ import annotations

import hashlib
import math
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from clipflow.llm.common import Manifest, remove, scratch, ship
from clipflow.llm.spans import CHUNK_BYTES, HOT, PLACE, RANGE_BYTES, Kind, _rows, filled, gather, merge_runs, pack_columns, ranges_for, repeats, sorted_runs, unpack_columns, word_tokens

WINDOW = 13
CHUNKS = "chunk long, bytes long, docs binary"


def _same_words(strings: list[bytes], windows: list[int], kind: Kind) -> list[np.ndarray]:
    """Numbers of the windows of each string, by their words themselves."""
    known: dict[bytes, int] = {}
    out = []
    for s, n in zip(strings, windows):
        _, starts, ends = word_tokens(s)
        out.append(np.fromiter((known.setdefault(s[starts[i] : ends[i + kind.width - 1]], len(known)) for i in range(n)), np.int64, n))
    return out


def _finish_all(doc, data: bytes, starts: np.ndarray, ends: np.ndarray, removed: np.ndarray) -> dict:
    kept = data if not removed.any() else b" ".join(data[starts[i] : ends[i]] for i in np.nonzero(~removed)[0])
    return {"doc_id": doc, "n_words": len(starts), "n_removed": int(removed.sum()), "kept": kept, "kept_sha256": hashlib.sha256(kept).hexdigest()}


def _finish(*args) -> dict:
    found = _finish_all(*args)
    del found["kept"]
    return found


def kind_of(width: int) -> Kind:
    return Kind(width, max(1, (width + 1) // 2), word_tokens)


class WindowIndex:
    """The windows of all batches so far, at ``root``, a folder that driver and executors share.

    Ids of a batch count as larger than those of the batches before it, whatever they are.
    """

    def __init__(self, spark: SparkSession, root: str, width: int = WINDOW, fan_in: int = 4, similar: float = 4.0,
                 chunk_bytes: int = CHUNK_BYTES, range_bytes: int = RANGE_BYTES, hot: int = HOT):
        self.spark, self.root, self.width, self.fan_in, self.similar = spark, root.rstrip("/"), width, fan_in, similar
        self.chunk_bytes, self.range_bytes, self.hot = chunk_bytes, range_bytes, hot
        self.manifest = Manifest(spark, self.root)
        ship(spark)

    def state(self) -> tuple[int, dict]:
        version, found = self.manifest.read()
        found = found or {"width": self.width, "batches": 0, "bytes": 0, "texts": [], "runs": []}
        if found["width"] != self.width:
            raise ValueError(f"the index has windows of {found['width']} words")
        return version, found

    def _runs(self, runs: list[dict], ranges: int) -> DataFrame:
        """The rows of some runs, cut into ``ranges``."""

        def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for body in batch.column(0):
                    keys, about, where = unpack_columns(body.as_py(), 3)
                    yield from _rows([(0, r, "run", pack_columns(keys[s], about[s], where[s]), None) for r, s in filled(keys, ranges)]).to_batches()

        if not runs:
            return self.spark.createDataFrame([], PLACE)
        return self.spark.read.schema("body binary").parquet(*[r["path"] for r in runs]).mapInArrow(cut, PLACE)

    def add(self, docs: DataFrame, with_kept: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """Add a batch; what ``dedup_words`` returns for it, against all earlier batches and itself.

        An empty batch adds nothing. If another writer commits meanwhile, CommitConflict is raised and nothing is added.
        """
        version, state = self.state()
        kind, name, hot = kind_of(self.width), uuid.uuid4().hex, self.hot
        texts, place = f"{self.root}/texts/{name}", f"{self.root}/runs/{name}"
        gather(docs, state["batches"] + 1, id_col, text_col, self.chunk_bytes).write.parquet(texts)
        chunks = self.spark.read.schema(CHUNKS).parquet(texts)
        size = int(chunks.agg(F.sum("bytes")).first()[0] or 0)
        ranges = ranges_for(size + state["bytes"], self.range_bytes)

        def merge(key: tuple, rows: pa.Table, old: pa.Table) -> pa.Table:
            if not rows.num_rows:
                return _rows([])
            return merge_runs(rows, [tuple(unpack_columns(b.as_py(), 3)) for b in old.column("body")], True, hot)

        history = self._runs(state["runs"], ranges)
        told = sorted_runs(chunks, kind, ranges).groupBy("range").cogroup(history.groupBy("range")).applyInArrow(merge, PLACE)
        told.write.partitionBy("what").parquet(place)
        told = self.spark.read.schema(PLACE).parquet(place)
        entries = int(told.where("what = 'run'").agg(F.sum("chunk")).first()[0] or 0)
        runs = state["runs"] + ([{"path": f"{place}/what=run", "entries": entries}] if entries else [])
        old = self.spark.read.schema(CHUNKS).parquet(*state["texts"]) if state["texts"] else None
        after = {**state, "batches": state["batches"] + 1, "bytes": state["bytes"] + size, "texts": state["texts"] + [texts], "runs": runs}
        try:
            self.manifest.commit(version, after)
        except Exception:
            for path in (texts, place):
                remove(self.spark, path)
            raise
        self.compact()
        return repeats(chunks, told, kind, _same_words, _finish_all if with_kept else _finish, _schema(with_kept), ranges, old)

    def compact(self) -> int:
        """Merge runs of similar size, ``fan_in`` or more, to one; returns the version. Readers of the last version keep their files."""
        while True:
            version, state = self.state()
            tiers: dict[int, list[dict]] = {}
            for r in state["runs"]:
                tiers.setdefault(int(math.log(max(r["entries"], 1), self.similar)), []).append(r)
            due = next((tiers[k] for k in sorted(tiers) if len(tiers[k]) >= self.fan_in), None)
            if due is None:
                return version
            path, ranges = f"{self.root}/runs/{uuid.uuid4().hex}", ranges_for(state["bytes"], self.range_bytes)

            def merge(rows: pa.Table) -> pa.Table:
                parts = [unpack_columns(b.as_py(), 3) for b in rows.column("body")]
                keys, about, where = (np.concatenate(c) for c in zip(*parts))
                order = np.lexsort((where, keys))
                return _rows([(len(keys), rows.column("range")[0].as_py(), "run", pack_columns(keys[order], about[order], where[order]), None)])

            self._runs(due, ranges).groupBy("range").applyInArrow(merge, PLACE).write.partitionBy("what").parquet(path)
            merged = {"path": f"{path}/what=run", "entries": sum(r["entries"] for r in due)}
            self.manifest.commit(version, {**state, "runs": [r for r in state["runs"] if r not in due] + [merged]})
            self.expire()

    def expire(self, keep: int = 2) -> None:
        """Forget all but the last ``keep`` versions and delete the runs that none of them names."""
        known = self.manifest.versions()
        if len(known) <= keep:
            return
        live = {r["path"] for v in known[-keep:] for r in self.manifest.read(v)[1]["runs"]}
        for v in known[:-keep]:
            for r in self.manifest.read(v)[1]["runs"]:
                if r["path"] not in live:
                    remove(self.spark, r["path"])
            self.manifest.forget(v)


def _schema(with_kept: bool) -> str:
    return "doc_id long, n_words long, n_removed long, " + "kept binary, " * with_kept + "kept_sha256 string"


def dedup_words(docs: DataFrame, width: int = WINDOW, with_kept: bool = True, id_col: str = "doc_id", text_col: str = "text", **sizes: int) -> DataFrame:
    """One row per row: doc_id, n_words, n_removed, kept (bytes of the kept words, joined by spaces), kept_sha256.

    A word goes if a window of ``width`` words over it also starts in a document with a smaller id. Null, empty and
    short texts lose nothing. Rows that repeat an id are one document's: they take nothing from each other. A null id
    counts as larger than all. An empty table gives no rows. Columns beside id and text are not read.
    The table is the first batch of a new index; ``WindowIndex.add`` takes further ones.
    """
    spark = docs.sparkSession
    return WindowIndex(spark, scratch(spark, "window-index"), width, **sizes).add(docs, with_kept, id_col, text_col)
