"""SimHash fingerprints and all their pairs within a Hamming radius, through vantage-point trees.

A tree's node parts fingerprints by their distance to one of them, and a search leaves out the side that the triangle
bound excludes. Over all 64 bits random fingerprints are 32 +- 4 apart, so a radius of 4 excludes little; the tree
therefore measures by bands of 16 bits, in sets (``cases``) of which every sought pair keeps one: two bands within a bit
each for radius 4. Its upper levels are the shards: a fingerprint is stored in the one where it falls and asks all that
its search would enter. In a shard the tree goes on down to small leaves, whose pairs are compared in all bits.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from clipflow.llm.common import lower_ascii, materialise, mix64, ship, utf8
from clipflow.llm.components import components

#: Stored fingerprints that a shard is meant to have; the tree's depth follows from their number.
SHARD_ROWS = 50_000
BAND_BITS = 16
_LANES = np.uint64(0x0101010101010101)


def _bit_counts(h: np.ndarray) -> np.ndarray:
    """How many of the values have each of the 64 bits: eight sums of byte lanes, 255 values at a time."""
    h = np.concatenate([h, np.zeros(-len(h) % 255, np.uint64)]).reshape(-1, 255)
    lanes = [((h >> np.uint64(s)) & _LANES).sum(axis=1, dtype=np.uint64).view(np.uint8).reshape(-1, 8).sum(axis=0, dtype=np.int64) for s in range(8)]
    return np.stack(lanes, axis=1).reshape(-1)


def fingerprint(text: bytes, width: int, words: int = 1) -> tuple[np.ndarray, int]:
    """64 * ``words`` bits as unsigned longs, and the number of shingles. A bit is 1 if over half of the shingles' hashes have it.

    The first 64 are XXH64 (seed 42) of the shingle, further ones are scrambled from it. No words: zero, and no shingle.
    """
    seen = lower_ascii(text).split()
    n = len(seen)
    if not n:
        return np.zeros(words, np.uint64), 0
    line, digest = b" ".join(seen), xxhash.xxh64_intdigest
    counts, total = np.zeros((words, 64), np.int64), max(1, n - width + 1)
    ends = list(accumulate(map(len, seen), lambda a, b: a + b + 1))
    starts = [0, *(e + 1 for e in ends)]
    tails = ends[width - 1 :] or ends[-1:]
    for i in range(0, total, 1 << 16):
        j = min(i + (1 << 16), total)
        h = np.fromiter((digest(line[a:b], 42) for a, b in zip(starts[i:j], tails[i:j])), np.uint64, j - i)
        for w in range(words):
            counts[w] += _bit_counts(h)
            h = mix64(h + np.uint64(0x9E3779B97F4A7C15)) if w + 1 < words else h
    return np.packbits(2 * counts > total, axis=1, bitorder="little").view(np.uint64)[:, 0], total


def _names(words: int) -> list[str]:
    return [f"w{i}" for i in range(words)]


def fingerprints(docs: DataFrame, width: int = 4, words: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_key (a hash of the text), size (its shingles), w0, w1, ... (the fingerprint's bits as signed longs).

    Null and empty texts have fingerprint zero and size zero.
    """
    ship(docs.sparkSession)
    names = ["doc_id", "text_key", "size", *_names(words)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [fingerprint(t.as_py(), width, words) for t in batch.column(2)]
            fp = np.array([f for f, _ in found], np.uint64).reshape(-1, words).view(np.int64)
            size = pa.array([n for _, n in found], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), size, *(pa.array(np.ascontiguousarray(c)) for c in fp.T)], names=names)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_key(text_col).alias("text_key"), utf8(text_col).alias("text"))
    return rows.mapInArrow(run, ", ".join(f"{n} long" for n in names))


def text_key(text_col: str) -> Column:
    """What tells rows of one id apart."""
    return F.xxhash64(F.coalesce(F.col(text_col), F.lit("")))


LEAF, WIDE_LEAF = 64, 512  # stored fingerprints that are compared without a further split, by bands and by all bits


@dataclass(frozen=True)
class Metric:
    """Hamming distance over one band of one word, and how far a sought pair may be apart in it."""

    word: int
    band: int
    slack: int

    def values(self, columns: list[np.ndarray]) -> np.ndarray:
        return ((columns[self.word] >> np.uint64(BAND_BITS * self.band)) & np.uint64((1 << BAND_BITS) - 1)).astype(np.uint16)


def shares(radius: int, parts: int) -> list[int]:
    """Bounds for parts of a fingerprint: two within ``radius`` bits are within its bound in one part at least.

    Each bound plus one sums to radius + 1, so that exceeding all of them exceeds the radius; -1 asks nothing of a part.
    """
    each, more = divmod(radius + 1, parts)
    return [each + (i < more) - 1 for i in range(parts)]


def cases(radius: int, words: int) -> list[tuple[Metric, ...]]:
    """Sets of bounds such that any two fingerprints within ``radius`` bits keep all bounds of one set.

    More than one bit in a band costs two, so at most radius // 2 bands have that. Where two others are left, the
    sets are pairs of bands within one bit each; else each is a single band within its share.
    """
    per = 64 // BAND_BITS
    bands = [(w, b) for w in range(words) for b in range(per)]
    if len(bands) - radius // 2 >= 2:
        return [(Metric(*x, 1), Metric(*y, 1)) for x, y in combinations(bands, 2)]
    return [(Metric(w, b, s),) for w, bound in enumerate(shares(radius, words)) for b, s in enumerate(shares(bound, per)) if s >= 0]


class BandTree:
    """The upper levels of a vantage-point tree by one band, over all values that it can have, whatever the data.

    ``home[v]`` is the leaf where a fingerprint of value v is stored; the leaves that its search enters are
    ``leaves[first[v] : first[v + 1]]``, as a branch is left out only where the triangle bound excludes it.
    """

    def __init__(self, depth: int, slack: int):
        values = np.arange(1 << BAND_BITS, dtype=np.uint64)
        self.home = np.zeros(len(values), np.int64)
        enters, entered = values, np.zeros(len(values), np.int64)
        for level in range(depth):
            home, out_v, out_n = np.zeros_like(self.home), [], []
            for node in range(1 << level):
                own = self.home == node
                asks = enters[entered == node]
                if not own.any():
                    continue
                vantage = values[own][(((1 << level) + node) * 2654435761 + 97) % own.sum()]
                d = np.bitwise_count(values[own] ^ vantage).astype(int)
                cut = int(np.median(d))
                cut -= int(cut == d.max())
                home[own] = 2 * node + (d > cut)
                e = np.bitwise_count(asks ^ vantage).astype(int)
                for side, some in ((0, asks[e <= cut + slack]), (1, asks[e > cut - slack])):
                    out_v.append(some)
                    out_n.append(np.full(len(some), 2 * node + side))
            self.home, enters, entered = home, np.concatenate(out_v), np.concatenate(out_n)
        order = np.argsort(enters, kind="stable")
        self.leaves = entered[order]
        self.first = np.searchsorted(enters[order], np.arange((1 << BAND_BITS) + 1))


_trees: dict[tuple, BandTree] = {}


def band_tree(depth: int, slack: int) -> BandTree:
    key = (depth, slack)
    if key not in _trees:
        _trees[key] = BandTree(*key)
    return _trees[key]


def _union(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Join the sets of a[i] and b[i] for all i; parents stay fully compressed and smallest."""
    while True:
        ra, rb = parent[a], parent[b]
        differ = ra != rb
        if not differ.any():
            return
        a, b, ra, rb = a[differ], b[differ], ra[differ], rb[differ]
        np.minimum.at(parent, np.maximum(ra, rb), np.minimum(ra, rb))
        while (parent[parent] != parent).any():
            parent[:] = parent[parent]


def _spread(columns: list[np.ndarray], rows: np.ndarray, vantage: int) -> np.ndarray:
    return sum(np.bitwise_count(c[rows] ^ c[vantage]).astype(np.int64) for c in columns)


def _search(columns: list[np.ndarray], sizes: np.ndarray, metrics: tuple[Metric, ...], stored: np.ndarray, asking: np.ndarray, radius: int, ratio: float, parent: np.ndarray) -> None:
    """Union all pairs (stored, asking) within ``radius`` bits that keep the metrics' bounds and whose sizes fit.

    A vantage-point tree over the stored fingerprints, built as it is searched by many at once. Its nodes part them by the
    distance to one of them, by each metric in turn (the logarithm of the size is one, where sizes must fit) and by all
    bits where none of these tells them apart; who asks follows to a side where the triangle bound leaves it a partner.
    It ends at ``LEAF`` fingerprints, or at equal ones.
    """
    bands = [(m.values(columns), m.slack) for m in metrics]
    logs, reach = np.log(np.maximum(sizes, 1)), -math.log(ratio) + 1e-9 if ratio else 0.0
    ways = len(bands) + bool(ratio)
    leaf = LEAF if bands else WIDE_LEAF

    def apart(way: int, rows: np.ndarray, vantage: int) -> tuple[np.ndarray, float]:
        if way < len(bands):
            values, slack = bands[way]
            return np.bitwise_count(values[rows] ^ values[vantage]).astype(np.int64), slack
        return (np.abs(logs[rows] - logs[vantage]), reach) if way < ways else (_spread(columns, rows, vantage), radius)

    work = [(stored, asking, 0, 1)]
    while work:
        s, q, level, seed = work.pop()
        if not len(s) or not len(q):
            continue
        vantage, split = int(s[(seed * 2654435761 + 97) % len(s)]), False
        if len(s) > leaf:
            for way in [(level + k) % ways for k in range(ways)] + [ways]:
                d, slack = apart(way, s, vantage)
                if split := bool(d.min() < d.max()):
                    break
        if split:
            e, cut = apart(way, q, vantage)[0], np.median(d)
            near = d <= cut if cut < d.max() else d < cut
            for side, some in enumerate((near, ~near)):
                meets = (e >= d[some].min() - slack) & (e <= d[some].max() + slack)
                work.append((s[some], q[meets], level + 1, (2 * seed + side) % 1_000_003))
            continue
        step = max(1, (1 << 16) // len(s))
        for i in range(0, len(q), step):
            part = q[i : i + step]
            if bands:
                close = np.bitwise_count(bands[0][0][part][:, None] ^ bands[0][0][s][None, :]) <= bands[0][1]
            else:  # half of the bits are enough to leave out nearly all
                close = sum(np.bitwise_count(c[part][:, None] ^ c[s][None, :]).astype(np.uint16) for c in columns[: max(1, len(columns) // 2)]) <= radius
            x, y = np.nonzero(close)
            x, y = part[x], s[y]
            for values, slack in bands[1:]:
                close = np.bitwise_count(values[x] ^ values[y]) <= slack
                x, y = x[close], y[close]
            new = parent[x] != parent[y]
            x, y = x[new], y[new]
            near = _spread_pairs(columns, x, y) <= radius
            near &= np.minimum(sizes[x], sizes[y]) >= ratio * np.maximum(sizes[x], sizes[y])
            _union(parent, x[near], y[near])


def _spread_pairs(columns: list[np.ndarray], x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return sum(np.bitwise_count(c[x] ^ c[y]).astype(np.int64) for c in columns)


def _class(size: np.ndarray, ratio: float) -> np.ndarray:
    """Size classes: sizes of at least that ratio are in one class or in neighbouring ones."""
    return np.floor(np.log(np.maximum(size, 1)) / -np.log(ratio) + 1e-9).astype(np.int64) if ratio else np.zeros(len(size), np.int64)


def linked(prints: DataFrame, radius: int = 4, words: int = 1, ratio: float = 0.0, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """Distinct fingerprints (node, size, w0, ...) -> links (a, b) between nodes.

    They join exactly the pairs within ``radius`` bits whose sizes have at least that ``ratio``, directly or in steps. A
    shard is a size class or, where that has more than ``shard_rows``, a leaf of the upper levels of a tree for each of
    the ``cases``: a fingerprint is stored in the one where it falls and asks all that its search enters. A shard
    returns a star for each set that it has joined, not all pairs; every pair meets where one of it is stored.
    """
    ship(prints.sparkSession)
    names, sets = _names(words), cases(radius, words)
    # at most some 60 size classes, as they grow by a factor
    held = {r["k"]: r["n"] for r in prints.groupBy(_class_column(ratio).alias("k")).agg(F.count(F.lit(1)).alias("n")).collect()}
    # without size classes two levels at least: what is dealt then grows with the rows, not by a leap
    depths = {k: max(0 if ratio else 2, math.ceil(math.log2(n / shard_rows))) for k, n in held.items()}

    def leaves(columns: list[np.ndarray], case: tuple[Metric, ...], depth: int) -> tuple[np.ndarray, ...]:
        """(row, leaf, is it the row's own leaf) for all leaves that each row enters; its bands share the depth."""
        who, leaf, own = np.arange(len(columns[0])), np.zeros(len(columns[0]), np.int64), np.ones(len(columns[0]), bool)
        for i, m in enumerate(case):
            part = min(BAND_BITS, (depth + i) // len(case))
            tree, v = band_tree(part, m.slack), m.values(columns).astype(np.int64)[who]
            n = tree.first[v + 1] - tree.first[v]
            at = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(tree.first[v], n)
            entered = tree.leaves[at]
            own = np.repeat(own, n) & (entered == np.repeat(tree.home[v], n))
            who, leaf = np.repeat(who, n), (np.repeat(leaf, n) << part) + entered
        return who, leaf, own

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            signed = [c.to_numpy() for c in batch.columns]
            kind = _class(signed[1], ratio)
            for k in np.unique(kind).tolist():
                for target in (k, k + 1) if ratio else (k,):
                    rows = np.nonzero(kind == k)[0]
                    mine = [c[rows] for c in signed]
                    columns = [c.view(np.uint64) for c in mine[2:]]
                    depth = depths.get(target, 0 if ratio else 2)
                    for n, case in enumerate(sets) if depth else [(-1, ())]:
                        who, leaf, own = leaves(columns, case, depth)
                        own &= target == k
                        for i in range(0, len(who), 1 << 17):
                            j = slice(i, i + (1 << 17))
                            shard = (target << 48) | ((n + 1) << 36) | leaf[j]
                            yield pa.RecordBatch.from_arrays([pa.array(shard), pa.array(own[j]), *(pa.array(c[who[j]]) for c in mine)], names=["shard", "stored", "node", "size", *names])

    def search(key: tuple, rows: pa.Table) -> pa.Table:
        columns = [rows.column(n).to_numpy().view(np.uint64) for n in names]
        case = ((key[0].as_py() >> 36) & 0xFFF) - 1
        stored, everyone = np.nonzero(rows.column("stored").to_numpy(zero_copy_only=False))[0], np.arange(rows.num_rows)
        parent = everyone.copy()
        # a size class that is one shard needs no bands: its tree is by size and by all bits
        _search(columns, rows.column("size").to_numpy(), sets[case] if case >= 0 else (), stored, everyone, radius, ratio, parent)
        moved = np.nonzero(parent != everyone)[0]
        node = rows.column("node").to_numpy()
        return pa.table({"a": node[moved], "b": node[parent[moved]]})

    longs = ", ".join(f"{n} long" for n in ["node", "size", *names])
    dealt = prints.select("node", "size", *names).mapInArrow(deal, f"shard long, stored boolean, {longs}")
    return dealt.groupBy("shard").applyInArrow(search, "a long, b long")


def _class_column(ratio: float) -> Column:
    return F.floor(F.log(F.greatest("size", F.lit(1))) / -math.log(ratio) + 1e-9) if ratio else F.lit(0).cast("long")


def _classed(marked: DataFrame, radius: int, words: int, ratio: float = 0.0) -> DataFrame:
    """Rows (doc_id, text_key, size, w0, ...) -> the same with ``first``, the smallest (doc_id, text_key) that links reach.

    What is shared by many rows is summed first. Rows without an id name no group.
    """
    kind = ["size"] * bool(ratio) + _names(words)
    own = F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "text_key"))
    prints = marked.groupBy(*kind).agg(F.min(own).alias("least")).withColumn("node", F.monotonically_increasing_id())
    prints = materialise(prints if ratio else prints.withColumn("size", F.lit(1).cast("long")), "prints")
    classes = components(linked(prints, radius, words, ratio))
    named = prints.join(classes.hint("merge"), "node", "left").withColumn("root", F.coalesce("root", "node"))
    best = named.groupBy("root").agg(F.min("least").alias("first"))
    of_print = named.join(best.hint("merge"), "root").select(*kind, "first")
    return marked.join(of_print.hint("merge"), kind)


def near_groups(docs: DataFrame, width: int = 4, radius: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id (smallest id that links reach).

    Texts with fewer words than a shingle are one shingle; null, empty and wordless ones have fingerprint zero and link
    like any other. Rows that repeat an id are returned each; null ids are members but never name a group. An empty
    table gives no rows. Other columns are not read.
    """
    marked = materialise(fingerprints(docs, width, 1, id_col, text_col), "fingerprints")
    return _classed(marked, radius, 1).select("doc_id", F.lpad(F.lower(F.hex("w0")), 16, "0").alias("fingerprint"), F.col("first.doc_id").alias("component_id"))


def keep_one(docs: DataFrame, width: int = 5, similarity: float = 0.8, words: int = 4) -> DataFrame:
    """The rows of ``docs`` that stay: of each group of near copies, that with the smallest id; all columns are kept.

    Two rows are near copies if their fingerprints agree in at least ``similarity`` of the bits and the smaller has at least
    that share of the larger's shingles, as texts must that share so many. 256 bits tell that from chance without a
    false link, and every such pair is found. Wordless rows are no copies of each other and all stay, as do rows without
    an id. Of rows that repeat an id, those of other texts are rows of their own; equal rows stay or go together. An
    empty table stays empty. Input columns may have any names.
    """
    radius = int(64 * words * (1 - similarity))
    marked = materialise(fingerprints(docs, width, words), "fingerprints")
    seen = _classed(marked.where("size > 0"), radius, words, similarity)
    gone = seen.where("doc_id IS NOT NULL AND (doc_id <> first.doc_id OR text_key <> first.text_key)").select(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key")).distinct()
    same = (docs["doc_id"] == gone["_id"]) & (text_key("text") == gone["_key"])
    return docs.join(gone.hint("merge"), same, "left_anti")
