"""Exact, near, substring and suffix duplicates against brute force."""

import hashlib
import re

import numpy as np
import pytest
import xxhash
from llm_texts import prose

from clipflow.llm import exact, simhash, substring, suffix
from clipflow.llm.components import components

SCHEMA = "doc_id long, text string"


def frame(spark, rows, extra=False):
    df = spark.createDataFrame(rows, SCHEMA)
    if extra:  # names that the operators use inside
        for n in ("text_sha256", "keep_id", "chunk", "fp", "node", "kept"):
            from pyspark.sql import functions as F

            df = df.withColumn(n, F.lit("x"))
    return df


def by_id(df):
    return {r.doc_id: r for r in df.collect()}


def test_exact_matches_brute_force(spark, corpus):
    norm = {d: re.sub("[\x20\x09-\x0d]+", " ", t or "") for d, t in corpus}
    index = exact.DigestIndex(spark, buckets=4)
    got = by_id(exact.exact_dedup(frame(spark, corpus, True), index))
    assert len(got) == len(corpus)
    for d, t in norm.items():
        same = [e for e, u in norm.items() if u == t]
        r = got[d]
        assert (r.keep_id, r.group_size, r.kept) == (min(same), len(same), d == min(same))
        assert r.text_sha256 == hashlib.sha256(t.encode()).hexdigest()
    # the index persists: a later batch loses what an earlier one had, and adds the rest
    later = by_id(exact.exact_dedup(frame(spark, [(100, corpus[0][1]), (101, "never seen"), (102, "never seen")]), index))
    assert (later[100].keep_id, later[100].kept) == (1, False)
    assert (later[101].kept, later[102].keep_id) == (True, 101)
    assert spark.table(index.name).count() == len(set(norm.values())) + 1
    index.drop()


def test_exact_keeps_columns_and_one_of_repeated_rows(spark):
    rows = [(1, "a b"), (1, "a b"), (2, "a  b"), (None, "c"), (3, "c")]
    kept = exact.keep_first(frame(spark, rows, True), exact.DigestIndex(spark, buckets=2))
    assert kept.columns[:2] == ["doc_id", "text"] and "keep_id" in kept.columns
    assert sorted((r.doc_id, r.text) for r in kept.collect()) == [(1, "a b"), (3, "c")]
    assert exact.exact_dedup(frame(spark, []), exact.DigestIndex(spark, buckets=2)).count() == 0


def slow_print(text, width):
    words = (text or "").encode().translate(bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz"))
    words = [w for w in re.split(b"[\x20\x09-\x0d]+", words) if w]
    if not words:
        return 0
    hs = [xxhash.xxh64_intdigest(b" ".join(words[i : i + width]), 42) for i in range(max(1, len(words) - width + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def slow_components(prints, radius):
    least = {d: d for d in prints}
    changed = True
    while changed:
        changed = False
        for a in prints:
            for b in prints:
                if (prints[a] ^ prints[b]).bit_count() <= radius and least[b] < least[a]:
                    least[a] = least[b]
                    changed = True
    return least


def test_simhash_matches_brute_force(spark, corpus):
    corpus = [r for r in corpus if len(r[1] or "") < 20_000]
    prints = {d: slow_print(t, 4) for d, t in corpus}
    got = by_id(simhash.near_groups(frame(spark, corpus, True)))
    assert {d: int(r.fingerprint, 16) for d, r in got.items()} == prints
    assert {d: r.component_id for d, r in got.items()} == slow_components(prints, 4)
    assert simhash.near_groups(frame(spark, [])).count() == 0


@pytest.mark.parametrize("shard_rows", [30, 50_000])
def test_vantage_point_search_finds_every_pair(spark, shard_rows):
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 63, 300, dtype=np.int64)
    base[200:] &= np.int64(0xFFFF)  # many that agree in three bands
    near = base[:200].copy()
    for _ in range(4):
        near ^= np.int64(1) << rng.integers(0, 63, 200)
    far = base[:50] ^ np.int64(0b11111)
    prints = np.unique(np.concatenate([base, near, far, [0, 1, 3, 15, 31]]))
    df = spark.createDataFrame([(int(x), 1, int(x)) for x in prints], "node long, size long, w0 long")
    roots = {r.node: r.root for r in components(simhash.linked(df, 4, shard_rows=shard_rows)).collect()}
    d = np.bitwise_count(prints.view(np.uint64)[:, None] ^ prints.view(np.uint64)[None, :])
    least = np.arange(len(prints))
    for _ in range(len(prints)):
        new = np.where(d <= 4, least[None, :], len(prints)).min(axis=1)
        if (new == least).all():
            break
        least = new
    expected = {int(p): int(prints[least[i]]) for i, p in enumerate(prints)}
    assert {int(p): roots.get(int(p), int(p)) for p in prints} == expected


def test_components_of_a_long_path_and_a_hub(spark):
    links = [(i, i + 1) for i in range(1, 60)] + [(100, 100 + i) for i in range(1, 40)] + [(7, 7), (None, 3)]
    got = {r.node: r.root for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {**{i: 1 for i in range(1, 61)}, **{i: 100 for i in range(100, 140)}}


def test_near_stage_keeps_one_of_each_group(spark, corpus):
    words = corpus[20][1].split()
    rows = [(1, " ".join(words)), (2, " ".join([*words[:-1], "other"])), (3, corpus[10][1]), (4, None), (5, ""), (None, corpus[12][1])]
    kept = simhash.keep_one(frame(spark, rows, True))
    assert sorted(str(r.doc_id) for r in kept.collect()) == ["1", "3", "4", "5", "None"]


def test_near_stage_finds_every_pair_up_to_its_radius(spark, monkeypatch):
    """Of pairs at 44 to 51 differing bits of 256, spread evenly over the bands, one stays; at 52 both do."""
    rng = np.random.default_rng(8)
    distances = [*range(44, 53)] * 40
    a = rng.integers(0, 2, (len(distances), 256), dtype=np.uint8)
    b = a.copy()
    for row, n in zip(b, distances):
        spread = np.concatenate([16 * np.arange(16) + p for p in rng.permuted(np.tile(np.arange(16), (16, 1)), axis=1).T[:4]])  # at most four in a band
        row[spread[:n]] ^= 1
    bits = np.concatenate([a, b])
    prints = np.packbits(bits, axis=1, bitorder="little").view(np.int64)
    df = spark.createDataFrame([(i, "x", 9, *map(int, p)) for i, p in enumerate(prints)], "doc_id long, text string, size long, w0 long, w1 long, w2 long, w3 long")
    df = df.withColumn("text_key", simhash.text_key("text"))
    monkeypatch.setattr(simhash, "fingerprints", lambda *_: df)
    kept = {r.doc_id for r in simhash.keep_one(df.select("doc_id", "text")).collect()}
    n = len(distances)
    assert kept == {*range(n), *(n + i for i, d in enumerate(distances) if d > 51)}
    far = (bits[:, None, :] != bits[None, :, :]).sum(axis=2)
    assert sorted(zip(*(x.tolist() for x in np.nonzero(np.triu(far <= 51, 1))))) == [(i, n + i) for i, d in enumerate(distances) if d <= 51]


def test_near_stage_and_repeated_ids(spark, corpus):
    """An id's other texts stay when one of them is a copy; sizes beyond the ratio are no copies."""
    words = corpus[20][1].split()
    rows = [(1, " ".join(words)), (2, " ".join([*words[:-1], "other"])), (2, corpus[10][1]), (3, " ".join(words * 2)), (2, " ".join([*words[:-1], "more"]))]
    kept = simhash.keep_one(frame(spark, rows, True))
    assert sorted((r.doc_id, r.text) for r in kept.collect()) == sorted([rows[0], rows[2], rows[3]])


def test_cases_keep_every_pair():
    rng = np.random.default_rng(4)
    for radius, words in ((4, 1), (3, 1), (7, 1), (12, 1), (51, 4), (20, 2)):
        sets = simhash.cases(radius, words)
        for _ in range(300):
            flips = rng.choice(64 * words, radius, replace=False)
            bits = np.zeros((words, 64), int)
            bits[flips // 64, flips % 64] = 1
            assert any(all(bits[m.word, 16 * m.band : 16 * m.band + 16].sum() <= m.slack for m in case) for case in sets)


def test_shares_bound_some_part():
    for radius, parts in ((51, 16), (51, 4), (12, 4), (4, 4), (2, 4), (0, 4)):
        assert sum(s + 1 for s in simhash.shares(radius, parts)) == radius + 1


def slow_spans(tokens, width):
    """tokens: (id, tuple or bytes) by id -> removed flags."""
    first = {}
    for d, t in tokens:
        for i in range(len(t) - width + 1):
            first.setdefault(t[i : i + width], d)
    for d, t in tokens:
        gone = bytearray(len(t))
        for i in range(len(t) - width + 1):
            if first[t[i : i + width]] < d:
                gone[i : i + width] = b"\1" * width
        yield d, t, gone


@pytest.mark.parametrize("sizes", [{}, {"chunk_bytes": 1 << 58, "range_bytes": 1 << 58}])
def test_substring_matches_brute_force(spark, corpus, sizes):
    got = by_id(substring.dedup_words(frame(spark, corpus, True), **sizes))
    removed = 0
    for d, t, gone in slow_spans([(d, tuple((t or "").encode().split())) for d, t in sorted(corpus)], 13):
        kept = b" ".join(w for w, g in zip(t, gone) if not g)
        r = got[d]
        assert (r.n_words, r.n_removed, bytes(r.kept)) == (len(t), sum(gone), kept), d
        assert r.kept_sha256 == hashlib.sha256(kept).hexdigest()
        removed += sum(gone)
    assert removed > 20_000
    assert substring.dedup_words(frame(spark, [])).count() == 0


def test_suffix_matches_brute_force(spark, corpus):
    got = by_id(suffix.dedup_bytes(frame(spark, corpus, True)))
    for d, t, gone in slow_spans([(d, (t or "").encode()) for d, t in sorted(corpus)], 50):
        kept = bytes(b for b, g in zip(t, gone) if not g)
        spans = sum(1 for i in range(len(gone)) if gone[i] and (i == 0 or not gone[i - 1]))
        r = got[d]
        assert (r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) == (len(t), sum(gone), spans, kept), d
    assert suffix.dedup_bytes(frame(spark, [])).count() == 0


@pytest.mark.parametrize("period", [8, 16, 32, 64])
def test_difference_cover(period):
    cover = suffix.difference_cover(period)
    table = suffix.shifts(period, cover)
    assert (table >= 0).all() and len(cover) < 3 * period**0.5 + 2


def test_suffixes_are_sorted_like_the_bytes():
    rng = np.random.default_rng(5)
    unit = bytes(rng.integers(97, 99, 40, dtype=np.uint8))
    text = b"\0".join([unit * 6, bytes(rng.integers(97, 101, 500, dtype=np.uint8)), unit * 5 + b"c", b"a" * 200])
    at = np.nonzero(np.frombuffer(text, np.uint8) != 0)[0]
    ordered = suffix.sort_suffixes(text, at, 300)
    line = [text[i:].split(b"\0")[0] for i in ordered]
    assert line == sorted(line)
    cls = suffix.prefix_classes(text, ordered, 50)
    padded = text + b"\0" * 60
    assert len(set(cls)) == len({padded[i : i + 50] for i in at})


def check_words(got, rows):
    for d, t, gone in slow_spans([(d, tuple((t or "").encode().split())) for d, t in rows], 13):
        kept = b" ".join(w for w, g in zip(t, gone) if not g)
        assert (got[d].n_words, got[d].n_removed, bytes(got[d].kept)) == (len(t), sum(gone), kept), d


def test_batches_of_the_window_index_equal_one(spark, corpus, tmp_path):
    """Three batches by id, each through an index opened anew, and compaction in between."""
    rows, got = sorted(corpus), {}
    root = f"file://{tmp_path}/index"
    for part in (rows[:12], rows[12:30], [], rows[30:]):
        index = substring.WindowIndex(spark, root, fan_in=2, similar=100.0, chunk_bytes=4_000, range_bytes=20_000)
        got |= by_id(index.add(frame(spark, part)))
    check_words(got, rows)
    _, state = index.state()
    assert state["batches"] == 4 and len(state["runs"]) < 3
    late = by_id(index.add(frame(spark, [(1, rows[3][1]), (2, "never seen")])))  # what came earlier wins, whatever the id
    assert late[1].n_removed == late[1].n_words > 0 and late[2].n_removed == 0


def boilerplate(n):
    shared = "all of these words are in nearly every document of the table and go on".split()
    return [(i, " ".join([*prose(i, 20).split(), *shared, *prose(1000 + i, 20).split()])) for i in range(n)]


@pytest.mark.parametrize("hot", [1, 1 << 15])
def test_a_gram_of_most_documents(spark, hot):
    """A passage that most documents share, with other words on either side: its grams have as many strings as documents."""
    rows, sizes = boilerplate(60), {"chunk_bytes": 2_000, "range_bytes": 1 << 30, "hot": hot}
    check_words(by_id(substring.dedup_words(frame(spark, rows), **sizes)), rows)
    got = by_id(suffix.dedup_bytes(frame(spark, rows), **sizes))
    for d, t, gone in slow_spans([(d, t.encode()) for d, t in rows], 50):
        assert (got[d].n_bytes, got[d].n_removed) == (len(t), sum(gone)), d


def test_spans_of_a_joined_table_repeated_and_null_ids(spark, corpus):
    docs = frame(spark, corpus).join(spark.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, toxic int"), "doc_id")
    check_words(by_id(substring.dedup_words(docs)), sorted(corpus))
    text = prose(77, 30)
    rows = [(5, text), (5, text), (None, text), (None, text), (4, None)]
    got = sorted(((r.doc_id is None, r.n_words, r.n_removed) for r in substring.dedup_words(frame(spark, rows)).collect()))
    assert got == [(False, 0, 0), (False, 30, 0), (False, 30, 0), (True, 30, 30), (True, 30, 30)]
    got = sorted(((r.doc_id is None, r.n_removed) for r in suffix.dedup_bytes(frame(spark, rows)).collect()))
    assert got == [(False, 0), (False, 0), (False, 0), (True, len(text)), (True, len(text))]


def test_near_stage_finds_what_shares_its_shingles(spark):
    """Of the given documents' pairs that share 0.8 of their five-word shingles, nine in ten at least are in one group,
    and no document of a group is without such a neighbour at 0.5."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    texts = {r.doc_id: (r.text or "").lower().split() for r in docs.collect()}
    sets = {d: {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for d, w in texts.items() if w}
    holders = {}
    for d, s in sets.items():
        for x in s:
            holders.setdefault(x, []).append(d)
    common = {}
    for ds in holders.values():
        for i, a in enumerate(ds):
            for b in ds[i + 1 :]:
                common[a, b] = common.get((a, b), 0) + 1
    share = {p: n / (len(sets[p[0]]) + len(sets[p[1]]) - n) for p, n in common.items()}
    marked = simhash.fingerprints(docs, 5, 4)
    first = {r.doc_id: r.first.doc_id for r in simhash._classed(marked.where("size > 0"), 51, 4, 0.8).collect()}
    near = [p for p, j in share.items() if j >= 0.8]
    assert len(near) > 50 and sum(first[a] == first[b] for a, b in near) >= 0.9 * len(near)
    best = {}
    for (a, b), j in share.items():
        if first[a] == first[b]:
            best[a], best[b] = max(best.get(a, 0), j), max(best.get(b, 0), j)
    groups = {}
    for d, f in first.items():
        groups.setdefault(f, []).append(d)
    assert all(best.get(d, 0) >= 0.5 for ds in groups.values() if len(ds) > 1 for d in ds)


@pytest.mark.parametrize("shard_rows", [25, 50_000])
def test_wide_search_in_one_shard_and_in_many(spark, shard_rows):
    """Size classes that are one shard and such as are dealt out by bands find the same pairs: those within both bounds."""
    rng = np.random.default_rng(6)
    a = rng.integers(0, 2, (120, 256), dtype=np.uint8)
    b = a.copy()
    for row, n in zip(b, rng.integers(30, 70, 120)):
        row[rng.choice(256, n, replace=False)] ^= 1
    bits, sizes = np.concatenate([a, b]), np.concatenate([rng.integers(60, 140, 120)] * 2)
    sizes[120:] = (sizes[120:] * rng.uniform(0.7, 1.3, 120)).astype(int)
    prints = np.packbits(bits, axis=1, bitorder="little").view(np.int64)
    df = spark.createDataFrame([(i, int(s), *map(int, p)) for i, (s, p) in enumerate(zip(sizes, prints))], "node long, size long, w0 long, w1 long, w2 long, w3 long")
    got = {(min(r.a, r.b), max(r.a, r.b)) for r in simhash.linked(df, 51, 4, 0.8, shard_rows).collect()}
    far = (bits[:, None, :] != bits[None, :, :]).sum(axis=2)
    fits = np.minimum.outer(sizes, sizes) >= 0.8 * np.maximum.outer(sizes, sizes)
    assert got == set(zip(*(x.tolist() for x in np.nonzero(np.triu((far <= 51) & fits, 1)))))
