"""Licences, shards, packing, contamination, toxicity, urls and the pipeline against brute force and invariants."""

import re
import struct
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from clipflow.llm import decontam, licences, packing, shards, toxicity, urls
from clipflow.llm.queries import tokenizer_path

from llm_texts import prose

SCHEMA = "doc_id long, text string"


def frame(spark, rows):
    return spark.createDataFrame(rows, SCHEMA)


# ---- licences


def slow_dice(a, b):
    pairs = [Counter(zip(w, w[1:])) for w in (licences._words(a), licences._words(b))]
    total = sum(map(lambda c: sum(c.values()), pairs))
    return 2 * sum((pairs[0] & pairs[1]).values()) / total if all(pairs) else 0.0


def test_licences_match_brute_force(spark):
    mit = licences.TEMPLATES["MIT"]
    rows = [
        (1, "Some words first.\nReleased under the MIT License.\nmore"), (2, mit), (3, mit.replace("Software", "Work", 2) + "\n"), (4, None), (5, ""), (6, "license"),
        (7, "Intro line here\n\n" + mit.replace(". ", ".\n") + "\n\nLast line"), (8, "licensed UNDER the Apache-License, version 2.0!!"), (9, prose(1, 300)),
        (10, "Released under the MIT License. And then a great many other words follow it on the same line here"), (11, "All rights reserved."), (11, "All rights reserved."),
        (None, "All rights reserved."), (12, "a\n\n" + mit.replace(". ", ".\n\n")),
    ]
    got = sorted(((str(r.doc_id), r.licence, r.dice, r.n_units) for r in licences.scan(frame(spark, rows).withColumn("licence", F.lit(1))).collect()), key=str)
    expected = []
    for d, t in rows:
        t = t or ""
        units = t.split("\n") + [p for p in re.split(r"\n[ \t]*\n", t) if "\n" in p.strip(" \n\t\r")] + [t] * bool(re.search(r"\n[ \t]*\n", t))
        hits = [(-slow_dice(u, x), n) for u in units for n, x in licences.TEMPLATES.items() if slow_dice(u, x) >= 0.8]
        n = len({i for i, u in enumerate(units) if any(slow_dice(u, x) >= 0.8 for x in licences.TEMPLATES.values())})
        expected.append((str(d), min(hits)[1] if hits else None, round(-min(hits)[0], 6) if hits else None, n))
    assert got == sorted(expected, key=str)
    assert licences.scan(frame(spark, [])).count() == 0


def test_licences_inside_longer_documents(spark):
    """Licences of several paragraphs or wrapped lines between other text, with either line end, and one beside a notice."""
    mit = licences.TEMPLATES["MIT"].replace(" The above", "\n\nThe above").replace(" THE SOFTWARE IS", "\n\nTHE SOFTWARE IS")
    gpl = licences.TEMPLATES["GPL-3.0-header"].replace(" This program is distributed", "\n\nThis program is distributed")
    apache = licences.TEMPLATES["Apache-2.0-header"].replace(" Unless", "\n \t\nUnless").replace(", ", ",\n")
    code = "\n".join(prose(s, 9) for s in range(40))
    want, rows = {}, []
    for i, (name, text) in enumerate([("MIT", mit), ("GPL-3.0-header", gpl), ("Apache-2.0-header", apache)]):
        for k, whole in enumerate([text, f"{code}\n\n{text}\n\n{code}", f"{code}\n{text}\n{code}", f"{code}\n\n{text}\n\n{code}".replace("\n", "\r\n")]):
            rows.append((10 * i + k, whole))
            want[10 * i + k] = name
    rows += [(90, code), (91, f"All rights reserved.\n\n{code}\n\n{mit}\n\n{code}")]
    assert {r.doc_id: r.licence for r in licences.scan(frame(spark, rows)).collect()} == want | {90: None, 91: "All-rights-reserved"}
    assert {r.licence for r in licences.matches(frame(spark, rows[-1:])).collect()} == {"All-rights-reserved", "MIT"}


def test_whole_licence_texts_alone_and_embedded(spark):
    code = "\n".join(prose(s, 9) for s in range(30))
    for name, parts in (("BSD-2-Clause", ("Redistributions of", "Redistributions in", "THIS SOFTWARE IS")), ("Unlicense", ("Anyone is free", "In jurisdictions", "THE SOFTWARE IS", "For more information"))):
        text = licences.TEMPLATES[name]
        for part in parts:
            assert " " + part in text
            text = text.replace(" " + part, "\n\n" + part)
        title = f"Copyright (c) 2001, A. Nobody\n\n{text}"
        got = licences.scan(frame(spark, [(1, text), (2, " ".join(text.split())), (3, f"{code}\n\n{title}\n\n{code}")]))
        found = licences.matches(frame(spark, [(3, f"{code}\n\n{title}\n\n{code}")]))
        assert [r.licence for r in got.where("doc_id < 3").collect()] == [name, name]
        assert name in {r.licence for r in found.collect()}


# ---- shards


def test_shards_round_trip_and_compaction(spark, tmp_path):
    rows = [(i, prose(i, 40)) for i in range(900)] + [(None, None), (5, ""), (5, "")]
    store = shards.ShardStore(spark, f"file://{tmp_path}/s", target=40_000, fan_in=3)
    for part in range(3):
        store.append(frame(spark, rows[part::3]).repartition(2), shard_rows=60)
    before = store.read_manifest()[2]
    assert store.versions() == [1, 2, 3] and sum(r.rows for r in before) == len(rows)
    stale = store.read()
    store.compact(all_tiers=True)
    _, _, after = store.read_manifest()
    assert sum(r.files for r in after) <= sum(r.files for r in before) / 3 and max(r.level for r in after) >= 1
    assert all(r.shard < 3 * 40_000 for r in after)
    assert sorted(map(str, (tuple(r) for r in store.read().collect()))) == sorted(map(str, rows))
    assert stale.count() == len(rows)  # a reader of the version before still has its files
    store.expire(keep=1)
    assert {p.parent.name for p in (tmp_path / "s/data").rglob("*.parquet")} == {r.path.rpartition("/")[2] for r in after}
    assert spark.conf.get("spark.sql.files.maxPartitionBytes") == "134217728b"
    # of two writers from one version, one loses
    version, schema, now = store.read_manifest()
    store.commit(version, schema, now)
    with pytest.raises(shards.CommitConflict):
        store.commit(version, schema, now)
    assert not [p for p in (tmp_path / "s/manifest").iterdir() if p.name.startswith(".") and not p.name.endswith(".crc")]


def test_compaction_beside_another_writer(spark, tmp_path, monkeypatch):
    """An append that commits while a merge runs stays; a merge whose runs are gone is dropped."""
    store = shards.ShardStore(spark, f"file://{tmp_path}/w", target=1 << 20, fan_in=2)
    for part in range(2):
        store.append(frame(spark, [(part, "a")]))
    merge, calls = store._merge, []

    def slow(runs, schema):
        calls.append(1)
        if len(calls) == 1:
            store.append(frame(spark, [(9, "late")]))
        return merge(runs, schema)

    monkeypatch.setattr(store, "_merge", slow)
    store.compact(all_tiers=True)
    assert sorted(r.doc_id for r in store.read().collect()) == [0, 1, 9]


def test_reshard_of_an_empty_table_and_clashing_name(spark, tmp_path):
    assert shards.reshard(frame(spark, []), f"file://{tmp_path}/e").count() == 0
    with pytest.raises(ValueError):
        shards.reshard(frame(spark, [(1, "a")]).withColumn("_shard", F.lit(1)), f"file://{tmp_path}/f")


# ---- packing


def test_packing_is_exact_and_tight(spark, corpus):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(tokenizer_path())
    rows = [*corpus, (60, "It's <|endoftext|> here, 3 x 4;\u00a0e\u0301 don't\x1cstop — \u2028ÀÉ ﬁ İ Σς"), (61, "".join(map(chr, range(1, 0x250))))]
    got = packing.pack(frame(spark, rows).repartition(5), tokenizer_path(), capacity=256, with_ids=True, open_bins=8, fan_in=2).collect()
    by = {}
    for r in got:
        by.setdefault(r.doc_id, []).append(r)
    for d, t in rows:
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 0]
        parts = sorted(by[d], key=lambda r: r.piece)
        assert [list(struct.unpack(f"<{len(p.ids) // 4}I", p.ids)) for p in parts] == [ids[i : i + 256] for i in range(0, len(ids), 256)], d
        assert [p.start for p in parts] == list(range(0, len(ids), 256))
        assert all(p.ids_crc32 == zlib.crc32(p.ids) and p.length == len(p.ids) // 4 for p in parts)
    bins = {}
    for r in got:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for places in bins.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 256
    total = sum(r.length for r in got)
    assert len(bins) <= 1.1 * total / 256 + 1
    assert packing.pack(frame(spark, []), tokenizer_path()).count() == 0


def test_best_fit_closes_the_fullest():
    bins = packing.BestFit(10, 2)
    assert bins.add(6, "a") is None and bins.add(7, "b") is None
    assert [i for *_, i in bins.add(8, "c")] == ["b"]
    assert [i for *_, i in bins.add(4, "d")] == ["a", "d"]
    assert [i for *_, i in bins.add(10, "e")] == ["e"]
    assert [[i for *_, i in b] for b in bins.rest()] == [["c"]]


# ---- contamination


def slow_hits(text, items, width):
    cut = lambda t: re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", "".join(c.lower() if c.isascii() else c for c in t or ""))
    words, hit, seen = cut(text), set(), set()
    for item, t in items:
        w = cut(t)
        n = min(width, len(w))
        for i in range(len(w) - n + 1 if n else 0):
            for j in range(len(words) - n + 1):
                if words[j : j + n] == w[i : i + n]:
                    hit |= set(range(j, j + n))
                    seen.add(str(item))
    return len(words), len(hit), sorted(seen)


def test_contamination_matches_brute_force(spark, corpus):
    items = [(1, " ".join(corpus[26][1].split()[45:70])), (2, "one"), (3, None), (4, "?!"), (5, "ÉTÉ 中文, Ünïcödé"), (6, prose(77, 14)), (7, corpus[2][1]), (7, corpus[2][1]), (10, "one")]
    docs = [r for r in corpus if len(r[1] or "") < 20_000] + [(70, "x ONE.two One"), (71, "été 中文! ünïcödé É"), (72, "ÉTÉ 中文 Ünïcödé")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {r.doc_id: (r.n_words, r.n_hit, r["items"]) for r in decontam.scan(frame(spark, docs), bench).collect()}
    assert got == {d: slow_hits(t, items, 10) for d, t in docs}
    clean = {r.doc_id for r in decontam.clean(frame(spark, docs).withColumn("n_hit", F.lit("x")), bench).collect()}
    assert clean == {d for d, v in got.items() if not v[1]}
    assert decontam.scan(frame(spark, []), bench).count() == 0
    assert decontam.scan(frame(spark, docs), bench.limit(0)).agg(F.sum("n_hit")).first()[0] == 0
    found = {(r.doc_id, r.passage) for r in decontam.located(frame(spark, docs), bench).collect()}
    assert (70, "ONE") in found and (72, "ÉTÉ 中文 Ünïcödé") in found


# ---- toxicity


def test_toxicity_learns_from_document_labels(spark):
    rng = np.random.default_rng(1)
    rows, labels = [], []
    for i in range(900):
        sentences = [prose(1000 * i + s, 8) for s in range(rng.integers(1, 8))]
        bad = i % 3 == 0
        if bad:
            at = rng.integers(len(sentences))
            sentences[at] = "you grumbl" + ["y", "ing", "ed"][i % 9 // 3] + " nincompoop " + sentences[at]
        rows.append((i, ". ".join(sentences)))
        labels.append((i, int(bad)))
    rows += [(5000, None), (5001, ""), (5002, "...")]
    docs, marks = frame(spark, rows), spark.createDataFrame([*labels, (None, 1), (1, None), (9999, 1)], "doc_id long, toxic int")
    model = toxicity.learn(docs, marks)
    got = {r.doc_id: r for r in toxicity.score(docs.withColumn("score", F.lit("x")), model).collect()}
    held = [i for i, _ in labels if zlib.crc32(str(i).encode()) % 3 == 1]
    right = sum(got[i].predicted == int(i % 3 == 0) for i in held)
    assert right >= 0.97 * len(held)
    bad = [i for i in held if i % 3 == 0 and got[i].predicted]
    assert all("nincompoop" in rows[i][1].split(".")[got[i].worst] for i in bad)
    assert got[5000].score == got[5001].score == got[5002].score < 0.1 and got[5000].worst is None
    assert {r.doc_id for r in toxicity.reject(docs, model).collect()} == {d for d, r in got.items() if not r.predicted}
    none = toxicity.learn(docs, marks.limit(0))
    assert toxicity.score(docs, none).where("predicted = 1").count() == 0


def test_noisy_or():
    model = toxicity.Model(0.0, {b"bad": 2.0})
    p = 1 / (1 + np.exp(-np.array([0.0, 2.0])))
    assert abs(model.score(b"fine day. Bad!") - (1 - np.prod(1 - p))) < 1e-12


# ---- urls


def slow_url(url):
    host = path = ""
    if url is not None and "://" in url:
        rest = url[url.index("://") + 3 :]
        host = re.split("[/?#]", rest, maxsplit=1)[0]
        path = re.split("[?#]", rest[len(host) :], maxsplit=1)[0]
        host = "".join(c.lower() if c.isascii() else c for c in host)
    fits = [r for r in urls.RULES if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
    return host, path, max(fits, key=lambda r: len(r.name), default=None)


def test_urls_match_brute_force(spark):
    given = [
        "http://a.net", "http://a.net/", "HTTP://A.Example.NET/en/1?x=/de/", "https://example.net/enx", "https://example.com/de/7", "https://notexample.com/de/7", "http://x.org/fr/",
        "http://x.org/en/#/fr/", "http://free-casino-bonus.test/jackpot", "", None, "no scheme.net/", "a://b://c.net/x", "http://ÉX.net/ü", "http://net/", "http://example.net?u=1/en/", "x://y.com#z",
        "https://blog.example.org/en/1", "http://a\nb.net/c\nd",
    ]
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate(given)], "page_id long, url string, host string")
    got = {r.page_id: r for r in urls.judge(pages, urls.labelled_table(spark)).collect()}
    for i, u in enumerate(given):
        host, path, rule = slow_url(u)
        assert (got[i].host, got[i].path, got[i].rule) == (host, path, rule and rule.name), u
        assert got[i].verdict == (rule.verdict if rule else "block" if got[i].score >= 0.5 else "allow")
    assert got[8].verdict == "block" and got[17].verdict == "allow"
    right = urls.judge(urls.labelled_table(spark).selectExpr("cast(label AS long) page_id", "url"), urls.labelled_table(spark), ()).collect()
    assert all((r.verdict == "block") == bool(r.page_id) for r in right)
    assert urls.judge(pages.limit(0), urls.labelled_table(spark)).count() == 0


def test_url_filter_stays_in_the_engine(spark):
    plan = urls.judge(spark.createDataFrame([(1, "http://a.b/c")], "page_id long, url string"), urls.labelled_table(spark))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Join" not in plan


# ---- the pipeline


def test_pipeline_stages(spark, tmp_path):
    import corpus_pipeline

    passage = prose(777, 30)
    rows = [(i, prose(i, 60), "en", "s", 1) for i in range(40)]
    rows += [(50, rows[4][1] + " ", "en", "s", 1), (51, rows[4][1].replace(" ", "  "), "en", "s", 1), (52, prose(9, 9) + " " + passage, "en", "s", 1), (53, None, None, None, None), (54, rows[6][1] + " extra", "fr", "t", 2)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 0, 0) for i in range(40)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, passage)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    kept = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, str(tmp_path))
        assert kept.columns == docs.columns, name
    ids = {r.doc_id for r in kept.collect()}
    assert ids == {*range(40), 50, 53} - {50}
    packed = corpus_pipeline.run(spark, str(tmp_path))
    assert {r.doc_id for r in packed.collect()} == ids
