"""Every opN query's columns and rows, and rarer inputs of the operators."""

import hashlib
import re

import duckdb
import pytest
from llm_texts import prose

from clipflow.llm import common, decontam, exact, toxicity, urls
from clipflow.llm.queries import ORACLE, QUERIES

SF = "/root/testdata/sf0.001"
COLUMNS = {
    "op1_licences": "doc_id licence dice n_units",
    "op2_simhash": "doc_id fingerprint component_id",
    "op3_shards": "doc_id lang source n_chars text_sha256",
    "op4_packing": "doc_id piece start length ids_crc32 sequence_id offset",
    "op5_substring": "doc_id n_words n_removed kept_sha256",
    "op6_suffix": "doc_id n_bytes n_removed n_spans kept_sha256",
    "op7_exact": "doc_id keep_id group_size kept text_sha256",
    "op8_decontam": "doc_id n_words n_hit n_items items_sha256 contaminated",
    "op9_toxicity": "doc_id held_out score predicted worst",
    "op10_urls": "page_id host path rule verdict score",
}


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in ("documents", "benchmark", "pages", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", COLUMNS)
def test_query_contract(spark, duck, name):
    """Columns, one row a document or page, and equality with SQL where there is some."""
    df = QUERIES[name](spark, SF)
    assert df.columns == COLUMNS[name].split()
    rows = df.collect()
    table, key = ("pages", "page_id") if name == "op10_urls" else ("documents", "doc_id")
    ids = [r[0] for r in duck.execute(f"SELECT {key} FROM {table}").fetchall()]
    assert set(ids) == {r[key] for r in rows}
    if name != "op4_packing":
        assert len(rows) == len(ids)
    if name in ORACLE:
        found = duck.execute(ORACLE[name])
        names = [c[0] for c in found.description]
        assert sorted(names) == sorted(df.columns)
        assert sorted(map(str, (tuple(r[n] for n in names) for r in rows))) == sorted(map(str, found.fetchall()))


def items(spark, rows):
    return spark.createDataFrame(rows, "item_id string, text string")


def test_passages_have_offsets_in_the_original(spark):
    """Repeated and null ids, null texts, other scripts; every passage is found where a scan by hand finds it."""
    item = prose(3, 12)
    odd = "Ünï 中文 — « " + item.replace(" ", ",\t", 3).upper() + " » tail"
    rows = [(1, odd), (1, None), (1, "x " + item), (None, item), (2, ""), (3, prose(4, 30))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((str(r.doc_id), r.start, r.end, r.passage) for r in decontam.located(docs, items(spark, [("a", item)])).collect())
    expected = []
    for d, t in rows:
        pattern = "[^0-9A-Za-z\\x80-\U0010ffff]+".join(map(re.escape, item.split()))
        expected += [(str(d), m.start(), m.end(), m[0]) for m in re.finditer(pattern, t or "", re.I)]
    assert got == sorted(expected) and len(got) == 3
    assert decontam.located(docs, items(spark, [])).count() == 0


def test_blocks_of_items_equal_one_automaton(spark, monkeypatch):
    texts = [prose(i, 25) for i in range(6)]
    docs = spark.createDataFrame([(i, " ".join([prose(90 + i, 8), texts[i % 6], texts[(i + 1) % 6][:60]])) for i in range(12)] + [(50, None), (50, texts[0]), (51, "nothing here")], "doc_id long, text string")
    bench = items(spark, [(f"i{i}", t) for i, t in enumerate(texts)] + [("i0", texts[0]), (None, texts[1]), ("z", None)])
    show = lambda df: sorted(map(str, df.collect()))
    one, places, kept = show(decontam.scan(docs, bench)), show(decontam.located(docs, bench)), show(decontam.clean(docs, bench))
    assert "None" not in "".join(i for r in decontam.scan(docs, bench).collect() for i in r["items"])
    monkeypatch.setattr(decontam, "BLOCK_CHARS", 200)
    assert len(list(decontam._blocks(bench, "item_id", "text"))) > 3
    assert show(decontam.scan(docs, bench)) == one and show(decontam.located(docs, bench)) == places and show(decontam.clean(docs, bench)) == kept
    assert [r.doc_id for r in decontam.clean(docs, bench).collect()] == [50, 51]


def test_exact_stage_keeps_columns_of_any_name(spark):
    docs = spark.createDataFrame([(1, "a", "x", "y"), (2, "a", "x", "z"), (3, "b", "x", None)], "doc_id long, text string, digest string, _digest string")
    kept = exact.keep_first(docs, exact.DigestIndex(spark, buckets=2))
    assert kept.columns == docs.columns and sorted(tuple(r) for r in kept.collect()) == [(1, "a", "x", "y"), (3, "b", "x", None)]


def test_arrivals_meet_the_index(spark):
    first = spark.createDataFrame([(1, "a"), (2, "b"), (3, "a")], "doc_id long, text string")
    second = spark.createDataFrame([(4, "a"), (5, "c"), (6, None)], "doc_id long, text string")
    index = exact.DigestIndex(spark, buckets=2)
    got = {r.doc_id: (r.keep_id, r.group_size, r.kept) for r in exact.in_arrivals([first, second], index).collect()}
    assert got == {1: (1, 3, True), 2: (2, 1, True), 3: (1, 3, False), 4: (1, 3, False), 5: (5, 1, True), 6: (6, 1, True)}
    assert index.batches() == 2
    index.drop()


def test_repeated_labels_and_documents_stay_within_the_sample(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(toxicity, "fit", lambda rows: seen.extend(rows))
    docs = spark.createDataFrame([(1, f"text {i}") for i in range(50)] + [(2, "calm"), (None, "x")], "doc_id long, text string")
    labels = spark.createDataFrame([(1, 1), (1, 1), (2, 0), (None, 1), (3, None), (4, 1)], "doc_id long, toxic int")
    usable = {r.doc_id for r in labels.where(toxicity.remainder("doc_id") != 1).collect()}
    toxicity.learn(docs, labels)
    assert len(seen) == len(usable & {1, 2})


def test_shared_folder_is_asked_for_on_a_cluster():
    class Unset:
        get = staticmethod(lambda key, default: default)

    class Context:
        master = "spark://host:7077"

    class Session:
        sparkContext, conf = Context(), Unset()

    with pytest.raises(RuntimeError):
        common.shared_dir(Session())
    Context.master = "local[4]"
    assert common.shared_dir(Session()).startswith("file:///")


#: URLs that training has not seen, of hosts that it has not seen.
UNSEEN = (
    ("http://mega-casino-slots.test/jackpot/win", 1), ("https://poker-bets-live.example.biz/bonus", 1), ("http://porn-xxx-videos.test/live", 1), ("https://cheap-cialis-pills.test/buy", 1),
    ("http://crack-keygen-full.test/download", 1), ("https://instant-cash-loans.example.info/apply", 1), ("http://verify-login-account.test/confirm", 1), ("https://free-torrent-movies.test/hd", 1),
    ("https://science.example.edu/course/12", 0), ("http://www.example.com/en/history/rome", 0), ("https://blog.example.org/de/wandern/8", 0), ("https://news.example.org/en/local/4412", 0),
    ("http://library.example.com/catalog/77", 0), ("https://wiki.example.net/fr/article/9", 0), ("https://recipes.example.org/es/pan", 0), ("http://city.example.edu/minutes/2020", 0),
)


def test_url_filter_on_unseen_hosts(spark):
    pages = spark.createDataFrame([(i, u) for i, (u, _) in enumerate(UNSEEN)], "page_id long, url string")
    got = {r.page_id: r.verdict for r in urls.judge(pages, urls.labelled_table(spark), rules=()).collect()}
    right = sum((got[i] == "block") == bool(y) for i, (_, y) in enumerate(UNSEEN))
    assert right >= 14, right


def test_text_hash_of_the_null_text(spark):
    assert hashlib.sha256(b"").hexdigest() == exact.exact_dedup(spark.createDataFrame([(1, None)], "doc_id long, text string"), exact.DigestIndex(spark, buckets=1)).first().text_sha256
