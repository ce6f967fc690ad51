"""The main table's graphs as arrays: what the driver holds, and clips that stay rows."""

import tracemalloc
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from clipflow.operators import baselines as B
from clipflow.operators import ctc, fst
from clipflow.sources import lattices as L
from tests.test_more import toy_decoder


def test_a_model_of_many_grams_takes_little_of_the_driver():
    rng, n, v = np.random.default_rng(0), 100_000, 5000
    words = sorted(["</s>", "<s>", *[f"w{i}" for i in range(v)]])
    pairs = np.unique(rng.integers(2, v, (n, 2)), axis=0)
    triples = np.unique(np.concatenate([pairs[rng.integers(0, len(pairs), n)], rng.integers(2, v, (n, 1))], axis=1), axis=0)
    contexts = {1: np.unique(pairs[:, :1], axis=0), 2: np.unique(triples[:, :2], axis=0)}
    grams = {1: np.arange(v)[:, None], 2: pairs, 3: triples}
    tracemalloc.start()
    model = fst.WordModel(words, 3, lambda k: (contexts[k].astype(np.int32), np.zeros(len(contexts[k]))), lambda k: (grams[k].astype(np.int32), -np.ones(len(grams[k]))))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(model.lm_key) >= len(pairs) + len(triples) and peak < 150 * len(model.lm_key)  # dictionaries of word tuples took over 400


def test_frames_of_a_clip_that_is_a_row_equal_the_long_lattice(spark):
    df = spark.createDataFrame([("a", "kaTs"), ("b", "i"), ("c", "")], "utt string, phones string")
    long = {tuple(r) for r in L.lattice(df, ["utt"], swap=0.5).collect()}
    rows = df.select("utt", L.lattice_frames(L.peaks("phones", ["utt"], 0.5)).alias("frames"))
    assert {tuple(r) for r in rows.select("utt", F.inline(F.flatten("frames"))).collect()} == long
    greedy = {r[0]: r[1] for r in ctc.ctc_greedy(L.lattice(df, ["utt"], swap=0.5), ["utt"]).collect()}
    assert {r[0]: r[1] for r in rows.select("utt", ctc.greedy_labels("frames")).collect()} == greedy | {"c": ""}


def test_clips_are_searched_without_a_shuffle(spark):
    decoder = toy_decoder(np.random.default_rng(3))
    df = spark.createDataFrame([("a", "xyz"), ("b", "")], "utt string, phones string")
    clips = df.select("utt", F.flatten(L.lattice_frames(L.peaks("phones", ["utt"], 0.0))).alias("rows"))
    found = fst.clip_decode(clips, spark.sparkContext.broadcast(fst.Graph(decoder)))
    assert "Exchange" not in found._jdf.queryExecution().executedPlan().toString()
    want = {r.utt: r.score for r in fst.fst_decode(L.lattice(df, ["utt"], swap=0.0), decoder, ["utt"]).collect()}
    got = {r.utt: r.score for r in found.collect()}
    assert got["a"] == pytest.approx(want["a"]) and got["b"] == 0


@pytest.mark.parametrize("most", (10**6, 40))
def test_the_model_in_numbers_scores_as_the_dictionaries(spark, most):
    rng = np.random.default_rng(4)
    lines = sorted({" ".join(rng.choice(list("abcdefgh"), 5)) for _ in range(60)})
    train = spark.createDataFrame([(x.split(),) for x in lines], "words array<string>")
    vocabulary = spark.createDataFrame([(c, c) for c in "abcdefg"], "w string, phones string")  # h is beyond it
    lm, back = B.language_model(train, vocabulary, 3, most)
    strings = fst.Decoder([(c, c) for c in "abcdefg"], lm, back, order=3)
    model = B.word_model(train, vocabulary, 3, most)
    number = {w: i for i, w in enumerate(model.vocabulary)}
    for _ in range(100):
        said, state, total = ("<s>",) if ("<s>",) in back else (), model.start, 0.0
        want = 0.0
        for w in rng.choice([*"abcdefg"], 4):
            gain, to = model.word_scores(np.array([state]), np.array([number[w]]))
            want, total, said, state = want + strings.word_score(said, w), total + gain[0], (*said, w), int(to[0])
        assert total == pytest.approx(want)


def test_the_model_is_built_in_tasks_and_sent_in_pieces(spark, monkeypatch):
    train = spark.createDataFrame([(list("abca"),), (list("bcab"),), (list("cc"),)], "words array<string>")
    vocabulary = spark.createDataFrame([(c, c) for c in "abc"], "w string, phones string")
    method = B.Method("x", 0.0, order=3)

    def refuse(*_):
        raise AssertionError("on the driver")

    want = fst.WordModel.of(fst.Decoder([(c, c) for c in "abc"], *B.language_model(train, vocabulary, 3), order=3))
    for kind in (fst.WordModel, fst.Tree):
        monkeypatch.setattr(kind, "__init__", refuse)
    (graph,) = B.graphs(train, vocabulary, (method,))
    found = graph.value
    assert found.n_nodes == 4 and found.n_states == want.n_states and sorted(found.word_scores.__self__.lm_p) == pytest.approx(sorted(want.lm_p))


def test_large_arrays_come_whole_through_pieces(spark):
    def made_of(batches):
        return SimpleNamespace(n=sum(b.num_rows for b in batches), ids=np.arange(1_500_000), x=np.sqrt(np.arange(200_000)), few=np.ones(3))

    got = fst.pieces(spark.range(7), made_of, "made")
    assert set(got.arrays) == {"ids", "x"}
    made = got.value
    assert made.n == 7 and (made.ids == np.arange(1_500_000)).all() and (made.x == np.sqrt(np.arange(200_000))).all() and len(made.few) == 3
    none = fst.pieces(spark.range(0), made_of, "made").value
    assert none.n == 0


def test_clips_of_like_length_are_searched_together(spark, monkeypatch):
    decoder = toy_decoder(np.random.default_rng(3))
    df = spark.createDataFrame([(f"{i:03}", "xyz" * (1 + i % 5 * 12)) for i in range(130)], "utt string, phones string").coalesce(1)
    clips = df.select("utt", F.flatten(L.lattice_frames(L.peaks("phones", ["utt"], 0.0))).alias("rows"))
    out = [r.utt for r in fst.clip_decode(clips, spark.sparkContext.broadcast(fst.Graph(decoder))).collect()]
    assert sorted(out) == [f"{i:03}" for i in range(130)]
    long = [int(u) % 5 for u in out]
    assert sum(a > b for a, b in zip(long, long[1:])) == 0  # by length, not as they came


def test_one_of_the_words_that_sound_alike_is_followed_without_a_history():
    lexicon = [(f"w{i}", "ab"[i % 2]) for i in range(40)]
    lm = {(w,): float(-1 - i) for i, (w, _) in enumerate(lexicon)}
    graph = fst.Graph(fst.Decoder(lexicon, lm, {}, order=1))
    assert len(graph.word) == 2 and [graph.vocabulary[i] for i in graph.word] == ["w0", "w1"]
    frames = [(0, "a", 0.9), (0, "b", 0.1), (1, "_", 1.0), (2, "b", 0.8), (2, "a", 0.2)]
    lists = pa.array([[{"t": t, "sym": s, "p": p} for t, s, p in frames]], pa.list_(pa.struct([("t", pa.int32()), ("sym", pa.string()), ("p", pa.float64())])))
    assert fst._search(graph, lists)[0][0] == ("w0", "w1")
