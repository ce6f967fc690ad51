"""Array search, ε-removal, gradients, tracks, thumbnails, towers, sources, observation and streams."""

import json
import math
from itertools import product

import numpy as np
import pytest
from pyspark.sql import functions as F

from clipflow.functions import frames as FR
from clipflow.functions import session
from clipflow.operators import ctc, fst, lm, nn, pipeline, sync, tracks, trained
from clipflow.sources import clock, standin
from clipflow.streaming import clips as C


def toy_decoder(rng, order=3):
    words = [("ab", "xy"), ("abb", "xy"), ("c", "z"), ("d", "xz"), ("e", "y")]
    names = [w for w, _ in words]
    model = {(w,): -rng.random() for w in [*names, "</s>"]}
    model |= {(a, b): -rng.random() for a, b in product(names, [*names, "</s>"]) if rng.random() < 0.5}
    model |= {(a, b, c): -rng.random() for a, b, c in product(names, names, names) if rng.random() < 0.3}
    back = {k[:-1]: -rng.random() for k in model if len(k) > 1}
    return fst.Decoder(words, model, back, order=order, beam=1e9, max_active=10**6)


def test_array_search_equals_the_search_by_strings():
    rng = np.random.default_rng(1)
    for order in (1, 2, 3):
        decoder = toy_decoder(rng, order)
        graph = fst.Graph(decoder)
        clips = [[dict(zip("xyz_", np.log(rng.dirichlet(np.ones(4))))) for _ in range(int(rng.integers(1, 7)))] for _ in range(25)]
        rows = [(i, t, graph.symbols.get(s, graph.n_symbols - 1), p) for i, c in enumerate(clips) for t, f in enumerate(c) for s, p in f.items()]
        got = graph.decode(*(np.array(x) for x in zip(*rows)), len(clips))
        for frames, (words, score) in zip(clips, got):
            best = decoder.decode(frames)[0]
            assert score == pytest.approx(best[1]) and (words == best[0] or any(w == words and s == pytest.approx(best[1]) for w, s in decoder.decode(frames, 50)))


def test_decoding_on_dataframes_handles_empty_and_unknown(spark):
    decoder = toy_decoder(np.random.default_rng(2))
    rows = [("a", 3, "x", 0.9), ("a", 5, "y", 0.5), ("a", 5, "y", 0.3), ("a", 5, "?", 0.2), ("b", 0, "?", 1.0)]
    got = {r.utt: r for r in fst.fst_decode(spark.createDataFrame(rows, "utt string, t int, sym string, p double"), decoder, ["utt"]).collect()}
    assert got["a"].words in (["ab"], ["abb"]) and got["b"].words == []
    assert fst.fst_decode(spark.createDataFrame([], "utt string, t int, sym string, p double"), decoder, ["utt"]).count() == 0


def test_epsilon_removal_keeps_strings_and_costs():
    m = fst.Fst(0)
    for a, i, w, b in ((0, "", 1.0, 1), (0, "a", 0.5, 2), (1, "b", 0.2, 2), (2, "", 0.1, 3), (3, "", 0.3, 0), (3, "c", 0.4, 4), (1, "", 0.0, 3)):
        m.add(a, i, i, w, b)
    m.finals = {4: 0.0, 2: 1.0}
    plain = fst.remove_epsilon(m)
    assert all(i for arcs in plain.arcs.values() for i, *_ in arcs)
    a, b = dict(fst.best_strings(m, 12)), dict(fst.best_strings(plain, 12))
    assert {k: round(v, 9) for k, v in a.items()} == {k: round(v, 9) for k, v in b.items()}
    assert dict(fst.best_strings(fst.determinise(plain), 3)).keys() == dict(fst.best_strings(plain, 3)).keys()


def test_rerank_takes_the_better_total(spark):
    text = spark.createDataFrame([(["a", "b"],)] * 6 + [(["a", "c"],)] + [(["b", "a"],)] * 3, "words array<string>")
    model, weights = lm.katz_model(text, 2)
    nbest = spark.createDataFrame([("u", 0, ["a", "c"], -1.0), ("u", 1, ["a", "b"], -1.1), ("v", 0, ["b", "a"], 0.0), ("v", 1, ["c", "c"], -0.01)], "utt string, rank int, words array<string>, score double")
    got = {r.utt: r.words for r in lm.rerank(nbest, ["utt"], model, weights, 2).collect()}
    assert got == {"u": ["a", "b"], "v": ["b", "a"]}
    pruned, _ = lm.katz_model(text, 2, most=2)
    assert pruned.where("order = 2").count() == 2


def numeric(f, x, eps=1e-6):
    g = np.zeros_like(x)
    for i in np.ndindex(x.shape):
        keep = x[i]
        x[i] = keep + eps
        a = f()
        x[i] = keep - eps
        b = f()
        x[i] = keep
        g[i] = (a - b) / (2 * eps)
    return g


def test_attention_gradients():
    rng = np.random.default_rng(0)
    attn, frames, label = nn.AttnDecoder.start(3, 4, 5), rng.normal(size=(6, 3)), [2, 4, 1]
    value, grads, of_frames = attn.loss(frames, label)
    assert value == pytest.approx(-attn.score(frames, label))
    for k, p in attn.params.items():
        assert np.allclose(grads[k], numeric(lambda: -attn.score(frames, label), p), atol=1e-5), k
    assert np.allclose(of_frames, numeric(lambda: -attn.score(frames, label), frames), atol=1e-5)


def test_convolutional_tower_gradients():
    rng = np.random.default_rng(0)
    t = sync.ConvTowers.start(3, 4, 4, dim=2, filters=(2,), width=3)
    a, v, y = rng.normal(size=(3, 12)), rng.normal(size=(3, 4, 16)), np.array([1, 0, 0])
    _, grads = t.step(a, v, y, 3.0)
    for k, p in t.params.items():
        assert np.allclose(grads[k], numeric(lambda: t.step(a, v, y, 3.0)[0], p), atol=1e-4), k


def test_training_sums_gradients_in_blocks(spark, monkeypatch):
    """The same steps with one block and with many, and from another number of workers' sums."""
    rng = np.random.default_rng(1)
    clips = spark.createDataFrame([(i, bytearray(rng.normal(size=(6, 4, 4)).astype(np.float32).tobytes()), [1 + i % 2, 1 + (i + 1) % 2]) for i in range(8)], "clip_id long, px binary, label array<int>")
    net = nn.Net.start(4, 1, [2], 4, 1, 3)
    one, a = nn.train(clips, net, 4, steps=3, workers=2, per_worker=8)
    monkeypatch.setattr(nn, "GRADIENT_BLOCK", 50)
    two, b = nn.train(clips, net, 4, steps=3, workers=4, per_worker=8)
    assert np.allclose(a, b) and a[-1] < a[0]
    assert all(np.allclose(one.params[k], two.params[k]) for k in net.params)
    s = nn.saliency(clips, one, 4).collect()
    assert len(s) == 8 * 6 and all(r.strength >= 0 and len(r.top) == 3 and len(r.map) == 16 for r in s)


def test_tracks_of_several_faces(spark):
    rows = []
    for t in range(6):
        rows.append((1, t, 0, float(t), 0.0, 10.0, [0.0]))
        if t != 3:
            rows.append((1, t, 1, 100.0 - t, 0.0, 10.0, [5.0] if t < 5 else [9.0]))
    df = spark.createDataFrame(rows, "g int, t int, face int, x double, y double, s double, who array<double>")
    got = {(r.t, r.face): r.track for r in tracks.multi_face_tracks(df, ["g"]).collect()}
    assert {got[t, 0] for t in range(6)} == {0}
    assert [got[t, 1] for t in (0, 1, 2, 4, 5)] == [1, 1, 1, 2, 2]
    by_face = {(r.t, r.face): r.track for r in tracks.multi_face_tracks(df, ["g"], identity="who").collect()}
    assert by_face[5, 1] != by_face[4, 1]


def test_thumbnail_of_the_identity_and_of_an_edge(spark):
    px = np.random.default_rng(3).random((5, 6))
    df = spark.createDataFrame([(px.ravel().tolist(),)], "px array<double>")
    same = FR.sample_bilinear("px", 5, 6, 5, 6, "1D", "0D", "0D", "0D", "1D", "0D")
    half = FR.sample_bilinear("px", 5, 6, 1, 1, "1D", "0D", "1.5D", "0D", "1D", "99D")
    row = df.select(same.alias("a"), half.alias("b")).first()
    assert np.allclose(row.a, px.ravel()) and row.b[0] == pytest.approx((px[4, 1] + px[4, 2]) / 2)


def test_random_shifts_are_of_another_row(spark):
    df = spark.createDataFrame([(g, i, [float(i)], [float(i)]) for g, n in ((0, 7), (1, 2), (2, 1)) for i in range(10 * g, 10 * g + n)], "g int, i int, a array<double>, v array<double>")
    rows = sync.random_shifts(df, "g", "i").collect()
    assert sum(r.y for r in rows) == 10
    assert sorted(r.i for r in rows if not r.y) == [*range(7), 10, 11] and all(r.a != r.v for r in rows if not r.y)


def test_observed_counts_equal_counting(spark, small):
    c = standin.clips(spark, small)
    kept, seen = pipeline.observed_cascade(c, every=("duration", "pose"))
    n = len(kept.collect())
    assert n == pipeline.run_cascade(c).count() == seen["out"].get["n"]
    assert seen["in"].get["n"] == c.count() and seen["duration"].get["n"] == pipeline.duration_filter(c).count() and set(seen) == {"in", "duration", "pose", "out"}


def test_full_cascade_modes(spark, small):
    from clipflow.workloads.corpus import evidence

    e = evidence(spark, small).cache()
    n = {m: pipeline.run_cascade(e, pipeline.FULL, m).count() for m in ("train", "infer", "eval")}
    assert n["eval"] <= n["train"] <= n["infer"]
    assert {r[0] for r in pipeline.rules_of("infer", pipeline.FULL)}.isdisjoint({"language", "words", "synchrony", "duration"})
    e.unpersist()


def test_frame_clock_reads_and_writes(spark, tmp_path):
    clock.register(spark)
    c = spark.read.format("frame_clock").options(clips=5, seconds=2, fps=3, clips_per_task=2).load()
    assert c.rdd.getNumPartitions() == 3 and c.count() == 30 and c.agg(F.max("sec")).first()[0] == pytest.approx(5 / 3)
    assert spark.read.format("frame_clock").options(clips=0).load().count() == 0
    c.where("t = 0").write.format("frame_clock").mode("append").save(str(tmp_path / "out"))
    listed = json.loads((tmp_path / "out/_list.json").read_text())
    assert sum(f["rows"] for f in listed) == 5
    rows = [json.loads(line) for f in listed for line in (tmp_path / "out" / f["name"]).read_text().splitlines()]
    assert sorted(r["clip"] for r in rows) == list(range(5))


def test_registered_functions_and_nulls(spark):
    names = session.register(spark)
    assert "clip_viseme" in names
    row = spark.sql("SELECT clip_edits('abc', 'axc') AS e, clip_edits_arrow(NULL, 'a') AS n, clip_collapse(array('_', 'a', 'a', '_', 'a')) AS c, clip_duration_ok(13D) AS ok").first()
    assert (row.e, row.n, row.c, row.ok) == (1, None, "aa", False)
    assert [(r.pos, r.phone) for r in spark.sql("SELECT * FROM clip_phone_frames('pA', 25D)").collect()] == [(0, "p"), (1, "A")]


def stream_of(spark, tmp_path, name, df, files=3):
    for i in range(files):
        df.where(F.pmod("i", F.lit(files)) == i).drop("i").coalesce(1).write.mode("append").parquet(str(tmp_path / name))
    return spark.readStream.schema(df.drop("i").schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / name))


def run(spark, tmp_path, df, mode="append"):
    name = f"t{abs(hash(str(tmp_path)))}"
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    try:
        assert q.awaitTermination(180)
        return [tuple(r) for r in spark.table(name).collect()]
    finally:
        q.stop()


def test_stream_joined_with_a_table_and_a_stream(spark, tmp_path):
    ev = spark.createDataFrame([(i, i % 3, f"2024-01-01 00:{i:02d}:00") for i in range(30)], "i int, user_id int, ts string").withColumn("ts", F.to_timestamp("ts"))
    table = spark.createDataFrame([(0, "a"), (1, "b")], "user_id int, name string")
    got = run(spark, tmp_path / "1", C.with_context(stream_of(spark, tmp_path, "ev", ev), table, "user_id"))
    want = [tuple(r) for r in ev.drop("i").join(table, "user_id", "left").collect()]
    assert sorted(map(str, got)) == sorted(map(str, want))
    faces = ev.select("i", "user_id", (F.col("ts") + F.expr("INTERVAL 4 MINUTES")).alias("face_ts"))
    both = C.speech_with_faces(stream_of(spark, tmp_path, "ev2", ev), stream_of(spark, tmp_path, "faces", faces))
    got = run(spark, tmp_path / "2", both.select("user_id", "ts", "face_ts"))
    a, b = ev.drop("i"), faces.drop("i").withColumnRenamed("user_id", "u")
    want = [tuple(r) for r in a.join(b, F.expr("user_id = u AND face_ts BETWEEN ts - INTERVAL 10 MINUTES AND ts + INTERVAL 10 MINUTES")).select("user_id", "ts", "face_ts").collect()]
    assert sorted(map(str, got)) == sorted(map(str, want)) and want


def test_timed_collapse_equals_the_batch(spark, tmp_path):
    text = "__aa_ab__bbc"
    rows = [(t, f"u{u}", t, s, f"2024-01-01 0{u}:00:{t:02d}") for u in range(3) for t, s in enumerate(text[u:])]
    df = spark.createDataFrame(rows, "i int, utt string, t int, sym string, ts string").withColumn("ts", F.to_timestamp("ts")).withColumn("i", F.floor(F.col("t") / 6).cast("int"))
    got = run(spark, tmp_path / "3", C.incremental_collapse(stream_of(spark, tmp_path, "frames", df, 2)))
    for u in range(3):
        said = "".join(x[2] for x in sorted((r for r in got if r[0] == f"u{u}"), key=lambda r: r[1]))
        want = "".join(c for i, c in enumerate(text[u:]) if c != "_" and (i == 0 or text[u:][i - 1] != c))
        assert said == want


def test_frames_stream_through_the_cheap_rules_to_files(spark, tmp_path):
    """Duplicates out, limits joined, survivors counted by hour; batches of a stream stored by split, each once."""
    ev = spark.createDataFrame([(i % 20, i % 20, i % 4, f"2024-01-01 0{(i % 20) // 6}:{i % 20:02d}:00", float(30 + 5 * (i % 20))) for i in range(40)], "i int, event_id int, user_id int, ts string, value double").withColumn("ts", F.to_timestamp("ts"))
    table = spark.createDataFrame([(0, 5.0), (1, 30.0)], "user_id int, max_yaw double")
    got = {(r[0].start.hour, r[1]): r[2] for r in run(spark, tmp_path / "4", C.mine(stream_of(spark, tmp_path, "raw", ev, 2), table), "complete")}
    kept = ev.dropDuplicates(["event_id"]).join(table, "user_id", "left").where("abs(value - 50) / 5 <= coalesce(max_yaw, 30)")
    assert got == {(r[0], r[1]): r[2] for r in kept.groupBy(F.hour("ts"), "user_id").count().collect()}
    q = C.store_batches(stream_of(spark, tmp_path, "raw2", ev.withColumn("split", F.col("user_id") % 2), 2), str(tmp_path / "out"), str(tmp_path / "c5"))
    assert q.awaitTermination(180)
    assert spark.read.parquet(str(tmp_path / "out")).count() == 40 and {p.name for p in (tmp_path / "out").iterdir() if p.name.startswith("batch")} == {"batch=0", "batch=1"}


def test_table_functions_equal_their_twins(spark):
    session.register(spark)
    got = [(r.pos, r.gram) for r in spark.sql("SELECT * FROM clip_ngrams(array('a', 'b', 'c'), 2)").collect()]
    assert got == [(0, ["a", "b"]), (1, ["b", "c"])]
    ops = [tuple(r) for r in spark.sql("SELECT * FROM clip_edit_ops(array('a', 'b'), array('a', 'c', 'd'))").collect()]
    assert [o for o, *_ in ops].count("match") == 1 and sum(o != "match" for o, *_ in ops) == 2
    starts = [r.start for r in spark.sql("SELECT * FROM clip_windows(60, 100, 9)").collect()]
    assert starts == spark.range(1).select(F.lit(60).alias("n")).select(sync.equally_spaced("n", 100, 9)).first()[0]
    assert spark.sql("SELECT * FROM clip_windows(5, 100, 9)").count() == 0


def test_beam_with_a_symbol_model(spark):
    """Equal to the search in one process with the same model as a function; the model turns the order of two strings."""
    frames = [[0.2, 0.45, 0.35], [0.9, 0.05, 0.05], [0.2, 0.35, 0.45]]
    df = spark.createDataFrame([("u", frames)], "utt string, lattice array<array<double>>")
    model = {(2, 2): -0.01, (1, 2): -9.0, (2, 1): -9.0, (1, 1): -9.0, (1,): -0.7, (2,): -0.7}
    got = [(tuple(r.label), r.logp) for r in ctc.ctc_beam(df, lm=model, beta=1.0).orderBy("rank").collect()]
    want = ctc.beam_search(np.log(frames), 16, 0, lambda prefix, k: model[(*prefix[-1:], k)], 1.0, 1.0)
    assert [x for x, _ in got] == [x for x, _ in want] and np.allclose([p for _, p in got], [p for _, p in want])
    plain = [tuple(r.label) for r in ctc.ctc_beam(df).orderBy("rank").collect()]
    places = [x for x, _ in got]
    assert plain.index((1, 2)) < plain.index((2, 2)) and places.index((2, 2)) < places.index((1, 2))


@pytest.fixture(scope="module")
def learnt(spark):
    return {r.method: r for r in trained.rates(spark, "/root/testdata/sf0.01").collect()}


def test_trained_methods_learn_and_keep_their_order(learnt):
    """Rates of networks that were trained, on clips that they haven't seen."""
    assert all(r.loss_last < 0.7 * r.loss_first for m, r in learnt.items() if not m.startswith("small"))
    rate = {m: r.unit_rate for m, r in learnt.items()}
    assert rate["audio_ph"] < rate["small_ph"] and rate["full_ph"] < rate["large_gru_ph"] <= rate["small_ph"] + 0.05
    assert learnt["full_ph"].word_rate < learnt["small_ph"].word_rate and learnt["full_ph"].n > 100


def test_lexicon_words_have_sounds_and_spellings_of_their_own():
    words = trained.lexicon()
    assert len({p for _, p, _ in words}) == len({s for *_, s in words}) == trained.WORDS
    assert math.isclose(sum(math.exp(p) for k, p in trained.decoder_of(trained.METHODS[-1], [["w0", "w1"]]).lm.items() if len(k) == 1), 1.0)
