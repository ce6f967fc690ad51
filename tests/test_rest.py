"""Synchrony, alignment, geometry, scoring, baselines, streams, plans."""

import math

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from clipflow.functions import frames as FR
from clipflow.operators import align, baselines, evaluate, pipeline, sync, tracks
from clipflow.sources import lattices, standin
from clipflow.streaming import clips as C
from clipflow.workloads import tables_main


def test_affine_recovers_a_known_map(spark):
    rng = np.random.default_rng(0)
    p = rng.normal(size=(32, 2))
    rows = [(1, float(x), float(y), 2 * x - y + 3, 0.5 * x + 4 * y - 1) for x, y in p]
    got = pipeline.fit_affine(spark.createDataFrame([tuple(map(float, r)) for r in rows], "k double, x double, y double, u double, v double"), "k").first()
    assert np.allclose([got[c] for c in "abcdef"], [2, -1, 3, 0.5, 4, -1], atol=1e-9) and abs(got.residual) < 1e-6


def test_smoothing_keeps_constants_and_downsampling_caps(spark):
    df = spark.createDataFrame([(1, i, 5.0, i / 50) for i in range(40)], "g int, t int, v double, sec double")
    assert {round(r[0], 9) for r in df.select(pipeline.gaussian_smooth(df, "v", ["g"], ["t"])).collect()} == {5.0}
    assert pipeline.downsample_fps(df, 30, ("g",)).count() <= 0.8 * 30 + 1


def test_cascade_modes_and_rule_order(spark, small):
    c = standin.clips(spark, small).cache()
    train, infer = (pipeline.run_cascade(c, mode=m).count() for m in ("train", "infer"))
    assert train <= infer
    assert pipeline.run_cascade(c, pipeline.RULES[::-1]).count() == train
    order = [r[0] for r in pipeline.reorder_rules(c, pipeline.RULES[1:], {"duration": 1.0, "pose": 100.0})]
    assert order[-1] == "pose"
    c.unpersist()


def test_plans_of_the_cascade(spark, small):
    text = standin.clips(spark, small).where("dur > 1")._jdf.queryExecution().executedPlan().toString()
    assert text.count("Exchange hashpartitioning") == 1 and "Cartesian" not in text, text
    seg = spark.createDataFrame([(1, 0.0, 5.0)], "v int, t0 double, t1 double")
    face = spark.createDataFrame([(1, 4.0, 9.0)], "v int, u0 double, u1 double")
    plan = pipeline.interval_join(seg, face, "v", 2.0)
    assert plan.count() == 1 and "Cartesian" not in plan._jdf.queryExecution().executedPlan().toString() and "NestedLoop" not in plan._jdf.queryExecution().executedPlan().toString()


def test_trim_undoes_padding(spark):
    px = np.random.default_rng(1).random((6, 6))
    df = spark.createDataFrame([(np.pad(px, ((1, 2), (3, 0))).ravel().tolist(),)], "px array<double>")
    assert tuple(df.select(FR.trim_bounds("px", 9, 9).alias("b")).first().b) == (1, 6, 3, 8)


def test_tracks_break_where_boxes_part(spark):
    boxes = [(1, t, float(x), 0.0, 10.0) for t, x in enumerate([0, 1, 2, 50, 51, 0])]
    got = [r.track for r in tracks.link_tracks(spark.createDataFrame(boxes, "g int, t int, x double, y double, s double"), ["g"]).orderBy("t").collect()]
    assert got == [1, 1, 1, 2, 2, 3]


def test_alignment_takes_the_likeliest_pronunciation(spark):
    lattice = [[0.8, 0.1, 0.1]] * 2 + [[0.1, 0.1, 0.8]] * 3
    df = spark.createDataFrame([("u", lattice, [["a", "b"], ["a", "c"]]), ("v", lattice[:1], [["a", "b"]])], "utt string, lattice array<array<double>>, prons array<array<string>>")
    got = {r.utt: r for r in align.forced_align(df, ["a", "b", "c"]).collect()}
    assert got["u"].phones == ["a", "c"] and got["u"].cuts == [2] and got["v"].phones is None


def test_log_mel_finds_a_tone():
    rate, t = 1000, np.arange(1000) / 1000
    low, high = (sync.log_mel(np.sin(2 * math.pi * f * t), rate) for f in (60, 400))
    assert low.mean(axis=0).argmax() < high.mean(axis=0).argmax()


def test_two_rounds_of_self_filtering_help(spark):
    rng = np.random.default_rng(2)
    rows = []
    for i in range(200):
        z = rng.normal(size=3)
        a = np.concatenate([z, rng.normal(size=2)])
        other = z if i % 5 else rng.normal(size=3)  # a fifth of the pairs are out of step
        rows.append((a.tolist(), (np.tile(other, 2) + 0.1 * rng.normal(size=6)).tolist(), 1, int(i % 5 > 0)))
        rows.append((a.tolist(), np.tile(rng.normal(size=3), 2).tolist(), 0, 0))
    pairs = spark.createDataFrame(rows, "a array<double>, v array<double>, y int, truth int").coalesce(2).cache()
    start = sync.Towers.start(5, 2, 3, 3)
    towers, kept, losses = sync.self_filter(pairs, start, 2, rounds=2, epochs=25)
    assert losses[24] < losses[0]
    share = lambda df: df.where("y = 1").agg(F.avg("truth")).first()[0]
    assert share(kept) > share(pairs)


def test_window_average_beats_single_windows(spark):
    rng = np.random.default_rng(3)
    rows = [(i, y, (rng.normal(1.0 + 0.3 * (1 - y), 0.4, 60)).tolist()) for i in range(100) for y in (0, 1)]
    s = sync.window_scores(spark.createDataFrame(rows, "i int, y int, ds array<double>"), "ds")
    averaged = s.select(((F.col("score") < 1.15) == (F.col("y") == 1)).cast("int").alias("ok")).agg(F.avg("ok")).first()[0]
    single = s.select(((F.col("ds")[0] < 1.15) == (F.col("y") == 1)).cast("int").alias("ok")).agg(F.avg("ok")).first()[0]
    assert averaged > single + 0.1


def test_error_rates_and_bootstrap(spark):
    rng = np.random.default_rng(4)
    n, e = rng.integers(5, 20, 400), rng.integers(0, 5, 400)
    df = spark.createDataFrame([("m", i, int(a), int(b)) for i, (a, b) in enumerate(zip(e, n))], "method string, utt int, edits long, ref_len long")
    got = evaluate.bootstrap_se(df, ["method"], ["utt"], 200).first()
    assert np.isclose(got.rate, e.sum() / n.sum())
    assert abs(got.se / evaluate.bootstrap_exact(e, n, 1000) - 1) < 0.2
    empty = spark.createDataFrame([("m", 0, 3, 0)], df.schema)
    assert evaluate.error_rate(empty, ["method"]).first().rate is None


def test_alignment_operations_add_up(spark):
    assert [o for o, *_ in evaluate.align(list("abcd"), list("axcde"))] == ["match", "sub", "match", "match", "ins"]
    rows = [(i, list(r), list(h)) for i, (r, h) in enumerate([("kitten", "sitting"), ("abc", ""), ("", "xy"), ("flaw", "lawn")])]
    ops = evaluate.align_ops(spark.createDataFrame(rows, "utt int, ref array<string>, hyp array<string>"), ["utt"])
    assert {r.utt: r.n for r in ops.where("op <> 'match'").groupBy("utt").agg(F.count("*").alias("n")).collect()} == {0: 3, 1: 3, 2: 2, 3: 2}


def test_lattice_frames_sum_to_one(spark):
    lat = lattices.lattice(spark.createDataFrame([("a", "kYnd"), ("b", "Vv"), ("c", "")], "utt string, phones string"), ["utt"])
    assert {round(r[0], 9) for r in lat.groupBy("utt", "t").agg(F.sum("p")).select("sum(p)").collect()} == {1.0}


@pytest.fixture(scope="module")
def main_table(spark):
    return {r.method: r for r in tables_main.e_table_main(spark, "/root/testdata/sf0.001").collect()}


def test_main_table_order(main_table):
    wer = {m: r.wer for m, r in main_table.items()}
    assert wer["audio_ph"] < wer["full_ph"] < wer["fullconv_ph"] < wer["large_gru_ph"] < wer["small_ph"]
    assert wer["full_ph"] < wer["unigram_ph"] and wer["full_ph"] < wer["attn_ch"] < wer["small_ch"]
    assert wer["human_plain"] > wer["large_gru_ph"] and wer["human_ctx"] > wer["large_gru_ph"]
    assert main_table["full_ph"].per == main_table["unigram_ph"].per  # measured before words are decoded
    assert main_table["small_ch"].per is None and len(main_table) == len(baselines.METHODS)


# ---- streams


def test_stream_sessions_equal_their_batch_twin(spark, small, tmp_path):
    ev = spark.read.parquet(f"{small}/events.parquet")
    ev.repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(f"{tmp_path}/in")
    q = C.sessions(C.read_events(spark, f"{tmp_path}/in", 100)).writeStream.format("memory").queryName("sess").outputMode("append").option("checkpointLocation", f"{tmp_path}/c").start()
    q.processAllAvailable()
    q.stop()
    got = {(r.user_id, r.w.start.timestamp(), r.n) for r in spark.table("sess").collect()}
    e = ev.select("event_id", "user_id", standin.epoch("ts").alias("e"))
    last = e.agg(F.max("e")).first()[0]
    batch = {(r.user_id, r.s0, r.n) for r in C.sessions_batch(e).collect() if r.s1 + C.SESSION_GAP <= last - 3600}
    rounded = lambda s: {(u, round(t, 3), n) for u, t, n in s}
    assert rounded(got) == rounded(batch) and got


def test_incremental_collapse_equals_the_whole(spark, tmp_path):
    text = {"u": "_aab_bb_c", "v": "xx__x"}
    rows = pd.DataFrame([(u, t, c) for u, s in text.items() for t, c in enumerate(s)], columns=["utt", "t", "sym"])
    for n, part in enumerate((rows[rows.t < 4], rows[rows.t >= 4])):
        spark.createDataFrame(part).select("utt", F.col("t").cast("int"), "sym").coalesce(1).write.parquet(f"{tmp_path}/f/p={n}")
    stream = spark.readStream.schema("utt string, t int, sym string").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/f")
    q = C.incremental_collapse(stream).writeStream.format("memory").queryName("labels").outputMode("append").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    assert q.awaitTermination(120)
    got = {}
    for r in spark.table("labels").orderBy("utt", "t").collect():
        got[r.utt] = got.get(r.utt, "") + r.label
    assert got == {"u": "abbc", "v": "xx"}
