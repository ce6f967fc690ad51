"""Operators whose cost grew with more than their rows."""

import time

import numpy as np
from pyspark.sql import functions as F

from clipflow.operators import nn, pipeline, sync, tracks


def test_tracks_of_many_clips_are_linked_at_once(spark):
    n = 20_000  # clips of three frames of two faces; a group of pandas rows each took over 100 seconds
    df = spark.range(n).select("id", F.explode(F.sequence(F.lit(0), F.lit(2))).alias("t")).select("id", "t", F.explode(F.array(F.lit(0), F.lit(1))).alias("face"))
    df = df.select("id", "t", "face", (F.col("face") * 1000.0 + F.when(F.col("t") == 2, 500).otherwise(0)).alias("x"), F.lit(0.0).alias("y"), F.lit(100.0).alias("s"))
    began = time.time()
    got = tracks.multi_face_tracks(df, ["id"]).groupBy("t", "face", "track").count().collect()
    assert time.time() - began < 60
    assert {(r.t, r.face): (r.track, r["count"]) for r in got} == {(t, f): (f + 2 * (t == 2), n) for t in range(3) for f in range(2)}


def test_tracks_that_cross_batches_stay_whole(spark):
    old = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        df = spark.range(5).select("id", F.explode(F.sequence(F.lit(0), F.lit(10))).alias("t")).select("id", "t", F.lit(0).alias("face"), F.lit(1.0).alias("x"), F.lit(1.0).alias("y"), F.lit(2.0).alias("s"))
        got = tracks.multi_face_tracks(df, ["id"]).collect()
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", old)
    assert len(got) == 55 and {r.track for r in got} == {0}


def test_windows_of_a_long_clip_cost_no_more_than_of_a_short_one(spark):
    n = 60_000  # prefix sums copied as arrays took n squared steps
    df = spark.range(1).select(F.expr(f"transform(sequence(0, {n - 1}), i -> cast(i AS double))").alias("ds"))
    began = time.time()
    score = sync.window_scores(df, "ds").first().score
    assert time.time() - began < 30
    assert np.isclose(score, np.mean([np.floor(i * (n - 9) / 99) + 4 for i in range(100)]))


def test_trigrams_of_a_text_are_no_rows(spark):
    rng = np.random.default_rng(5)
    rows = [(i, "ab"[i % 2] if i % 7 else None, " " + "".join(rng.choice(list("xyz "[: 3 + i % 2]), int(rng.integers(0, 60)))) + " ") for i in range(80)]
    rows += [(80, "a", ""), (81, "a", None), (82, None, " q ")]
    df = spark.createDataFrame(rows, "k long, lab string, x string")
    learn = F.col("k") % 5 != 0
    g = df.where("length(x) > 2").select("k", "lab", F.explode(F.expr("transform(sequence(1, length(x) - 2), i -> substring(x, i, 3))")).alias("g")).groupBy("k", "lab", "g").agg(F.count(F.lit(1)).alias("n"))
    want = {r.k: r.guess for r in pipeline.naive_bayes(g, "k", "lab", "g", learn).collect()}
    found = pipeline.trigram_bayes(df, "k", "lab", "x", "xyzq ", learn)
    assert {r.k: r.guess for r in found.collect()} == want and 82 not in want
    assert pipeline.trigram_bayes(df.where("false"), "k", "lab", "x", "xyz ", learn).count() == 0
    assert "Generate" not in found._jdf.queryExecution().executedPlan().toString()


def test_towers_take_windows_as_arrays(spark):
    rng = np.random.default_rng(2)
    t = sync.ConvTowers.start(6, 9, 6, dim=6, filters=(3, 2))
    a, v, y = rng.normal(size=(6000, 54)), rng.normal(size=(6000, 9, 36)), np.arange(6000) % 2
    began = time.time()
    loss, grads = t.step(a, v, y, 1.0)  # window by window 6,000 took over ten seconds
    assert time.time() - began < 6
    few = [t.step(a[i : i + 500], v[i : i + 500], y[i : i + 500], 1.0) for i in range(0, 6000, 500)]
    assert np.isclose(loss, sum(x for x, _ in few)) and all(np.allclose(g, sum(x[k] for _, x in few)) for k, g in grads.items())
    video, back = nn.conv3d_windows(v[:5].reshape(5, 9, 6, 6, 1), t.params["v0.w"], t.params["v0.b"])
    sound, back_sound = nn.dilated_windows(a[:5].reshape(5, 9, 6), t.params["a0.w"], t.params["a0.b"])
    g, h = rng.normal(size=video.shape), rng.normal(size=sound.shape)
    dx, dw = back(g)
    dz, du = back_sound(h)
    alone = [nn.conv3d(v[i].reshape(9, 6, 6, 1), t.params["v0.w"], t.params["v0.b"]) for i in range(5)]
    heard = [nn.dilated(a[i].reshape(9, 6), t.params["a0.w"], t.params["a0.b"], 1) for i in range(5)]
    assert all(np.allclose(video[i], alone[i][0]) and np.allclose(dx[i], alone[i][1](g[i])[0]) for i in range(5))
    assert all(np.allclose(sound[i], heard[i][0]) and np.allclose(dz[i], heard[i][1](h[i])[0]) for i in range(5))
    assert all(np.allclose(dw[k], sum(alone[i][1](g[i])[1][k] for i in range(5))) and np.allclose(du[k], sum(heard[i][1](h[i])[1][k] for i in range(5))) for k in "wb")
